"""Data-independent releases: equal grids whose granularity follows from the noisy total.

The total, its noise and the granularity stay one-row tables inside the plan, so a release is one job without a collect.
"""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from privmatrix.functions import boxes, noise
from privmatrix.functions.budget import root_share
from privmatrix.sources.spec import MatrixSpec

C0 = 10 / math.sqrt(2)
Rule = Callable[[Column, float, int], Column]


def noisy_total(cells: DataFrame, eps0: float, s: float = 1.0, *, salt: str, matrix: str = "") -> DataFrame:
    """One row: n, the number of records plus Laplace noise of scale s / eps0."""
    salt = noise.release_salt(salt, "total", eps0, matrix, s)
    return cells.agg((F.coalesce(F.sum("f"), F.lit(0)) + noise.laplace(salt, "total", s / eps0)).alias("n"))


def granularity_error(n: Column, eps: float, d: int, r: float | None = None, c0: float = C0) -> Column:
    """Cuts per axis that balance noise and uniformity error; for queries of share r, or on average over all shares.

    At d = 1 the balance has no root other than 0, and the entropy rule takes its place.
    """
    if d == 1:
        return granularity_entropy(n, eps, d)
    a = 2 * (d - 1) / d * n * eps / (math.sqrt(2) * c0)
    if r is not None:
        return F.pow(a * r ** (1 / d - 0.5), F.lit(2 / (3 * d - 2)))
    return F.pow(a, F.lit(2 / (3 * d - 2))) * (d * (3 * d - 2) / (3 * d * d - 3 * d + 2))


def granularity_entropy(n: Column, eps: float, d: int) -> Column:
    """Cuts per axis at which the entropy of the noise equals the information lost by coarsening."""
    return F.pow(n * eps / math.sqrt(2), F.lit(2 / (3 * d)))


def granularity_log(n: Column, eps: float, d: int) -> Column:
    """Cuts per axis from the total alone."""
    return F.when(n > math.e, F.pow(n / F.sqrt(F.log(F.greatest(n, F.lit(math.e)))), F.lit(2 / (d + 2)))).otherwise(F.lit(1.0))


def rounded(m: Column, width: int, rounding: str = "round") -> Column:
    turned = {"round": F.round(m), "floor": F.floor(m), "ceil": F.ceil(m)}[rounding]
    return F.greatest(F.lit(1), F.least(turned.cast("double"), F.lit(float(width)))).cast("int")


def granularity(total: DataFrame, spec: MatrixSpec, eps: float, rule: Rule, rounding: str = "round") -> DataFrame:
    """One row m1..md: the rule's value rounded and held within each axis."""
    g = total.select(rule(F.greatest(F.col("n"), F.lit(0.0)), eps, spec.d).alias("g"))
    return g.select(*[rounded(F.col("g"), w, rounding).alias(f"m{i}") for i, w in enumerate(spec.widths, 1)])


def grid_release(cells: DataFrame, spec: MatrixSpec, eps: float, rule: Rule, method: str, eps0: float | None = None, rounding: str = "round", s: float = 1.0, *, salt: str, label: str = "", noisy: bool = True, addends: bool = False) -> DataFrame:
    """Boxes of an equal grid with noisy counts; every box of the domain is released, the empty ones too.

    pid, lo1, hi1, .., n_entries, ncount, depth, eps_path. ``method`` names the rule and its parameters, ``label`` the state of the data. With ``noisy`` off, the granularity is still private, the counts are exact.
    ``addends``, for the curator's evaluation: bounds and ncount of rows that add up to the same boxes (noise, and a row of its box for every cell), so that answers need no join.
    """
    d, eps0 = spec.d, root_share(eps) if eps0 is None else eps0
    salt = noise.release_salt(salt, method, eps, spec.key, eps0, rounding, s, label)
    one = granularity(noisy_total(cells, eps0, s, salt=salt), spec, eps - eps0, rule, rounding)
    js = [f"j{i}" for i in range(1, d + 1)]
    if addends:
        ms = [F.col(f"m{i}") for i in range(1, d + 1)]
        at = cells.join(F.broadcast(one)).select(*[boxes.even_index(F.col(f"x{i}"), 0, w, m).alias(f"j{i}") for i, (w, m) in enumerate(zip(spec.widths, ms), 1)], *ms, "f")
        ends = [boxes.even_bound(F.col(f"j{i}") + k, 0, w, m).alias(f"{side}{i}") for i, (w, m) in enumerate(zip(spec.widths, ms), 1) for side, k in (("lo", 0), ("hi", 1))]
        counted = at.select(*ends, F.col("f").cast("double").alias("ncount"))
        return counted.unionByName(boxes.grid_domain(cells.sparkSession, spec.widths, one).select(*boxes.bounds(d), noise.laplace(salt, "count", s / (eps - eps0), *js).alias("ncount"))) if noisy else counted
    placed = cells.join(F.broadcast(one)).select(*[boxes.even_index(F.col(f"x{i}"), 0, w, F.col(f"m{i}")).alias(f"j{i}") for i, w in enumerate(spec.widths, 1)], "f")
    counts = placed.groupBy(*js).agg(F.sum("f").alias("cnt"))
    domain = boxes.grid_domain(cells.sparkSession, spec.widths, one)
    full = domain.join(counts, js, "left")
    drawn = noise.laplace(salt, "count", s / (eps - eps0), *js) if noisy else F.lit(0.0)
    return full.select(F.concat_ws(".", F.lit("g"), *js).alias("pid"), *boxes.bounds(d), boxes.volume(d).alias("n_entries"), (F.coalesce("cnt", F.lit(0)) + drawn).alias("ncount"), F.lit(1).alias("depth"), F.lit(eps).alias("eps_path"))


def uniform_grid(cells: DataFrame, spec: MatrixSpec, eps: float, r: float | None = None, c0: float = C0, **options) -> DataFrame:
    return grid_release(cells, spec, eps, lambda n, e, d: granularity_error(n, e, d, r, c0), f"uniform_grid({r},{c0})", **options)


def entropy_grid(cells: DataFrame, spec: MatrixSpec, eps: float, **options) -> DataFrame:
    return grid_release(cells, spec, eps, granularity_entropy, "entropy_grid", **options)
