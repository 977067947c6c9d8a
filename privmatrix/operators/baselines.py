"""Baselines: noise on every entry, the budget-free grid, and a single box."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from privmatrix.functions import boxes, noise
from privmatrix.operators import grids
from privmatrix.sources.spec import MatrixSpec


def log_grid(cells: DataFrame, spec: MatrixSpec, eps: float, **options) -> DataFrame:
    return grids.grid_release(cells, spec, eps, grids.granularity_log, "log_grid", **options)


def one_box(cells: DataFrame, spec: MatrixSpec, eps: float, s: float = 1.0, *, salt: str, label: str = "", noisy: bool = True) -> DataFrame:
    """The whole domain as one box."""
    salt = noise.release_salt(salt, "one_box", eps, spec.key, s, label)
    bounds = [F.lit(v).cast("int").alias(f"{side}{i}") for i, w in enumerate(spec.widths, 1) for side, v in (("lo", 0), ("hi", w))]
    drawn = noise.laplace(salt, "leaf", s / eps, F.lit("r")) if noisy else F.lit(0.0)
    return cells.agg((F.coalesce(F.sum("f"), F.lit(0)) + drawn).alias("ncount")).select(F.lit("r").alias("pid"), *bounds, F.lit(float(spec.entries)).alias("n_entries"), "ncount", F.lit(0).alias("depth"), F.lit(eps).alias("eps_path"))


def _entries(spark: SparkSession, spec: MatrixSpec) -> DataFrame:
    """x1..xd of the whole domain in the order of its axes."""
    rest, columns = F.col("id"), []
    for i in range(spec.d, 0, -1):
        w = spec.widths[i - 1]
        columns.append(F.pmod(rest, F.lit(w)).cast("int").alias(f"x{i}"))
        rest = F.floor(rest / w)
    return spark.range(spec.entries).select(*reversed(columns))


def drawn_noise(spark: SparkSession, spec: MatrixSpec, eps: float, s: float = 1.0, *, salt: str, label: str = "") -> DataFrame:
    """lo1.., ncount: the noise of ``cell_noise`` alone, for every entry. Answers to it and exact counts add up to the answers of the release."""
    salt = noise.release_salt(salt, "cell_noise", eps, spec.key, s, label)
    return _entries(spark, spec).select(*[F.col(x).alias(f"lo{x[1:]}") for x in spec.axes], noise.laplace(salt, "cell", s / eps, *spec.axes).alias("ncount"))


def cell_noise(cells: DataFrame, spec: MatrixSpec, eps: float, s: float = 1.0, *, salt: str, label: str = "", noisy: bool = True) -> DataFrame:
    """Every entry of the domain as a box of size 1. The entries come from a distributed range; cells too many to be broadcast are joined by a shuffle of the whole domain, for which ``cell_noise_lazy`` is the way out."""
    salt = noise.release_salt(salt, "cell_noise", eps, spec.key, s, label)
    d = spec.d
    full = _entries(cells.sparkSession, spec).join(cells, spec.axes, "left")
    drawn = noise.laplace(salt, "cell", s / eps, *spec.axes) if noisy else F.lit(0.0)
    sides = [c for i in range(1, d + 1) for c in (F.col(f"x{i}").alias(f"lo{i}"), (F.col(f"x{i}") + 1).alias(f"hi{i}"))]
    return full.select(F.concat_ws(".", F.lit("c"), *spec.axes).alias("pid"), *sides, F.lit(1.0).alias("n_entries"), (F.coalesce("f", F.lit(0)) + drawn).alias("ncount"), F.lit(1).alias("depth"), F.lit(eps).alias("eps_path"))


def cell_noise_lazy(cells: DataFrame, queries: DataFrame, spec: MatrixSpec, eps: float, s: float = 1.0, *, salt: str, label: str = "") -> DataFrame:
    """qid, est as ``cell_noise`` would answer: an entry's noise is a function of its key, so only the entries asked for are drawn."""
    salt = noise.release_salt(salt, "cell_noise", eps, spec.key, s, label)
    out = queries
    for i in range(1, spec.d + 1):
        out = out.where(f"qlo{i} < qhi{i}").withColumn(f"x{i}", F.explode(F.sequence(F.col(f"qlo{i}"), F.col(f"qhi{i}") - 1)))
    asked = out.select("qid", *spec.axes).join(cells, spec.axes, "left")
    summed = asked.groupBy("qid").agg(F.sum(F.coalesce("f", F.lit(0)) + noise.laplace(salt, "cell", s / eps, *spec.axes)).alias("est"))
    return queries.select("qid").join(summed, "qid", "left").select("qid", F.coalesce("est", F.lit(0.0)).alias("est"))


def cell_noise_answers(truth: DataFrame, queries: DataFrame, d: int, eps: float, s: float = 1.0, *, salt: str, matrix: str = "", label: str = "") -> DataFrame:
    """qid, est for evaluation on domains too large to draw: a query's summed noise in one draw of the same distribution.

    The sum of k Laplace draws is the difference of two Gamma(k) draws. Up to 64 entries these are sums of keyed exponentials;
    beyond, a normal draw of the same variance. truth: qid, truth.
    """
    salt = noise.release_salt(salt, "cell_noise_answers", eps, matrix, s, label)
    scale, k = s / eps, boxes.volume(d, "q")
    exponentials = lambda tag: F.aggregate(F.sequence(F.lit(1), F.least(k, F.lit(64.0)).cast("int")), F.lit(0.0), lambda acc, i: acc - F.log(noise.keyed_uniform(salt, f"query{tag}", F.col("qid"), i)))
    u1, u2 = (noise.keyed_uniform(salt, f"query{t}", F.col("qid")) for t in ("a", "b"))
    normal = F.sqrt(-2 * F.log(u1)) * F.cos(2 * F.pi() * u2) * F.sqrt(2 * k)
    drawn = F.when(k == 0, F.lit(0.0)).when(k <= 64, exponentials("+") - exponentials("-")).otherwise(normal)
    return queries.join(truth.select("qid", "truth"), "qid").select("qid", (F.col("truth") + scale * drawn).alias("est"))
