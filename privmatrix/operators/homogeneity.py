"""Private choice of split points by the homogeneity of the slabs they make.

The objective of a set of cuts is the total absolute deviation of all entries, the empty ones too, from the mean of their slab. It is
evaluated without empty entries: a slab of a given size, sum and number of non-empty entries owes each empty entry its mean. A node's
profile (how many entries hold which count at which coordinate) is made once and serves all candidates.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from privmatrix.functions import boxes, noise

SENSITIVITY = 2.0
#: Scale of a candidate's noise for p candidates and budget e, and whether the choice is then proven to cost e.
CANDIDATE_NOISE = {
    "composed": (lambda p, e: SENSITIVITY * p / e, True),
    "noisy_min": (lambda p, e: 2 * SENSITIVITY / e, True),
    "equation": (lambda p, e: SENSITIVITY / e, False),
    "algorithm": (lambda p, e: SENSITIVITY / (p * e), False),
}


def base_intervals(lo: Column, width: Column, m: Column) -> Column:
    """Lower ends of m equal intervals, and the upper end of the last: array<int>."""
    return F.transform(F.sequence(F.lit(0), m), lambda j: (lo + F.floor(j.cast("long") * width / m)).cast("int"))


def candidates(nodes: DataFrame, p: int, cuts: str = "m", *, salt: str) -> DataFrame:
    """node, cand (1..p), ends: slab ends of every candidate; one uniform position in each base interval.

    nodes: node, lo, hi, m of the axis to split. ``cuts``: ``m`` cuts in all intervals, or ``m-1`` that leave the first out. Cuts at the
    lower end and repeated cuts make no slab.
    """
    listed = nodes.select("node", "lo", "hi", "m", F.explode(F.sequence(F.lit(1), F.lit(p))).alias("cand"))
    base = listed.withColumn("base", base_intervals(F.col("lo"), F.col("hi") - F.col("lo"), F.col("m")))
    first = 0 if cuts == "m" else 1
    numbers = F.filter(F.sequence(F.lit(0), F.col("m") - 1), lambda j: j >= first)

    def position(j: Column) -> Column:
        low, high = F.element_at("base", j + 1), F.element_at("base", j + 2)
        return (low + F.floor(noise.keyed_uniform(salt, "pos", "node", "cand", j) * (high - low))).cast("int")

    inner = F.array_distinct(F.filter(F.transform(numbers, position), lambda c: c > F.col("lo")))
    return base.select("node", "cand", F.concat(F.array("lo"), inner, F.array("hi")).alias("ends"))


def slab_of(ends: Column, x: Column) -> Column:
    """Number of the slab that holds coordinate x."""
    return F.size(F.filter(ends, lambda e: e <= x)) - 1


def slab_near(ends: Column, x: Column, lo: Column, width: Column, m: Column) -> Column:
    """``slab_of`` without a search: of m cuts each lies in a base interval of its own, so only the cut of x's own interval is compared.

    Where the first interval's cut is left out or at the lower end, all others are one place further to the front.
    """
    at = boxes.even_index(x, lo, width, m) + F.size(ends) - 1 - m
    return at - (F.element_at(ends, at + 1) > x).cast("int")


def profile(cells: DataFrame, axis: str) -> DataFrame:
    """node, coord, f, n: non-empty entries of a node by coordinate and count. cells may hold n, the number of entries that a row stands for."""
    return cells.groupBy("node", F.col(axis).alias("coord"), "f").agg((F.sum("n") if "n" in cells.columns else F.count("*")).alias("n"))


def objective(profiles: DataFrame, cands: DataFrame, sides: DataFrame) -> DataFrame:
    """node, cand, o, ends for every candidate. sides: node, area (entries of the node for each coordinate of the axis), and m, if all cuts are of ``candidates``.

    Profiles, which partial sums have made small, are dealt out by node and candidate once; all that follows stays there. A slab's counts with
    their numbers of entries are one array, as long as there are distinct counts. Every candidate has a row without entries, which
    carries its ends.
    """
    listed = cands.join(sides, "node")
    length = F.element_at("ends", F.col("slab") + 2) - F.element_at("ends", F.col("slab") + 1)
    ends, coord = F.col("ends"), F.col("coord")
    lo = F.element_at("ends", 1)
    slab = slab_near(ends, coord, lo, F.element_at("ends", -1) - lo, F.col("m")) if "m" in sides.columns else slab_of(ends, coord)
    placed = profiles.join(listed, "node").withColumn("slab", slab)
    placed = placed.select("node", "cand", "slab", (length * F.col("area")).alias("size"), "f", "n", F.lit(None).cast("array<int>").alias("ends"))
    blank = cands.select("node", "cand", F.lit(-1).alias("slab"), F.lit(1.0).alias("size"), F.lit(0).cast("long").alias("f"), F.lit(0).cast("long").alias("n"), "ends")
    tallied = placed.unionByName(blank).repartition("node", "cand").groupBy("node", "cand", "slab", "size", "f").agg(F.sum("n").alias("n"), F.first("ends", True).alias("ends"))
    held = tallied.groupBy("node", "cand", "slab", "size").agg(
        F.sort_array(F.collect_list(F.struct("f", "n"))).alias("held"), F.sum("n").alias("filled"), (F.sum(F.col("f") * F.col("n")).cast("double") / F.col("size")).alias("mu"), F.first("ends", True).alias("ends")
    )
    off = F.aggregate("held", F.lit(0.0), lambda acc, x: acc + x["n"] * F.abs(x["f"] - F.col("mu"))) + (F.col("size") - F.col("filled")) * F.col("mu")
    return held.withColumn("off", off).groupBy("node", "cand").agg(F.sum("off").alias("o"), F.first("ends", True).alias("ends"))


def choose(objectives: DataFrame, budgets: DataFrame, p: int, candidate_noise: str = "composed", *, salt: str) -> DataFrame:
    """node, ends, cand of the least noisy objective; ties go to the smaller candidate. budgets: node, eps_prt."""
    scale = CANDIDATE_NOISE[candidate_noise][0](p, F.col("eps_prt"))
    noisy = objectives.join(budgets, "node").withColumn("noisy", F.col("o") + noise.laplace(salt, "cand", scale, "node", "cand"))
    least = F.struct("noisy", "cand")
    return noisy.groupBy("node").agg(F.min_by("ends", least).alias("ends"), F.min_by("cand", least).alias("cand"))
