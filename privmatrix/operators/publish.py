"""Releases as files: saving, loading, slicing, and what may be done to published values without further budget."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from privmatrix.functions import boxes
from privmatrix.sources.spec import MatrixSpec


def metadata(spark: SparkSession, method: str, spec: MatrixSpec, eps: float, **options: object) -> DataFrame:
    """One row that describes a release. The salt is no option: it never leaves the curator."""
    if "salt" in options:
        raise ValueError("a salt is not published")
    return spark.createDataFrame([(method, spec.d, float(eps), {k: str(v) for k, v in options.items()}, spec.unit, spec.json())], "method string, d int, eps double, options map<string,string>, unit string, spec string")


def save(partitions: DataFrame, meta: DataFrame, path: str, kind: str = "parquet") -> None:
    """Boxes in the order of their first axis, so that readers can skip files; an existing release is never overwritten, as a second one would spend budget again."""
    laid = partitions.repartitionByRange("lo1").sortWithinPartitions("lo1") if kind == "parquet" else partitions
    laid.write.mode("errorifexists").format(kind).option("header", "true").save(f"{path}/boxes")
    (meta if kind != "csv" else meta.withColumn("options", F.to_json("options"))).write.mode("errorifexists").format(kind).option("header", "true").save(f"{path}/meta")


def load(spark: SparkSession, path: str) -> tuple[DataFrame, DataFrame]:
    """(boxes, metadata) of a saved release."""
    return spark.read.parquet(f"{path}/boxes"), spark.read.parquet(f"{path}/meta")


def timed_sink(partitions: DataFrame) -> None:
    """Computes everything and keeps nothing; for measuring."""
    partitions.write.format("noop").mode("overwrite").save()


def to_entries(partitions: DataFrame, d: int, box: list[tuple[int, int]] | None = None) -> DataFrame:
    """x1..xd, value: every entry has its box's count over its box's size. Entries are made for the asked box only."""
    out = partitions
    for i in range(1, d + 1):
        lo, hi = (F.col(f"lo{i}"), F.col(f"hi{i}")) if box is None else (F.greatest(f"lo{i}", F.lit(box[i - 1][0])), F.least(f"hi{i}", F.lit(box[i - 1][1])))
        out = out.withColumn(f"__a{i}", lo).withColumn(f"__b{i}", hi).where(f"__a{i} < __b{i}").withColumn(f"x{i}", F.explode(F.sequence(F.col(f"__a{i}"), F.col(f"__b{i}") - 1)))
    return out.select(*[f"x{i}" for i in range(1, d + 1)], (F.col("ncount") / F.col("n_entries")).alias("value"))


def cut(partitions: DataFrame, d: int, axis: int, lo: int, hi: int) -> DataFrame:
    """The release within lo <= x_axis < hi; boxes across the ends keep the share of their count that lies within."""
    a, b = F.greatest(f"lo{axis}", F.lit(lo)), F.least(f"hi{axis}", F.lit(hi))
    share = (b - a) / (F.col(f"hi{axis}") - F.col(f"lo{axis}"))
    inside = partitions.where((F.col(f"lo{axis}") < hi) & (F.col(f"hi{axis}") > lo))
    return inside.withColumns({"ncount": F.col("ncount") * share, "n_entries": F.col("n_entries") * share, f"lo{axis}": a, f"hi{axis}": b})


def marginal(partitions: DataFrame, d: int, axes: list[int]) -> DataFrame:
    """Counts by box sides on the given axes, the other axes summed away."""
    sides = [c for i in axes for c in (f"lo{i}", f"hi{i}")]
    return partitions.groupBy(*sides).agg(F.sum("ncount").alias("ncount"))


def postprocess(partitions: DataFrame, nonneg: bool = False, integer: bool = False, total: float | None = None) -> DataFrame:
    """Changes of released values, which cost no budget: no negative counts, scaled to a released total, whole numbers."""
    out = partitions
    if nonneg:
        out = out.withColumn("ncount", F.greatest("ncount", F.lit(0.0)))
    if total is not None:
        one = out.agg(F.sum("ncount").alias("__sum"))
        out = out.join(F.broadcast(one)).withColumn("ncount", F.coalesce(F.try_divide(F.col("ncount") * total, F.col("__sum")), F.lit(0.0))).drop("__sum")
    if integer:
        out = out.withColumn("ncount", F.round("ncount"))
    return out


def compared(a: DataFrame, b: DataFrame, d: int) -> DataFrame:
    """Boxes of two releases side by side; a box of one only has null for the other."""
    on = boxes.bounds(d)
    return a.select(*on, F.col("ncount").alias("a")).join(b.select(*on, F.col("ncount").alias("b")), on, "full_outer")


def uncovered(partitions: DataFrame, cells: DataFrame, d: int) -> DataFrame:
    """Entries outside every box; a release has none."""
    named = partitions.select(*[F.col(c).alias(f"q{c}") for c in boxes.bounds(d)])
    return cells.join(named, boxes.holds(d), "left_anti")


def overlapping(partitions: DataFrame, d: int) -> DataFrame:
    """Pairs of boxes that overlap; a release has none. For tests: boxes meet all others."""
    other = partitions.select(F.col("pid").alias("qpid"), *[F.col(c).alias(f"q{c}") for c in boxes.bounds(d)])
    return partitions.join(other, (F.col("pid") < F.col("qpid")) & boxes.overlaps(d)).select("pid", "qpid")


def describe(spec_json: str) -> list[dict]:
    """The dimensions in a release's metadata."""
    return [dict(zip(("name", "expr", "lo", "hi", "width"), dim)) for dim in json.loads(spec_json)]
