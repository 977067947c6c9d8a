"""Range queries: random shapes and fixed coverage, from keyed draws on a distributed range."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from privmatrix.functions.noise import keyed_uniform
from privmatrix.sources.spec import MatrixSpec

#: Sides of the three query sizes, as shares of an axis.
SIZES = {"small": 0.01, "medium": 0.05, "large": 0.10}


def random_queries(spark: SparkSession, spec: MatrixSpec, n: int = 1000, salt: str = "", ids: DataFrame | None = None) -> DataFrame:
    """qid and a box between two random positions of every axis, at least one entry wide; n of them, or one for every id (column qid)."""
    q = spark.range(n).withColumnRenamed("id", "qid") if ids is None else ids
    columns = []
    for i, w in enumerate(spec.widths, 1):
        a, b = (F.floor(keyed_uniform(salt, "query", "qid", i, k) * w).cast("int") for k in (1, 2))
        columns += [F.least(a, b).alias(f"qlo{i}"), (F.greatest(a, b) + 1).alias(f"qhi{i}")]
    return q.select("qid", *columns)


def coverage_queries(spark: SparkSession, spec: MatrixSpec, share: float, n: int = 1000, coverage_of: str = "side", salt: str = "", ids: DataFrame | None = None) -> DataFrame:
    """Boxes of one size at random corners: ``share`` of each side, or of the whole volume; n of them, or one for every id (column qid)."""
    side_share = share if coverage_of == "side" else share ** (1 / spec.d)
    q = spark.range(n).withColumnRenamed("id", "qid") if ids is None else ids
    columns = []
    for i, w in enumerate(spec.widths, 1):
        side = max(1, int(side_share * w + 0.5))
        lo = F.floor(keyed_uniform(salt, "query", "qid", i, 1) * (w - side + 1)).cast("int")
        columns += [lo.alias(f"qlo{i}"), (lo + side).alias(f"qhi{i}")]
    return q.select("qid", *columns)


def sized(spark: SparkSession, spec: MatrixSpec, size: str, n: int = 1000, salt: str = "") -> DataFrame:
    return coverage_queries(spark, spec, SIZES[size], n, "side", salt)
