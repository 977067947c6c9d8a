"""Synthetic points around the given orders: Gaussian clouds and Zipf axes, by keyed draws."""

from __future__ import annotations

from itertools import accumulate

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from privmatrix.functions.noise import keyed_uniform
from privmatrix.sources.spec import MatrixSpec, plain


def points(orders: DataFrame, copies: int = 7) -> DataFrame:
    """key, copy: ``copies`` points for each order. Keys are dealt out first, as a small file is few splits and every point costs several hashes."""
    n = 4 * orders.sparkSession.sparkContext.defaultParallelism
    return orders.select(F.col("o_orderkey").alias("key")).repartition(n, "key").select("key", F.explode(F.sequence(F.lit(1), F.lit(copies))).alias("copy"))


def width(n: int, d: int) -> int:
    """Cells per axis at which n points fill as many entries."""
    return max(1, round(n ** (1 / d)))


def gaussian_spec(n: int, d: int) -> MatrixSpec:
    return plain(f"gaussian{d}", *[width(n, d)] * d)


def gaussian(keys: DataFrame, spec: MatrixSpec, sd: float = 0.05, salt: str = "", outside: str = "drop") -> DataFrame:
    """x1..xd, f: normal coordinates around one random centre; sd is a share of the axis. Points outside are dropped or clamped."""
    columns = []
    for i, w in enumerate(spec.widths, 1):
        centre = keyed_uniform(salt, "point", F.lit("centre"), i) * w
        u1, u2 = (keyed_uniform(salt, "point", "key", "copy", i, k) for k in (1, 2))
        x = F.floor(centre + sd * w * F.sqrt(-2 * F.log(u1)) * F.cos(2 * F.pi() * u2)).cast("int")
        columns.append((F.greatest(F.lit(0), F.least(x, F.lit(w - 1))) if outside == "clamp" else x).alias(f"x{i}"))
    drawn = keys.select(*columns)
    inside = " AND ".join(f"x{i} >= 0 AND x{i} < {w}" for i, w in enumerate(spec.widths, 1))
    return drawn.where(inside).groupBy(*spec.axes).agg(F.count("*").alias("f"))


def normals(keys: DataFrame, d: int, salt: str = "") -> DataFrame:
    """z1..zd: the standard normal draws of ``gaussian``, which serve every spread."""
    draws = [[keyed_uniform(salt, "point", "key", "copy", i, k) for k in (1, 2)] for i in range(1, d + 1)]
    return keys.select(*[(F.sqrt(-2 * F.log(u1)) * F.cos(2 * F.pi() * u2)).alias(f"z{i}") for i, (u1, u2) in enumerate(draws, 1)])


def gaussian_of(drawn: DataFrame, spec: MatrixSpec, sd: float = 0.05, salt: str = "") -> DataFrame:
    """As ``gaussian`` from the draws of ``normals``; points outside are dropped."""
    columns = [F.floor(keyed_uniform(salt, "point", F.lit("centre"), i) * w + sd * w * F.col(f"z{i}")).cast("int").alias(f"x{i}") for i, w in enumerate(spec.widths, 1)]
    inside = " AND ".join(f"x{i} >= 0 AND x{i} < {w}" for i, w in enumerate(spec.widths, 1))
    return drawn.select(*columns).where(inside).groupBy(*spec.axes).agg(F.count("*").alias("f"))


def zipf_table(w: int, a: float) -> list[float]:
    """Distribution function of a Zipf variable on 1..w at skew a."""
    mass = [k**-a for k in range(1, w + 1)]
    total = sum(mass)
    return [x / total for x in accumulate(mass)]


def zipf(keys: DataFrame, spec: MatrixSpec, a: float = 1.6, salt: str = "") -> DataFrame:
    """x1..xd, f: every coordinate the rank of a Zipf draw, from a range join of the draw with the table of its axis.

    Draws and table rows meet in equal bins of the unit interval; a bin holds the few ranks that reach into it.
    """
    spark, rows = keys.sparkSession, keys
    for i, w in enumerate(spec.widths, 1):
        cdf, bins = zipf_table(w, a), max(1, min(w, 1000))
        table = spark.createDataFrame([(b, k, cdf[k - 1] if k else 0.0, cdf[k]) for k in range(w) for b in range(int((cdf[k - 1] if k else 0.0) * bins), min(bins - 1, int(cdf[k] * bins)) + 1)], "bin int, rank int, low double, high double")
        rows = rows.withColumn("u", keyed_uniform(salt, "point", "key", "copy", i)).withColumn("bin", F.least(F.floor(F.col("u") * bins), F.lit(bins - 1)).cast("int"))
        rows = rows.join(F.broadcast(table), "bin").where("low <= u AND (u < high OR rank = %d)" % (w - 1)).drop("bin", "u", "low", "high").withColumnRenamed("rank", f"x{i}")
    return rows.groupBy(*spec.axes).agg(F.count("*").alias("f"))
