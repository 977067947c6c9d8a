"""Frequency matrices as sparse tables: x1..xd and the count f of every non-empty entry."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from privmatrix.functions.noise import keyed_uniform
from privmatrix.sources.spec import MatrixSpec


def build_cells(df: DataFrame, spec: MatrixSpec, outside: str = "drop") -> DataFrame:
    """One record, one count in its entry; partial counts are made before the only shuffle."""
    return spec.index_columns(df, outside).groupBy(*spec.axes).agg(F.count("*").alias("f"))


def clustered(cells: DataFrame, d: int) -> DataFrame:
    """Cells in the order of their axes; those that agree on the first half of the axes are in one partition."""
    axes = [f"x{i}" for i in range(1, d + 1)]
    return cells.repartition(*axes[: max(1, d - d // 2)]).sortWithinPartitions(*axes)


def excluded(df: DataFrame, spec: MatrixSpec) -> DataFrame:
    """One row: records, and how many of them a null or out-of-domain coordinate keeps out."""
    outside = [dim.index().isNull() for dim in spec.dims]
    any_outside = outside[0]
    for x in outside[1:]:
        any_outside = any_outside | x
    return df.agg(F.count("*").alias("records"), F.count_if(any_outside).alias("excluded"))


def region(df: DataFrame, x: str, y: str, centre: tuple[float, float], side: float) -> DataFrame:
    """Records within a square around a centre, half-open; written on the raw columns, so the scan can prune."""
    (cx, cy), h = centre, side / 2
    return df.where((F.col(x) >= cx - h) & (F.col(x) < cx + h) & (F.col(y) >= cy - h) & (F.col(y) < cy + h))


def region_km(df: DataFrame, lat: str, lon: str, centre: tuple[float, float], side_km: float) -> DataFrame:
    """As ``region`` for degrees: a side in km around (lat, lon), by the length of a degree at the centre's latitude."""
    from math import cos, radians

    dlat = side_km / 111.195 / 2
    dlon = dlat / max(1e-9, cos(radians(centre[0])))
    return df.where((F.col(lat) >= centre[0] - dlat) & (F.col(lat) < centre[0] + dlat) & (F.col(lon) >= centre[1] - dlon) & (F.col(lon) < centre[1] + dlon))


def bound_contributions(df: DataFrame, unit: str, most: int, salt: str, *keys: str) -> DataFrame:
    """At most ``most`` records of each unit, chosen by keyed draws; the unit's sensitivity is then ``most``."""
    order = Window.partitionBy(unit).orderBy(keyed_uniform(salt, "sample", unit, *keys), *keys)
    return df.withColumn("__rank", F.row_number().over(order)).where(F.col("__rank") <= most).drop("__rank")


def prefix_rollup(cells: DataFrame, d: int) -> DataFrame:
    """Marginals on the first k axes for k = 0..d: depth k, null beyond it. One pass; each level is summed from cells."""
    axes = [f"x{i}" for i in range(1, d + 1)]
    depth = F.lit(d) - F.bit_count(F.grouping_id())
    return cells.rollup(*axes).agg(depth.cast("int").alias("depth"), F.sum("f").alias("f"))


def prefix_marginal(cells: DataFrame, k: int) -> DataFrame:
    """The marginal on the first k axes."""
    return cells.groupBy(*[f"x{i}" for i in range(1, k + 1)]).agg(F.sum("f").alias("f"))


def marginals(cells: DataFrame, d: int, sets: list[tuple[int, ...]] | None = None) -> DataFrame:
    """Grouping sets of the axes; by default every pair of axes. gid tells the set, axes outside it are null."""
    axes = [f"x{i}" for i in range(1, d + 1)]
    sets = sets or [(i, j) for i in range(1, d + 1) for j in range(i + 1, d + 1)]
    groups = [[F.col(f"x{i}") for i in s] for s in sets]
    return cells.groupingSets(groups, *[F.col(x) for x in axes]).agg(F.grouping_id().cast("long").alias("gid"), F.sum("f").alias("f"))


def density(cells: DataFrame, spec: MatrixSpec) -> DataFrame:
    """One row: records, occupied entries, share of the domain, largest entry, an estimate of distinct first coordinates."""
    return cells.agg(
        F.sum("f").alias("records"), F.count("*").alias("occupied"), (F.count("*") / float(spec.entries)).alias("share"), F.max("f").alias("largest"), F.approx_count_distinct("x1").alias("first_axis")
    )


def neighbour(df: DataFrame, row: DataFrame, add: bool = False) -> DataFrame:
    """``df`` without one row, or with one more: a neighbouring dataset."""
    return df.unionByName(row) if add else df.exceptAll(row)


def coarse(cells: DataFrame, index: dict[str, Column]) -> DataFrame:
    """Sums over coarser coordinates."""
    return cells.groupBy(*[c.alias(n) for n, c in index.items()]).agg(F.sum("f").alias("f"))
