"""Origin-destination records with intermediate stops, from ordered locations or from one location per time frame."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from privmatrix.operators.cells import build_cells
from privmatrix.sources.spec import MatrixSpec


def ordered(df: DataFrame, unit: list[str], order: list[str], location: list[str]) -> DataFrame:
    """unit columns and ``stops``: array of (order.., location..), sorted; one trajectory per unit."""
    return df.groupBy(*unit).agg(F.array_sort(F.collect_list(F.struct(*order, *location))).alias("stops"))


def od_records(trips: DataFrame, location: list[str], stops: int = 0) -> DataFrame:
    """p{i}_{axis} for the first location, ``stops`` evenly placed ones in between, and the last; shorter trajectories are left out."""
    n, frames = F.size("stops"), stops + 2
    at = [(F.floor((n - 1) * i / (frames - 1)) + 1).cast("int") for i in range(frames)]
    columns = [F.element_at("stops", at[i])[c].alias(f"p{i}_{c}") for i in range(frames) for c in location]
    return trips.where(n >= frames).select(*[c for c in trips.columns if c != "stops"], *columns)


def od_cells(df: DataFrame, unit: list[str], order: list[str], location: list[str], spec: MatrixSpec, stops: int = 0) -> DataFrame:
    """The matrix of trajectories with ``stops`` intermediate stops: two axes more for each."""
    return build_cells(od_records(ordered(df, unit, order, location), location, stops), spec)


def ends(df: DataFrame, unit: list[str], order: list[str], location: list[str], least: int = 2) -> DataFrame:
    """First and last location of each unit with ``least`` records: constant state per unit, so no list is gathered."""
    key, place = F.struct(*order), F.struct(*location)
    both = df.groupBy(*unit).agg(F.count("*").alias("__n"), F.min_by(place, key).alias("a"), F.max_by(place, key).alias("b")).where(F.col("__n") >= least)
    return both.select(*unit, *[F.col(f"{s}.{c}").alias(f"p{i}_{c}") for i, s in enumerate("ab") for c in location])


def frames(df: DataFrame, unit: list[str], frame: Column, n_frames: int, order: list[str], location: list[str], pick: str = "first") -> DataFrame:
    """One location of each time frame (0..n-1) of a unit: its first or last; units without all frames are left out."""
    by = F.min_by if pick == "first" else F.max_by
    place, key = F.struct(*location), F.struct(*order)
    marked = df.withColumn("__frame", frame)
    found = marked.groupBy(*unit).agg(*[by(F.when(F.col("__frame") == k, place), F.when(F.col("__frame") == k, key)).alias(f"f{k}") for k in range(n_frames)])
    whole = found.where(" AND ".join(f"f{k} IS NOT NULL" for k in range(n_frames)))
    return whole.select(*unit, *[F.col(f"f{k}.{c}").alias(f"p{k}_{c}") for k in range(n_frames) for c in location])


def frame_cells(df: DataFrame, unit: list[str], frame: Column, n_frames: int, order: list[str], location: list[str], spec: MatrixSpec, pick: str = "first") -> DataFrame:
    return build_cells(frames(df, unit, frame, n_frames, order, location, pick), spec)


def legs(df: DataFrame, unit: list[str], order: list[str], location: list[str]) -> DataFrame:
    """Consecutive locations of each unit: from_{axis}, to_{axis} and whether another leg follows."""
    w = Window.partitionBy(*unit).orderBy(*order)
    from_, to = [F.lag(c).over(w).alias(f"from_{c}") for c in location], [F.col(c).alias(f"to_{c}") for c in location]
    listed = df.select(*unit, *order, *from_, *to, F.lead(order[0]).over(w).isNotNull().alias("goes_on"))
    return listed.where(F.col(f"from_{location[0]}").isNotNull())


def close_trips(df: DataFrame, unit: list[str], seconds: Column, span: int) -> DataFrame:
    """Each record with the number of the unit's records in the ``span`` seconds up to it, itself included."""
    w = Window.partitionBy(*unit).orderBy("__s").rangeBetween(-span, 0)
    return df.withColumn("__s", seconds.cast("long")).withColumn("recent", F.count("*").over(w)).drop("__s")
