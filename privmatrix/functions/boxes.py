"""Axis-aligned boxes, half-open: columns lo1,hi1..lod,hid; queries qlo1,qhi1..qlod,qhid."""

from __future__ import annotations

from functools import reduce
from operator import and_, mul

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def bounds(d: int, prefix: str = "") -> list[str]:
    return [f"{prefix}{side}{i}" for i in range(1, d + 1) for side in ("lo", "hi")]


def overlap1(i: int, a: str = "", b: str = "q") -> Column:
    """Length of the common part on one axis."""
    return F.greatest(F.lit(0), F.least(F.col(f"{a}hi{i}"), F.col(f"{b}hi{i}")) - F.greatest(F.col(f"{a}lo{i}"), F.col(f"{b}lo{i}")))


def overlap(d: int, a: str = "", b: str = "q") -> Column:
    """Entries that two boxes have in common, as a double."""
    return reduce(mul, [overlap1(i, a, b).cast("double") for i in range(1, d + 1)])


def overlaps(d: int, a: str = "", b: str = "q") -> Column:
    return reduce(and_, [(F.col(f"{a}lo{i}") < F.col(f"{b}hi{i}")) & (F.col(f"{b}lo{i}") < F.col(f"{a}hi{i}")) for i in range(1, d + 1)])


def disjoint(d: int, a: str = "", b: str = "q") -> Column:
    return ~overlaps(d, a, b)


def contains(d: int, a: str = "", b: str = "q") -> Column:
    """Box a holds all of box b."""
    return reduce(and_, [(F.col(f"{a}lo{i}") <= F.col(f"{b}lo{i}")) & (F.col(f"{b}hi{i}") <= F.col(f"{a}hi{i}")) for i in range(1, d + 1)])


def holds(d: int, box: str = "q") -> Column:
    """The box holds the entry x1..xd."""
    return reduce(and_, [(F.col(f"x{i}") >= F.col(f"{box}lo{i}")) & (F.col(f"x{i}") < F.col(f"{box}hi{i}")) for i in range(1, d + 1)])


def adjacent(d: int, a: str = "", b: str = "q") -> Column:
    """The boxes share a face: they touch on one axis and overlap on all others."""
    touch = [(F.col(f"{a}hi{i}") == F.col(f"{b}lo{i}")) | (F.col(f"{b}hi{i}") == F.col(f"{a}lo{i}")) for i in range(1, d + 1)]
    over = [overlap1(i, a, b) > 0 for i in range(1, d + 1)]
    return reduce(lambda x, y: x | y, [reduce(and_, [touch[i], *[over[j] for j in range(d) if j != i]]) for i in range(d)])


def volume(d: int, prefix: str = "") -> Column:
    return reduce(mul, [(F.col(f"{prefix}hi{i}") - F.col(f"{prefix}lo{i}")).cast("double") for i in range(1, d + 1)])


def even_index(x: Column, lo: Column | int, width: Column | int, m: Column | int) -> Column:
    """Which of m equal intervals of [lo, lo + width) holds x: the inverse of ``even_bound``."""
    as_long = lambda v: v.cast("long") if isinstance(v, Column) else F.lit(v).cast("long")
    lo, width, m = as_long(lo), as_long(width), as_long(m)
    return F.floor(((x.cast("long") - lo + 1) * m - 1) / width).cast("int")


def even_bound(j: Column, lo: Column | int, width: Column | int, m: Column | int) -> Column:
    """Lower end of the j-th of m equal intervals; exact in doubles up to products of 2**53."""
    return (lo + F.floor(j.cast("long") * width / m)).cast("int")


def array_view(df: DataFrame, d: int, prefix: str = "") -> DataFrame:
    """The box as array<struct<lo, hi>>, the same type for any d."""
    box = F.array(*[F.struct(F.col(f"{prefix}lo{i}").alias("lo"), F.col(f"{prefix}hi{i}").alias("hi")) for i in range(1, d + 1)])
    return df.select(*[c for c in df.columns if c not in bounds(d, prefix)], box.alias("box"))


def grid_domain(spark: SparkSession, widths: tuple[int, ...], granularity: DataFrame) -> DataFrame:
    """j1..jd and bounds of every box of a grid; ``granularity`` is one row m1..md.

    Boxes come from one distributed range and arithmetic on its number, so a grid of any size streams through the executors.
    """
    d = len(widths)
    total = reduce(mul, [F.col(f"m{i}").cast("long") for i in range(1, d + 1)])
    step = 1 << 14
    # the one row gives the numbers of blocks of boxes, which are dealt out before each is resolved into its boxes
    blocks = granularity.select("*", total.alias("__n")).select("*", F.explode(F.sequence(F.lit(0).cast("long"), F.floor((F.col("__n") - 1) / step))).alias("__b"))
    number = blocks.repartition(max(2, spark.sparkContext.defaultParallelism), "__b").select(*[f"m{i}" for i in range(1, d + 1)], F.explode(F.sequence(F.col("__b") * step, F.least((F.col("__b") + 1) * step, F.col("__n")) - 1)).alias("__k"))
    out, rest = number, F.col("__k")
    columns = []
    for i in range(d, 0, -1):
        m = F.col(f"m{i}").cast("long")
        columns.append((i, F.pmod(rest, m)))
        rest = F.floor(rest / m)
    for i, j in columns:
        out = out.withColumn(f"j{i}", j.cast("int"))
    for i, w in enumerate(widths, 1):
        out = out.withColumn(f"lo{i}", even_bound(F.col(f"j{i}"), 0, w, F.col(f"m{i}"))).withColumn(f"hi{i}", even_bound(F.col(f"j{i}") + 1, 0, w, F.col(f"m{i}")))
    return out.select(*[f"j{i}" for i in range(1, d + 1)], *bounds(d))
