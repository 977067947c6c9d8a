"""The matrices of the experiment workloads on the given tables: public domains and how records come to be."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from privmatrix.operators import trajectories
from privmatrix.operators.cells import build_cells
from privmatrix.sources.spec import DimSpec, MatrixSpec
from privmatrix.sources.tables import load

SHIP_DAY = "datediff(to_date(l_shipdate), date'1995-01-01')"
EVENT_SECOND = "timestampdiff(MICROSECOND, timestamp_ntz'2024-01-01 00:00:00', ts) / 1000000.0D"
PRICE = DimSpec("price", "l_extendedprice", 0, 105000, 1000)
SOURCES = tuple(f"src{i}" for i in range(20))
ROLES = ("system", "user", "assistant")

LINE = (
    DimSpec("quantity", "l_quantity", 1, 51, 10),
    DimSpec("price", "l_extendedprice", 0, 105000, 10),
    DimSpec("discount", "l_discount", -0.005, 0.105, 11),
    DimSpec("tax", "l_tax", -0.005, 0.085, 9),
    DimSpec("ship_day", SHIP_DAY, 0, 2520, 10),
    DimSpec("line", "l_linenumber", 1, 8, 7),
)
ORIGIN = (DimSpec("s_nation", "s_nationkey", 0, 25, 25), DimSpec("s_balance", "s_acctbal", -1000, 10000, 20))
STOP = (DimSpec("p_size", "p_size", 1, 51, 10), DimSpec("p_price", "p_retailprice", 900, 1000, 10))
TARGET = (DimSpec("c_nation", "c_nationkey", 0, 25, 25), DimSpec("c_balance", "c_acctbal", -1000, 10000, 20))


def _steps(n: int, cells: int) -> tuple[DimSpec, ...]:
    return tuple(d for i in range(n) for d in (DimSpec(f"value{i}", f"p{i}_value", 0, 600, cells), DimSpec(f"k{i}", f"p{i}_k", 0, 100, cells)))


SPECS = {
    "price2": MatrixSpec("price2", (DimSpec("quantity", "l_quantity", 1, 51, 50), PRICE)),
    "ship2": MatrixSpec("ship2", (DimSpec("ship_day", SHIP_DAY, 0, 2520, 1000), PRICE)),
    "clock2": MatrixSpec("clock2", (DimSpec("second", EVENT_SECOND, 0, 2592000, 1000), DimSpec("value", "value", 0, 600, 1000))),
    **{f"line{d}": MatrixSpec(f"line{d}", LINE[:d]) for d in range(1, 7)},
    **{f"vec{d}": MatrixSpec(f"vec{d}", tuple(DimSpec(f"e{i}", f"embedding[{i}]", -0.6, 0.6, 30) for i in range(d))) for d in range(2, 7)},
    "od4": MatrixSpec("od4", ORIGIN + TARGET),
    "od6": MatrixSpec("od6", ORIGIN + STOP + TARGET),
    "traj4": MatrixSpec("traj4", _steps(2, 20), "user-day"),
    "traj6": MatrixSpec("traj6", _steps(3, 10), "user-day"),
    "docs2": MatrixSpec("docs2", (DimSpec("n_chars", "n_chars", 0, 150000, 100), DimSpec("source", "source", values=SOURCES))),
    "quality2": MatrixSpec("quality2", (DimSpec("n_chars", "n_chars", 0, 150000, 20), DimSpec("quality", "quality", 0, 2, 2))),
    "conv3": MatrixSpec("conv3", tuple(DimSpec(f"role{t}", f"r{t}", values=ROLES) for t in (1, 2, 3)), "conversation"),
    "pages1": MatrixSpec("pages1", (DimSpec("length", "length(html)", 0, 80000, 100),)),
    "bench1": MatrixSpec("bench1", (DimSpec("length", "length(text)", 0, 500, 50),)),
}


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events with their day, hour and the number in props."""
    return load(spark, sf_dir, "events").select("event_id", "user_id", "ts", "value", F.get_json_object("props", "$.k").cast("int").alias("k"), F.to_date("ts").alias("day"), F.hour("ts").alias("hour"))


def trips(spark: SparkSession, sf_dir: str, stop: bool = False) -> DataFrame:
    """Deliveries from suppliers to customers, with the part as a stop between. Small tables are broadcast where their size allows."""
    lines = load(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey", "l_partkey", "l_linenumber")
    orders = load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    customers = load(spark, sf_dir, "customer").select("c_custkey", "c_nationkey", "c_acctbal")
    suppliers = load(spark, sf_dir, "supplier").select("s_suppkey", "s_nationkey", "s_acctbal")
    out = lines.join(suppliers, F.col("l_suppkey") == F.col("s_suppkey")).join(orders, F.col("l_orderkey") == F.col("o_orderkey")).join(customers, F.col("o_custkey") == F.col("c_custkey"))
    if stop:
        parts = load(spark, sf_dir, "part").select("p_partkey", "p_size", "p_retailprice")
        out = out.join(parts, F.col("l_partkey") == F.col("p_partkey"))
    return out


def records(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """The records whose entries the named matrix counts."""
    base = name.rstrip("0123456789")
    if base in ("price", "ship", "line", "partsupp"):
        return load(spark, sf_dir, "lineitem")
    if base == "clock":
        return load(spark, sf_dir, "events")
    if base == "vec":
        return load(spark, sf_dir, "embeddings")
    if base == "od":
        return trips(spark, sf_dir, name == "od6")
    if name == "traj4":
        return trajectories.ends(events(spark, sf_dir), ["user_id", "day"], ["ts", "event_id"], ["value", "k"])
    if name == "traj6":
        return trajectories.frames(events(spark, sf_dir), ["user_id", "day"], F.floor(F.col("hour") / 8), 3, ["ts", "event_id"], ["value", "k"])
    if base == "docs":
        return load(spark, sf_dir, "documents")
    if base == "quality":
        return load(spark, sf_dir, "documents").select("doc_id", "n_chars").join(load(spark, sf_dir, "labels"), "doc_id", "left")
    if base == "conv":
        turns = load(spark, sf_dir, "conversations")
        return turns.groupBy("conv_id").agg(*[F.max(F.when(F.col("turn") == t, F.col("role"))).alias(f"r{t}") for t in (1, 2, 3)])
    return load(spark, sf_dir, {"pages": "pages", "bench": "benchmark"}[base])


def spec(spark: SparkSession, sf_dir: str, name: str) -> MatrixSpec:
    """The public domain; key ranges of ``partsupp2`` are those of the catalogue, which is public."""
    if name == "partsupp2":
        n_parts, n_suppliers = (load(spark, sf_dir, t).count() for t in ("part", "supplier"))
        return MatrixSpec("partsupp2", (DimSpec("part", "l_partkey", 0, n_parts, 1000), DimSpec("supplier", "l_suppkey", 0, n_suppliers, 1000)))
    return SPECS[name]


def cells(spark: SparkSession, sf_dir: str, name: str) -> tuple[DataFrame, MatrixSpec]:
    domain = spec(spark, sf_dir, name)
    return build_cells(records(spark, sf_dir, name), domain), domain
