"""Scans: the given tables with a schema check, declared readers, catalog tables and SQL, file streams, keyed samples."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from privmatrix.functions.noise import keyed_uniform

#: Columns of the given tables.
SCHEMAS = {
    "region": "r_regionkey int, r_name string",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
    "customer": "c_custkey long, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string",
    "supplier": "s_suppkey long, s_name string, s_nationkey int, s_acctbal double",
    "part": "p_partkey long, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
    "orders": "o_orderkey long, o_custkey long, o_orderstatus string, o_totalprice double, o_orderdate timestamp_ntz, o_orderpriority string",
    "lineitem": "l_orderkey long, l_partkey long, l_suppkey long, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp_ntz",
    "events": "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string",
    "documents": "doc_id long, text string, lang string, source string, n_chars long",
    "labels": "doc_id long, quality int, toxic int",
    "embeddings": "vec_id long, embedding array<float>, label int",
    "pages": "page_id long, url string, html string",
    "benchmark": "item_id long, text string",
    "conversations": "conv_id long, turn long, role string, text string",
}


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table; raises where a declared column is missing or has another type (integer widths may differ)."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    whole = ("int", "bigint", "smallint", "tinyint")
    found = dict(df.dtypes)
    for field in T.StructType.fromDDL(SCHEMAS[name]).fields:
        kind, want = found.get(field.name), field.dataType.simpleString()
        if kind != want and not (kind in whole and want in whole):
            raise ValueError(f"{name}.{field.name}: {kind}, not {want}")
    return df


def read(spark: SparkSession, path: str, schema: str, kind: str = "csv", **options: str) -> DataFrame:
    """csv, json, orc or parquet files with a declared schema; nothing is inferred."""
    return spark.read.schema(schema).options(**options).format(kind).load(path)


def relation(spark: SparkSession, text: str) -> DataFrame:
    """A catalog table or view by name, or the result of a SQL text."""
    return spark.sql(text) if " " in text.strip() else spark.table(text.strip())


def event_stream(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """A file stream of events; ``ts`` becomes a timestamp with time zone rules, which watermarks need."""
    stream = spark.readStream.schema(SCHEMAS["events"]).option("maxFilesPerTrigger", files_per_trigger).parquet(path)
    return stream.withColumn("ts", F.col("ts").cast("timestamp"))


def keyed_share(df: DataFrame, share: float, salt: str, *keys: str) -> DataFrame:
    """About ``share`` of the rows, the same ones whatever the partitioning: those whose keyed draw is below it."""
    return df.where(keyed_uniform(salt, "sample", *keys) < share)


def keyed_sample(df: DataFrame, n: int, salt: str, *keys: str) -> DataFrame:
    """The n rows of smallest keyed draw (all rows if there are fewer); a bounded top-n in every task, then one merge."""
    return df.withColumn("__u", keyed_uniform(salt, "sample", *keys)).orderBy("__u", *keys).limit(n).drop("__u")
