"""A training-data pipeline over the documents table: toxicity, near-duplicates, benchmark leaks, personal data, pieces.

Every stage takes (spark, docs, sf_dir), works on all that its predecessor kept and returns a DataFrame that is written as Parquet
and read again before the next one. All but the last return the columns of documents.

Nulls and empty texts pass every stage (they score as clean, equal nothing, hold nothing). Rows that repeat an id and
a text are one; rows of one id with different texts, and rows without an id, are judged each by itself.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import wraps

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from privmatrix.llm import decontaminate, langid, near_dup, pieces, pii, toxicity
from privmatrix.llm.queries import piece_model, table
from privmatrix.llm.store import eased, written

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")
Stage = Callable[[SparkSession, DataFrame, str], DataFrame]


def _on_its_own(stage: Stage) -> Stage:
    """The stage, begun with a driver that holds nothing of its predecessor's plans."""

    @wraps(stage)
    def begun(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
        eased(spark)
        return stage(spark, docs, sf_dir)

    return begun


@_on_its_own
def toxicity_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that score at least 0.5 go. Labels are learned from the rows that are not held out."""
    labels = table(spark, sf_dir, "labels")
    net = toxicity.fit(docs, labels.where(~langid.held_out()).select("doc_id", "toxic"))
    return toxicity.score(docs, net, out="__score").where(F.col("__score") < 0.5).select(*COLUMNS)


@_on_its_own
def near_dup_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of five-word shingle similarity 0.8 or more, the document of smallest id stays."""
    return near_dup.kept_only(docs, near_dup.Options(words=5)).select(*COLUMNS)


@_on_its_own
def benchmark_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a benchmark item go."""
    return decontaminate.clean(docs, table(spark, sf_dir, "benchmark")).select(*COLUMNS)


@_on_its_own
def pii_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Personal data is replaced by its kind; n_chars is that of the new text."""
    return pii.redact(docs.select(*COLUMNS)).withColumn("n_chars", F.coalesce(F.length("text"), F.lit(0)).cast("long")).select(*COLUMNS)


@_on_its_own
def pieces_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document with its piece ids, their number, and whether decoding them gives its text back."""
    coded = pieces.code(docs.select(*COLUMNS), piece_model())
    return coded.select(*COLUMNS, "ids", F.coalesce(F.size("ids"), F.lit(0)).cast("long").alias("n_pieces"), F.col("decoded").eqNullSafe(F.col("text")).alias("round_trip"))


STAGES: list[tuple[str, Stage]] = [
    ("toxicity", toxicity_stage),
    ("near_dup", near_dup_stage),
    ("benchmark", benchmark_stage),
    ("pii", pii_stage),
    ("pieces", pieces_stage),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = written(stage(spark, docs, sf_dir), f"pipeline-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)


#: The network, SimHash and the piece transducer have no SQL form; a test compares near_dup with brute force, pii by its number of
#: rows and pieces by its round trips. The toxicity and benchmark stages are not compared on a table.
ORACLE_SQL: str | None = None
QUERIES = {"pipeline": run}
ORACLES: dict[str, str] = {}
