"""The queries opN_<name> and the pipeline's, with their SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from privmatrix.llm import decontaminate, html_text, langid, lm_score, near_dup, neighbours, pieces, pii, toxicity, url_filter

PIECE_MODEL = "/opt/tokenizers/piece_bpe_32k.model"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def piece_model(path: str = PIECE_MODEL) -> bytes:
    """A vocabulary file, read on the driver."""
    with open(path, "rb") as f:
        return f.read()


def op1_near_dup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dup.groups(table(spark, sf_dir, "documents"))


def op2_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.judged(table(spark, sf_dir, "documents").select("doc_id", "text"), table(spark, sf_dir, "benchmark"))


def op3_pieces(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, n_pieces, ids_sha256 (of the comma-joined ids) and whether decoding gives the text back."""
    model = piece_model()
    coded = pieces.code(table(spark, sf_dir, "documents").select("doc_id", "text"), model)
    return coded.select(
        "doc_id",
        F.coalesce(F.size("ids"), F.lit(0)).cast("long").alias("n_pieces"),
        F.sha2(F.array_join(F.col("ids").cast("array<string>"), ","), 256).alias("ids_sha256"),
        F.col("decoded").eqNullSafe(F.col("text")).alias("round_trip"),
    )


def op4_urls(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_filter.judge(table(spark, sf_dir, "pages").select("page_id", "url", "html")).select("page_id", "host", "path", "rule", "verdict", "basis")


def op5_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = langid.learn(docs.where(~langid.held_out()).select("text", "lang"))
    return langid.predict(docs.select("doc_id", "text"), model).select("doc_id", langid.held_out().alias("held_out"), "lang_pred", "score")


def op6_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.digest(table(spark, sf_dir, "documents"))


def op7_html(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = html_text.main_text(table(spark, sf_dir, "pages").select("page_id", "url", "html"))
    return pages.select("page_id", "url", "text", F.length("text").cast("long").alias("n_chars"))


def op8_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    net = toxicity.fit(docs, labels.where(~langid.held_out()).select("doc_id", "toxic"))
    scored = toxicity.score(docs.select("doc_id", "text"), net)
    return scored.select("doc_id", langid.held_out().alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def op9_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    return neighbours.search(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 100 == 0)


def op10_lm(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    words = lm_score.vocabulary(lm_score.count(docs), docs)
    scored = lm_score.score(docs, words, lm_score.train(docs, words))
    return scored.select("doc_id", "n_words", "log_prob", "log_unigram", F.coalesce(F.try_divide("log_prob", F.col("n_words").cast("double")), F.lit(0.0)).alias("per_word"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {"op1_near_dup": op1_near_dup, "op2_decontaminate": op2_decontaminate, "op3_pieces": op3_pieces, "op4_urls": op4_urls, "op5_language": op5_language, "op6_pii": op6_pii, "op7_html": op7_html, "op8_toxicity": op8_toxicity, "op9_neighbours": op9_neighbours, "op10_lm": op10_lm}
ORACLES: dict[str, str] = {"op4_urls": url_filter.oracle(), "op6_pii": pii.oracle()}
