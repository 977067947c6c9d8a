"""Cheap tests of membership in a large id set, so that long texts are not shuffled for a join that keeps few of them.

A filter of a fixed number of bits (a Bloom filter with one hash) is built from the ids: each task sets bits, Spark merges them,
and the driver sees at most one word per 64 bits, a megabyte in all. It goes into plans as a scalar. Rows that the filter rules out are
surely not in the set; the others are settled by an exact join. A set so large that it fills the filter only makes it
useless, never wrong.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

BITS = 1 << 23


def _bit(key: Column) -> Column:
    return F.pmod(F.xxhash64(key.cast("long")), F.lit(BITS))


def maybe_in(ids: DataFrame, key: Column, id_col: str = "id") -> Column:
    """A condition on other rows that is true for every key in ``ids``, and for a few others."""
    spark = ids.sparkSession
    words = ids.select(_bit(F.col(id_col)).alias("b")).groupBy(F.floor(F.col("b") / 64).alias("word")).agg(F.expr("bit_or(shiftleft(1L, cast(b % 64 as int)))").alias("bits")).toArrow()
    dense = np.zeros(BITS // 64, np.int64)
    dense[words["word"].to_numpy()] = words["bits"].to_numpy()
    bits = spark.createDataFrame([(dense.tolist(),)], "bits array<long>").scalar()
    at = _bit(key)
    word = F.element_at(bits, (F.floor(at / 64) + 1).cast("int"))
    return F.coalesce(F.call_function("getbit", word, (at % 64).cast("int")) == 1, F.lit(False))


def row_key(id_col: str, text_col: str) -> Column:
    """A row's own key, a 64-bit hash of its id and text; a null and an empty text differ, as do a null id and any other."""
    return F.xxhash64(F.col(id_col).isNull(), F.col(id_col), F.col(text_col).isNull(), F.col(text_col))


def only(df: DataFrame, ids: DataFrame, key: str, id_col: str = "id") -> DataFrame:
    """The rows of ``df`` whose key is in ``ids``."""
    wanted = ids.select(F.col(id_col).cast("long").alias("__wanted")).distinct()
    near = df.where(maybe_in(wanted, F.col(key), "__wanted"))
    return near.join(wanted, near[key] == wanted["__wanted"], "left_semi")


def without(df: DataFrame, ids: DataFrame, key: str, id_col: str = "id", single: DataFrame | None = None) -> DataFrame:
    """The rows of ``df`` whose key is not in ``ids``; of rows whose key is in ``single`` one stays."""
    gone = ids.select(F.col(id_col).cast("long").alias("__gone")).distinct()
    suspects = gone if single is None else gone.unionByName(single.select(F.col(id_col).cast("long").alias("__gone")))
    suspect = maybe_in(suspects, F.col(key), "__gone")
    clear, near = df.where(~suspect), df.where(suspect)
    kept = near.join(gone, near[key] == gone["__gone"], "left_anti")
    if single is not None:
        kept = kept.dropDuplicates([key])
    return clear.unionByName(kept)
