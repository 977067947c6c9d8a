"""Benchmark decontamination, with DataFrame functions only.

For every benchmark item, windows of the item's number of words are fingerprinted (128-bit SimHash of their words, each as often as it
occurs). Fingerprints are cut into one block more than the search radius has bits, so any two within the radius agree on a whole
block: joining windows and items of the same size on (block number, block value) finds all of them. What is within the radius is
verified by the exact weighted Jaccard similarity of the word shingles; a shingle weighs its number of occurrences times the logarithm of
one plus the number of items over the number of items that hold it.

An edited word changes one feature of a fingerprint but several shingles, so windows at a similarity of 0.8 to an item differ from it in 8 to 17
of 128 bits on average. The radius of 22 leaves out few of them (a test measures how many), while of unrelated fingerprints two fifths
share a block. A window without a shingle in common with any item cannot reach a similarity above 0, so only windows that align
one of their shingles with an item's are fingerprinted: every place of every text is looked up among the items' shingles. Only
positions are joined there; words are fetched for the texts that hold a window. A window that runs over a text's bounds is cut there.

Words are runs of letters and digits, lower-cased. A text or item of fewer than ``shingle`` words is one shingle; null texts and
texts without a word never match, nor do such items. Rows that repeat an item's id and words are one item; rows of one id with other
words are searched each and reported under the id, on both sides. Extra columns are ignored; empty tables
give no hits.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from privmatrix.llm.membership import only, row_key, without
from privmatrix.llm.store import eased, written

SHINGLE, THRESHOLD = 5, 0.8
RADIUS = 22
HASHES, BITS = 2, 64
BROADCAST_ROWS = 1_000_000  # of items' shingles and blocks (40 bytes each); beyond it they are joined by a shuffle
DIGITS = 9


def words(text: Column) -> Column:
    return F.filter(F.split(F.lower(text), r"[^\p{L}\p{N}]+"), lambda x: x != "")


def _coded(text: Column) -> Column:
    """64-bit hashes of a text's words, in order."""
    return F.transform(words(text), lambda x: F.xxhash64(x))


def _grams(w: str, n: int) -> Column:
    """Hashes of the n-word shingles of the array column w of coded words, in order; a shingle's length is part of its hash."""
    each = ", ".join(f"{w}[i + {j}]" if j else f"{w}[i]" for j in range(n))
    return F.expr(f"transform(sequence(0, size({w}) - {n}), i -> xxhash64({n}, {each}))")


def _shingles(w: str, k: int) -> Column:
    out = F.expr("cast(array() as array<bigint>)")
    for n in range(1, k + 1):
        enough = F.size(w) >= n if n == k else F.size(w) == n
        out = F.when(enough, _grams(w, n)).otherwise(out)
    return out


def _fingerprints(words_: DataFrame, keys: list[str], prefix: str = "fp") -> DataFrame:
    """keys, fp0, fp1 from rows (keys, word): a bit is set if most words' hashes set it. A sum counts the words of two bits, one in each half."""
    hashed = words_.select(*keys, *[F.expr(f"xxhash64({i}, word)").alias(f"__h{i}") for i in range(HASHES)])
    counted = hashed.groupBy(*keys).agg(F.count("*").alias("__n"), *[F.expr(f"sum(shiftrightunsigned(__h{i}, {b}) & 4294967297L)").alias(f"__{i}_{b}") for i in range(HASHES) for b in range(BITS // 2)])
    set_ = "if(({0}) * 2 > __n, {1}L, 0L)".format
    packed = [" | ".join(set_(f"__{i}_{b} & 4294967295L", 1 << b) + " | " + set_(f"shiftrightunsigned(__{i}_{b}, 32)", _signed(1 << b + BITS // 2)) for b in range(BITS // 2)) for i in range(HASHES)]
    return counted.select(*keys, *[F.expr(x).alias(f"{prefix}{i}") for i, x in enumerate(packed)])


def _signed(mask: int) -> int:
    return mask - (1 << BITS) if mask >> BITS - 1 else mask


def _blocks(prefix: str, radius: int) -> Column:
    """radius + 1 blocks: block k holds every (radius + 1)-th bit from bit k on of the fingerprint."""
    own = [[_signed(sum(1 << b for b in range(BITS) if (i * BITS + b) % (radius + 1) == k)) for i in range(HASHES)] for k in range(radius + 1)]
    each = ", ".join(f"named_struct('no', {k}, " + ", ".join(f"'value{i}', {prefix}{i} & {m}L" for i, m in enumerate(masks)) + ")" for k, masks in enumerate(own))
    return F.expr(f"array({each})")


def hits(docs: DataFrame, items: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text", shingle: int = SHINGLE, threshold: float = THRESHOLD, radius: int = RADIUS) -> DataFrame:
    """doc, item, start (of the best window, in words), similarity: one row for each document and item at or above the threshold."""
    item = items.select(F.col(item_col).alias("name"), _coded(F.col(item_text_col)).alias("w")).where(F.size("w") > 0).distinct()
    item = written(item.select(F.xxhash64("name", "w").alias("item"), "name", "w", F.size("w").alias("size"), _shingles("w", shingle).alias("grams")), "benchmark-items")
    places = written(item.select("item", "size", F.posexplode("grams").alias("at", "gram")), "benchmark-shingles")
    n_items = item.count()
    few = places.count() + (radius + 1) * n_items <= BROADCAST_ROWS
    small = F.broadcast if few else (lambda df: df)
    weights = places.select("gram", "item").distinct().groupBy("gram").agg(F.log(1 + F.lit(float(n_items)) / F.count("*")).alias("weight"))
    weights = written(weights, "benchmark-weights")
    item_bags = places.groupBy("item", "size", "gram").agg(F.count("*").alias("n")).join(weights, "gram")
    anchors = places.select("gram", "size", "at").distinct()

    texts = docs.select(F.col(id_col).alias("doc"), row_key(id_col, text_col).alias("row"), F.col(text_col).alias("text"))
    split = texts.select("row", _coded(F.col("text")).alias("w"))
    lengths = [r[0] for r in places.where(F.col("size") < shingle).select("size").distinct().collect()]  # at most shingle - 1 rows
    looked = [split.select("row", F.size("w").alias("len"), F.posexplode(_shingles("w", shingle)).alias("pos", "gram"))]
    looked += [split.where(F.size("w") > n).select("row", F.size("w").alias("len"), F.posexplode(_grams("w", n)).alias("pos", "gram")) for n in sorted(lengths)]
    low, high = F.greatest(F.col("pos") - F.col("at"), F.lit(0)), F.least(F.col("pos") - F.col("at") + F.col("size"), F.col("len"))
    spans = reduce(DataFrame.unionByName, [part.join(small(anchors), "gram").select("row", "size", low.alias("start"), high.alias("stop")) for part in looked])
    spans = written(spans.distinct(), "window-places")
    held = only(texts, spans, "row", "row").dropDuplicates(["row"]).select("doc", "row", _coded(F.col("text")).alias("w"))
    cut = spans.join(held, "row").select("doc", "row", "size", "start", F.slice("w", F.col("start") + 1, F.col("stop") - F.col("start")).alias("w"))
    cut = written(cut, "windows")

    keys = ["doc", "row", "size", "start"]
    bags = cut.select(*keys, F.explode(_shingles("w", shingle)).alias("gram")).groupBy(*keys, "gram").agg(F.count("*").alias("n"))
    bags = written(bags.join(small(weights), "gram", "left").withColumn("weight", F.coalesce("weight", F.lit(0.0) + F.log(F.lit(1.0 + n_items)))), "window-shingles")
    mass = F.col("n") * F.col("weight")
    window_mass = bags.groupBy(*keys).agg(F.sum(mass).alias("window_mass"))
    item_mass = item_bags.groupBy("item").agg(F.sum(mass).alias("item_mass"))

    left = written(_fingerprints(cut.select(*keys, F.explode("w").alias("word")), keys), "window-prints").select("*", F.explode(_blocks("fp", radius)).alias("block"))
    right = _fingerprints(item.select("item", "size", F.explode("w").alias("word")), ["item", "size"], "own")
    right = written(right.select("*", F.explode(_blocks("own", radius)).alias("block")), "benchmark-blocks")
    eased(docs.sparkSession)  # the prints' sums make the largest plans
    apart = sum((F.bit_count(F.col(f"fp{i}").bitwiseXOR(F.col(f"own{i}"))) for i in range(HASHES)), F.lit(0))
    near = left.join(small(right), ["size", "block"]).where(apart <= radius).select(*keys, "item").distinct()
    common = near.join(bags, keys).join(small(item_bags.select("item", "gram", F.col("n").alias("item_n"))), ["item", "gram"])
    both = common.groupBy(*keys, "item").agg(F.sum(F.least("n", "item_n") * F.col("weight")).alias("both"))
    verified = both.join(window_mass, keys).join(small(item_mass), "item")
    verified = verified.withColumn("similarity", F.round(F.col("both") / (F.col("window_mass") + F.col("item_mass") - F.col("both")), DIGITS)).where(F.col("similarity") >= threshold)
    named = verified.join(small(item.select("item", "name")), "item").select("doc", F.col("name").alias("item"), "start", "similarity")
    return named.groupBy("doc", "item").agg(F.max("similarity").alias("similarity"), F.min_by("start", F.struct(-F.col("similarity"), "start")).alias("start"))


def judged(docs: DataFrame, items: DataFrame, id_col: str = "doc_id", **options) -> DataFrame:
    """One row per document: whether it holds a benchmark item, how many, which, and the best similarity."""
    found = hits(docs, items, id_col, **options).groupBy("doc").agg(F.count("*").alias("n_items"), F.array_join(F.transform(F.array_sort(F.collect_list("item")), lambda x: x.cast("string")), ",").alias("item_ids"), F.max("similarity").alias("similarity"))
    return docs.select(id_col).join(found, F.col(id_col) == F.col("doc"), "left").select(
        id_col, F.col("doc").isNotNull().alias("contaminated"), F.coalesce("n_items", F.lit(0)).cast("long").alias("n_items"), F.coalesce("item_ids", F.lit("")).alias("item_ids"), F.coalesce("similarity", F.lit(0.0)).alias("similarity")
    )


def clean(docs: DataFrame, items: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """``docs`` without the documents that hold a benchmark item. Rows are judged, not ids, so null and repeated ids do no harm."""
    rows = docs.withColumn("__row", row_key(id_col, text_col))
    found = written(hits(rows, items, "__row", text_col, **options).select(F.col("doc").alias("id")), "contaminated")
    return without(rows, found, "__row").select(docs.columns)
