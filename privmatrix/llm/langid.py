"""Language identification with a bit-sliced Bloom filter over n-grams.

Learning counts byte n-grams (3 and 4, over lower-cased letters and word bounds) of every training text, summed per
language in Spark. An n-gram belongs to the languages whose relative frequency of it is at least ``share`` of the largest;
each such pair sets the language's bit in ``hashes`` rows of one table of bitmasks. Looking an n-gram up ANDs its rows and so
returns all languages that contain it. A slot of n-grams longer than three stands for several. A text's score for a language is the number of its n-grams found, corrected for
the false positives that the filter's fill and shared slots make likely; the largest decides, ties go to the language first in the alphabet.

Null texts and texts without a letter get ``und`` and score 0, as does every text if nothing was learned. Whole texts are
read, whatever their length; repeated rows get equal predictions. ``predict`` keeps extra columns; a column named
like an output column is replaced.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from privmatrix.llm import textscan
from privmatrix.llm.store import written

SIZES = (3, 4)
SLOT_BITS = 18
ROW_BITS = 20
FLUSH_LANGUAGES = 16

#: Bytes as one of 64 symbols: 0 parts words, 1..26 are a..z, the rest stand for bytes of other letters.
_SYMBOL = np.zeros(256, np.uint32)
_SYMBOL[97:123] = np.arange(1, 27)
_SYMBOL[65:91] = np.arange(1, 27)
_SYMBOL[128:] = 27 + np.arange(128) % 37
_ASCII_LETTER = np.zeros(256, bool)
_ASCII_LETTER[65:91] = _ASCII_LETTER[97:123] = True


def _slots(symbols: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Slot of the n-gram at each position, and whether it counts (no two word bounds beside each other)."""
    m = len(symbols) - n + 1
    if m <= 0:
        return np.zeros(0, np.uint32), np.zeros(0, bool)
    key = np.zeros(m, np.uint32)
    blank, good = symbols == 0, np.ones(m, bool)
    for j in range(n):
        key = (key << np.uint32(6)) | symbols[j : j + m]
        if j:
            good &= ~(blank[j - 1 : j - 1 + m] & blank[j : j + m])
    if 6 * n > SLOT_BITS:
        key = (key * np.uint32(2654435761)) >> np.uint32(32 - SLOT_BITS)
    return key, good


def _rows(n: int, hashes: int) -> np.ndarray:
    """Filter rows of every slot of n-grams of length n: hashes x slots."""
    slots = np.arange(1 << SLOT_BITS, dtype=np.uint64) + np.uint64(n << 40)
    return np.stack([textscan.mix(slots * np.uint64(2 * j + 1) + np.uint64(j)) >> np.uint64(64 - ROW_BITS) for j in range(hashes)]).astype(np.int64)


@dataclass(frozen=True)
class LanguageFilter:
    """languages, for each n-gram size the languages' bits of every slot, as the filter returns them, and how often it wrongly says yes.

    An unseen n-gram finds all its rows set by chance; where n-grams share slots, it also meets a slot that the filter rightly holds.
    """

    languages: tuple[str, ...]
    masks: tuple[np.ndarray, ...]
    false_rate: np.ndarray


def count(df: DataFrame, text_col: str = "text", lang_col: str = "lang") -> DataFrame:
    """lang, size, slot, n: n-gram counts over all rows whose language is known; pre-aggregated in each task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[tuple[str, int], np.ndarray] = {}

        def out() -> Iterator[pa.RecordBatch]:
            for (lang, n), counts in held.items():
                at = np.flatnonzero(counts)
                yield pa.RecordBatch.from_arrays([pa.array([lang] * len(at), pa.string()), pa.array(np.full(len(at), n, np.int32)), pa.array(at.astype(np.int32)), pa.array(counts[at])], ["lang", "size", "slot", "n"])
            held.clear()

        for batch in batches:
            langs = np.array(textscan.string_column(batch, lang_col).to_pylist(), object)
            data, offsets = textscan.buffers(pc.utf8_lower(textscan.string_column(batch, text_col)))
            for lang in sorted(set(langs)):
                for row in np.flatnonzero(langs == lang).tolist():
                    symbols = _SYMBOL[data[offsets[row] : offsets[row + 1]]]
                    for n in SIZES:
                        key, good = _slots(symbols, n)
                        if (lang, n) not in held:
                            held[lang, n] = np.zeros(1 << SLOT_BITS, np.int64)
                        held[lang, n] += np.bincount(key[good], minlength=1 << SLOT_BITS) if len(key) > 200_000 else 0
                        if len(key) <= 200_000:
                            np.add.at(held[lang, n], key[good], 1)
                if len(held) >= 2 * FLUSH_LANGUAGES:
                    yield from out()
        yield from out()

    known = df.select(text_col, lang_col).where(F.col(text_col).isNotNull() & F.col(lang_col).isNotNull())
    return textscan.mapped(known, run, "lang string, size int, slot int, n long").groupBy("lang", "size", "slot").agg(F.sum("n").alias("n"))


def owned(counts: DataFrame, languages: list[str], share: float, least: float) -> DataFrame:
    """size, slot, mask: the bits of the languages (by their place in the list) to which a slot's n-grams belong; only slots with any."""
    totals = counts.groupBy("lang", "size").agg(F.sum("n").alias("all"))  # at most 64 languages x sizes
    freq = counts.join(F.broadcast(totals), ["lang", "size"]).withColumn("freq", F.col("n") / F.col("all"))
    bits = [x for i, lang in enumerate(languages) for x in (F.lit(lang), F.lit(int(np.uint64(1 << i).view(np.int64))))]
    bit = F.element_at(F.create_map(*bits), F.col("lang"))
    slots = freq.groupBy("size", "slot").agg(F.max("freq").alias("most"), F.collect_list(F.struct("freq", bit.alias("bit"))).alias("held"))  # at most 64 each
    mine = F.filter("held", lambda x: (x["freq"] >= share * F.col("most")) & (x["freq"] >= least))
    return slots.select("size", "slot", F.aggregate(mine, F.lit(0).cast("long"), lambda acc, x: acc.bitwiseOR(x["bit"])).alias("mask")).where("mask <> 0")


def learn(df: DataFrame, text_col: str = "text", lang_col: str = "lang", share: float = 0.5, least: float = 1e-6, hashes: int = 3) -> LanguageFilter:
    """The filter of all rows of ``df``. Slots' languages are told in Spark; a mask for each slot and n-gram size comes to the driver."""
    counts = written(count(df, text_col, lang_col), "language-counts")
    languages = sorted(r["lang"] for r in counts.select("lang").distinct().limit(65).collect())
    if len(languages) > 64:
        raise ValueError("the bitmasks hold 64 languages")
    table = np.zeros(1 << ROW_BITS, np.uint64)
    rows = {k: _rows(k, hashes) for k in SIZES}
    if languages:
        found = owned(counts, languages, share, least).toArrow()
        size, slot, mask = (found[c].to_numpy() for c in ("size", "slot", "mask"))
        for k in SIZES:
            here = size == k
            for j in range(hashes):
                np.bitwise_or.at(table, rows[k][j][slot[here]], mask[here].view(np.uint64))
    masks = tuple(np.bitwise_and.reduce(table[rows[k]], axis=0) for k in SIZES)
    bits = np.arange(len(languages), dtype=np.uint64)
    fill = np.array([np.mean(table >> i & np.uint64(1)) for i in bits])
    rates = [np.array([np.mean(m >> i & np.uint64(1)) for i in bits]) if 6 * k > SLOT_BITS else fill**hashes for k, m in zip(SIZES, masks)]
    return LanguageFilter(tuple(languages), masks, np.array(rates).reshape(len(SIZES), len(languages)))


def _scored(model: LanguageFilter, data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """Corrected popcounts: rows x languages."""
    symbols, rows = _SYMBOL[data], len(offsets) - 1
    score = np.zeros((rows, len(model.languages)))
    for n, masks, rate in zip(SIZES, model.masks, model.false_rate):
        hits, total = np.zeros_like(score), np.zeros(rows)
        key, good = _slots(symbols, n)
        a = np.minimum(offsets[:-1], len(key))
        b = np.maximum(a, np.minimum(offsets[1:] - n + 1, len(key)))  # an n-gram that runs into the next row is left out
        found = np.where(good, masks[key], np.uint64(0))
        for i, each in enumerate([*(found >> np.uint64(i) & np.uint64(1) for i in range(len(model.languages))), good]):
            sums = np.concatenate(([0], np.cumsum(each, dtype=np.int64)))
            if i < len(model.languages):
                hits[:, i] += sums[b] - sums[a]
            else:
                total += sums[b] - sums[a]
        score += (hits - total[:, None] * rate) / (1 - rate).clip(1e-9)
    return np.maximum(0, score)


def _has_letter(data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    sums = np.concatenate(([0], np.cumsum(_ASCII_LETTER[data], dtype=np.int64)))
    found = sums[offsets[1:]] > sums[offsets[:-1]]
    for row in np.flatnonzero(~found & (offsets[1:] > offsets[:-1])).tolist():
        found[row] = any(map(str.isalpha, bytes(data[offsets[row] : offsets[row + 1]]).decode(errors="replace")))
    return found


def predict(df: DataFrame, model: LanguageFilter, text_col: str = "text", out: tuple[str, str] = ("lang_pred", "score")) -> DataFrame:
    """``df`` with the predicted language and its share of the corrected counts (0 to 1)."""
    shared = df.sparkSession.sparkContext.broadcast(model)  # of a fixed size: one mask for each slot and n-gram size
    kept = [c for c in df.columns if c not in out]
    schema = T.StructType([df.schema[c] for c in kept] + [T.StructField(out[0], T.StringType()), T.StructField(out[1], T.DoubleType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = shared.value
        names = np.array([*model.languages, "und"], object)
        for batch in batches:
            data, offsets = textscan.buffers(pc.utf8_lower(textscan.string_column(batch, text_col)))
            for a, b, part, at in textscan.slices(data, offsets):
                if model.languages:
                    scores = _scored(model, part, at)
                    best, total = scores.argmax(axis=1), scores.sum(axis=1)
                    share = np.where(total > 0, scores.max(axis=1) / np.maximum(total, 1e-12), 0.0)
                else:
                    best, share = np.zeros(b - a, int), np.zeros(b - a)
                none = ~_has_letter(part, at) | (len(model.languages) == 0)
                best, share = np.where(none, len(model.languages), best), np.where(none, 0.0, share)
                rows = batch.slice(a, b - a)
                yield pa.RecordBatch.from_arrays([rows.column(rows.schema.get_field_index(c)) for c in kept] + [pa.array(names[best].tolist(), pa.string()), pa.array(share)], [*kept, *out])

    return textscan.mapped(df, run, schema)


def held_out(id_col: str = "doc_id") -> Column:
    """True for the fifth of the rows that nothing is learned from."""
    return F.crc32(F.col(id_col).cast("string")) % 5 == 0
