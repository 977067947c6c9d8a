"""Masked pseudo-likelihood: a bidirectional window network predicts every word from its neighbours on both sides.

Words are hashed to a fixed number of buckets, whose counts over all texts are summed in Spark. The most frequent buckets are
classes of their own; another bucket's class is the frequent word that it stands beside most often for that word's frequency. The network
gives each class's probability from the words around the place: every place of the window has an embedding for each context symbol, their
sum is the hidden vector, and a softmax layer scores the classes by it. A bucket has its share of its class by the counts, so that
probabilities over all buckets sum to 1. A text's score is the sum of the log-probabilities of its words.

The network is trained in numpy on all places of all texts. It starts from the best low-rank fit of the pointwise mutual information of
context symbols and classes, whose co-occurrence counts Spark sums. Each round then sums the gradient of the log-likelihood and the
hidden vectors' second moments over all places, and takes the step that maximises the softmax layer's quadratic lower bound, which never lowers the
likelihood. All that is learned is made of sums over places, so it doesn't depend on how texts are dealt out. What is gathered so grows with
the corpus, while what comes to the driver (a row for each bucket, for each symbol and class, for each weight) has a fixed size.

Null and empty texts have no words and score 0. Whole texts are scored, in slices that bound memory. Equal texts get equal
scores, but for rounding. ``score`` keeps extra columns; a column named like an output column is replaced.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from privmatrix.llm import textscan

BUCKET_BITS = 18
OWN = 95  # classes of one bucket
BESIDE = 48  # frequent words that give other buckets their classes
CLASSES = OWN + BESIDE + 1  # the last: buckets that stand beside none
SYMBOLS = 4096  # context symbols: own classes, the bound of a text, hashed others
REACH, HIDDEN = 2, 32
ROUNDS = 1
DAMP = 0.45  # neighbours' evidence overlaps, so the parts of a hidden vector count less than alone
BLOCK = 8192


@dataclass(frozen=True)
class Vocabulary:
    log_share: np.ndarray  # of each bucket in its class
    log_unigram: np.ndarray  # of each bucket
    label: np.ndarray  # class of each bucket
    symbol: np.ndarray  # context symbol of each bucket
    class_prior: np.ndarray


@dataclass(frozen=True)
class Weights:
    embedding: np.ndarray  # places of the window x SYMBOLS x HIDDEN
    out: np.ndarray  # CLASSES x (HIDDEN + 1), the last for the bias

    def hidden(self, context: np.ndarray) -> np.ndarray:
        out = np.ones((len(context), HIDDEN + 1), np.float32)
        out[:, :HIDDEN] = self.embedding[0][context[:, 0]]
        for k in range(1, 2 * REACH):
            out[:, :HIDDEN] += self.embedding[k][context[:, k]]
        return out

    def judged(self, context: np.ndarray, label: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Log-probability of each place's class, probabilities of all classes, hidden vectors."""
        h = self.hidden(context)
        z = h @ self.out.T
        z -= z.max(axis=1, keepdims=True)
        own = z[np.arange(len(z)), label]
        np.exp(z, out=z)
        total = z.sum(axis=1)
        return own - np.log(total), z / total[:, None], h


def buckets(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Bucket of each word, and each row's first word."""
    words = textscan.Words(data, offsets)
    return (words.hashes() >> np.uint64(64 - BUCKET_BITS)).astype(np.int32), words.first


def _blocks(batches: Iterator[pa.RecordBatch], text_col: str, symbol: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(bucket, context) of all places, by blocks."""
    for batch in batches:
        data, offsets = textscan.buffers(textscan.string_column(batch, text_col))
        for _, _, part, at in textscan.slices(data, offsets):
            bucket, first = buckets(part, at)
            for a in range(0, len(bucket), 16 * BLOCK):
                places = np.arange(a, min(len(bucket), a + 16 * BLOCK))
                yield bucket[places], contexts(symbol[bucket], first, places)


def contexts(symbol: np.ndarray, first: np.ndarray, places: np.ndarray) -> np.ndarray:
    """Symbols around each place, nearest last on the left and first on the right; OWN stands beyond a text's bounds."""
    row = np.searchsorted(first, places, "right") - 1
    low, high = first[row], first[row + 1]
    out = np.empty((len(places), 2 * REACH), np.int32)
    for k, shift in enumerate([*range(-REACH, 0), *range(1, REACH + 1)]):
        at = places + shift
        inside = (at >= low) & (at < high)
        out[:, k] = np.where(inside, symbol[np.where(inside, at, 0)], OWN)
    return out


def count(df: DataFrame, text_col: str = "text") -> DataFrame:
    """bucket, n over all texts; summed in each task before the shuffle."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(1 << BUCKET_BITS, np.int64)
        for batch in batches:
            data, offsets = textscan.buffers(textscan.string_column(batch, text_col))
            for _, _, part, at in textscan.slices(data, offsets):
                total += np.bincount(buckets(part, at)[0], minlength=1 << BUCKET_BITS)
        seen = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(seen.astype(np.int32)), pa.array(total[seen])], ["bucket", "n"])

    return textscan.mapped(df.select(text_col), run, "bucket int, n long").groupBy("bucket").agg(F.sum("n").alias("n"))


def _summed(df: DataFrame, text_col: str, symbol: np.ndarray, size: int, add: Callable, known: object, kind: type) -> DataFrame:
    """at, n: the cells of the sums that ``add(cells, bucket, context, known)`` makes over all places; each task sums its own before the shuffle."""
    shared = df.sparkSession.sparkContext.broadcast((symbol, known))  # of a fixed size

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        symbol, known = shared.value
        total = np.zeros(size, kind)
        for bucket, context in _blocks(batches, text_col, symbol):
            add(total, bucket, context, known)
        seen = np.flatnonzero(total)
        for a in range(0, len(seen), 1 << 16):
            at = seen[a : a + (1 << 16)]
            yield pa.RecordBatch.from_arrays([pa.array(at.astype(np.int32)), pa.array(total[at].astype(np.float64 if kind is np.float64 else np.int64))], ["at", "n"])

    schema = f"at int, n {'double' if kind is np.float64 else 'long'}"
    return textscan.mapped(df.select(text_col), run, schema).groupBy("at").agg(F.sum("n").alias("n"))


def _dense(found: pa.Table, size: int) -> np.ndarray:
    out = np.zeros(size)
    out[found["at"].to_numpy()] = found["n"].to_numpy()
    return out


def vocabulary(counts: DataFrame, df: DataFrame, text_col: str = "text") -> Vocabulary:
    """From one row for each bucket at most, and another for its class."""
    found = counts.toArrow()
    n = np.ones(1 << BUCKET_BITS)  # one more than counted, so that no word is impossible
    n[found["bucket"].to_numpy()] += found["n"].to_numpy()
    index = np.arange(1 << BUCKET_BITS)
    top = np.lexsort((index, -n))[:OWN]
    symbol = (OWN + 1 + textscan.mix(index.astype(np.uint64) + np.uint64(1 << 32)) % np.uint64(SYMBOLS - OWN - 1)).astype(np.int32)
    symbol[top] = np.arange(OWN)

    def beside(total: np.ndarray, bucket: np.ndarray, context: np.ndarray, known: None) -> None:
        for k in range(2 * REACH):
            near = np.flatnonzero(context[:, k] < BESIDE)
            cells, times = np.unique(bucket[near] * BESIDE + context[near, k], return_counts=True)
            total[cells] += times.astype(np.int32)

    pairs = _summed(df, text_col, symbol, BESIDE << BUCKET_BITS, beside, None, np.int32)
    weight = F.element_at(F.lit([float(1 / np.sqrt(n[w])) for w in top[:BESIDE]]), F.col("word") + 1)
    pairs = pairs.select(F.expr(f"at div {BESIDE}").alias("bucket"), F.expr(f"at % {BESIDE}").alias("word"), "n")
    named = pairs.groupBy("bucket").agg(F.max_by("word", F.struct(F.col("n") * weight, -F.col("word"))).alias("word")).toArrow()
    label = np.full(1 << BUCKET_BITS, CLASSES - 1, np.int16)
    label[named["bucket"].to_numpy()] = OWN + named["word"].to_numpy()
    label[top] = np.arange(OWN)
    of_class = np.bincount(label, n, CLASSES) + 1e-3
    return Vocabulary((np.log(n) - np.log(of_class[label])).astype(np.float32), (np.log(n) - np.log(n.sum())).astype(np.float32), label, symbol, of_class / of_class.sum())


def _first(words: Vocabulary, together: np.ndarray) -> Weights:
    """The best fit of rank HIDDEN to the damped mutual information of context symbols and classes (counts: places x SYMBOLS x CLASSES), weighed by frequency."""
    prior, seen = words.class_prior, together.sum(axis=2, keepdims=True)
    info = np.log((together + 5 * prior) / (seen * prior + 5 * prior)) * np.sqrt(seen / (seen + 20))
    info -= (info * prior).sum(axis=2, keepdims=True)
    weight = np.sqrt(seen.reshape(-1, 1) + 1)
    weighed = info.reshape(-1, CLASSES) * weight * np.sqrt(prior)
    _, vectors = np.linalg.eigh(weighed.T @ weighed)
    axes = vectors[:, ::-1][:, :HIDDEN]
    embedding = DAMP * (weighed @ axes / weight).reshape(2 * REACH, SYMBOLS, HIDDEN)
    out = np.concatenate((axes / np.sqrt(prior)[:, None], np.log(prior)[:, None]), axis=1)
    return Weights(embedding.astype(np.float32), out.astype(np.float32))


def train(df: DataFrame, words: Vocabulary, text_col: str = "text", rounds: int = ROUNDS) -> Weights:
    """Weights learned from every place of every text."""

    def together(total: np.ndarray, bucket: np.ndarray, context: np.ndarray, label: np.ndarray) -> None:
        label = label[bucket].astype(np.int64)
        for k in range(2 * REACH):
            cells, times = np.unique((k * SYMBOLS + context[:, k]) * CLASSES + label, return_counts=True)
            total[cells] += times

    size = 2 * REACH * SYMBOLS * CLASSES
    weights = _first(words, _dense(_summed(df, text_col, words.symbol, size, together, words.label, np.int64).toArrow(), size).reshape(2 * REACH, SYMBOLS, CLASSES))
    cut, wide = CLASSES * (HIDDEN + 1), HIDDEN + 1
    for _ in range(rounds):

        def gradient(total: np.ndarray, bucket: np.ndarray, context: np.ndarray, known: tuple[np.ndarray, Weights]) -> None:
            label, weights = known[0][bucket], known[1]
            for a in range(0, len(label), BLOCK):
                _, p, h = weights.judged(context[a : a + BLOCK], label[a : a + BLOCK])
                p[np.arange(len(p)), label[a : a + BLOCK]] -= 1
                total[:cut] -= (p.T @ h).ravel()
                total[cut:] += (h.T @ h).ravel()

        sums = _dense(_summed(df, text_col, words.symbol, cut + wide * wide, gradient, (words.label, weights), np.float64).toArrow(), cut + wide * wide)
        slope, moments = sums[:cut].reshape(CLASSES, wide), sums[cut:].reshape(wide, wide)
        if moments.any():
            ridge = 1e-3 * np.trace(moments) / wide * np.eye(wide)
            weights = Weights(weights.embedding, (weights.out + 2 * np.linalg.solve(moments + ridge, slope.T).T).astype(np.float32))
    return weights


def score(df: DataFrame, words: Vocabulary, weights: Weights, text_col: str = "text", out: tuple[str, str, str] = ("n_words", "log_prob", "log_unigram")) -> DataFrame:
    """``df`` with each text's number of words, summed conditional log-probability, and summed log-probability without context."""
    shared = df.sparkSession.sparkContext.broadcast((words, weights))  # of a fixed size
    kept = [c for c in df.columns if c not in out]
    schema = T.StructType([df.schema[c] for c in kept] + [T.StructField(out[0], T.LongType()), T.StructField(out[1], T.DoubleType()), T.StructField(out[2], T.DoubleType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words, net = shared.value
        for batch in batches:
            data, offsets = textscan.buffers(textscan.string_column(batch, text_col))
            for a, b, part, at in textscan.slices(data, offsets):
                bucket, first = buckets(part, at)
                sums = [np.concatenate(([0.0], np.cumsum(x, dtype=np.float64))) for x in (_log_probabilities(words, net, bucket, first), words.log_unigram[bucket])]
                rows = batch.slice(a, b - a)
                made = [pa.array(np.diff(first).astype(np.int64)), *(pa.array(x[first[1:]] - x[first[:-1]]) for x in sums)]
                yield pa.RecordBatch.from_arrays([rows.column(rows.schema.get_field_index(c)) for c in kept] + made, [*kept, *out])

    return textscan.mapped(df, run, schema)


def _log_probabilities(words: Vocabulary, net: Weights, bucket: np.ndarray, first: np.ndarray) -> np.ndarray:
    symbol, label, out = words.symbol[bucket], words.label[bucket], words.log_share[bucket].astype(np.float64)
    for a in range(0, len(bucket), BLOCK):
        places = np.arange(a, min(len(bucket), a + BLOCK))
        out[places] += net.judged(contexts(symbol, first, places), label[places])[0]
    return out
