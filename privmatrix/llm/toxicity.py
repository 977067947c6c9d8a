"""Toxicity with a convolutional text classifier over hashed word embeddings, trained in numpy.

A word's embedding joins four hashed ones: of the whole word and of its first 4, 5 and 6 bytes. Filters of widths 1 to 3 slide
over the words, each filter's largest response in a text is kept (max pooling), and a logistic layer scores these. The
embeddings start from smoothed log-odds of the labels, then everything is trained by mini-batches of a sample of labelled
rows of at most ``max_train`` rows and ``max_chars`` characters. A threshold for each language, which is told by common words of the text itself, is chosen on
a part of the sample that training does not see; scores are shifted so that 0.5 is that threshold.

Null and empty texts score like a text without any response. Whole texts are read, in slices that bound memory; repeated
rows score the same; with no labelled rows of both classes every score is 0. ``score`` keeps extra columns; a column named
like an output column is replaced.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from privmatrix.llm import textscan

BUCKETS = 1 << 17
PREFIXES = (0, 4, 5, 6)
DIM = 4
WIDTHS = (1, 2, 3)
FILTERS = 8
MAX_TRAIN = 5000
MAX_CHARS = 1 << 26

#: Common words by language, to tell a text's language when choosing its threshold.
COMMON = {
    "de": "der die das und ist nicht ein eine mit von zu den sich auf für als auch im dem es",
    "en": "the of and to in is that it for was on are with as be at by this from or",
    "es": "el la de que y en un los se del las por con una para su al lo como más",
    "fr": "le la de et les des en un du une que est pour qui dans par plus pas sur au",
}

_PART = np.zeros(256, bool)
_PART[:128] = True
_PART[48:58] = _PART[65:91] = _PART[97:123] = False


def _word_hash(word: str) -> np.uint64:
    data = np.frombuffer(word.encode(), np.uint8)
    return textscan.Words(data, np.array([0, len(data)]), _PART).hashes()[0]


_LANGUAGES = tuple(COMMON)
_COMMON = {lang: np.unique(np.array([_word_hash(w) for w in words.split()], np.uint64)) for lang, words in COMMON.items()}


def features(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Buckets of each word (words x 4), each row's first word, and each row's language number (the last: unknown)."""
    words = textscan.Words(data, offsets, _PART)
    buckets = np.empty((len(words.starts), len(PREFIXES)), np.int32)
    whole = words.hashes()
    for i, k in enumerate(PREFIXES):
        h = whole if not k else words.span_hashes(words.starts, np.minimum(words.starts + k, words.ends))
        buckets[:, i] = (h >> np.uint64(47)).astype(np.int32)
    hits = np.empty((len(offsets) - 1, len(_LANGUAGES) + 1), np.int64)
    hits[:, -1] = 0
    for i, known in enumerate(_COMMON.values()):
        at = np.searchsorted(known, whole)
        sums = np.concatenate(([0], np.cumsum(known[np.minimum(at, len(known) - 1)] == whole)))
        hits[:, i] = sums[words.first[1:]] - sums[words.first[:-1]]
    language = np.where(hits.max(axis=1) > 0, hits.argmax(axis=1), len(_LANGUAGES))
    return buckets, words.first, language


@dataclass
class Network:
    embedding: np.ndarray  # 4 x buckets x DIM
    kernels: list[np.ndarray]  # of each width: width x 4 * DIM x FILTERS
    biases: list[np.ndarray]
    out: np.ndarray
    bias: float
    thresholds: np.ndarray  # by language, of the logit

    def embedded(self, buckets: np.ndarray) -> np.ndarray:
        return np.concatenate([self.embedding[i][buckets[:, i]] for i in range(len(PREFIXES))], axis=1) if len(buckets) else np.zeros((0, DIM * len(PREFIXES)), np.float32)

    def responses(self, x: np.ndarray, i: int) -> np.ndarray:
        """Of the filters of one width, at each position where one starts."""
        w, m = WIDTHS[i], len(x) - WIDTHS[i] + 1
        if m <= 0:
            return np.zeros((0, FILTERS), np.float32)
        return sum(x[j : j + m] @ self.kernels[i][j] for j in range(w)) + self.biases[i]

    def logits(self, buckets: np.ndarray, first: np.ndarray) -> np.ndarray:
        x, rows = self.embedded(buckets), len(first) - 1
        pooled = np.zeros((rows, FILTERS * len(WIDTHS)), np.float32)
        for i, w in enumerate(WIDTHS):
            r = self.responses(x, i)
            long = np.flatnonzero(first[1:] - first[:-1] >= w)
            if len(long):
                # each row's windows, then what lies before the next row's, which starts in one row and ends in another
                cuts = np.stack([first[long], first[long + 1] - w + 1], axis=1).ravel()
                best = np.maximum.reduceat(r, cuts[cuts < len(r)], axis=0)[::2]
                pooled[long, i * FILTERS : (i + 1) * FILTERS] = np.maximum(best, 0)
        return pooled @ self.out + self.bias

    def score(self, buckets: np.ndarray, first: np.ndarray, language: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.logits(buckets, first) - self.thresholds[language], -30, 30).astype(np.float64)))


def train(texts: pa.Array, labels: np.ndarray, epochs: int = 6, rate: float = 0.05, batch: int = 32, seed: int = 3) -> Network | None:
    """The network of labelled texts, or None without both classes."""
    if not 0 < labels.sum() < len(labels):
        return None
    data, offsets = textscan.buffers(texts)
    parts = [features(part, at) for _, _, part, at in textscan.slices(data, offsets)]
    docs = [b[x:y] for b, first, _ in parts for x, y in zip(first[:-1].tolist(), first[1:].tolist())]
    language = np.concatenate([p[2] for p in parts])
    textscan.free_powers()
    draw = np.random.default_rng(seed)
    order = draw.permutation(len(docs))
    hold, fit = order[: len(docs) // 5], order[len(docs) // 5 :]
    if not 0 < labels[fit].sum() < len(fit):
        hold, fit = order[:0], order
    net = Network(draw.normal(0, 0.05, (len(PREFIXES), BUCKETS, DIM)).astype(np.float32), [draw.normal(0, 0.1, (w, DIM * len(PREFIXES), FILTERS)).astype(np.float32) for w in WIDTHS], [np.full(FILTERS, -0.1, np.float32) for _ in WIDTHS], draw.normal(0.2, 0.05, FILTERS * len(WIDTHS)).astype(np.float32), -1.0, np.zeros(len(_LANGUAGES) + 1))
    toxic, clean = labels[fit].sum(), len(fit) - labels[fit].sum()
    for i in range(len(PREFIXES)):
        seen = np.zeros((2, BUCKETS), np.float32)
        for d in fit.tolist():
            seen[labels[d]][np.unique(docs[d][:, i])] += 1
        odds = np.log((seen[1] + 0.5) / (toxic + 1)) - np.log((seen[0] + 0.5) / (clean + 1))
        sure = np.sqrt(np.minimum(seen.sum(axis=0), 8) / 8)
        net.embedding[i][:, 0] = np.where(seen.sum(axis=0) > 0, odds * sure / 2, -0.5)
    for i, w in enumerate(WIDTHS):
        net.kernels[i][0, ::DIM, : FILTERS // 2] += 0.4
    moments = [np.full(x.shape, 1e-6, np.float32) for x in (net.embedding, *net.kernels, *net.biases, net.out)]
    bias_moment = 1e-6
    weight = np.where(labels == 1, min(5.0, clean / toxic) ** 0.5, 1.0)
    for _ in range(epochs):
        shuffled = draw.permutation(fit)
        for a in range(0, len(fit), batch):
            chosen = shuffled[a : a + batch]
            rows = [docs[d] for d in chosen]
            buckets = np.concatenate(rows) if rows else np.zeros((0, len(PREFIXES)), np.int32)
            first = np.concatenate(([0], np.cumsum([len(r) for r in rows])))
            x = net.embedded(buckets)
            pooled, where = np.zeros((len(rows), FILTERS * len(WIDTHS)), np.float32), []
            for i, w in enumerate(WIDTHS):
                r = net.responses(x, i)
                at = np.full((len(rows), FILTERS), -1)
                for d in range(len(rows)):
                    if first[d + 1] - first[d] >= w:
                        own = r[first[d] : first[d + 1] - w + 1]
                        at[d] = first[d] + own.argmax(axis=0)
                        best = own.max(axis=0)
                        at[d][best <= 0] = -1
                        pooled[d, i * FILTERS : (i + 1) * FILTERS] = np.maximum(best, 0)
                where.append(at)
            p = 1 / (1 + np.exp(-np.clip(pooled @ net.out + net.bias, -30, 30)))
            slope = ((p - labels[chosen]) * weight[chosen] / len(rows)).astype(np.float32)
            grads = [pooled.T @ slope]
            back = slope[:, None] * net.out
            emb: list[tuple[np.ndarray, np.ndarray]] = []
            for i, w in enumerate(WIDTHS):
                g = back[:, i * FILTERS : (i + 1) * FILTERS]
                d, f = np.nonzero(where[i] >= 0)
                pos, gv = where[i][d, f], g[d, f]
                kernel = np.zeros_like(net.kernels[i])
                for j in range(w):
                    np.add.at(kernel[j].T, f, gv[:, None] * x[pos + j])
                    emb.append((pos + j, gv[:, None] * net.kernels[i][j].T[f]))
                bias = np.bincount(f, gv, FILTERS).astype(np.float32)
                for value, moment, grad in ((net.kernels[i], moments[1 + i], kernel), (net.biases[i], moments[1 + len(WIDTHS) + i], bias)):
                    moment += grad**2
                    value -= rate * grad / np.sqrt(moment)
            moments[-1] += grads[0] ** 2
            net.out -= rate * grads[0] / np.sqrt(moments[-1])
            bias_moment += float(slope.sum()) ** 2
            net.bias -= rate * float(slope.sum()) / bias_moment**0.5
            pos, grad = np.concatenate([e[0] for e in emb]), np.concatenate([e[1] for e in emb])
            for i in range(len(PREFIXES)):
                own, index = np.unique(buckets[pos, i], return_inverse=True)
                total = np.zeros((len(own), DIM), np.float32)
                np.add.at(total, index, grad[:, i * DIM : (i + 1) * DIM])
                moments[0][i][own] += total**2
                net.embedding[i][own] -= rate * total / np.sqrt(moments[0][i][own])
    judged = hold if len(hold) and 0 < labels[hold].sum() < len(hold) else fit
    logits = np.array([net.logits(docs[d], np.array([0, len(docs[d])]))[0] for d in judged.tolist()])
    overall = _threshold(logits, labels[judged], 0.0)
    net.thresholds[:] = overall
    for i in range(len(_LANGUAGES)):
        own = language[judged] == i
        if labels[judged][own].sum() >= 10:
            net.thresholds[i] = _threshold(logits[own], labels[judged][own], overall)
    return net


def _threshold(logits: np.ndarray, labels: np.ndarray, default: float) -> float:
    """The middle of the widest gap between logits among the cuts of best F1."""
    if not 0 < labels.sum() < len(labels):
        return default
    order = np.argsort(-logits, kind="stable")
    value, hit = logits[order], np.cumsum(labels[order])
    f1 = 2 * hit / (np.arange(1, len(order) + 1) + labels.sum())
    f1[:-1][value[:-1] == value[1:]] = -1
    best = np.flatnonzero(f1 >= f1.max() - 1e-12)
    below = np.append(value[1:], value[-1] - 2)
    k = best[np.argmax((value - below)[best])]
    return float((value[k] + below[k]) / 2)


def sample(docs: DataFrame, labels: DataFrame, id_col: str, text_col: str, label_col: str, max_train: int, max_chars: int) -> DataFrame:
    """id, text, label of the training sample: labelled ids by a hash, as long as rows and characters stay within their bounds.

    Texts are taken whole or not at all. Of rows that repeat an id the first text by order is taken.
    """
    order = (F.xxhash64(id_col), F.col(id_col))
    chosen = labels.where(F.col(label_col).isNotNull() & F.col(id_col).isNotNull()).groupBy(id_col).agg(F.max(label_col).cast("int").alias("__label")).orderBy(*order).limit(max_train)
    rows = docs.select(id_col, text_col).join(F.broadcast(chosen), id_col)  # at most max_train ids are broadcast
    single = rows.groupBy(id_col).agg(F.min(text_col).alias(text_col), F.max("__label").alias("__label"))
    upto = F.sum(F.coalesce(F.length(text_col), F.lit(0)).cast("long")).over(Window.orderBy(*order).rowsBetween(Window.unboundedPreceding, 0))  # at most max_train rows
    return single.withColumn("__upto", upto).where(F.col("__upto") <= max_chars).select(id_col, text_col, "__label")


def fit(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic", max_train: int = MAX_TRAIN, max_chars: int = MAX_CHARS) -> Network | None:
    """The network of a sample of at most ``max_train`` rows of ``labels`` and ``max_chars`` characters."""
    rows = sample(docs, labels, id_col, text_col, label_col, max_train, max_chars).toArrow()
    if not len(rows):
        return None
    rows = rows.sort_by(id_col).combine_chunks()
    net = train(rows[text_col].combine_chunks(), rows["__label"].to_numpy().astype(np.int64))
    del rows
    textscan.trim()
    return net


def score(df: DataFrame, net: Network | None, text_col: str = "text", out: str = "score") -> DataFrame:
    """``df`` with the probability-like score (0 to 1; 0.5 is the language's threshold)."""
    shared = df.sparkSession.sparkContext.broadcast(net)  # of a fixed size
    kept = [c for c in df.columns if c != out]
    schema = T.StructType([df.schema[c] for c in kept] + [T.StructField(out, T.DoubleType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        net = shared.value
        for batch in batches:
            data, offsets = textscan.buffers(textscan.string_column(batch, text_col))
            for a, b, part, at in textscan.slices(data, offsets):
                values = np.zeros(b - a) if net is None else net.score(*features(part, at))
                rows = batch.slice(a, b - a)
                yield pa.RecordBatch.from_arrays([rows.column(rows.schema.get_field_index(c)) for c in kept] + [pa.array(values)], [*kept, out])

    return textscan.mapped(df, run, schema)
