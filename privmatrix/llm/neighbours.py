"""Approximate nearest neighbours with balanced posting lists.

Centroids are fitted on a bounded sample by k-means whose assignment charges crowded lists, and joined by an in-memory
neighbour graph that a beam search walks; a query that wants more lists than half the beam is ranked against all centroids. Every vector goes to the list of its nearest centroid, and a boundary vector also to the
lists whose centroids are nearly as near, unless a chosen list stands between. A query reads the lists whose distance is
within a ratio of the nearest one's, and at least so many that they hold a multiple of k vectors. Lists beyond these
name only entries that are as near as the k + 1 nearest of the sample, which leaves out none of the true k + 1 nearest; a farther entry that would stand in for one missed may change.

Equal vectors are one class: of its members only the k + 1 of smallest id can be among k nearest, so the lists hold classes and
a vector that a third of all rows share costs one entry. Lists above ``MOST`` entries are dealt out over several tasks, which
all see the list's queries.

Vectors that are null, zero, of another length than most, or hold null or non-finite components take no part, neither as
query nor as candidate. Ties go to the smaller id, those at a list's last place included. An id that occurs twice is two rows: each is a candidate of
the other, rows of one id with different vectors are queries of their own under that id, and rows that repeat both are one query. An empty table gives an empty result.
Extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from privmatrix.llm import textscan
from privmatrix.llm.store import written

SAMPLE = 20_000
PER_LIST, LISTS = 250, 4096
MOST = 2_000
DEGREE, BEAM = 24, 96
COPIES, COPY_RATIO = 4, 1.12
QUERY_RATIO, QUERY_FILL = 1.25, 40


@dataclass(frozen=True)
class Index:
    centroids: np.ndarray
    graph: np.ndarray  # neighbours of each centroid

    def search(self, x: np.ndarray, beam: int = BEAM) -> tuple[np.ndarray, np.ndarray]:
        """For each row, nearest centroids found and their distances, nearest first; at most ``beam``."""
        c, n = self.centroids, len(self.centroids)
        width = min(beam, n)
        norms, rows = (c * c).sum(axis=1), np.arange(len(x))[:, None]
        start = np.linspace(0, n - 1, min(n, 16)).astype(int)
        seen = np.zeros((len(x), n), bool)
        seen[:, start] = True
        ids = np.full((len(x), width), -1)
        dist = np.full((len(x), width), np.inf)
        done = np.zeros((len(x), width), bool)

        def add(new: np.ndarray, d: np.ndarray) -> None:
            nonlocal ids, dist, done
            ids, dist, done = np.concatenate((ids, new), 1), np.concatenate((dist, d), 1), np.concatenate((done, np.zeros(new.shape, bool)), 1)
            keep = np.argsort(dist, axis=1, kind="stable")[:, :width]
            ids, dist, done = ids[rows, keep], dist[rows, keep], done[rows, keep]

        add(np.broadcast_to(start, (len(x), len(start))), norms[start] - 2 * x @ c[start].T)
        while True:
            waiting = ~done & np.isfinite(dist)
            if not waiting.any():
                break
            found, good = [], []
            for _ in range(4):  # the nearest four waiting centroids of each row at a time
                pick = np.where(waiting, dist, np.inf).argmin(axis=1)
                live = waiting[rows[:, 0], pick]
                waiting[rows[:, 0], pick] = False
                done[rows[:, 0], pick] |= live
                near = self.graph[ids[rows[:, 0], pick]]
                fresh = ~seen[rows, near] & live[:, None]
                seen[rows, near] |= live[:, None]
                found.append(near)
                good.append(fresh)
            near, fresh = np.concatenate(found, 1), np.concatenate(good, 1)
            d = norms[near] - 2 * np.einsum("bd,bkd->bk", x, c[near])
            add(np.where(fresh, near, -1), np.where(fresh, d, np.inf))
        d2 = np.maximum(dist + (x * x).sum(axis=1, keepdims=True), 0)
        return ids, np.sqrt(d2)

    def ranked(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """For each row, all centroids and their distances, nearest first."""
        c = self.centroids
        d2 = (c * c).sum(axis=1) - 2 * x @ c.T + (x * x).sum(axis=1, keepdims=True)
        ids = np.argsort(d2, axis=1, kind="stable")
        return ids, np.sqrt(np.maximum(np.take_along_axis(d2, ids, 1), 0))


def fit(x: np.ndarray, lists: int, rounds: int = 8, seed: int = 9) -> Index:
    """Balanced k-means of a sample, and the graph of each centroid's nearest ones (both ways)."""
    draw = np.random.default_rng(seed)
    x = x.astype(np.float32)
    lists = max(1, min(lists, len(x)))
    c = x[draw.permutation(len(x))[:lists]].copy()
    load = np.zeros(lists)
    for _ in range(rounds):
        own = np.empty(len(x), int)
        spread = 0.0
        for a in range(0, len(x), 4096):
            d = (c * c).sum(axis=1) - 2 * x[a : a + 4096] @ c.T + (x[a : a + 4096] ** 2).sum(axis=1, keepdims=True)
            spread = float(np.mean(d.min(axis=1))) if not a else spread
            own[a : a + 4096] = (d + 0.1 * spread * np.maximum(load / max(1.0, len(x) / lists) - 1, 0)).argmin(axis=1)
        load = np.bincount(own, minlength=lists).astype(float)
        total = np.zeros_like(c)
        np.add.at(total, own, x)
        c = np.where(load[:, None] > 0, total / np.maximum(load, 1)[:, None], x[draw.integers(0, len(x), lists)])
    degree = min(DEGREE, max(1, lists - 1))
    d = (c * c).sum(axis=1) - 2 * c @ c.T
    np.fill_diagonal(d, np.inf)
    near = np.argsort(d, axis=1)[:, :degree] if lists > 1 else np.zeros((1, 1), int)
    ring = (np.arange(lists)[:, None] + np.array([1, lists // 2 + 1])) % lists  # keeps the graph in one piece
    return Index(c, np.concatenate((near, ring), axis=1))


def valid(vector: Column, dim: int) -> Column:
    finite = F.forall(vector, lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) != float("inf")))
    return vector.isNotNull() & (F.size(vector) == dim) & finite & F.exists(vector, lambda v: v != 0)


def _matrix(column: pa.Array) -> np.ndarray:
    values = column.flatten().to_numpy(zero_copy_only=False).astype(np.float32)
    return values.reshape(len(column), -1) if len(column) else values.reshape(0, 1)


def _postings(index, copies: int, ratio: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        index_ = index.value
        for whole in batches:
            for a in range(0, len(whole), 512):
                batch = whole.slice(a, 512)
                x = _matrix(batch.column(1))
                ids, dist = index_.search(x, 16)
                chosen = np.zeros(ids.shape, bool)
                chosen[:, 0] = True
                for j in range(1, ids.shape[1]):
                    ok = (ids[:, j] >= 0) & (dist[:, j] <= ratio * dist[:, 0]) & (chosen.sum(axis=1) < copies)
                    for k in range(j):
                        p, q = index_.centroids[ids[:, j]], index_.centroids[ids[:, k]]
                        between = np.sqrt(((p - q) ** 2).sum(axis=1))
                        ok &= ~chosen[:, k] | (between >= 0.6 * dist[:, j])
                    chosen[:, j] = ok
                row, at = np.nonzero(chosen)
                picked = batch.take(pa.array(row))
                yield pa.RecordBatch.from_arrays([*picked.columns, pa.array(ids[row, at].astype(np.int32))], [*batch.schema.names, "list"])

    return run


def probed(index: Index, x: np.ndarray, sizes: np.ndarray, need: int, ratio: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """row, list, and whether it is one of the nearest that hold ``need`` entries: the lists within ``ratio`` of each row's nearest one, and the nearest that hold ``need`` entries, however many they are."""

    def wanted(ids: np.ndarray, dist: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        held = np.where(ids >= 0, sizes[np.maximum(ids, 0)], 0)
        fills = np.cumsum(held, axis=1) - held < need
        return (ids >= 0) & ((dist <= ratio * dist[:, :1]) | fills), fills

    ids, dist = index.search(x)
    take, fills = wanted(ids, dist)
    more = (2 * take.sum(axis=1) > ids.shape[1]) & (ids.shape[1] < len(index.centroids))  # near its width the beam misses some lists, beyond it all
    take[more] = False
    row, at = np.nonzero(take)
    rows, lists, first = [row], [ids[row, at]], [fills[row, at]]
    if more.any():
        ids, dist = index.ranked(x[more])
        take, fills = wanted(ids, dist)
        row, at = np.nonzero(take)
        rows.append(np.flatnonzero(more)[row])
        lists.append(ids[row, at])
        first.append(fills[row, at])
    return np.concatenate(rows), np.concatenate(lists), np.concatenate(first)


def bounds(x: np.ndarray, known: np.ndarray, most: int) -> np.ndarray:
    """For each row a distance within which ``most`` of the known entries lie, so that none of its ``most`` nearest is farther."""
    if len(known) < most:
        return np.full(len(x), np.inf)
    d2 = (known * known).sum(axis=1) - 2 * x @ known.T + (x * x).sum(axis=1, keepdims=True)
    scale = (x * x).sum(axis=1) + (known * known).sum(axis=1).max()
    return np.sqrt(np.maximum(np.partition(d2, most - 1, axis=1)[:, most - 1], 0) + 1e-4 * scale)  # more than single precision may be off


def _probes(index, known, sizes: np.ndarray, need: int, ratio: float, most: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        index_ = index.value
        for whole in batches:
            for a in range(0, len(whole), 512):
                batch = whole.slice(a, 512)
                x = _matrix(batch.column(1))
                row, lists, first = probed(index_, x, sizes, need, ratio)
                bound = np.where(first, np.inf, bounds(x, known.value, most)[row])
                picked = batch.take(pa.array(row))
                yield pa.RecordBatch.from_arrays([*picked.columns, pa.array(lists.astype(np.int32)), pa.array(bound.astype(np.float64))], [*batch.schema.names, "list", "bound"])

    return run


def _nearest(most: int):
    def run(queries: pd.DataFrame, entries: pd.DataFrame) -> pd.DataFrame:
        if not len(queries) or not len(entries):
            return pd.DataFrame({"query": np.zeros(0, np.int64), "entry": np.zeros(0, np.int64), "members": np.zeros(0, object), "score": np.zeros(0)})
        p = np.stack(entries["vector"].to_numpy()).astype(np.float64)
        ids, members = entries["class"].to_numpy(), entries["members"].to_numpy()
        norm, out = (p * p).sum(axis=1), []
        place = min(len(p), most) - 1
        vectors, bound = np.stack(queries["vector"].to_numpy()).astype(np.float64), queries["bound"].to_numpy()
        for a in range(0, len(vectors), 256):
            q = vectors[a : a + 256]
            rough = norm - 2 * q @ p.T
            slack = 1e-9 * (norm.max() + (q * q).sum(axis=1))  # more than double precision may be off
            for i, row in enumerate(rough):
                near = np.flatnonzero(row <= np.partition(row, place)[place] + slack[i])  # ties at the last place too
                exact = np.sqrt(((p[near] - q[i]) ** 2).sum(axis=1))
                order = np.lexsort((ids[near], exact))[:most]
                near, exact = (z[order[exact[order] <= bound[a + i]]] for z in (near, exact))
                out.append((queries["class"].iloc[a + i], near, exact))
        near = np.concatenate([n for _, n, _ in out])
        return pd.DataFrame({"query": np.repeat([q for q, _, _ in out], [len(n) for _, n, _ in out]), "entry": ids[near], "members": members[near], "score": np.concatenate([e for _, _, e in out])})

    return run


def search(df: DataFrame, is_query: Column, k: int = 10, id_col: str = "vec_id", vector_col: str = "embedding", sample: int = SAMPLE, per_list: int = PER_LIST, query_ratio: float = QUERY_RATIO) -> DataFrame:
    """query_id, rank, vec_id, score: the k nearest found of every row that ``is_query`` picks, itself left out."""
    spark = df.sparkSession
    result = "query_id long, rank int, vec_id long, score double"
    single = df.schema[vector_col].dataType.simpleString() in ("array<float>", "array<tinyint>", "array<smallint>")
    rows = df.select(F.col(id_col).cast("long").alias("id"), F.col(vector_col).cast("array<float>" if single else "array<double>").alias("vector"), is_query.alias("asks"))
    dim = rows.where("vector IS NOT NULL").agg(F.mode(F.size("vector"), True)).first()[0]
    if dim is None:
        return spark.createDataFrame([], result)
    rows = rows.where(valid(F.col("vector"), dim))
    by_vector = Window.partitionBy("vector").orderBy("id")
    first = rows.withColumn("place", F.row_number().over(by_vector)).where(F.col("place") <= k + 1)
    classes = written(first.groupBy("vector").agg(F.min("id").alias("class"), F.array_sort(F.collect_list("id")).alias("members")).select("class", "vector", "members"), "ann-classes")
    n = classes.count()
    if not n:
        return spark.createDataFrame([], result)
    chosen = classes.select("vector").orderBy(F.xxhash64("vector")).limit(sample).toArrow()  # bounded by ``sample``
    known = spark.sparkContext.broadcast(_matrix(chosen["vector"].combine_chunks()))
    index = spark.sparkContext.broadcast(fit(known.value, min(LISTS, -(-n // per_list))))  # LISTS centroids at most
    entry = T.StructType([*classes.schema.fields, T.StructField("list", T.IntegerType())])
    postings = written(textscan.mapped(classes, _postings(index, COPIES, COPY_RATIO), entry), "ann-lists")
    counted = postings.groupBy("list").count().toArrow()  # LISTS rows at most
    sizes = np.zeros(len(index.value.centroids), np.int64)
    sizes[counted["list"].to_numpy()] = counted["count"].to_numpy()
    shares = F.element_at(F.lit([int(-(-s // MOST)) or 1 for s in sizes]), F.col("list") + 1)
    dealt = postings.withColumn("share", (F.pmod(F.xxhash64("class"), shares)).cast("int"))
    asking = rows.where("asks").select("id", "vector")
    query_ids = asking.join(classes.select("class", "vector"), "vector").select(F.col("id").alias("query_id"), F.col("class").alias("query"))
    query_ids = written(query_ids.distinct(), "ann-queries")
    wanted = classes.join(query_ids.select(F.col("query").alias("class")).distinct(), "class", "left_semi").select("class", "vector")
    probe_schema = T.StructType([classes.schema["class"], classes.schema["vector"], T.StructField("list", T.IntegerType()), T.StructField("bound", T.DoubleType())])
    probes = textscan.mapped(wanted, _probes(index, known, sizes, QUERY_FILL * k, query_ratio, k + 1), probe_schema).withColumn("share", F.explode(F.sequence(F.lit(0), shares - 1)))
    found = probes.groupBy("list", "share").cogroup(dealt.groupBy("list", "share")).applyInPandas(_nearest(k + 1), "query long, entry long, members array<long>, score double")
    best = Window.partitionBy("query").orderBy("score", "entry")
    top = found.groupBy("query", "entry").agg(F.first("members").alias("members"), F.min("score").alias("score")).withColumn("place", F.row_number().over(best)).where(F.col("place") <= k + 1)
    at = F.when(F.col("entry") == F.col("query"), F.array_position("members", F.col("query_id"))).otherwise(0).cast("int")
    others = F.when(at > 0, F.concat(F.slice("members", F.lit(1), at - 1), F.slice("members", at + 1, F.size("members")))).otherwise(F.col("members"))
    pairs = query_ids.join(top, "query").select("query_id", "query", F.explode(others).alias("vec_id"), "score")
    ranked = Window.partitionBy("query_id", "query").orderBy("score", "vec_id")
    return pairs.withColumn("rank", F.row_number().over(ranked)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
