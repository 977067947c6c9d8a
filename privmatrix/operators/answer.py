"""Range counts: estimates from a release under uniformity, and exact counts from the cells.

queries: qid, qlo1, qhi1, .., half-open. Strategies give the same answers and differ in how boxes and queries meet.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce
from operator import mul

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from privmatrix.functions import boxes

NESTED_QUERIES = 10_000  # up to so many queries are broadcast (about 100 bytes each)
BIN_SHARE = 64
BATCHED_ROWS = 1 << 17  # boxes that a task weighs at once
TABLE_VALUES = 8_000_000  # shares of kept boxes of the last axes by queries: 64 MB in a task
CHUNK_VALUES = 1_000_000
SPARSE_COST = 16  # a box weighed alone costs as much as so many of a matrix product


def _qbounds(d: int) -> list[str]:
    return boxes.bounds(d, "q")


def _finished(queries: DataFrame, summed: DataFrame, name: str) -> DataFrame:
    return queries.select("qid").join(summed, "qid", "left").select("qid", F.coalesce(name, F.lit(0.0)).alias(name))


def answer(partitions: DataFrame, queries: DataFrame, d: int, strategy: str = "auto", widths: tuple[int, ...] | None = None) -> DataFrame:
    """qid, est: each box gives its noisy count times the share of it that the query covers.

    auto: the queries are counted; few are broadcast and every box meets all of them, else boxes and queries meet by bins of the first axis.
    """
    if strategy == "auto":
        strategy = "nested" if queries.count() <= NESTED_QUERIES else "binned"
    if strategy == "separable":
        return answer_separable(partitions, queries, d)
    if strategy == "batched":
        return answer_batched(partitions, queries, d)
    share = F.col("ncount") * boxes.overlap(d) / F.col("n_entries")
    q = queries.select("qid", *_qbounds(d))
    if strategy == "nested":
        met = partitions.join(F.broadcast(q), boxes.overlaps(d))
    else:
        met = _binned(partitions, q, d, widths)
    return _finished(queries, met.groupBy("qid").agg(F.sum(share).alias("est")), "est")


def _bin_width(widths: tuple[int, ...] | None, df: DataFrame) -> Column | int:
    if widths:
        return max(1, widths[0] // BIN_SHARE)
    return max(1, (df.agg(F.max("hi1")).first()[0] or 1) // BIN_SHARE)


def _binned(partitions: DataFrame, q: DataFrame, d: int, widths: tuple[int, ...] | None) -> DataFrame:
    """Pairs that overlap, each once: it is counted in the first bin that both reach."""
    w = _bin_width(widths, partitions)
    left = partitions.withColumn("bin", F.explode(F.sequence(F.floor(F.col("lo1") / w), F.floor((F.col("hi1") - 1) / w))))
    right = q.where("qlo1 < qhi1").withColumn("bin", F.explode(F.sequence(F.floor(F.col("qlo1") / w), F.floor((F.col("qhi1") - 1) / w))))
    first = F.greatest(F.floor(F.col("lo1") / w), F.floor(F.col("qlo1") / w))
    return left.join(right, "bin").where(boxes.overlaps(d) & (F.col("bin") == first))


def answer_separable(partitions: DataFrame, queries: DataFrame, d: int) -> DataFrame:
    """For equal grids: the covered share of a box is a product of shares per axis, so queries meet the few intervals of each axis.

    The partial intervals are found once per axis; boxes are then reached by equality on their lower ends.
    """
    q, hits = queries.select("qid", *_qbounds(d)), None
    for i in range(1, d + 1):
        axis = F.broadcast(partitions.select(f"lo{i}", f"hi{i}").distinct())  # at most one row for each position of the axis
        met = q.join(axis, (F.col(f"qlo{i}") < F.col(f"hi{i}")) & (F.col(f"lo{i}") < F.col(f"qhi{i}"))).select("qid", f"lo{i}", (boxes.overlap1(i) / (F.col(f"hi{i}") - F.col(f"lo{i}"))).alias(f"w{i}"))
        hits = met if hits is None else hits.join(met, "qid")
    lows = [f"lo{i}" for i in range(1, d + 1)]
    weight = reduce(mul, [F.col(f"w{i}") for i in range(1, d + 1)])
    summed = hits.join(partitions.select(*lows, "ncount"), lows).groupBy("qid").agg(F.sum(F.col("ncount") * weight).alias("est"))
    return _finished(queries, summed, "est")


class Weigher:
    """Sums of boxes by query, for a task. A box's covered share is the product of that on its first axes and that on its last ones.

    Shares on the last axes are kept in one table by query. Rows that stand in the order of the axes repeat few boxes of the first axes, so their counts
    are a small dense matrix and meet the table by a matrix product; others are weighed one by one.
    """

    def __init__(self, qlo: np.ndarray, qhi: np.ndarray, d: int):
        self.qlo, self.qhi, self.head = qlo, qhi, d - max(1, d // 2)
        self.axes, self.n = d, qlo.shape[1]
        self.total = np.zeros(self.n)
        self.most = TABLE_VALUES // max(1, self.n)
        self.table, self.used = np.empty((self.most, self.n)), 0
        self.keys, self.slots = np.empty(0, np.int64), np.empty(0, np.int64)

    def shares(self, lo: np.ndarray, hi: np.ndarray, first: int) -> np.ndarray:
        """Boxes by queries; lo, hi: an array for each axis from ``first``."""
        out = None
        for i, (a, b) in enumerate(zip(lo, hi), first):
            part = np.minimum(b[:, None], self.qhi[i]) - np.maximum(a[:, None], self.qlo[i])
            part = np.maximum(part, 0) / (b - a)[:, None]
            out = part if out is None else np.multiply(out, part, out=out)
        return np.ones((len(lo[0]) if len(lo) else 1, self.n)) if out is None else out

    @staticmethod
    def coded(columns: list[np.ndarray], rows: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, bool]:
        """Keys of the distinct boxes, a row of each, every row's number among them, and whether keys mean the same in the next call."""
        if not columns:
            return np.zeros(1, np.int64), np.zeros(1, np.int64), np.zeros(rows, np.int64), True
        bits = 62 // len(columns)
        if any(c.min() < 0 or c.max() >> bits for c in columns):
            _, first, number = np.unique(np.stack(columns, 1), axis=0, return_index=True, return_inverse=True)
            return first, first, number.reshape(-1), False
        key = reduce(lambda k, c: (k << bits) | c, columns, np.zeros(rows, np.int64))
        return *np.unique(key, return_index=True, return_inverse=True), True

    def kept(self, keys: np.ndarray, lo: list[np.ndarray], hi: list[np.ndarray]) -> np.ndarray | None:
        """The table's rows of boxes of the last axes; None where there is no room for new ones."""
        at = np.minimum(np.searchsorted(self.keys, keys), max(0, len(self.keys) - 1))
        new = np.ones(len(keys), bool) if not len(self.keys) else self.keys[at] != keys
        if grown := int(new.sum()):
            if self.used + grown > self.most:
                return None
            self.table[self.used : self.used + grown] = self.shares([a[new] for a in lo], [b[new] for b in hi], self.head)
            both, slots = np.concatenate([self.keys, keys[new]]), np.concatenate([self.slots, np.arange(self.used, self.used + grown)])
            order = np.argsort(both)
            self.keys, self.slots, self.used = both[order], slots[order], self.used + grown
            at = np.searchsorted(self.keys, keys)
        return self.slots[at]

    def add(self, lo: list[np.ndarray], hi: list[np.ndarray], count: np.ndarray, units: bool) -> None:
        k, rows = self.head, len(count)
        _, first, number, _ = self.coded([*lo[:k], *([] if units else hi[:k])], rows)
        heads = len(first)
        tail_keys, tail_first, tail, stable = self.coded([*lo[k:], *([] if units else hi[k:])], rows)
        slots = None
        if stable and heads * max(self.used, len(tail_keys)) <= SPARSE_COST * rows:
            slots = self.kept(tail_keys, [a[tail_first] for a in lo[k:]], [b[tail_first] for b in hi[k:]])
        if slots is not None and heads * self.used <= SPARSE_COST * rows:
            counts = np.bincount(number * self.used + slots[tail], count, heads * self.used).reshape(heads, self.used)
            step = max(1, CHUNK_VALUES // max(1, self.n))
            for i in range(0, heads, step):
                at = first[i : i + step]
                weights = self.shares([a[at] for a in lo[:k]], [b[at] for b in hi[:k]], 0) if k else 1.0
                self.total += ((counts[i : i + step] @ self.table[: self.used]) * weights).sum(0)
            return
        step = max(1, CHUNK_VALUES // max(1, self.n))
        for i in range(0, rows, step):
            at = slice(i, i + step)
            self.total += count[at] @ self.shares([a[at] for a in lo], [b[at] for b in hi], 0)


def answer_batched(weighted: DataFrame, queries: DataFrame, d: int, name: str = "est") -> DataFrame:
    """qid and the sum of ``ncount`` by covered share: boxes lo1, hi1, .. or, without hi1, single entries; several rows of one box add up.

    Queries, at most some ten thousand, go to every task, which returns one sum for each; boxes only stream. Any order of boxes is right, the order of their axes is fast.
    """
    units = "hi1" not in weighted.columns
    asked = queries.select("qid", *_qbounds(d)).toArrow()
    qid = asked.column("qid").to_pylist()
    qlo, qhi = (np.array([asked.column(f"q{side}{i}").to_numpy() for i in range(1, d + 1)], np.int64) for side in ("lo", "hi"))
    boxes_ = [f"lo{i}" for i in range(1, d + 1)] + ([] if units else [f"hi{i}" for i in range(1, d + 1)])

    def sums(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        weigher, held, rows = Weigher(qlo, qhi, d), [], 0

        def flush() -> None:
            table = pa.Table.from_batches(held)
            lo = [table.column(f"lo{i}").to_numpy().astype(np.int64) for i in range(1, d + 1)]
            hi = [a + 1 for a in lo] if units else [table.column(f"hi{i}").to_numpy().astype(np.int64) for i in range(1, d + 1)]
            weigher.add(lo, hi, table.column("ncount").to_numpy(), units)
            held.clear()

        for batch in batches:
            if batch.num_rows:
                held.append(batch)
                rows += batch.num_rows
            if rows >= BATCHED_ROWS:
                flush()
                rows = 0
        if rows:
            flush()
        yield pa.RecordBatch.from_arrays([pa.array(qid, pa.int64()), pa.array(weigher.total, pa.float64())], names=["qid", "part"])

    found = weighted.select(*boxes_, F.col("ncount").cast("double").alias("ncount")).mapInArrow(sums, "qid long, part double")
    return _finished(queries, found.groupBy("qid").agg(F.sum("part").alias(name)), name)


def truth(cells: DataFrame, queries: DataFrame, d: int, strategy: str = "auto", widths: tuple[int, ...] | None = None) -> DataFrame:
    """qid, truth: exact counts, for evaluation by the curator only."""
    if strategy == "auto":
        strategy = "nested" if queries.count() <= NESTED_QUERIES else "binned"
    q = queries.select("qid", *_qbounds(d))
    if strategy == "prefix":
        return truth_prefix(cells, queries, d)
    if strategy == "batched":
        return answer_batched(cells.select(*[F.col(f"x{i}").alias(f"lo{i}") for i in range(1, d + 1)], F.col("f").alias("ncount")), queries, d, "truth")
    if strategy == "nested":
        met = cells.join(F.broadcast(q), boxes.holds(d))
    else:
        w = max(1, (widths[0] if widths else (cells.agg(F.max("x1")).first()[0] or 0) + 1) // BIN_SHARE)
        right = q.where("qlo1 < qhi1").withColumn("bin", F.explode(F.sequence(F.floor(F.col("qlo1") / w), F.floor((F.col("qhi1") - 1) / w))))
        met = cells.withColumn("bin", F.floor(F.col("x1") / w)).join(right, "bin").where(boxes.holds(d))
    return _finished(queries, met.groupBy("qid").agg(F.sum("f").cast("double").alias("truth")), "truth")


def prefix_sums(cells: DataFrame, d: int, corners: DataFrame, kind: str = "long") -> DataFrame:
    """c1..cd, s: the number of records (or sum of noisy counts) below each asked corner on all axes.

    Axis by axis, cells and corners are laid on the same lines and summed by a window over the positions; a line is all rows that agree on the
    other coordinates.
    """
    axes = [f"x{i}" for i in range(1, d + 1)]
    state = cells.select(*axes, F.col("f").cast(kind).alias("s"))
    for i in range(1, d + 1):
        x = f"x{i}"
        others = [a for a in axes if a != x]
        asked = corners.select(F.col(f"c{i}").alias(x)).distinct()
        lines = state.select(*others).distinct() if others else None
        grid = lines.join(F.broadcast(asked)) if lines is not None else asked
        # a corner's sum takes positions below it, so at equal positions the corner's row comes first
        rows = state.select(*axes, "s", F.lit(1).alias("side")).unionByName(grid.select(*axes, F.lit(0).cast(kind).alias("s"), F.lit(0).alias("side")))
        order = Window.partitionBy(*others).orderBy(x, "side").rowsBetween(Window.unboundedPreceding, 0)
        state = rows.withColumn("s", F.sum("s").over(order)).where("side = 0").select(*axes, "s")
    return state.select(*[F.col(f"x{i}").alias(f"c{i}") for i in range(1, d + 1)], "s")


def truth_prefix(cells: DataFrame, queries: DataFrame, d: int) -> DataFrame:
    """Exact counts from prefix sums at the 2**d corners of each query; for low d and many queries."""
    return _finished(queries, _from_corners(cells, queries, d, "long", "truth"), "truth")


def answer_entries(partitions: DataFrame, queries: DataFrame, d: int) -> DataFrame:
    """For releases whose boxes are single entries: 2**d prefix sums for each query instead of all entries that it covers."""
    entries = partitions.select(*[F.col(f"lo{i}").alias(f"x{i}") for i in range(1, d + 1)], F.col("ncount").alias("f"))
    return _finished(queries, _from_corners(entries, queries, d, "double", "est"), "est")


def _from_corners(cells: DataFrame, queries: DataFrame, d: int, kind: str, name: str) -> DataFrame:
    corners = None
    for bits in range(1 << d):
        c = [F.col(f"q{'hi' if bits >> (i - 1) & 1 else 'lo'}{i}").alias(f"c{i}") for i in range(1, d + 1)]
        sign = -1 if (d - bin(bits).count("1")) % 2 else 1
        one = queries.where(" AND ".join(f"qlo{i} < qhi{i}" for i in range(1, d + 1))).select("qid", *c, F.lit(sign).alias("sign"))
        corners = one if corners is None else corners.unionByName(one)
    sums = prefix_sums(cells, d, corners, kind)
    on = [f"c{i}" for i in range(1, d + 1)]
    return corners.join(sums, on, "left").groupBy("qid").agg(F.sum(F.col("sign") * F.coalesce("s", F.lit(0))).cast("double").alias(name))
