"""Near-duplicate groups by a chosen-path set similarity join.

A document's set holds its distinct word shingles. Documents of equal sets are one class, so exact copies cost nothing further. Of each
class the minwise tokens are kept, and independent random trees branch the classes: a node picks some of the tokens'
coordinates, and each gives a child of the classes that agree there. Two sets of similarity s stay together at a coordinate with
probability s, so that similar sets meet in some node of some tree and others part after few branchings.

* A node of more than ``leaf`` classes is branched again, ``levels`` times at most, unless it kept most of its parent's classes.
* Nodes of at most ``leaf`` classes are compared exhaustively by their tokens. The likeliest pairs that join what can be joined (a
  spanning forest, by the same order of pairs in all nodes) are verified first. A node in which likely pairs still lie between different
  groups is then gathered with its texts, and every such pair is verified until its ends are in one group.
* Nodes that stay large are groups of very similar classes. They are compared with a few leaders; if that leaves one group, no further
  link can change the result and the node is done. If not, and few classes stand outside the largest group, or it has been branched
  ``depth`` times, all of these become leaders, which is exhaustive as well; else the node is branched again.

Every link is confirmed on the full sets before it counts, so no false link is made. The chance that two sets at the threshold share
no node at the first level is 0.2 ** (trees * branches), about 1e-7, and they part at later levels of all trees with 1e-6.

Null and empty texts, and texts without a word, have empty sets and stand alone. Ties: a group is named by its smallest id, and that
document is kept. Repeated rows of one id get the same group. Extra columns are ignored by ``groups`` and kept by
``kept_only``. Texts are taken whole.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from privmatrix.llm import textscan
from privmatrix.llm.components import components
from privmatrix.llm.membership import only, row_key, without
from privmatrix.llm.store import written


@dataclass(frozen=True)
class Options:
    words: int = 4
    percent: int = 80  # similarity at which documents are linked
    tokens: int = 128
    trees: int = 5
    branches: int = 2
    leaf: int = 4096
    levels: int = 3
    stays: float = 0.6  # share of its parent's classes from which a large node is taken for a group of similar ones
    leaders: int = 4
    minority: int = 64
    depth: int = 16
    margin: float = 0.16  # 4.5 standard deviations of the tokens' estimate at the threshold

    @property
    def likely(self) -> int:
        """Agreeing tokens from which a pair is worth verifying."""
        return int(np.floor((self.percent / 100 - self.margin) * self.tokens))


def sign(df: DataFrame, o: Options, id_col: str, text_col: str) -> DataFrame:
    """id, n (set size), key (128-bit hash of the set) and tokens of each document; the last two null for empty sets."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        minwise = textscan.Minwise(o.tokens)
        for batch in batches:
            data, offsets = textscan.buffers(textscan.string_column(batch, "text"))
            ids = batch.column(0)
            for a, b, part, at in textscan.slices(data, offsets):
                sizes, keys, tokens = [], [], []
                for s in textscan.shingle_sets(part, at, o.words):
                    sizes.append(len(s))
                    keys.append(np.array([s.sum(dtype=np.uint64), textscan.mix(s ^ np.uint64(len(s))).sum(dtype=np.uint64)]).tobytes() if len(s) else None)
                    tokens.append(minwise(s).tobytes() if len(s) else None)
                yield pa.RecordBatch.from_arrays([ids.slice(a, b - a), pa.array(sizes, pa.int64()), pa.array(keys, pa.binary()), pa.array(tokens, pa.binary())], ["id", "n", "key", "sig"])

    return textscan.mapped(df.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text")), run, "id long, n long, key binary, sig binary")


def _tokens(column: pa.Array, t: int) -> np.ndarray:
    return np.frombuffer(b"".join(column.to_pylist()), np.uint32).reshape(-1, t)


def _child(node: np.ndarray, coordinate: np.ndarray, token: np.ndarray) -> np.ndarray:
    return textscan.mix(textscan.mix(node + coordinate.astype(np.uint64) + np.uint64(1)) ^ (token.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)))


def roots(reps: DataFrame, o: Options) -> DataFrame:
    """node, id, parent: the first branching of every tree; its parent holds all classes, so its size tells nothing and is given as -1."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        picks = np.random.default_rng(41).permutation(o.tokens)[: o.trees * o.branches]
        for batch in batches:
            sig, ids = _tokens(batch.column(1), o.tokens), batch.column(0).to_numpy()
            nodes = [_child(np.uint64(1000 + k // o.branches), np.full(len(ids), c), sig[:, c]) for k, c in enumerate(picks)]
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(nodes).view(np.int64)), pa.array(np.tile(ids, len(picks))), pa.array(np.full(len(ids) * len(picks), -1, np.int64))], ["node", "id", "parent"])

    return textscan.mapped(reps.select("id", "sig"), run, "node long, id long, parent long")


def branched(members: DataFrame, reps: DataFrame, o: Options) -> DataFrame:
    """node, id, parent (size of the parent): children of the given nodes (node, id, size)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            node, ids, sig, size = batch.column(0).to_numpy().view(np.uint64), batch.column(1).to_numpy(), _tokens(batch.column(2), o.tokens), batch.column(3).to_numpy()
            row, out, start = np.arange(len(ids)), [], textscan.mix(node)
            for k in range(o.branches):
                c = ((start + np.uint64(k) * (textscan.mix(start) % np.uint64(o.tokens // o.branches) + np.uint64(1))) % np.uint64(o.tokens)).astype(np.int64)
                out.append(_child(node, c, sig[row, c]))
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(out).view(np.int64)), pa.array(np.tile(ids, o.branches)), pa.array(np.tile(size, o.branches))], ["node", "id", "parent"])

    return textscan.mapped(members.join(reps.select("id", "sig"), "id").select("node", "id", "sig", "size"), run, "node long, id long, parent long")


def dense(members: DataFrame, what: str) -> DataFrame:
    """node, id, size, parent: nodes of two classes at least, once where several hold the same classes."""
    print_ = [F.expr(f"bit_xor(xxhash64(id, {k}))").alias(f"p{k}") for k in range(2)]
    sizes = members.groupBy("node").agg(F.count("*").alias("size"), F.max("parent").alias("parent"), *print_).where("size >= 2")
    once = sizes.groupBy("size", "p0", "p1").agg(F.min(F.struct("node", "parent")).alias("one")).select("one.node", "size", "one.parent")
    return written(members.select("node", "id").join(once, "node").select("node", "id", "size", "parent"), what)


class _Groups:
    """Union-find over ids as they come."""

    def __init__(self) -> None:
        self.up: dict[int, int] = {}

    def top(self, x: int) -> int:
        while (up := self.up.get(x, x)) != x:
            self.up[x] = self.up.get(up, up)
            x = up
        return x

    def join(self, x: int, y: int) -> bool:
        """False if they were together."""
        a, b = self.top(x), self.top(y)
        self.up[a] = b
        return a != b


class _Node:
    """A node's classes in order of set size, so that the sets which may be similar to one lie in a range about it."""

    def __init__(self, ids: np.ndarray, n: np.ndarray, sig: np.ndarray, o: Options):
        self.order = np.lexsort((ids, n))
        self.ids, self.n, self.sig, self.likely = ids[self.order], n[self.order], sig[self.order], o.likely
        self.first = np.searchsorted(self.n * 100, self.n * o.percent, "left").tolist()
        self.last = np.searchsorted(self.n * o.percent, self.n * 100, "right").tolist()

    def agreeing(self, i: int, start: int | None = None) -> tuple[int, np.ndarray]:
        """(first place, agreeing tokens from there on) of the sets in range of the i-th."""
        a = self.first[i] if start is None else start
        return a, (self.sig[a : self.last[i]] == self.sig[i]).sum(axis=1)


def _forest(ids: np.ndarray, n: np.ndarray, sig: np.ndarray, o: Options) -> list[tuple[int, int]]:
    """The likeliest pairs of a node that join what can be joined: a tree grows by the class nearest to it, until none is likely; then the next."""
    node, m, out = _Node(ids, n, sig, o), len(ids), []
    best, parent, waiting = np.full(m, -1), np.zeros(m, np.int64), np.ones(m, bool)
    for _ in range(m):
        i = int(np.where(waiting, best, -2).argmax())
        if best[i] >= node.likely:
            out.append((int(node.ids[parent[i]]), int(node.ids[i])))
        waiting[i] = False
        a, agree = node.agreeing(i)
        near = slice(a, a + len(agree))
        closer = (agree > best[near]) | ((agree == best[near]) & (node.ids[i] < node.ids[parent[near]]))
        best[near][closer] = agree[closer]
        parent[near][closer] = i
    return out


def _open_rows(ids: np.ndarray, n: np.ndarray, sig: np.ndarray, label: np.ndarray, o: Options) -> np.ndarray:
    """Rows of a node that have a likely pair of another label."""
    node, found = _Node(ids, n, sig, o), np.zeros(len(ids), bool)
    label = label[node.order]
    for i in range(len(ids) - 1):
        a, agree = node.agreeing(i, i + 1)
        ok = (agree >= node.likely) & (label[a : a + len(agree)] != label[i])
        if ok.any():
            found[i] = True
            found[a : a + len(agree)] |= ok
    return np.sort(node.order[found])


def _pairs(out: list[tuple[int, int]]) -> pa.RecordBatch:
    both = np.array(out, np.int64).reshape(-1, 2)
    return pa.RecordBatch.from_arrays([pa.array(both.min(axis=1)), pa.array(both.max(axis=1))], ["a", "b"])


def _by_node(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, list[pa.Array]]]:
    """(node, its other columns) from rows that come sorted by node, the first column; one node's rows are held at a time."""
    held: list[pa.RecordBatch] = []

    def whole() -> tuple[int, list[pa.Array]]:
        table = pa.Table.from_batches(held).combine_chunks()
        return table.column(0)[0].as_py(), [c.combine_chunks() if isinstance(c, pa.ChunkedArray) else c for c in table.columns[1:]]

    for batch in batches:
        node = batch.column(0).to_numpy()
        cuts = [0, *(np.flatnonzero(node[1:] != node[:-1]) + 1).tolist(), len(node)]
        for a, b in zip(cuts[:-1], cuts[1:]):
            if held and b > a and held[0].column(0)[0].as_py() != node[a]:
                yield whole()
                held = []
            if b > a:
                held.append(batch.slice(a, b - a))
    if held:
        yield whole()


def _sorted_by_node(rows: DataFrame) -> DataFrame:
    """Rows of a node together in one task; nodes are bounded by ``leaf``."""
    return rows.repartition("node").sortWithinPartitions("node")


def small_pairs(members: DataFrame, reps: DataFrame, o: Options) -> DataFrame:
    """a, b: pairs to verify first, of nodes of at most ``leaf`` classes."""
    rows = _sorted_by_node(members.join(reps.select("id", "n", "sig"), "id").select("node", "id", "n", "sig"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out = []
        for _, (ids, n, sig) in _by_node(batches):
            out += _forest(ids.to_numpy(), n.to_numpy(), _tokens(sig, o.tokens), o)
            if len(out) > 10_000:
                yield _pairs(out)
                out = []
        yield _pairs(out)

    return textscan.mapped(rows, run, "a long, b long").distinct()


def open_members(members: DataFrame, reps: DataFrame, labels: DataFrame, o: Options) -> DataFrame:
    """node, id, label, n, sig of the classes that have a likely pair with another group of their node."""
    rows = _sorted_by_node(_labelled(members, labels).join(reps.select("id", "n", "sig"), "id").select("node", "id", "label", "n", "sig"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for node, columns in _by_node(batches):
            ids, label, n, sig = columns
            keep = pa.array(_open_rows(ids.to_numpy(), n.to_numpy(), _tokens(sig, o.tokens), label.to_numpy(), o))
            if len(keep):
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(keep), node)), *[c.take(keep) for c in columns]], ["node", "id", "label", "n", "sig"])

    return textscan.mapped(rows, run, "node long, id long, label long, n long, sig binary")


def open_links(open_: DataFrame, texts: DataFrame, o: Options) -> DataFrame:
    """a, b: links between different groups of a node, from its classes' full sets; pairs that links already join are passed over."""
    rows = _sorted_by_node(open_.join(texts, "id").select("node", "id", "label", "n", "sig", "text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, (ids, label, n, sig, text) in _by_node(batches):
            node = _Node(ids.to_numpy(), n.to_numpy(), _tokens(sig, o.tokens), o)
            label, groups, sets, out = label.to_numpy()[node.order].tolist(), _Groups(), {}, []

            def set_of(k: int, node=node, sets=sets, text=text) -> np.ndarray:
                if k not in sets:
                    sets[k] = next(textscan.shingle_sets(*textscan.buffers(text.slice(int(node.order[k]), 1)), o.words))
                return sets[k]

            for i in range(len(label) - 1):
                a, agree = node.agreeing(i, i + 1)
                likely = np.flatnonzero(agree >= node.likely)
                for j in (a + likely[np.argsort(-agree[likely], kind="stable")]).tolist():
                    if groups.top(label[i]) != groups.top(label[j]) and _similar(set_of(i), set_of(j), o):
                        groups.join(label[i], label[j])
                        out.append((int(node.ids[i]), int(node.ids[j])))
                sets.pop(i, None)
            yield _pairs(out)

    return textscan.mapped(rows, run, "a long, b long").distinct()


def _similar(x: np.ndarray, y: np.ndarray, o: Options) -> bool:
    both = len(np.intersect1d(x, y, assume_unique=True))
    return both > 0 and 100 * both >= o.percent * (len(x) + len(y) - both)


def star_pairs(members: DataFrame, leaders: DataFrame, reps: DataFrame, o: Options) -> DataFrame:
    """a, b: likely pairs of a node's classes with its leaders (node, leader).

    A node's classes are dealt out in shares of about ``leaf``; each share meets all leaders of its node in one task, which gives
    out likely pairs only.
    """
    tokens = reps.select("id", "n", "sig")
    share = lambda size: F.greatest(F.lit(1), F.ceil(F.col(size) / o.leaf)).cast("int")
    rows = members.join(tokens, "id").select(F.col("node").alias("node"), F.pmod(F.xxhash64("id"), share("size")).cast("int").alias("share"), "id", "n", "sig")
    sizes = members.groupBy("node").agg(F.max("size").alias("size"))
    heads = leaders.withColumnRenamed("leader", "id").join(tokens, "id").join(sizes, "node")
    heads = heads.select(F.col("node").alias("node_"), F.explode(F.sequence(F.lit(0), share("size") - 1)).alias("share_"), F.col("id").alias("id_"), F.col("n").alias("n_"), F.col("sig").alias("sig_"))

    def run(own: pd.DataFrame, head: pd.DataFrame) -> pd.DataFrame:
        out = []
        if len(own) and len(head):
            ids, n = own["id"].to_numpy(), own["n"].to_numpy()
            sig = np.frombuffer(b"".join(own["sig"]), np.uint32).reshape(-1, o.tokens)
            for x, k, tokens in zip(head["id_"], head["n_"], head["sig_"]):
                agree = (sig == np.frombuffer(tokens, np.uint32)).sum(axis=1)
                ok = (agree >= o.likely) & (np.minimum(n, k) * 100 >= np.maximum(n, k) * o.percent) & (ids != x)
                out += [(min(x, y), max(x, y)) for y in ids[ok].tolist()]
        both = np.array(out, np.int64).reshape(-1, 2)
        return pd.DataFrame({"a": both[:, 0], "b": both[:, 1]})

    return rows.groupBy("node", "share").cogroup(heads.groupBy("node_", "share_")).applyInPandas(run, "a long, b long").distinct()


def verified(pairs: DataFrame, texts: DataFrame, o: Options) -> DataFrame:
    """a, b, linked: each pair judged on its full sets."""
    rows = pairs.join(texts.select(F.col("id").alias("a"), F.col("text").alias("ta")), "a").join(texts.select(F.col("id").alias("b"), F.col("text").alias("tb")), "b").select("a", "b", "ta", "tb")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            step = max(1, int(len(whole) * textscan.SLICE_BYTES / max(1, whole.nbytes)))
            for k in range(0, len(whole), step):
                batch = whole.slice(k, step)
                left, right = (textscan.shingle_sets(*textscan.buffers(batch.column(c)), o.words) for c in (2, 3))
                linked = [_similar(x, y, o) for x, y in zip(left, right)]
                yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(linked, pa.bool_())], ["a", "b", "linked"])

    return textscan.mapped(rows, run, "a long, b long, linked boolean")


def _labelled(members: DataFrame, labels: DataFrame) -> DataFrame:
    return members.join(labels, "id", "left").withColumn("label", F.coalesce("label", "id"))


def nodes(reps: DataFrame, o: Options) -> tuple[DataFrame, DataFrame | None]:
    """node, id, size of the small nodes of all levels, and of the nodes that stay large (None if there are none)."""
    members, small, large = dense(roots(reps, o), "nodes"), [], []
    for level in range(o.levels + 1):
        small.append(members.where(F.col("size") <= o.leaf))
        rest = members.where(F.col("size") > o.leaf)
        if not rest.take(1):
            break
        similar = (F.col("size") >= o.stays * F.col("parent")) & (F.col("parent") > 0) if level < o.levels else F.lit(True)
        large.append(rest.where(similar))
        again = rest.where(~similar)
        if not again.take(1):
            break
        members = dense(branched(again, reps, o), "nodes")
    return reduce(DataFrame.unionByName, small), reduce(DataFrame.unionByName, large) if large else None


class _Judged:
    """Links that were confirmed, and the groups that they make."""

    def __init__(self, docs: DataFrame, o: Options):
        self.docs, self.o, self.links, self.labels = docs, o, None, None

    def texts(self, ids: DataFrame) -> DataFrame:
        return only(self.docs, ids, "id")

    def add(self, links: DataFrame) -> None:
        links = written(links, "links")
        self.links = links if self.links is None else self.links.unionByName(links)
        if self.labels is None or links.take(1):
            self.labels = written(components(self.links), "labels")

    def verify(self, pairs: DataFrame) -> None:
        pairs = written(pairs, "pairs")
        ids = pairs.select(F.col("a").alias("id")).unionByName(pairs.select(F.col("b").alias("id")))
        self.add(verified(pairs, written(self.texts(ids), "texts"), self.o).where("linked").select("a", "b"))

    def mixed(self, members: DataFrame) -> DataFrame:
        """The nodes that hold more than one group."""
        found = _labelled(members, self.labels).groupBy("node").agg(F.min("label").alias("x"), F.max("label").alias("y")).where("x <> y").select("node")
        return members.join(found, "node")

    def close(self, members: DataFrame, reps: DataFrame) -> None:
        """Finds all links that small nodes still lack."""
        open_ = written(open_members(self.mixed(members), reps, self.labels, self.o), "open")
        if open_.take(1):
            self.add(open_links(open_, self.texts(open_), self.o))


def links(reps: DataFrame, docs: DataFrame, o: Options) -> DataFrame:
    """id, label of the classes that have a link. docs: id, text; reps: id, n, sig."""
    small, large = nodes(reps, o)
    pairs = small_pairs(small, reps, o)
    if large is not None:
        picks = [F.min_by("id", F.xxhash64("id", "node", F.lit(k))).alias(f"l{k}") for k in range(o.leaders)]
        leaders = large.groupBy("node").agg(*picks).select("node", F.explode(F.array_distinct(F.array(*[f"l{k}" for k in range(o.leaders)]))).alias("leader"))
        pairs = pairs.unionByName(star_pairs(large, leaders, reps, o)).distinct()
    judged = _Judged(docs, o)
    judged.verify(pairs)
    judged.close(small, reps)
    level = o.levels
    while large is not None:
        level += 1
        within = written(_labelled(judged.mixed(large).select("node", "id", "size"), judged.labels), "large")
        if not within.take(1):
            break
        counts = within.groupBy("node", "label").agg(F.count("*").alias("k"))
        largest = written(counts.groupBy("node").agg(F.max_by("label", F.struct("k", "label")).alias("main"), (F.sum("k") - F.max("k")).alias("others")), "largest")
        final = F.col("others") <= (o.minority if level < o.depth else 1 << 62)
        outside = within.join(largest.where(final), "node").where("label <> main").select("node", F.col("id").alias("leader"))
        judged.verify(star_pairs(within.join(largest.where(final).select("node"), "node"), outside, reps, o))
        rest = written(within.join(largest.where(~final).select("node"), "node").select("node", "id", "size"), "open")
        if not rest.take(1):
            break
        members = dense(branched(rest, reps, o), "nodes")
        low, large = members.where(F.col("size") <= o.leaf), members.where(F.col("size") > o.leaf)
        judged.close(low, reps)
    return judged.labels


def groups(df: DataFrame, o: Options = Options(), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: id_col, n_shingles, component_id (smallest id reachable by links), kept."""
    signed = written(sign(df, o, id_col, text_col), "signed")
    reps = written(signed.where("n > 0").groupBy("key").agg(F.min("id").alias("id"), F.first("n").alias("n"), F.first("sig").alias("sig")), "classes")
    labels = links(reps, df.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text")), o)
    named = reps.select("key", "id").join(labels, "id", "left").select("key", F.coalesce("label", "id").alias("component_id"))
    out = signed.select("id", "n", "key").join(named, "key", "left")
    component = F.coalesce("component_id", "id")
    return out.select(F.col("id").alias(id_col), F.col("n").alias("n_shingles"), component.alias("component_id"), (F.col("id") == component).alias("kept"))


def kept_only(df: DataFrame, o: Options = Options(), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``df`` without the documents that another of their group stands for; the one of smallest id stays, null ids last.

    Rows are judged, not ids: a row goes by a 64-bit hash of its id and text. Rows that repeat both are one. Rows of null id without a
    word are never repeats.
    """
    rows = df.withColumn("__row", row_key(id_col, text_col))
    ids = rows.select("__row", F.col(id_col).cast("long").alias("own"))
    judged = written(groups(rows, o, "__row", text_col).select(F.col("__row").alias("id"), "n_shingles", "component_id"), "judged")
    distinct = ids.groupBy("__row").agg(F.min("own").alias("own"), F.count("*").alias("n"))
    known = written(judged.groupBy("id", "component_id").agg(F.max("n_shingles").alias("n_shingles")).join(distinct, F.col("id") == F.col("__row")), "rows")
    first = known.groupBy("component_id").agg(F.min(F.struct(F.col("own").isNull(), "own", "id"))["id"].alias("first"))
    gone = known.join(first, known["id"] == first["first"], "left_anti").select("id")
    repeated = known.where("n > 1 AND (own IS NOT NULL OR n_shingles > 0)").select("id")
    return without(rows, gone, "__row", single=repeated).select(df.columns)
