"""Density-aware trees: one axis is split per level, the number of parts follows from a node's noisy count.

Siblings are independent, so all nodes of a level are handled at once; draws are keyed by the node's path, so this gives the same
release as any other order. A level is: children of the open nodes, their counts (empty children too), noise, fan-out, stop test.
Node tables are small and written out at each level, which cuts the plan. Cells pass through one join per level, which is a broadcast while nodes are
few, and keep only the axes that are not split yet: an even tree sums what agrees on them, a homogeneous one, which looks at
single entries, counts entries of one value. So each level reads what the one before has made smaller.
"""

from __future__ import annotations

import math
from dataclasses import dataclass
from functools import reduce
from operator import mul

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from privmatrix.functions import boxes, budget, noise
from privmatrix.operators import homogeneity
from privmatrix.operators.stops import Stop, below_noise
from privmatrix.sources.spec import MatrixSpec
from privmatrix.sources.store import written

SPENT = "array<struct<purpose: string, eps: double, proven: boolean>>"


@dataclass(frozen=True)
class TreeOptions:
    """stop: when a node is left whole. final: a stopped node's count is drawn anew with the budget left, or combined with the first draw.

    levels: budgets in geometric or equal shares; base: see ``budget.level_budgets``. The rest is for homogeneous trees: p candidates, the
    share q of a level's budget for choosing among them, how many cuts, the candidates' noise, how the root's budget is used, and whether
    a node is tested before or after its split was paid.
    """

    stop: Stop | None = None
    final: str = "redraw"
    levels: str = "geometric"
    base: str = "net"
    root_fraction: float = budget.ROOT_FRACTION
    s: float = 1.0
    noisy: bool = True
    homogeneous: bool = False
    p: int = 5
    q: float = budget.SPLIT_SHARE
    cuts: str = "m"
    candidate_noise: str = "composed"
    root_prt: str = "share"
    stop_order: str = "after"

    def text(self) -> str:
        """The options that change a release."""
        even = (self.final, self.levels, self.base, self.root_fraction, self.s)
        chosen = (self.p, self.q, self.cuts, self.candidate_noise, self.root_prt, self.stop_order)
        return ",".join(map(str, ((self.stop or below_noise()).text, *even, *(chosen if self.homogeneous else ()))))


@dataclass
class Tree:
    """leaves: released boxes with their ledger; nodes: all nodes, for the curator only."""

    spec: MatrixSpec
    leaves: DataFrame
    nodes: DataFrame

    def partitions(self, keep_nodes: bool = False) -> DataFrame:
        """pid, bounds, n_entries, ncount, depth, eps_path of the leaves; or of all nodes, for inspection."""
        d, source = self.spec.d, self.nodes if keep_nodes else self.leaves
        return source.select(F.col("node").alias("pid"), *boxes.bounds(d), boxes.volume(d).alias("n_entries"), "ncount", "depth", F.aggregate("spent", F.lit(0.0), lambda acc, x: acc + x["eps"]).alias("eps_path"))

    def ledger(self) -> DataFrame:
        """path, purpose, eps, proven: every expense on the path to every leaf."""
        return self.leaves.select(F.col("node").alias("path"), F.explode("spent").alias("e")).select("path", "e.purpose", "e.eps", "e.proven")


def fanout(ncount: Column, eps_left: Column, dims_left: int) -> Column:
    """The entropy rule on the axes that are left, before rounding."""
    return F.pow(F.greatest(ncount, F.lit(0.0)) * eps_left / math.sqrt(2), F.lit(2 / (3 * dims_left)))


def _clamped(g: Column, width: Column) -> Column:
    return F.greatest(F.lit(1.0), F.least(F.round(g), width.cast("double"))).cast("int")


def _spend(purpose: str, eps: Column, proven: bool = True) -> Column:
    return F.array(F.struct(F.lit(purpose).alias("purpose"), eps.alias("eps"), F.lit(proven).alias("proven")))


def _sanitised(nodes: DataFrame, k: int, d: int, eps: float, o: TreeOptions, salt: str) -> DataFrame:
    """Noisy counts, budgets, fan-out and the stop test of the nodes of depth k < d."""
    width = F.col(f"hi{k + 1}") - F.col(f"lo{k + 1}")
    whole = F.lit(budget.root_share(eps, o.root_fraction)) if k == 0 else F.element_at("levels", k)
    chooses = o.homogeneous and not (k == 0 and o.root_prt == "even")
    prt, data = budget.split(whole, o.q) if chooses else (F.lit(0.0), whole)
    drawn = noise.laplace(salt, "count", F.lit(o.s) / F.col("eps_k"), "node") if o.noisy else F.lit(0.0)
    out = nodes.withColumn("eps_prt", prt).withColumn("eps_k", data).withColumn("ncount", F.col("cnt") + drawn).withColumn("acc", F.col("acc") + whole)
    out = out.withColumn("eps_left", F.lit(eps) - F.col("acc")).withColumn("width", width).withColumn("g", fanout(F.col("ncount"), F.col("eps_left"), d - k)).withColumn("m", _clamped(F.col("g"), width))
    if k == 0:
        shares = budget.equal_budgets(eps, d, budget.root_share(eps, o.root_fraction)) if o.levels == "equal" else budget.level_budgets(F.col("g"), eps, d, budget.root_share(eps, o.root_fraction), o.base)
        out = out.withColumn("levels", shares)
    stop = (o.stop or below_noise()).column()
    saved = F.col("eps_prt") if o.homogeneous and o.stop_order == "before" else F.lit(0.0)
    out = out.withColumn("leaf", F.coalesce(stop, F.lit(False))).withColumn("eps_left", F.when(F.col("leaf"), F.col("eps_left") + saved).otherwise(F.col("eps_left")))
    spent = F.concat("spent", _spend("count", F.col("eps_k")))
    if chooses:
        proven = homogeneity.CANDIDATE_NOISE[o.candidate_noise][1]
        paid = F.concat(spent, _spend("split", F.col("eps_prt"), proven))
        spent = F.when(F.col("leaf"), spent).otherwise(paid) if o.stop_order == "before" else paid
    return out.withColumn("spent", spent)


def _leaves(nodes: DataFrame, d: int, o: TreeOptions, salt: str, stopped: bool) -> DataFrame:
    """The last draw of leaves: with all budget that their path has left."""
    drawn = noise.laplace(salt, "leaf", F.lit(o.s) / F.col("eps_left"), "node") if o.noisy else F.lit(0.0)
    last = F.col("cnt") + drawn
    if stopped and o.final == "combine":
        a, b = F.col("eps_k") * F.col("eps_k"), F.col("eps_left") * F.col("eps_left")
        last = (F.col("ncount") * a + last * b) / (a + b)
    return nodes.withColumn("ncount", last).withColumn("spent", F.concat("spent", _spend("leaf", F.col("eps_left")))).select("node", "depth", *boxes.bounds(d), "ncount", "spent")


def _with_ends(nodes: DataFrame, cells: DataFrame, k: int, d: int, o: TreeOptions, salt: str) -> DataFrame:
    """Open nodes with ``ends``: lower ends of their parts on axis k + 1, and its upper end."""
    axis = k + 1
    if not o.homogeneous or (k == 0 and o.root_prt == "even"):
        return nodes.withColumn("ends", homogeneity.base_intervals(F.col(f"lo{axis}"), F.col("width"), F.col("m")))
    cands = homogeneity.candidates(nodes.select("node", F.col(f"lo{axis}").alias("lo"), F.col(f"hi{axis}").alias("hi"), "m"), o.p, o.cuts, salt=salt)
    others = [(F.col(f"hi{i}") - F.col(f"lo{i}")).cast("double") for i in range(1, d + 1) if i != axis]
    sides = nodes.select("node", (reduce(mul, others) if others else F.lit(1.0)).alias("area"), "m")
    profiles = homogeneity.profile(cells.join(nodes.select("node"), "node", "left_semi"), f"x{axis}")
    objectives = homogeneity.objective(profiles, cands, sides)
    noise_of = o.candidate_noise if o.noisy else None
    if noise_of:
        chosen = homogeneity.choose(objectives, nodes.select("node", "eps_prt"), o.p, noise_of, salt=salt)
    else:
        chosen = objectives.groupBy("node").agg(F.min_by("ends", F.struct("o", "cand")).alias("ends"))
    return nodes.join(chosen.select("node", "ends"), "node")


def grow(cells: DataFrame, spec: MatrixSpec, eps: float, o: TreeOptions = TreeOptions(), *, salt: str, label: str = "") -> Tree:
    """Release a tree over cells (x1..xd, f). ``label`` names the state of the data."""
    d, salt = spec.d, noise.release_salt(salt, "tree", eps, spec.key, o.text(), label)
    cells = written(cells, "cells").select(F.lit("r").alias("node"), *spec.axes, "f", F.lit(1).cast("long").alias("n"))
    root = [F.lit(v).cast("int").alias(f"{side}{i}") for i, w in enumerate(spec.widths, 1) for side, v in (("lo", 0), ("hi", w))]
    nodes = cells.agg(F.coalesce(F.sum("f"), F.lit(0)).cast("long").alias("cnt")).select(F.lit("r").alias("node"), F.lit(0).alias("depth"), *root, "cnt", F.lit(0.0).alias("acc"), F.expr(f"cast(array() as {SPENT})").alias("spent"))
    leaves, every = [], []
    for k in range(d):
        nodes = written(_sanitised(nodes, k, d, eps, o, salt), "tree-nodes")
        leaves.append(_leaves(nodes.where("leaf"), d, o, salt, True))
        every.append(nodes.where("NOT leaf").select("node", "depth", *boxes.bounds(d), "ncount", "spent"))
        open_ = _with_ends(nodes.where("NOT leaf"), cells, k, d, o, salt)
        if o.homogeneous:
            open_ = written(open_, "tree-splits")
        axis = k + 1
        part = F.posexplode(F.slice("ends", F.lit(1), F.size("ends") - 1)).alias("j", "__lo")
        same = [c for c in boxes.bounds(d) if c not in (f"lo{axis}", f"hi{axis}")]
        children = open_.select("node", "acc", "levels", "spent", "ends", *same, part).select(
            F.concat_ws(".", "node", "j").alias("node"), F.lit(k + 1).alias("depth"), *same, F.col("__lo").alias(f"lo{axis}"), F.element_at("ends", F.col("j") + 2).alias(f"hi{axis}"), "acc", "levels", "spent"
        )
        x, lo, width, m = F.col(f"x{axis}"), F.col(f"lo{axis}"), F.col("width"), F.col("m")
        j = homogeneity.slab_near(F.col("ends"), x, lo, width, m) if o.homogeneous else boxes.even_index(x, lo, width, m)
        route = open_.select("node", f"lo{axis}", "width", "m", *(["ends"] if o.homogeneous else []))
        routed, left = cells.join(route, "node").select(F.concat_ws(".", "node", j).alias("node"), *spec.axes[k:], "f", "n"), spec.axes[axis:]
        if left:
            if o.homogeneous:
                routed = routed.groupBy("node", *left, "f").agg(F.sum("n").alias("n"))
            else:
                routed = routed.groupBy("node", *left).agg(F.sum("f").alias("f")).withColumn("n", F.lit(1).cast("long"))
            routed = cells = written(routed, "tree-cells")
        counts = routed.groupBy("node").agg(F.sum(F.col("f") * F.col("n")).alias("cnt"))
        nodes = children.join(counts, "node", "left").withColumn("cnt", F.coalesce("cnt", F.lit(0)).cast("long"))
    last = nodes.withColumn("eps_left", F.lit(eps) - F.col("acc"))
    leaves.append(_leaves(last, d, o, salt, False))
    released = reduce(DataFrame.unionByName, leaves)
    return Tree(spec, released, reduce(DataFrame.unionByName, [released, *every]))


def even_tree(cells: DataFrame, spec: MatrixSpec, eps: float, stop: Stop | None = None, *, salt: str, label: str = "", **options) -> Tree:
    return grow(cells, spec, eps, TreeOptions(stop=stop, **options), salt=salt, label=label)


def homogeneous_tree(cells: DataFrame, spec: MatrixSpec, eps: float, p: int = 5, stop: Stop | None = None, *, salt: str, label: str = "", **options) -> Tree:
    return grow(cells, spec, eps, TreeOptions(stop=stop, homogeneous=True, p=p, **options), salt=salt, label=label)
