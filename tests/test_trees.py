"""Trees against a depth-first reference, their options, and the homogeneity objective against dense arrays."""

import hashlib
import math

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from privmatrix.functions import budget, measures, noise
from privmatrix.operators import cells, homogeneity, publish, stops, tree
from privmatrix.plans import matrices
from privmatrix.sources.spec import plain


def uniform(salt, purpose, *keys):
    return (int(hashlib.sha256("|".join([salt, purpose, *map(str, keys)]).encode()).hexdigest()[:13], 16) + 0.5) / 2**52


def laplace(salt, scale, purpose, *keys):
    u = uniform(salt, purpose, *keys)
    return -scale * np.sign(u - 0.5) * math.log(1 - 2 * abs(u - 0.5))


def depth_first(array, eps, salt):
    """Leaves of the even tree by plain recursion over a dense array."""
    d, out = array.ndim, []

    def visit(path, box, k, acc, levels):
        part = array[tuple(slice(a, b) for a, b in box)]
        count = int(part.sum())
        if k == d:
            out.append((path, box, count + laplace(salt, 1 / (eps - acc), "leaf", path)))
            return
        own = eps / 100 if k == 0 else levels[k - 1]
        noisy, left = count + laplace(salt, 1 / own, "count", path), eps - acc - own
        g = (max(noisy, 0) * left / math.sqrt(2)) ** (2 / (3 * (d - k)))
        lo, hi = box[k]
        if k == 0:
            m0 = max(1.0, g)
            weights = [m0 ** (i / 3) for i in range(1, d + 1)]
            levels = [0.99 * eps * w / sum(weights) for w in weights]
        if noisy < math.sqrt(2) / own:
            out.append((path, box, count + laplace(salt, 1 / left, "leaf", path)))
            return
        m, w = int(max(1, min(math.floor(g + 0.5), hi - lo))), hi - lo
        for j in range(m):
            visit(f"{path}.{j}", [*box[:k], (lo + j * w // m, lo + (j + 1) * w // m), *box[k + 1 :]], k + 1, acc + own, levels)

    visit("r", [(0, w) for w in array.shape], 0, 0.0, None)
    return out


def dense(table, widths):
    array = np.zeros(widths, int)
    for row in table.collect():
        array[tuple(row[f"x{i}"] for i in range(1, len(widths) + 1))] = row["f"]
    return array


@pytest.mark.parametrize("name, eps", [("line3", 0.5), ("clock2", 0.3)])
def test_even_tree_equals_depth_first(spark, small, name, eps):
    table, spec = matrices.cells(spark, small, name)
    want = {p: (box, n) for p, box, n in depth_first(dense(table, spec.widths), eps, noise.release_salt("42", "tree", eps, spec.key, tree.TreeOptions().text(), ""))}
    got = {r["pid"]: r for r in tree.even_tree(table.repartition(5), spec, eps, salt="42").partitions().collect()}
    assert set(got) == set(want)
    for p, (box, n) in want.items():
        assert [(got[p][f"lo{i}"], got[p][f"hi{i}"]) for i in range(1, spec.d + 1)] == [tuple(b) for b in box]
        assert got[p]["ncount"] == pytest.approx(n, abs=1e-6)


OPTIONS = [{}, {"final": "combine"}, {"levels": "equal"}, {"base": "gross"}, {"stop": stops.below(300.0)}, {"stop": stops.never()}, {"stop": stops.any_of(stops.max_depth(2), stops.min_width(2))}, {"homogeneous": True}, {"homogeneous": True, "cuts": "m-1"}, {"homogeneous": True, "root_prt": "even"}, {"homogeneous": True, "stop_order": "before"}]


@pytest.mark.parametrize("options", OPTIONS)
def test_boxes_tile_the_domain_and_paths_spend_eps(spark, small, options):
    table, spec = matrices.cells(spark, small, "line3")
    grown = tree.grow(table, spec, 0.4, tree.TreeOptions(**options), salt="42")
    parts = grown.partitions().persist()
    assert parts.agg(F.sum("n_entries")).first()[0] == spec.entries
    assert publish.overlapping(parts, 3).count() == 0 and publish.uncovered(parts, table, 3).count() == 0
    low, high = budget.path_total(grown.ledger()).agg(F.min("eps"), F.max("eps")).first()
    assert low == pytest.approx(0.4, abs=1e-9) and high == pytest.approx(0.4, abs=1e-9)


def test_root_may_stop(spark, small):
    table, spec = matrices.cells(spark, small, "line3")
    parts = tree.even_tree(table, spec, 0.1, stop=stops.below(1e12), salt="42").partitions().collect()
    assert [p["pid"] for p in parts] == ["r"] and parts[0]["n_entries"] == spec.entries


def test_empty_table(spark):
    empty = spark.createDataFrame([], "x1 int, x2 int, f long")
    parts = tree.even_tree(empty, plain("e", 5, 4), 0.5, salt="42").partitions()
    assert parts.agg(F.sum("n_entries")).first()[0] == 20


def test_printed_candidate_noise_is_marked_unproven(spark, small):
    table, spec = matrices.cells(spark, small, "line2")
    for kind, proven in (("composed", True), ("noisy_min", True), ("equation", False), ("algorithm", False)):
        grown = tree.homogeneous_tree(table, spec, 0.4, p=2, stop=stops.never(), salt="42", candidate_noise=kind)
        assert grown.ledger().agg(F.min("proven")).first()[0] is proven


def test_stop_may_not_read_true_counts():
    with pytest.raises(ValueError):
        stops.Stop("cnt < 5")


def test_inspection_keeps_inner_nodes(spark, small):
    table, spec = matrices.cells(spark, small, "line2")
    grown = tree.even_tree(table, spec, 0.5, salt="42")
    every = grown.partitions(keep_nodes=True)
    assert every.where("pid = 'r'").count() == 1 and every.count() > grown.partitions().count()
    assert measures.fanouts(every).count() >= 1


def dense_objective(array, ends, axis):
    total = 0.0
    for a, b in zip(ends[:-1], ends[1:]):
        slab = np.take(array, range(a, b), axis=axis).astype(float)
        total += np.abs(slab - slab.mean()).sum()
    return total


@settings(max_examples=8, deadline=None)
@given(st.integers(0, 10_000))
def test_objective_equals_dense_and_moves_by_less_than_two(spark, seed):
    draw = np.random.default_rng(seed)
    array = draw.integers(0, 4, (6, 5)) * draw.integers(0, 2, (6, 5))
    other = array.copy()
    other[tuple(draw.integers(0, (6, 5)))] += 1
    ends = [0, *sorted({int(x) for x in draw.integers(1, 6, 2)}), 6]
    cands = spark.createDataFrame([("r", 1, ends)], "node string, cand int, ends array<int>")
    sides = spark.createDataFrame([("r", 5.0)], "node string, area double")
    found = []
    for a in (array, other):
        rows = [("r", int(i), int(j), int(a[i, j])) for i in range(6) for j in range(5) if a[i, j]]
        table = spark.createDataFrame(rows, "node string, x1 int, x2 int, f long")
        found.append(homogeneity.objective(homogeneity.profile(table, "x1"), cands, sides).first()["o"])
        assert found[-1] == pytest.approx(dense_objective(a, ends, 0))
    assert abs(found[0] - found[1]) < homogeneity.SENSITIVITY


def test_neighbour_changes_one_box_by_one(spark, small):
    records = matrices.records(spark, small, "line2")
    spec = matrices.SPECS["line2"]
    one = records.limit(1)
    exact = lambda df: tree.even_tree(cells.build_cells(df, spec), spec, 0.5, stop=stops.never(), salt="42", noisy=False)
    a, b = exact(records).partitions(), exact(cells.neighbour(records, one)).partitions()
    both = publish.compared(a, b, 2).where("a <> b OR a IS NULL OR b IS NULL").collect()
    assert len(both) == 1 and both[0]["a"] - both[0]["b"] == 1
