"""Noise, budgets and golden numbers of the rules."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from privmatrix.functions import budget, measures, noise
from privmatrix.operators import baselines, grids, tree
from privmatrix.plans.sqlapi import PrivateMatrix
from privmatrix.sources.spec import plain


def test_keyed_uniform_is_uniform_and_stable(spark):
    u = np.array([r[0] for r in spark.range(10_000).select(noise.keyed_uniform("s", "count", "id")).collect()])
    again = np.array([r[0] for r in spark.range(10_000).repartition(7).orderBy("id").select(noise.keyed_uniform("s", "count", "id")).collect()])
    assert (u == again).all() and 0 < u.min() and u.max() < 1
    assert np.abs(np.sort(u) - (np.arange(10_000) + 0.5) / 10_000).max() < 0.02


def test_purposes_draw_apart(spark):
    row = spark.range(1).select(*[noise.keyed_uniform("s", p, "id").alias(p) for p in noise.PURPOSES]).first()
    assert len(set(row)) == len(noise.PURPOSES)


def test_laplace_moments(spark):
    x = np.array([r[0] for r in spark.range(10_000).select(noise.laplace("s", "leaf", 10.0, "id")).collect()])
    assert abs(x.mean()) < 0.6 and abs(x.var() - 200) < 20


def test_geometric_is_whole_and_centred(spark):
    x = np.array([r[0] for r in spark.range(5_000).select(noise.geometric("s", "leaf", 5.0, "id")).collect()])
    assert (x == np.round(x)).all() and abs(x.mean()) < 0.5


GOLDEN = [(2, 0.1, 99.50, 41.21), (3, 0.3, 21.62, 15.23), (4, 0.5, 9.92, 8.39), (5, 0.1, 4.64, 4.43), (6, 0.5, 4.30, 4.13)]


@pytest.mark.parametrize("d, eps, error, entropy", GOLDEN)
def test_golden_granularity(spark, d, eps, error, entropy):
    n = F.lit(1e6)
    row = spark.range(1).select(grids.granularity_error(n, eps * 0.99, d), grids.granularity_entropy(n, eps * 0.99, d)).first()
    assert row[0] == pytest.approx(error, abs=0.006) and row[1] == pytest.approx(entropy, abs=0.006)


def test_two_dimensional_base_case(spark):
    got = spark.range(1).select(grids.granularity_error(F.lit(5e5), 0.2, 2), grids.granularity_error(F.lit(5e5), 0.2, 2, r=0.3)).first()
    assert got[0] == pytest.approx(math.sqrt(5e5 * 0.2 / 10)) and got[1] == pytest.approx(got[0])


def test_known_share_minimises_the_error_model(spark):
    m = spark.range(1).select(grids.granularity_error(F.lit(1e6), 0.1, 4, r=0.2)).first()[0]
    cost = lambda x: math.sqrt(0.4) * x**2 / 0.1 + 0.2**0.25 * 1e6 / (grids.C0 * x**3)
    assert cost(m) < cost(m * 1.02) and cost(m) < cost(m / 1.02)


def test_total_and_budget_are_exchangeable(spark):
    row = spark.range(1).select(*[rule(n, e, 3) for rule in (grids.granularity_error, grids.granularity_entropy, grids.granularity_log) for n, e in ((F.lit(1e6), 0.1), (F.lit(5e5), 0.2))]).first()
    assert row[0] == pytest.approx(row[1]) and row[2] == pytest.approx(row[3]) and row[4] != pytest.approx(row[5])


def test_level_budgets(spark):
    for d, eps, expected in ((2, 0.1, [0.0222, 0.0768]), (4, 0.5, [0.0318, 0.0647, 0.1314, 0.2671])):
        m0 = grids.granularity_entropy(F.lit(1e6), eps * 0.99, d)
        got = spark.range(1).select(budget.level_budgets(m0, eps, d), m0).first()
        assert list(got[0]) == pytest.approx(expected, abs=6e-5) and sum(got[0]) == pytest.approx(0.99 * eps)
        best = measures.level_noise(got[1], got[0])
        moved = [got[0][0] * 1.05, *got[0][1:-1], got[0][-1] - got[0][0] * 0.05]
        assert best < measures.level_noise(got[1], moved) and best < measures.level_noise(got[1], [eps * 0.99 / d] * d)


def test_gross_base_spends_all(spark):
    got = spark.range(1).select(budget.level_budgets(F.lit(9.0), 0.1, 3, base="gross"), budget.level_budgets(F.lit(1.0), 0.1, 3)).first()
    assert sum(got[0]) == pytest.approx(0.099) and list(got[1]) == pytest.approx([0.033] * 3)


def test_ledger_guard(spark):
    ok = spark.createDataFrame([("r.1", "count", 0.04, True), ("r.1", "leaf", 0.06, True), ("r.2", "leaf", 0.1, True)], "path string, purpose string, eps double, proven boolean")
    budget.assert_within(ok, 0.1)
    with pytest.raises(ValueError):
        budget.assert_within(ok, 0.09)


def test_releases_share_no_noise(spark):
    """Two budgets, methods, matrices or labels under one secret salt: their noise cannot be solved for a count."""
    table, spec = spark.createDataFrame([(i % 10, i // 10, i) for i in range(100)], "x1 int, x2 int, f long"), plain("shared", 10, 10)
    a, b = ({r["pid"]: r["ncount"] for r in baselines.cell_noise(table, spec, e, salt="42").collect()} for e in (0.1, 0.5))
    solved = np.array([(0.1 * a[k] - 0.5 * b[k]) / (0.1 - 0.5) for k in sorted(a)])
    true = np.array([float(k.split(".")[1]) + 10 * float(k.split(".")[2]) for k in sorted(a)])
    assert np.abs(solved - true).max() > 1 and np.median(np.abs(solved - true)) > 0.5
    salts = [noise.release_salt("42", m, e, n, x) for m in ("tree", "one_box") for e in (0.1, 0.5) for n in ("p:2", "q:2") for x in ("", "day 2")]
    assert len(set(salts)) == len(salts) == 16
    one = [grids.entropy_grid(table, spec, 0.5, salt="42", label=x).orderBy("pid").first()["ncount"] for x in ("", "", "later")]
    assert one[0] == one[1] != one[2]
    for make in (lambda: grids.entropy_grid(table, spec, 0.5), lambda: tree.even_tree(table, spec, 0.5), lambda: baselines.one_box(table, spec, 0.5)):
        with pytest.raises(TypeError):
            make()
    with pytest.raises(ValueError):
        grids.entropy_grid(table, spec, 0.5, salt="")


def test_a_release_is_claimed_once(spark, tmp_path):
    releases = budget.Releases(spark, f"file://{tmp_path}/claims")
    matrix = PrivateMatrix(spark.createDataFrame([(1, 2), (3, 4)], "x1 int, x2 int"), plain("claimed", 10, 10))
    first = matrix.release("entropy_grid", 0.5, "42", releases=releases).partitions.collect()
    with pytest.raises(ValueError):
        matrix.release("entropy_grid", 0.5, "42", releases=releases)
    second = matrix.release("entropy_grid", 0.5, "42", label="tomorrow", releases=releases).partitions.collect()
    assert {r["pid"]: r["ncount"] for r in first} != {r["pid"]: r["ncount"] for r in second}
