"""Experiment workloads at and above the sizes of their oracles' run."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from privmatrix.operators import answer, baselines, homogeneity
from privmatrix.operators.cells import clustered
from privmatrix.plans import catalogue, experiments, matrices
from privmatrix.sources import synth, workload

FULL = "/root/testdata/sf0.1"


@pytest.mark.parametrize("query, name", [("workload_od", "od4"), ("workload_od_stops", "od6")])
def test_od_counts_every_trip(spark, monkeypatch, query, name):
    """sf0.1 has 600,000 trips; the SQL counts them all."""
    held = {}

    class Held(Exception):
        pass

    def caught(cells, *rest):
        held["n"] = cells.agg({"f": "sum"}).first()[0]
        raise Held

    monkeypatch.setattr(experiments, "accuracy", caught)
    with pytest.raises(Held):
        catalogue.QUERIES[query](spark, FULL)
    assert held["n"] == matrices.records(spark, FULL, name).count() > 500_000


@pytest.mark.parametrize("name", ["line1", "line2", "line3", "line5"])
def test_batched_answers_agree(spark, small, monkeypatch, name):
    """Matrix products, boxes weighed alone, a full table and several batches give the answers of the pairwise join."""
    table, spec = matrices.cells(spark, small, name)
    q = workload.random_queries(spark, spec, 40, "7").unionByName(workload.coverage_queries(spark, spec, 1.0, 1).withColumn("qid", F.lit(999).cast("long")))
    want = {r[0]: r[1] for r in answer.truth(table, q, spec.d, "nested").collect()}
    for cells in (clustered(table, spec.d), table.orderBy(F.rand(1))):
        assert {r[0]: r[1] for r in answer.truth(cells, q, spec.d, "batched").collect()} == want
    for method in ("entropy_grid", "even_tree"):
        parts = experiments.release(method, table, spec, 0.5, "42").persist()
        a, b = ({r[0]: r[1] for r in answer.answer(parts, q, spec.d, s).collect()} for s in ("nested", "batched"))
        assert a.keys() == b.keys() and all(a[k] == pytest.approx(b[k], abs=1e-6) for k in a)
    grids_ = experiments.release("entropy_grid", table, spec, 0.5, "42", addends=True)
    a, b = ({r[0]: r[1] for r in answer.answer(p, q, spec.d, "batched").collect()} for p in (experiments.release("entropy_grid", table, spec, 0.5, "42"), grids_))
    assert all(a[k] == pytest.approx(b[k], abs=1e-6) for k in a)


def test_weigher_takes_any_batches(monkeypatch):
    rng = np.random.default_rng(1)
    for d, units, room in [(1, False, 8_000_000), (2, True, 8_000_000), (2, False, 300), (4, True, 8_000_000), (3, False, 900)]:
        monkeypatch.setattr(answer, "TABLE_VALUES", room)
        monkeypatch.setattr(answer, "CHUNK_VALUES", 100)
        ends = np.sort(rng.integers(0, 9, (2, d, 30)), 0)
        qlo, qhi = ends[0], ends[1] + 1
        w = answer.Weigher(qlo, qhi, d)
        want = np.zeros(30)
        for rows in (1, 400, 50):
            lo = rng.integers(0, 8, (d, rows))
            hi = lo + (1 if units else rng.integers(1, 4, (d, rows)))
            f = rng.normal(size=rows)
            w.add(list(lo), list(hi), f, units)
            share = np.prod(np.maximum(0, np.minimum(hi[:, :, None], qhi[:, None]) - np.maximum(lo[:, :, None], qlo[:, None])) / (hi - lo)[:, :, None], 0)
            want += f @ share
        assert np.allclose(w.total, want)


@pytest.mark.parametrize("cuts", ["m", "m-1"])
def test_slab_by_base_interval(spark, cuts):
    nodes = spark.range(60).select(F.col("id").cast("string").alias("node"), F.lit(3).alias("lo"), (F.lit(4) + F.col("id") % 40).cast("int").alias("hi"))
    nodes = nodes.withColumn("m", F.least(F.col("hi") - F.col("lo"), (1 + F.col("node").cast("int") % 7)).cast("int"))
    c = homogeneity.candidates(nodes, 5, cuts, salt="42").join(nodes, "node").select("*", F.explode(F.sequence(F.col("lo"), F.col("hi") - 1)).alias("x"))
    near = homogeneity.slab_near(F.col("ends"), F.col("x"), F.col("lo"), F.col("hi") - F.col("lo"), F.col("m"))
    assert c.where(near != homogeneity.slab_of(F.col("ends"), F.col("x"))).count() == 0 < c.count()


def test_noise_of_entries_and_truth_are_the_release(spark, small):
    table, spec = matrices.cells(spark, small, "line2")
    q = workload.random_queries(spark, spec, 40, "7")
    got = {r["qid"]: r["est"] for r in experiments.accuracy(table, spec, q, "42", ("cell_noise",), (0.1,)).collect()}
    want = {r["qid"]: r["est"] for r in answer.answer(baselines.cell_noise(table, spec, 0.1, salt="42"), q, 2, "nested").collect()}
    assert got.keys() == want.keys() and all(got[k] == pytest.approx(want[k], abs=1e-6) for k in want)


@pytest.mark.parametrize("d", [2, 4])
def test_spreads_share_draws(spark, small, d):
    keys = synth.points(matrices.load(spark, small, "orders"), 2)
    spec = synth.gaussian_spec(keys.count(), d)
    drawn = synth.normals(keys, d, "42")
    for sd in (0.05, 0.4):
        assert sorted(map(tuple, synth.gaussian(keys, spec, sd, "42").collect())) == sorted(map(tuple, synth.gaussian_of(drawn, spec, sd, "42").collect()))


@pytest.mark.parametrize("name", ["candidates", "coverage_queries", "level_budgets", "random_queries", "sql_grid_boxes", "worked_example"])
def test_query_reads_a_given_table_and_equals_its_sql(spark, duck, small, name):
    df = catalogue.QUERIES[name](spark, small)
    assert any(f.startswith(f"file://{small}") for f in df.inputFiles())
    columns, rel = sorted(df.columns), duck.execute(catalogue.ORACLES[name])
    names = [x[0] for x in rel.description]
    got = sorted((tuple(r[c] for c in columns) for r in df.collect()), key=str)
    want = sorted((tuple(r[names.index(c)] for c in columns) for r in rel.fetchall()), key=str)
    assert sorted(names) == columns and len(got) == len(want) > 0
    assert all(x == (pytest.approx(y, abs=2e-6) if isinstance(y, float) else y) for r, s in zip(got, want) for x, y in zip(r, s))
