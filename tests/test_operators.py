"""Grids, baselines, answers, measures, sources, publishing, trajectories and SQL text of the catalogue."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from privmatrix.functions import boxes, measures
from privmatrix.operators import answer, baselines, cells, grids, publish, trajectories
from privmatrix.plans import catalogue, experiments, matrices
from privmatrix.sources import synth, tables, workload
from privmatrix.sources.spec import DimSpec, MatrixSpec, plain


def test_even_index_inverts_bounds(spark):
    rows = [(w, m, x) for w in range(1, 30, 3) for m in range(1, w + 1) for x in range(w)]
    df = spark.createDataFrame(rows, "w int, m int, x int")
    j = boxes.even_index(F.col("x"), 0, F.col("w"), F.col("m"))
    bad = df.withColumn("j", j).where((boxes.even_bound(F.col("j"), 0, F.col("w"), F.col("m")) > F.col("x")) | (boxes.even_bound(F.col("j") + 1, 0, F.col("w"), F.col("m")) <= F.col("x")))
    assert bad.count() == 0


@pytest.mark.parametrize("method", ["uniform_grid", "entropy_grid", "log_grid", "cell_noise", "one_box"])
def test_grids_tile_the_domain(spark, small, method):
    table, spec = matrices.cells(spark, small, "line3")
    parts = experiments.release(method, table, spec, 0.5, "42").persist()
    assert parts.agg(F.sum("n_entries")).first()[0] == spec.entries
    assert publish.uncovered(parts, table, 3).count() == 0


def test_entries_answer_by_prefix_sums(spark, small):
    table, spec = matrices.cells(spark, small, "line2")
    q, boxes = workload.random_queries(spark, spec, 60, "42"), baselines.cell_noise(table, spec, 0.3, salt="42").persist()
    want = {r["qid"]: r["est"] for r in answer.answer(boxes, q, 2, "nested").collect()}
    assert {r["qid"]: pytest.approx(r["est"], abs=1e-6) for r in answer.answer_entries(boxes, q, 2).collect()} == want


def test_noise_off_and_every_cell_gives_exact_answers(spark, small):
    table, spec = matrices.cells(spark, small, "line2")
    q = workload.random_queries(spark, spec, 40, "42")
    est = answer.answer(baselines.cell_noise(table, spec, 0.1, noisy=False, salt="42"), q, 2)
    assert measures.errors(answer.truth(table, q, 2), est).where("abs(truth - est) > 1e-6").count() == 0


@pytest.mark.parametrize("strategy", ["nested", "binned", "separable"])
def test_strategies_agree(spark, small, strategy):
    table, spec = matrices.cells(spark, small, "line3")
    parts, q = grids.entropy_grid(table, spec, 0.5, salt="42").persist(), workload.random_queries(spark, spec, 60, "42")
    a = {r[0]: r[1] for r in answer.answer(parts, q, 3, "nested").collect()}
    b = {r[0]: r[1] for r in answer.answer(parts, q, 3, strategy).collect()}
    assert a.keys() == b.keys() and all(a[k] == pytest.approx(b[k], abs=1e-6) for k in a)


@pytest.mark.parametrize("strategy", ["binned", "prefix"])
def test_truth_strategies_agree(spark, small, strategy):
    table, spec = matrices.cells(spark, small, "line2")
    q = workload.random_queries(spark, spec, 50, "7").unionByName(workload.coverage_queries(spark, spec, 1.0, 1).withColumn("qid", F.lit(999).cast("long")))
    a = sorted(map(tuple, answer.truth(table, q, 2, "nested").collect()))
    assert a == sorted(map(tuple, answer.truth(table, q, 2, strategy).collect()))


def test_worked_example(spark):
    parts = catalogue.example_boxes(spark)
    q = spark.createDataFrame([(0, 1, 3, 0, 1, 0, 1)], "qid long, qlo1 int, qhi1 int, qlo2 int, qhi2 int, qlo3 int, qhi3 int")
    assert answer.answer(parts, q, 3).first()["est"] == 2.5
    more = parts.withColumn("ncount", F.col("ncount") + F.when(F.col("pid") == "c", 6.0).when(F.col("pid") == "a", 4.0).otherwise(9.0))
    assert answer.answer(more, q, 3).first()["est"] == pytest.approx(2.5 + 1 + 1)


def test_query_outside_and_whole(spark, small):
    table, spec = matrices.cells(spark, small, "line2")
    parts = grids.uniform_grid(table, spec, 0.5, salt="42").persist()
    q = spark.createDataFrame([(0, 50, 60, 50, 60), (1, 0, 10, 0, 10)], "qid long, qlo1 int, qhi1 int, qlo2 int, qhi2 int")
    got = {r[0]: r[1] for r in answer.answer(parts, q, 2).collect()}
    assert got[0] == 0.0 and got[1] == pytest.approx(parts.agg(F.sum("ncount")).first()[0])


def test_lazy_cells_answer_as_materialised(spark, small):
    table, spec = matrices.cells(spark, small, "line2")
    q = workload.coverage_queries(spark, spec, 0.3, 20, salt="42")
    a = {r[0]: r[1] for r in answer.answer(baselines.cell_noise(table, spec, 0.2, salt="42"), q, 2).collect()}
    b = {r[0]: r[1] for r in baselines.cell_noise_lazy(table, q, spec, 0.2, salt="42").collect()}
    assert all(a[k] == pytest.approx(b[k]) for k in a)


def test_summed_cell_noise_has_the_right_spread(spark):
    q = spark.range(3000).select(F.col("id").alias("qid"), F.lit(0).alias("qlo1"), F.lit(9).alias("qhi1"))
    truth = q.select("qid", F.lit(0.0).alias("truth"))
    x = np.array([r["est"] for r in baselines.cell_noise_answers(truth, q, 1, 1.0, salt="42").collect()])
    assert abs(x.mean()) < 0.4 and abs(x.var() - 18) < 2.5


def test_index_policies(spark):
    df = spark.createDataFrame([(None,), (float("nan"),), (-1.0,), (0.0,), (9.99,), (10.0,)], "v double")
    dim = DimSpec("v", "v", 0, 10, 5)
    assert [r[0] for r in df.select(dim.index()).collect()] == [None, None, None, 0, 4, None]
    assert [r[0] for r in df.select(dim.index("clamp")).collect()] == [None, None, 0, 0, 4, 4]
    with pytest.raises(Exception, match="out of bounds"):
        df.select(dim.index("error")).collect()
    named = DimSpec("v", "v", values=("a", "b"))
    assert [r[0] for r in spark.createDataFrame([("b",), ("c",), (None,)], "v string").select(named.index()).collect()] == [1, None, None]


def test_excluded_records_are_counted(spark):
    df = spark.createDataFrame([(1.0,), (None,), (50.0,)], "v double")
    spec = MatrixSpec("t", (DimSpec("v", "v", 0, 10, 5),))
    assert tuple(cells.excluded(df, spec).first()) == (3, 2)


def test_relative_error_of_zero(spark):
    df = spark.createDataFrame([(0.0, 5.0), (10.0, 5.0)], "t double, e double")
    assert [r[0] for r in df.select(measures.relative_error(F.col("t"), F.col("e"))).collect()] == [None, 50.0]
    assert [r[0] for r in df.select(measures.relative_error(F.col("t"), F.col("e"), "floor", 2.0)).collect()] == [250.0, 50.0]


def test_errors_fall_with_budget_and_query_size(spark, small):
    table, spec = matrices.cells(spark, small, "price2")
    table = table.persist()
    mean = {}
    for share in (0.1, 0.6):
        q = workload.coverage_queries(spark, spec, share, 80, salt="42")
        truth = answer.truth(table, q, 2).persist()
        for eps in (0.05, 1.0):
            found = [measures.errors(truth, answer.answer(grids.entropy_grid(table, spec, eps, salt=str(s)), q, 2)).agg(F.avg("rel_err")).first()[0] for s in range(3)]
            mean[share, eps] = float(np.mean(found))
    assert mean[0.6, 1.0] < mean[0.6, 0.05] and mean[0.6, 0.05] < mean[0.1, 0.05]


def test_weak_baseline_is_worse_on_a_cloud(spark, small):
    keys = synth.points(tables.load(spark, small, "orders"), 4)
    spec = plain("g", 60, 60)
    table = synth.gaussian(keys, spec, 0.05, "42").persist()
    q = workload.random_queries(spark, spec, 100, "42")
    found = measures.mre(experiments.accuracy(table, spec, q, "42", ("cell_noise", "entropy_grid", "even_tree"), (0.1,)), "method")
    mre = {r["method"]: r["mre"] for r in found.collect()}
    assert mre["cell_noise"] > 2 * min(mre["entropy_grid"], mre["even_tree"])


def test_zipf_is_skewed(spark, small):
    keys = synth.points(tables.load(spark, small, "orders"), 2)
    flat, steep = (synth.zipf(keys, plain("z", 30), a, "42").where("x1 = 0").first()["f"] for a in (1.2, 2.4))
    assert steep > flat


def test_save_load_and_no_second_release(spark, small, tmp_path):
    table, spec = matrices.cells(spark, small, "line2")
    parts = grids.entropy_grid(table, spec, 0.5, salt="42")
    meta = publish.metadata(spark, "entropy_grid", spec, 0.5, rounding="round")
    publish.save(parts, meta, str(tmp_path / "r"))
    back, info = publish.load(spark, str(tmp_path / "r"))
    assert back.exceptAll(parts).count() == 0 and info.first()["eps"] == 0.5
    assert publish.describe(info.first()["spec"])[0]["width"] == 10
    with pytest.raises(Exception, match="(?i)exist"):
        publish.save(parts, meta, str(tmp_path / "r"))
    with pytest.raises(ValueError):
        publish.metadata(spark, "entropy_grid", spec, 0.5, salt="42")


def test_postprocessing(spark):
    parts = catalogue.example_boxes(spark).withColumn("ncount", F.col("ncount") - 3)
    done = publish.postprocess(parts, nonneg=True, integer=True, total=20.0).collect()
    assert all(r["ncount"] >= 0 and r["ncount"] == round(r["ncount"]) for r in done) and sum(r["ncount"] for r in done) == 20


def test_trajectories(spark):
    rows = [("u", t, float(v)) for t, v in enumerate([5, 6, 7, 8, 9])] + [("w", 0, 1.0)]
    df = spark.createDataFrame(rows, "u string, t int, v double")
    assert tuple(trajectories.ends(df, ["u"], ["t"], ["v"]).first()) == ("u", 5.0, 9.0)
    assert tuple(trajectories.od_records(trajectories.ordered(df, ["u"], ["t"], ["v"]), ["v"], 1).first()) == ("u", 5.0, 7.0, 9.0)
    assert trajectories.frames(df, ["u"], F.floor(F.col("t") / 2), 3, ["t"], ["v"], "last").collect()[0][1:] == (6.0, 8.0, 9.0)
    assert trajectories.legs(df, ["u"], ["t"], ["v"]).count() == 4


def test_keyed_sample_ignores_partitioning(spark, small):
    df = tables.load(spark, small, "orders")
    a = {r[0] for r in tables.keyed_sample(df, 50, "s", "o_orderkey").select("o_orderkey").collect()}
    b = {r[0] for r in tables.keyed_sample(df.repartition(9), 50, "s", "o_orderkey").select("o_orderkey").collect()}
    assert a == b and len(a) == 50


def test_schema_check(spark, tmp_path):
    spark.range(1).selectExpr("cast(id as string) AS r_regionkey", "'x' AS r_name").write.parquet(str(tmp_path / "region.parquet"))
    with pytest.raises(ValueError, match="r_regionkey"):
        tables.load(spark, str(tmp_path), "region")


def test_readers(spark, tmp_path):
    spark.createDataFrame([(1, "a")], "k int, v string").write.option("header", "true").csv(str(tmp_path / "c"))
    assert tables.read(spark, str(tmp_path / "c"), "k int, v string", header="true").first()["v"] == "a"
    tables.read(spark, str(tmp_path / "c"), "k int, v string", header="true").createOrReplaceTempView("readers_view")
    assert tables.relation(spark, "readers_view").count() == 1 and tables.relation(spark, "SELECT k + 1 AS k FROM readers_view").first()["k"] == 2


def test_release_is_one_lazy_plan_without_python(spark, small):
    table, spec = matrices.cells(spark, small, "price2")
    plan = grids.entropy_grid(table, spec, 0.5, salt="42")._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "CartesianProduct" not in plan and "ReadSchema: struct<l_quantity:double,l_extendedprice:double>" in plan


def test_boxes_relations(spark):
    df = spark.createDataFrame([(0, 2, 0, 2, 2, 4, 0, 2), (0, 2, 0, 2, 1, 3, 1, 3), (0, 9, 0, 9, 1, 3, 1, 3)], "lo1 int, hi1 int, lo2 int, hi2 int, qlo1 int, qhi1 int, qlo2 int, qhi2 int")
    got = df.select(boxes.overlaps(2), boxes.disjoint(2), boxes.contains(2), boxes.adjacent(2), boxes.overlap(2)).collect()
    assert [tuple(r) for r in got] == [(False, True, False, True, 0.0), (True, False, False, False, 1.0), (True, False, True, False, 4.0)]
    assert boxes.array_view(df.drop("qlo1", "qhi1", "qlo2", "qhi2"), 2).first()["box"][0]["hi"] == 2


def test_pandas_variants(spark):
    from privmatrix.plans import sqlapi

    df = spark.createDataFrame([(0.5,), (2.5,), (None,)], "v double")
    assert [r[0] for r in df.select(sqlapi.vectorised_index(np.floor)("v")).collect()] == [0, 2, None]
    errors = spark.createDataFrame([(float(i),) for i in range(40)] + [(None,), (1e9,)], "rel_err double")
    assert errors.agg(sqlapi.error_summary()("rel_err")).first()[0] == pytest.approx(20.5, abs=1)


def test_many_boxes_are_dealt_out(spark):
    one = spark.createDataFrame([(600, 500)], "m1 int, m2 int")
    domain = boxes.grid_domain(spark, (1000, 1000), one)
    assert domain.count() == 300_000 and domain.select("lo1", "lo2").distinct().count() == 300_000
    assert domain.rdd.getNumPartitions() > 1


def test_entropy_values(spark):
    df = spark.createDataFrame([(1,), (1,), (2,)], "f long")
    assert measures.entropy(df).first()[0] == pytest.approx(1.5)
    assert math.isclose(spark.range(1).select(measures.noise_entropy(F.lit(4.0), 0.5, 2)).first()[0], math.log2(math.sqrt(2) * 4 / 0.5))


def test_a_cluster_without_a_shared_folder_is_refused():
    from types import SimpleNamespace

    from privmatrix.sources.store import shared_folder

    def session(master, **settings):
        return SimpleNamespace(sparkContext=SimpleNamespace(master=master, getConf=lambda: settings))

    assert shared_folder(session("spark://host:7077", **{"spark.checkpoint.dir": "s3a://b/c"})) == "s3a://b/c"
    assert shared_folder(session("local[2]")).startswith("file://")
    with pytest.raises(ValueError):
        shared_folder(session("spark://host:7077"))
