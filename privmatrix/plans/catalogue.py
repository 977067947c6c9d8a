"""Registered queries and their oracles."""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from privmatrix.functions import boxes, budget, measures
from privmatrix.operators import answer as answering
from privmatrix.operators import baselines, cells, grids, homogeneity, publish, stops, trajectories, tree
from privmatrix.plans import experiments, matrices, oracle, sqlapi
from privmatrix.sources import synth, workload
from privmatrix.sources.spec import DimSpec, MatrixSpec, plain
from privmatrix.sources.store import written
from privmatrix.sources.tables import keyed_sample as keyed
from privmatrix.streaming import daily

SALT = oracle.SALT
EPS = 0.1
Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def registered(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def add(f: Query) -> Query:
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


def six(c: str) -> Column:
    return F.round(c, 6).alias(c)


# --- matrices

for _name in ("price2", "ship2", "partsupp2", "clock2", "line5", "docs2", "vec4", "od4", "od6", "traj4", "traj6", "quality2", "conv3", "pages1", "bench1"):
    registered(f"cells_{_name}", oracle.cells(_name))(lambda spark, d, n=_name: matrices.cells(spark, d, n)[0])


@registered("excluded_quality2", f"SELECT count(*) AS records, count(*) FILTER (WHERE NOT coalesce({oracle._dim(*oracle.MATRICES['quality2'][1][0])[1]} AND {oracle._dim(*oracle.MATRICES['quality2'][1][1])[1]}, false)) AS excluded FROM documents LEFT JOIN labels USING (doc_id)")
def excluded_quality2(spark: SparkSession, d: str) -> DataFrame:
    return cells.excluded(matrices.records(spark, d, "quality2"), matrices.SPECS["quality2"])


@registered("region_filter", oracle.cells("price2", "l_quantity >= 22 AND l_quantity < 28 AND l_linenumber >= 1 AND l_linenumber < 7"))
def region_filter(spark: SparkSession, d: str) -> DataFrame:
    return cells.build_cells(cells.region(matrices.records(spark, d, "price2"), "l_quantity", "l_linenumber", (25.0, 4.0), 6.0), matrices.SPECS["price2"])


@registered("bounded_contributions", f"""SELECT user_id, cast(dy AS VARCHAR) AS dy, n FROM (SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY {oracle.uniform("sample", "user_id", "dy")}, dy) AS r
  FROM (SELECT user_id, ts::DATE AS dy, count(*) AS n FROM events GROUP BY ALL)) WHERE r <= 3""")
def bounded_contributions(spark: SparkSession, d: str) -> DataFrame:
    days = matrices.events(spark, d).groupBy("user_id", F.col("day").alias("dy")).agg(F.count("*").alias("n"))
    return cells.bound_contributions(days, "user_id", 3, SALT, "dy").withColumn("dy", F.col("dy").cast("string"))


@registered("od_legs_lag", f"""SELECT user_id, event_id, fv, k0, value AS to_value, k AS to_k, goes_on FROM (SELECT user_id, event_id, value, k, lag(value) OVER w AS fv, lag(k) OVER w AS k0, lead(ts) OVER w IS NOT NULL AS goes_on
  FROM {oracle._EVENTS} WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)) WHERE fv IS NOT NULL""")
def od_legs_lag(spark: SparkSession, d: str) -> DataFrame:
    found = trajectories.legs(matrices.events(spark, d), ["user_id"], ["ts", "event_id"], ["value", "k"])
    return found.select("user_id", "event_id", F.col("from_value").alias("fv"), F.col("from_k").alias("k0"), "to_value", "to_k", "goes_on")


@registered("close_trips", "SELECT user_id, event_id, count(*) OVER (PARTITION BY user_id ORDER BY s RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS recent FROM (SELECT *, date_diff('second', TIMESTAMP '2024-01-01', date_trunc('second', ts)) AS s FROM events)")
def close_trips(spark: SparkSession, d: str) -> DataFrame:
    seconds = F.floor(F.expr(matrices.EVENT_SECOND))
    return trajectories.close_trips(matrices.events(spark, d), ["user_id"], seconds, 3600).select("user_id", "event_id", "recent")


@registered("od_stops", f"""SELECT user_id, cast(dy AS VARCHAR) AS dy, p0, p1, p2 FROM (SELECT user_id, dy, l[1].v AS p0, l[cast(floor((len(l) - 1) * 1 / 2) AS BIGINT) + 1].v AS p1, l[len(l)].v AS p2
  FROM (SELECT user_id, dy, list({{'t': ts, 'e': event_id, 'v': value}} ORDER BY ts, event_id) AS l FROM {oracle._EVENTS} GROUP BY user_id, dy) WHERE len(l) >= 3)""")
def od_stops(spark: SparkSession, d: str) -> DataFrame:
    trips = trajectories.ordered(matrices.events(spark, d), ["user_id", "day"], ["ts", "event_id"], ["value"])
    return trajectories.od_records(trips, ["value"], 1).select("user_id", F.col("day").cast("string").alias("dy"), F.col("p0_value").alias("p0"), F.col("p1_value").alias("p1"), F.col("p2_value").alias("p2"))


@registered("semi_frames", f"SELECT user_id, cast(dy AS VARCHAR) AS dy, count(*) AS n FROM {oracle._EVENTS} SEMI JOIN (SELECT user_id, dy FROM {oracle._TRAJ6}) t USING (user_id, dy) GROUP BY ALL")
def semi_frames(spark: SparkSession, d: str) -> DataFrame:
    whole = matrices.records(spark, d, "traj6").select("user_id", "day")
    return matrices.events(spark, d).join(whole, ["user_id", "day"], "left_semi").groupBy("user_id", F.col("day").cast("string").alias("dy")).agg(F.count("*").alias("n"))


@registered("marginals_cube", f"SELECT x1, x2, x3, x4, cast(grouping_id(x1, x2, x3, x4) AS BIGINT) AS gid, sum(f)::BIGINT AS f FROM ({oracle.cells('od4')}) GROUP BY GROUPING SETS ((x1, x2), (x1, x3), (x1, x4), (x2, x3), (x2, x4), (x3, x4))")
def marginals_cube(spark: SparkSession, d: str) -> DataFrame:
    return cells.marginals(matrices.cells(spark, d, "od4")[0], 4)


@registered("prefix_rollup", f"SELECT x1, x2, x3, x4, (4 - bit_count(grouping_id(x1, x2, x3, x4)))::INTEGER AS depth, sum(f)::BIGINT AS f FROM ({oracle.cells('od4')}) GROUP BY ROLLUP (x1, x2, x3, x4)")
def prefix_rollup(spark: SparkSession, d: str) -> DataFrame:
    return cells.prefix_rollup(matrices.cells(spark, d, "od4")[0], 4)


@registered("density", f"SELECT sum(f)::BIGINT AS records, count(*) AS occupied, count(*) / 250000.0::DOUBLE AS share, max(f) AS largest FROM ({oracle.cells('od4')})")
def density(spark: SparkSession, d: str) -> DataFrame:
    table, spec = matrices.cells(spark, d, "od4")
    return cells.density(table, spec).drop("first_axis")


# --- granularity and budgets


@registered("noisy_total", f"SELECT round(sum(f) + {oracle.laplace('total', '1 / 0.001', salt=oracle.total_key(SALT, 0.001))}, 6) AS n FROM ({oracle.cells('price2')})")
def noisy_total(spark: SparkSession, d: str) -> DataFrame:
    return grids.noisy_total(matrices.cells(spark, d, "price2")[0], 0.001, salt=SALT).select(six("n"))


_RULES = {"entropy": grids.granularity_entropy, "error": grids.granularity_error, "error_r": lambda n, e, d: grids.granularity_error(n, e, d, 0.1), "log": grids.granularity_log}
_RULE_SQL = " UNION ALL ".join(
    f"SELECT '{k}' AS rule, {d} AS d, {e!r}::DOUBLE AS eps, round({oracle.rule('error' if k == 'error_r' else k, 'n', e * 0.99, d, 0.1 if k == 'error_r' else None)}, 6) AS m FROM n" for k in _RULES for d in range(1, 7) for e in experiments.BUDGETS
)


@registered("granularity_rules", f"WITH n AS (SELECT count(*)::DOUBLE AS n FROM lineitem) {_RULE_SQL}")
def granularity_rules(spark: SparkSession, d: str) -> DataFrame:
    n = matrices.load(spark, d, "lineitem").agg(F.count("*").cast("double").alias("n"))
    rows = [F.struct(F.lit(k).alias("rule"), F.lit(dim).alias("d"), F.lit(e).alias("eps"), F.round(rule(F.col("n"), e * 0.99, dim), 6).alias("m")) for k, rule in _RULES.items() for dim in range(1, 7) for e in experiments.BUDGETS]
    return n.select(F.explode(F.array(*rows)).alias("r")).select("r.*")


def _level_sql() -> str:
    out = []
    for d in range(1, 7):
        for e in experiments.BUDGETS:
            m0 = f"greatest(1.0, pow(n * {e * 0.99!r} / {math.sqrt(2)!r}, {2 / (3 * d)!r}))"
            total = " + ".join(f"pow({m0}, {j / 3!r})" for j in range(1, d + 1))
            out += [f"SELECT {d} AS d, {e!r}::DOUBLE AS eps, {i} AS level, round({e * 0.99!r} * pow({m0}, {i / 3!r}) / ({total}), 9) AS share FROM n" for i in range(1, d + 1)]
    return f"WITH n AS (SELECT greatest(sum(f) + {oracle.laplace('total', '1 / 0.001', salt=oracle.total_key(SALT, 0.001))}, 0.0) AS n FROM ({oracle.cells('price2')})) " + " UNION ALL ".join(out)


@registered("level_budgets", _level_sql())
def level_budgets(spark: SparkSession, d: str) -> DataFrame:
    """For the noisy total of a matrix, as if it had 1 to 6 axes."""
    n = grids.noisy_total(matrices.cells(spark, d, "price2")[0], 0.001, salt=SALT).select(F.greatest("n", F.lit(0.0)).alias("n"))
    rows = [F.struct(F.lit(dim).alias("d"), F.lit(e).alias("eps"), budget.level_budgets(grids.granularity_entropy(F.col("n"), e * 0.99, dim), e, dim).alias("shares")) for dim in range(1, 7) for e in experiments.BUDGETS]
    each = n.select(F.explode(F.array(*rows)).alias("r")).select("r.d", "r.eps", F.posexplode("r.shares").alias("level", "share"))
    return each.select("d", "eps", (F.col("level") + 1).alias("level"), F.round("share", 9).alias("share"))


# --- releases


def _released(df: DataFrame, d: int) -> DataFrame:
    return df.select("pid", *boxes.bounds(d), "n_entries", six("ncount"), "depth")


def _grid(key: str, name: str, method: str, kind: str, **options) -> None:
    width = len(oracle.WIDTHS[name])

    @registered(key, oracle.released(oracle.grid(name, kind, EPS, options.get("r")), width))
    def run(spark: SparkSession, d: str) -> DataFrame:
        table, spec = matrices.cells(spark, d, name)
        return _released(experiments.release(method, table, spec, EPS, SALT, **options), spec.d)


_grid("uniform_grid_price2", "price2", "uniform_grid", "error")
_grid("uniform_grid_known_r", "price2", "uniform_grid", "error", r=0.05)
_grid("uniform_grid_traj6", "traj6", "uniform_grid", "error")
_grid("entropy_grid_ship2", "ship2", "entropy_grid", "entropy")
_grid("entropy_grid_od4", "od4", "entropy_grid", "entropy")
_grid("entropy_grid_pages1", "pages1", "entropy_grid", "entropy")
_grid("log_grid_partsupp2", "partsupp2", "log_grid", "log")


@registered("cell_noise_small", oracle.released(oracle.every_cell("line2", EPS), 2))
def cell_noise_small(spark: SparkSession, d: str) -> DataFrame:
    table, spec = matrices.cells(spark, d, "line2")
    return _released(baselines.cell_noise(table, spec, EPS, salt=SALT), 2)


@registered("cell_noise_lazy", f"WITH {oracle.every_cell('line2', EPS)}, q AS ({oracle.random_queries('line2', 50)}) SELECT qid, round(est, 6) AS est FROM ({oracle.answers('b', 'q', 2)})")
def cell_noise_lazy(spark: SparkSession, d: str) -> DataFrame:
    table, spec = matrices.cells(spark, d, "line2")
    return baselines.cell_noise_lazy(table, workload.random_queries(spark, spec, 50, SALT), spec, EPS, salt=SALT).select("qid", six("est"))


@registered("one_box", oracle.released(oracle.single("price2", EPS), 2))
def one_box(spark: SparkSession, d: str) -> DataFrame:
    table, spec = matrices.cells(spark, d, "price2")
    return _released(baselines.one_box(table, spec, EPS, salt=SALT), 2)


def _tree(key: str, name: str, homogeneous: bool = False, stop: stops.Stop | None = None) -> None:
    width = len(oracle.WIDTHS[name])
    sql = oracle.tree(name, EPS, homogeneous=homogeneous, **({"stop": stop.text} if stop else {}))

    @registered(key, oracle.released(sql, width))
    def run(spark: SparkSession, d: str) -> DataFrame:
        table, spec = matrices.cells(spark, d, name)
        return _released(experiments.release("homogeneous_tree" if homogeneous else "even_tree", table, spec, EPS, SALT, **({"stop": stop} if stop else {})), spec.d)


for _name in ("price2", "od4", "od6", "traj6", "clock2"):
    _tree(f"even_tree_{_name}", _name)
_tree("even_tree_stop", "od4", stop=stops.below(400.0))
_tree("even_tree_never", "line3", stop=stops.never())
for _name in ("price2", "od4", "line3"):
    _tree(f"homogeneous_tree_{_name}", _name, homogeneous=True)


# --- pieces of the homogeneous tree, at the root of price2

_ROOT_M, _P = 12, 4


def _root(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame, DataFrame]:
    table, spec = matrices.cells(spark, d, "price2")
    nodes = spark.range(1).select(F.lit("r").alias("node"), F.lit(0).alias("lo"), F.lit(spec.widths[0]).alias("hi"), F.lit(_ROOT_M).alias("m"), F.lit(float(spec.widths[1])).alias("area"), F.lit(0.01).alias("eps_prt"))
    cands = homogeneity.candidates(nodes, _P, salt=SALT)
    return nodes, cands, table.withColumn("node", F.lit("r"))


_CAND_SQL = f"""base AS (SELECT [0 + j * 50 // {_ROOT_M} FOR j IN range(0, {_ROOT_M + 1})] AS base), pos AS (SELECT t, base[j + 1] + cast(floor({oracle.uniform("pos", "'r'", "t", "j")} * (base[j + 2] - base[j + 1])) AS BIGINT) AS c
  FROM base CROSS JOIN (SELECT unnest(range(1, {_P + 1})) AS t) CROSS JOIN (SELECT unnest(range(0, {_ROOT_M})) AS j)),
  cand AS (SELECT t, list_concat(list_concat([0::BIGINT], list_sort(list(DISTINCT c) FILTER (WHERE c > 0))), [50::BIGINT]) AS ends FROM pos GROUP BY t)"""
_OBJ_SQL = f"""{_CAND_SQL}, cells AS ({oracle.cells("price2")}), dense AS (SELECT a.x1, b.x2, coalesce(f, 0) AS f FROM (SELECT unnest(range(0, 50)) AS x1) a CROSS JOIN (SELECT unnest(range(0, 1000)) AS x2) b LEFT JOIN cells USING (x1, x2)),
  placed AS (SELECT t, len(list_filter(ends, lambda z: z <= x1)) AS i, f FROM dense CROSS JOIN cand), obj AS (SELECT t, sum(abs(f - mu)) AS o FROM (SELECT t, f, avg(f) OVER (PARTITION BY t, i) AS mu FROM placed) GROUP BY t)"""


@registered("candidates", f"""WITH node AS (SELECT 'r.' || cast(l_linenumber AS VARCHAR) AS node, cast(greatest(1, least(round(pow(count(l_quantity) * {EPS!r} / {math.sqrt(2)!r}, {1 / 3!r})), 50)) AS BIGINT) AS m FROM lineitem WHERE l_linenumber IS NOT NULL GROUP BY l_linenumber),
  pos AS (SELECT node, t, j * 50 // m + cast(floor({oracle.uniform("pos", "node", "t", "j")} * ((j + 1) * 50 // m - j * 50 // m)) AS BIGINT) AS c FROM node CROSS JOIN (SELECT unnest(range(1, {_P + 1})) AS t) CROSS JOIN LATERAL (SELECT unnest(range(0, m)) AS j))
  SELECT node, t::INTEGER AS cand, array_to_string(list_concat(list_concat([0::BIGINT], list_sort(coalesce(list(DISTINCT c) FILTER (WHERE c > 0), []))), [50::BIGINT]), ',') AS ends FROM pos GROUP BY node, t""")
def candidates(spark: SparkSession, d: str) -> DataFrame:
    """Candidate cuts of the quantities of every line number's records; their number follows from the records."""
    counted = matrices.load(spark, d, "lineitem").where("l_linenumber IS NOT NULL").groupBy("l_linenumber").agg(F.count("l_quantity").alias("n"))
    m = grids.rounded(grids.granularity_entropy(F.col("n"), EPS, 2), 50)
    nodes = counted.select(F.concat(F.lit("r."), F.col("l_linenumber").cast("string")).alias("node"), F.lit(0).alias("lo"), F.lit(50).alias("hi"), m.alias("m"))
    return homogeneity.candidates(nodes, _P, salt=SALT).select("node", "cand", F.array_join(F.col("ends").cast("array<string>"), ",").alias("ends"))


def _objectives(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame, DataFrame]:
    nodes, cands, table = _root(spark, d)
    return homogeneity.objective(homogeneity.profile(table, "x1"), cands, nodes.select("node", "area")), cands, nodes


@registered("objective", f"WITH {_OBJ_SQL} SELECT t::INTEGER AS cand, round(o, 6) AS o FROM obj")
def objective(spark: SparkSession, d: str) -> DataFrame:
    return _objectives(spark, d)[0].select("cand", six("o"))


@registered("choose_split", f"WITH {_OBJ_SQL} SELECT t::INTEGER AS cand, array_to_string(ends, ',') AS ends FROM obj JOIN cand USING (t) ORDER BY o + {oracle.laplace('cand', str(2.0 * _P / 0.01), chr(39) + 'r' + chr(39), 't')}, t LIMIT 1")
def choose_split(spark: SparkSession, d: str) -> DataFrame:
    objs, cands, nodes = _objectives(spark, d)
    chosen = homogeneity.choose(objs, nodes.select("node", "eps_prt"), _P, salt=SALT)
    return chosen.select("cand", F.array_join(F.col("ends").cast("array<string>"), ",").alias("ends"))


_PATHS = " UNION ALL ".join(f"SELECT '{m}' AS method, {EPS!r}::DOUBLE AS least, {EPS!r}::DOUBLE AS most, true AS proven" for m in ("even_tree", "homogeneous_tree"))


@registered("budget_ledger", _PATHS)
def budget_ledger(spark: SparkSession, d: str) -> DataFrame:
    table, spec = matrices.cells(spark, d, "line3")
    grown = {"even_tree": tree.even_tree(table, spec, EPS, salt=SALT), "homogeneous_tree": tree.homogeneous_tree(table, spec, EPS, salt=SALT)}
    parts = [budget.path_total(t.ledger()).agg(F.round(F.min("eps"), 9).alias("least"), F.round(F.max("eps"), 9).alias("most"), F.min("proven").alias("proven")).select(F.lit(m).alias("method"), "*") for m, t in grown.items()]
    return parts[0].unionByName(parts[1])


# --- queries, truth, answers


def _query_ids(spark: SparkSession, d: str, table: str, key: str) -> DataFrame:
    return matrices.load(spark, d, table).select(F.col(key).alias("qid")).where("qid IS NOT NULL").distinct()


@registered("random_queries", oracle.random_queries("od4", 0, "SELECT DISTINCT o_custkey AS qid FROM orders WHERE o_custkey IS NOT NULL"))
def random_queries(spark: SparkSession, d: str) -> DataFrame:
    """A query for every customer with an order."""
    return workload.random_queries(spark, matrices.SPECS["od4"], salt=SALT, ids=_query_ids(spark, d, "orders", "o_custkey"))


@registered("coverage_queries", oracle.coverage_queries("price2", 0.05, 0, "SELECT DISTINCT l_partkey AS qid FROM lineitem WHERE l_partkey IS NOT NULL"))
def coverage_queries(spark: SparkSession, d: str) -> DataFrame:
    """A query for every part delivered."""
    return workload.coverage_queries(spark, matrices.SPECS["price2"], 0.05, salt=SALT, ids=_query_ids(spark, d, "lineitem", "l_partkey"))


_TRUTH = f"WITH c AS ({oracle.cells('price2')}), q AS ({oracle.random_queries('price2', 300)}) SELECT qid, truth FROM ({oracle.truth('c', 'q', 2)})"


def _truth(key: str, strategy: str) -> None:
    @registered(key, _TRUTH)
    def run(spark: SparkSession, d: str) -> DataFrame:
        table, spec = matrices.cells(spark, d, "price2")
        return answering.truth(table, workload.random_queries(spark, spec, 300, SALT), 2, strategy, spec.widths)


_truth("truth_price2", "nested")
_truth("truth_binned", "binned")
_truth("truth_prefix", "prefix")


def _answer(key: str, method: str, sql: str, strategy: str = "nested") -> None:
    @registered(key, f"WITH {sql}, q AS ({oracle.random_queries('price2', 300)}) SELECT qid, round(est, 5) AS est FROM ({oracle.answers('b', 'q', 2)})")
    def run(spark: SparkSession, d: str) -> DataFrame:
        table, spec = matrices.cells(spark, d, "price2")
        parts = written(experiments.release(method, table, spec, EPS, SALT), "release")
        return answering.answer(parts, workload.random_queries(spark, spec, 300, SALT), 2, strategy, spec.widths).select("qid", F.round("est", 5).alias("est"))


for _strategy in ("nested", "binned", "separable"):
    _answer(f"answer_uniform_grid_{_strategy}", "uniform_grid", oracle.grid("price2", "error", EPS), _strategy)
_answer("answer_even_tree", "even_tree", oracle.tree("price2", EPS))
_answer("answer_even_tree_binned", "even_tree", oracle.tree("price2", EPS), "binned")
_answer("answer_homogeneous_tree", "homogeneous_tree", oracle.tree("price2", EPS, homogeneous=True))


# --- measures


def _ctes(method: str, name: str, eps: float, prefix: str, noisy: bool = True) -> str:
    if method == "cell_noise":
        return oracle.every_cell(name, eps, prefix, noisy)
    if method.endswith("_tree"):
        return oracle.tree(name, eps, homogeneous=method[0] == "h", prefix=prefix, noisy=noisy)
    return oracle.grid(name, {"log_grid": "log", "uniform_grid": "error", "entropy_grid": "entropy"}[method], eps, prefix=prefix, noisy=noisy)


_MRE_NAME, _MRE_N = "line3", 100
_MRE_CTES = ", ".join(_ctes(m, _MRE_NAME, e, f"{m}{i}") for m in experiments.METHODS for i, e in enumerate(experiments.BUDGETS))
_MRE_ROWS = " UNION ALL ".join(f"SELECT '{m}' AS method, {e!r}::DOUBLE AS eps, truth, est FROM ({oracle.answers(f'{m}{i}b', 'q', 3)}) JOIN t USING (qid)" for m in experiments.METHODS for i, e in enumerate(experiments.BUDGETS))


@registered("mre_by_method", f"""WITH q AS ({oracle.random_queries(_MRE_NAME, _MRE_N)}), c AS ({oracle.cells(_MRE_NAME)}), t AS ({oracle.truth("c", "q", 3)}), {_MRE_CTES}
  SELECT method, eps, round(avg(e), 4) AS mre, round(median(e), 4) AS median, count(*) FILTER (WHERE e IS NULL) AS skipped FROM (SELECT method, eps, abs(truth - est) / nullif(truth, 0) * 100 AS e FROM ({_MRE_ROWS})) GROUP BY method, eps""")
def mre_by_method(spark: SparkSession, d: str) -> DataFrame:
    table, spec = matrices.cells(spark, d, _MRE_NAME)
    found = measures.mre(experiments.accuracy(table, spec, workload.random_queries(spark, spec, _MRE_N, SALT), SALT), "method", "eps")
    return found.select("method", "eps", F.round("mre", 4).alias("mre"), F.round("median", 4).alias("median"), "skipped")


_SPLIT = ("uniform_grid", "entropy_grid", "even_tree", "homogeneous_tree")
_SPLIT_CTES = ", ".join(_ctes(m, "line3", EPS, f"{m}{k}", k == "n") for m in _SPLIT for k in "nx")


@registered("error_decomposition", f"""WITH q AS ({oracle.random_queries("line3", _MRE_N)}), c AS ({oracle.cells("line3")}), t AS ({oracle.truth("c", "q", 3)}), {_SPLIT_CTES} """ + " UNION ALL ".join(f"""SELECT '{m}' AS method, round(avg(abs(x.est - truth)), 4) AS uniformity, round(avg(abs(n.est - x.est)), 4) AS noise, bool_and(abs(n.est - truth) <= abs(x.est - truth) + abs(n.est - x.est) + 1e-9) AS bounded
  FROM t JOIN ({oracle.answers(f"{m}xb", "q", 3)}) x USING (qid) JOIN ({oracle.answers(f"{m}nb", "q", 3)}) n USING (qid)""" for m in ("uniform_grid", "entropy_grid")))  # fmt: skip
def error_decomposition(spark: SparkSession, d: str) -> DataFrame:
    """For grids, whose boxes do not depend on the noise of the counts."""
    table, spec = matrices.cells(spark, d, "line3")
    table, q, parts = written(table, "cells"), workload.random_queries(spark, spec, _MRE_N, SALT), None
    exact = answering.truth(table, q, 3)
    for m in ("uniform_grid", "entropy_grid"):
        noisy, plain_ = (answering.answer(experiments.release(m, table, spec, EPS, SALT, noisy), q, 3) for noisy in (True, False))
        row = measures.decompose(exact, plain_, noisy).agg(F.round(F.avg("uniformity"), 4).alias("uniformity"), F.round(F.avg("noise"), 4).alias("noise"), F.bool_and(F.col("total") <= F.col("uniformity") + F.col("noise") + 1e-9).alias("bounded")).select(F.lit(m).alias("method"), "*")
        parts = row if parts is None else parts.unionByName(row)
    return parts


_LOSS = " UNION ALL ".join(
    f"SELECT {m} AS m, 4 AS d, round((SELECT h FROM h), 6) AS h, round(sum(-p * log2(p)), 6) AS hm, round((SELECT h FROM h) - sum(-p * log2(p)), 6) AS loss, round(log2({math.sqrt(2)!r} * pow({m}, 2.0) / {EPS!r}), 6) AS noise_bits FROM (SELECT sum(f) / (SELECT sum(f) FROM c) AS p FROM c GROUP BY "
    + ", ".join(f"((x{i} + 1) * {min(m, w)} - 1) // {w}" for i, w in enumerate(oracle.WIDTHS["od4"], 1))
    + ")"
    for m in (1, 2, 4, 8)
)


@registered("entropy_measures", f"WITH c AS ({oracle.cells('od4')}), h AS (SELECT sum(-p * log2(p)) AS h FROM (SELECT f / (SELECT sum(f) FROM c) AS p FROM c)) {_LOSS}")
def entropy_measures(spark: SparkSession, d: str) -> DataFrame:
    table, spec = matrices.cells(spark, d, "od4")
    table, parts = written(table, "cells"), None
    for m in (1, 2, 4, 8):
        row = measures.information_loss(table, spec.widths, m).select("m", "d", six("h"), six("hm"), six("loss"), F.round(measures.noise_entropy(F.col("m").cast("double"), EPS, 4), 6).alias("noise_bits"))
        parts = row if parts is None else parts.unionByName(row)
    return parts


_CURVE = [(2, 0.05), (4, 0.2)]


@registered("grid_error_curve", "WITH n AS (SELECT count(*)::DOUBLE AS n FROM lineitem), m AS (SELECT unnest(range(1, 101))::INTEGER AS m) " + " UNION ALL ".join(f"SELECT {d} AS d, m, round({math.sqrt(2 * r) / EPS!r} * pow(m, {d / 2!r}), 6) AS noise, round({r ** (1 / d)!r} * n / {grids.C0!r} / pow(m, {float(d - 1)!r}), 6) AS uniformity FROM n, m" for d, r in _CURVE))
def grid_error_curve(spark: SparkSession, d: str) -> DataFrame:
    n = matrices.load(spark, d, "lineitem").count()
    parts = [measures.grid_error_curve(spark, float(n), EPS, dim, r, grids.C0, list(range(1, 101))).select(F.lit(dim).alias("d"), "m", six("noise"), six("uniformity")) for dim, r in _CURVE]
    return parts[0].unionByName(parts[1])


@registered("structure", f"WITH {oracle.tree('od4', EPS, 'ncount < 400.0')} SELECT depth, count(*) AS n_boxes, min(n_entries) AS smallest, max(n_entries) AS biggest, sum(n_entries) AS covered FROM b GROUP BY depth")
def structure(spark: SparkSession, d: str) -> DataFrame:
    table, spec = matrices.cells(spark, d, "od4")
    return measures.structure(experiments.release("even_tree", table, spec, EPS, SALT, stop=stops.below(400.0)))


@registered("topk_boxes", f"WITH {oracle.tree('price2', EPS)} SELECT pid, round(ncount / n_entries, 6) AS density FROM b ORDER BY density DESC, pid LIMIT 20")
def topk_boxes(spark: SparkSession, d: str) -> DataFrame:
    table, spec = matrices.cells(spark, d, "price2")
    return experiments.release("even_tree", table, spec, EPS, SALT).select("pid", F.round(F.col("ncount") / F.col("n_entries"), 6).alias("density")).orderBy(F.desc("density"), "pid").limit(20)


@registered("noise_variance", f"WITH {oracle.grid('price2', 'entropy', EPS)}, q AS ({oracle.random_queries('price2', 100)}) SELECT qid, round(sum(2 * pow(1 / {EPS * 0.99!r}, 2) * pow({oracle.overlap(2)} / n_entries, 2)), 4) AS variance FROM b CROSS JOIN q WHERE {oracle.overlap(2)} > 0 GROUP BY qid")
def noise_variance(spark: SparkSession, d: str) -> DataFrame:
    table, spec = matrices.cells(spark, d, "price2")
    parts = experiments.release("entropy_grid", table, spec, EPS, SALT)
    return measures.noise_variance(parts, workload.random_queries(spark, spec, 100, SALT), 2, 1 / (EPS * 0.99)).select("qid", F.round("variance", 4).alias("variance"))


@registered("anti_uncovered", "SELECT 0::BIGINT AS n")
def anti_uncovered(spark: SparkSession, d: str) -> DataFrame:
    table, spec = matrices.cells(spark, d, "line3")
    table = written(table, "cells")
    return publish.uncovered(experiments.release("homogeneous_tree", table, spec, EPS, SALT), table, 3).agg(F.count("*").alias("n"))


@registered("slice_marginal", f"WITH {oracle.grid('price2', 'entropy', EPS)} SELECT lo1, hi1, round(sum(ncount * (least(hi2, 500) - greatest(lo2, 100)) / (hi2 - lo2)), 5) AS ncount FROM b WHERE lo2 < 500 AND hi2 > 100 GROUP BY lo1, hi1")
def slice_marginal(spark: SparkSession, d: str) -> DataFrame:
    table, spec = matrices.cells(spark, d, "price2")
    part = publish.cut(experiments.release("entropy_grid", table, spec, EPS, SALT), 2, 2, 100, 500)
    return publish.marginal(part, 2, [1]).select("lo1", "hi1", F.round("ncount", 5).alias("ncount"))


@registered("entries_of_box", f"WITH {oracle.tree('price2', EPS)} SELECT x1::INTEGER AS x1, x2::INTEGER AS x2, round(ncount / n_entries, 6) AS value FROM b JOIN (SELECT unnest(range(10, 15)) AS x1) ON x1 >= lo1 AND x1 < hi1 JOIN (SELECT unnest(range(200, 240)) AS x2) ON x2 >= lo2 AND x2 < hi2")
def entries_of_box(spark: SparkSession, d: str) -> DataFrame:
    table, spec = matrices.cells(spark, d, "price2")
    return publish.to_entries(experiments.release("even_tree", table, spec, EPS, SALT), 2, [(10, 15), (200, 240)]).select("x1", "x2", six("value"))


# --- synthetic points

def _gaussian_sql(w: int, sd: float) -> str:
    def x(i: int) -> str:
        u1, u2 = (oracle.uniform("point", "o_orderkey", "c", str(i), str(k)) for k in (1, 2))
        centre = oracle.uniform("point", "'centre'", str(i))
        return f"cast(floor({centre} * {w} + {sd!r} * {w} * sqrt(-2 * ln({u1})) * cos(2 * pi() * {u2})) AS INTEGER)"

    return f"SELECT x1, x2, count(*) AS f FROM (SELECT {x(1)} AS x1, {x(2)} AS x2 FROM orders CROSS JOIN (SELECT unnest(range(1, 3)) AS c)) WHERE x1 BETWEEN 0 AND {w - 1} AND x2 BETWEEN 0 AND {w - 1} GROUP BY x1, x2"


@registered("gaussian_points", _gaussian_sql(64, 0.1))
def gaussian_points(spark: SparkSession, d: str) -> DataFrame:
    return synth.gaussian(synth.points(matrices.load(spark, d, "orders"), 2), plain("gaussian2", 64, 64), 0.1, SALT)


_CDF = synth.zipf_table(50, 1.6)
_ZIPF = "(SELECT unnest([" + ", ".join(repr(x) for x in _CDF) + "]) AS h, unnest([0.0, " + ", ".join(repr(x) for x in _CDF[:-1]) + "]) AS l, unnest(range(0, 50)) AS r)"


@registered("zipf_points", f"""SELECT a.r::INTEGER AS x1, b.r::INTEGER AS x2, count(*) AS f FROM (SELECT {oracle.uniform("point", "o_orderkey", "c", "1")} AS u1, {oracle.uniform("point", "o_orderkey", "c", "2")} AS u2 FROM orders CROSS JOIN (SELECT unnest(range(1, 3)) AS c))
  JOIN {_ZIPF} a ON u1 >= a.l AND (u1 < a.h OR a.r = 49) JOIN {_ZIPF} b ON u2 >= b.l AND (u2 < b.h OR b.r = 49) GROUP BY a.r, b.r""")
def zipf_points(spark: SparkSession, d: str) -> DataFrame:
    return synth.zipf(synth.points(matrices.load(spark, d, "orders"), 2), plain("zipf2", 50, 50), 1.6, SALT)


# --- worked example and stream


def example_boxes(spark: SparkSession) -> DataFrame:
    """The literal 3 x 2 x 3 matrix with boxes of 4, 8 and 6 entries and totals 2, 4 and 12."""
    rows = [("a", 0, 2, 0, 2, 0, 1, 4.0, 2.0), ("b", 0, 2, 0, 2, 1, 3, 8.0, 4.0), ("c", 2, 3, 0, 2, 0, 3, 6.0, 12.0)]
    return spark.createDataFrame(rows, "pid string, lo1 int, hi1 int, lo2 int, hi2 int, lo3 int, hi3 int, n_entries double, ncount double")


EXAMPLE = MatrixSpec("example3", (DimSpec("flag", "l_returnflag", values=("A", "N", "R")), DimSpec("status", "l_linestatus", values=("F", "O")), DimSpec("quantity", "l_quantity", 1, 52, 3)))


@registered("worked_example", """SELECT 0::BIGINT AS qid, (count(*) FILTER (WHERE l_returnflag IN ('A', 'N') AND l_quantity < 18))::DOUBLE / 4 + (count(*) FILTER (WHERE l_returnflag = 'R'))::DOUBLE / 6 AS est
  FROM lineitem WHERE l_returnflag IN ('A', 'N', 'R') AND l_linestatus IN ('F', 'O') AND l_quantity >= 1 AND l_quantity < 52""")
def worked_example(spark: SparkSession, d: str) -> DataFrame:
    """The example's boxes and query on a matrix of its shape: return flags, line statuses and thirds of the quantities."""
    q = spark.createDataFrame([(0, 1, 3, 0, 1, 0, 1)], "qid long, qlo1 int, qhi1 int, qlo2 int, qhi2 int, qlo3 int, qhi3 int")
    table = cells.build_cells(matrices.load(spark, d, "lineitem"), EXAMPLE)
    named = example_boxes(spark).drop("ncount")
    counts = table.join(F.broadcast(named), boxes.holds(3, "")).groupBy("pid").agg(F.sum("f").cast("double").alias("ncount"))
    return answering.answer(named.join(counts, "pid"), q, 3, "nested")


STREAM = MatrixSpec("stream2", (DimSpec("value", "value", 0, 600, 6), DimSpec("k", "cast(get_json_object(props, '$.k') as int)", 0, 100, 4)))


@registered("stream_daily_cells", """SELECT cast(day AS VARCHAR) AS day, x1, x2, count(*) AS f FROM (SELECT ts::DATE AS day, cast(floor(value * 6 / 600) AS INTEGER) AS x1, cast(floor(cast(json_extract_string(props, '$.k') AS INTEGER) * 4 / 100) AS INTEGER) AS x2 FROM events WHERE value >= 0 AND value < 600)
  WHERE day + INTERVAL 1 DAY <= (SELECT max(ts) - INTERVAL 1 HOUR FROM events) GROUP BY ALL""")
def stream_daily_cells(spark: SparkSession, d: str) -> DataFrame:
    return daily.daily_cells(spark, f"{d}/events.parque[t]", STREAM).select(F.to_date("start").cast("string").alias("day"), "x1", "x2", "f")


# --- SQL and fluent surfaces


@registered("sql_functions", f"SELECT l_linenumber AS k, round({oracle.laplace('count', '4.0', 'l_linenumber')}, 6) AS noise, round(pow(60000.0 * 0.1 / {math.sqrt(2)!r}, 2.0 / (3 * l_linenumber)), 6) AS m, cast(((l_linenumber + 1) * 3 - 1) // 10 AS INTEGER) AS j FROM (SELECT DISTINCT l_linenumber FROM lineitem)")
def sql_functions(spark: SparkSession, d: str) -> DataFrame:
    sqlapi.register(spark)
    matrices.load(spark, d, "lineitem").select(F.col("l_linenumber").alias("k")).distinct().createOrReplaceTempView("catalogue_lines")
    return spark.sql("SELECT k, round(laplace_noise('42', 'count', cast(k AS STRING), 4.0D), 6) AS noise, round(granularity_entropy(60000D, 0.1D, k), 6) AS m, even_index(k, 0, 10, 3) AS j FROM catalogue_lines")


@registered("sql_grid_boxes", f"WITH c AS ({oracle.cells('price2')}), g AS (SELECT cast(a * 50 // 7 AS INTEGER) AS lo1, cast((a + 1) * 50 // 7 AS INTEGER) AS hi1, cast(b * 1000 // 9 AS INTEGER) AS lo2, cast((b + 1) * 1000 // 9 AS INTEGER) AS hi2 FROM (SELECT unnest(range(0, 7)) AS a) CROSS JOIN (SELECT unnest(range(0, 9)) AS b)) SELECT lo1, hi1, lo2, hi2, coalesce(sum(f), 0)::BIGINT AS f FROM g LEFT JOIN c ON x1 >= lo1 AND x1 < hi1 AND x2 >= lo2 AND x2 < hi2 GROUP BY lo1, hi1, lo2, hi2")
def sql_grid_boxes(spark: SparkSession, d: str) -> DataFrame:
    """Records of the matrix in every box of a grid."""
    sqlapi.register(spark)
    matrices.cells(spark, d, "price2")[0].createOrReplaceTempView("catalogue_price2")
    return spark.sql("""SELECT lo1, hi1, lo2, hi2, coalesce(f, 0L) AS f FROM grid_boxes(7, 50, 9, 1000) LEFT JOIN (SELECT /*+ BROADCAST(g) */ lo1, hi1, lo2, hi2, sum(f) AS f
      FROM catalogue_price2 JOIN grid_boxes(7, 50, 9, 1000) g ON x1 >= lo1 AND x1 < hi1 AND x2 >= lo2 AND x2 < hi2 GROUP BY lo1, hi1, lo2, hi2) USING (lo1, hi1, lo2, hi2)""")


@registered("sql_split_box", "SELECT r_regionkey::INTEGER AS k, j::INTEGER AS j, cast(j * (r_regionkey * 10 + 7) // 3 AS INTEGER) AS lo, cast((j + 1) * (r_regionkey * 10 + 7) // 3 AS INTEGER) AS hi FROM region CROSS JOIN (SELECT unnest(range(0, 3)) AS j)")
def sql_split_box(spark: SparkSession, d: str) -> DataFrame:
    sqlapi.register(spark)
    matrices.load(spark, d, "region").select(F.col("r_regionkey").cast("int").alias("k")).createOrReplaceTempView("catalogue_regions")
    return spark.sql("SELECT k, s.j, s.lo, s.hi FROM catalogue_regions, LATERAL split_box(0, k * 10 + 7, 3) s")


@registered("sql_answer_view", f"WITH {oracle.grid('price2', 'entropy', EPS)}, q AS ({oracle.random_queries('price2', 200)}) SELECT qid, round(est, 5) AS est FROM ({oracle.answers('b', 'q', 2)})")
def sql_answer_view(spark: SparkSession, d: str) -> DataFrame:
    sqlapi.register(spark)
    table, spec = matrices.cells(spark, d, "price2")
    text = sqlapi.views(experiments.release("entropy_grid", table, spec, EPS, SALT), workload.random_queries(spark, spec, 200, SALT), 2, "catalogue_")
    return spark.sql(text).select("qid", F.round("est", 5).alias("est"))


@registered("facade_answer", f"WITH {oracle.grid('line3', 'entropy', EPS)}, q AS ({oracle.random_queries('line3', 200)}) SELECT qid, round(est, 5) AS est FROM ({oracle.answers('b', 'q', 3)})")
def facade_answer(spark: SparkSession, d: str) -> DataFrame:
    spec = matrices.SPECS["line3"]
    released = sqlapi.PrivateMatrix(matrices.records(spark, d, "line3"), spec).release("entropy_grid", EPS, SALT)
    return released.answer(workload.random_queries(spark, spec, 200, SALT)).select("qid", F.round("est", 5).alias("est"))


@registered("grouped_counts", f"SELECT x2, cast(((x1 + 1) * 4 - 1) // 10 AS INTEGER) AS j, sum(f)::BIGINT AS f FROM ({oracle.cells('line2')}) GROUP BY ALL")
def grouped_counts(spark: SparkSession, d: str) -> DataFrame:
    return sqlapi.grouped_counts(matrices.cells(spark, d, "line2")[0], 4, 10)


@registered("compared_releases", f"WITH {oracle.single('line2', EPS, 'p')}, {oracle.grid('line2', 'entropy', EPS, prefix='r')} SELECT lo1, hi1, lo2, hi2, round(pb.ncount, 6) AS a, round(rb.ncount, 6) AS b FROM pb FULL JOIN rb USING (lo1, hi1, lo2, hi2)")
def compared_releases(spark: SparkSession, d: str) -> DataFrame:
    table, spec = matrices.cells(spark, d, "line2")
    both = publish.compared(experiments.release("one_box", table, spec, EPS, SALT), experiments.release("entropy_grid", table, spec, EPS, SALT), 2)
    return both.select("lo1", "hi1", "lo2", "hi2", six("a"), six("b"))


@registered("postprocessed", f"WITH {oracle.grid('line3', 'error', EPS)} SELECT pid, round(greatest(ncount, 0.0) * 1000.0 / (SELECT sum(greatest(ncount, 0.0)) FROM b), 4) AS ncount FROM b")
def postprocessed(spark: SparkSession, d: str) -> DataFrame:
    table, spec = matrices.cells(spark, d, "line3")
    return publish.postprocess(experiments.release("uniform_grid", table, spec, EPS, SALT), nonneg=True, total=1000.0).select("pid", F.round("ncount", 4).alias("ncount"))


@registered("keyed_sample", f"SELECT o_orderkey FROM orders ORDER BY {oracle.uniform('sample', 'o_orderkey')}, o_orderkey LIMIT 500")
def keyed_sample(spark: SparkSession, d: str) -> DataFrame:
    return keyed(matrices.load(spark, d, "orders"), 500, SALT, "o_orderkey").select("o_orderkey")


# --- workloads: rows of methods, budgets and query classes

_N = 1000
_FOUR = experiments.METHODS[2:]


def _classes_sql(name: str, n: int, coverages: tuple[float, ...]) -> str:
    kinds = {"random": oracle.random_queries(name, n), **{f"{int(c * 100)}%": oracle.coverage_queries(name, c, n) for c in coverages}}
    return " UNION ALL ".join(f"SELECT * REPLACE (qid + {k * n} AS qid), '{label}' AS queries FROM ({sql})" for k, (label, sql) in enumerate(kinds.items()))


def _accuracy_sql(name: str, methods: tuple[str, ...], budgets: tuple[float, ...], coverages: tuple[float, ...] = (), n: int = _N) -> str:
    """Errors of all methods and budgets by query class."""
    d = len(oracle.WIDTHS[name])
    ctes = ", ".join(_ctes(m, name, e, f"{m}{i}") for m in methods for i, e in enumerate(budgets))
    rows = " UNION ALL ".join(f"SELECT '{m}' AS method, {e!r}::DOUBLE AS eps, qid, est FROM ({oracle.answers(f'{m}{i}b', 'q', d)})" for m in methods for i, e in enumerate(budgets))
    return f"""WITH q AS ({_classes_sql(name, n, coverages)}), c AS ({oracle.cells(name)}), t AS ({oracle.truth("c", "q", d)}), {ctes}
      SELECT method, eps, queries, round(mre, 4) AS mre, round(median, 4) AS median, skipped, rank() OVER (PARTITION BY queries, eps ORDER BY mre) AS rank FROM (SELECT method, eps, queries, avg(e) AS mre, median(e) AS median, count(*) FILTER (WHERE e IS NULL) AS skipped
        FROM (SELECT method, eps, queries, abs(truth - est) / nullif(truth, 0) * 100 AS e FROM ({rows}) JOIN t USING (qid) JOIN (SELECT qid, queries FROM q) USING (qid)) GROUP BY method, eps, queries)"""


def _table(found: DataFrame, *by: str) -> DataFrame:
    return found.select("method", "eps", *by, F.round("mre", 4).alias("mre"), F.round("median", 4).alias("median"), "skipped", F.col("rank").cast("long").alias("rank"))


def _city(key: str, name: str) -> None:
    """The four methods and three budgets on a city's matrix, random and fixed-coverage queries."""

    @registered(key, _accuracy_sql(name, _FOUR, experiments.BUDGETS, experiments.COVERAGES))
    def run(spark: SparkSession, d: str) -> DataFrame:
        return _table(experiments.city(spark, d, name, SALT, weak=False), "queries")


for _name in ("price2", "ship2", "partsupp2"):
    _city(f"workload_city_{_name}", _name)


@registered("workload_city")
def workload_city(spark: SparkSession, d: str) -> DataFrame:
    """All six methods and three budgets on the skewed clock matrix, random and fixed-coverage queries."""
    return experiments.city(spark, d, "clock2", SALT)


def _od(key: str, name: str, budgets: tuple[float, ...]) -> None:
    """Origin-destination matrices of all trips, without and with an intermediate stop."""

    @registered(key, _accuracy_sql(name, _FOUR, budgets))
    def run(spark: SparkSession, d: str) -> DataFrame:
        return _table(experiments.od(spark, d, name, SALT, budgets=budgets).withColumn("queries", F.lit("random")), "queries")


_od("workload_od", "od4", experiments.BUDGETS)
_od("workload_od_stops", "od6", (EPS,))


@registered("workload_dimensions", " UNION ALL ".join(f"SELECT {k} AS d, * FROM ({_accuracy_sql(f'line{k}', _FOUR, (EPS,))})" for k in range(2, 7)))
def workload_dimensions(spark: SparkSession, d: str) -> DataFrame:
    """The four methods on the first 2 to 6 axes of one table."""
    found = experiments.dimensions(spark, d, "line", SALT, budgets=(EPS,)).withColumn("queries", F.lit("random"))
    return _table(found, "d", "queries")


def _gaussian(key: str, dim: int, sds: tuple[float, ...], budgets: tuple[float, ...]) -> None:
    @registered(key)
    def run(spark: SparkSession, d: str) -> DataFrame:
        return experiments.gaussian(spark, d, dim, SALT, sds=sds, budgets=budgets)


_gaussian("workload_gaussian", 2, experiments.SD_SHARES, (0.1,))
_gaussian("workload_gaussian_budgets", 2, (0.1,), experiments.BUDGETS)
_gaussian("workload_gaussian_d4", 4, (0.05, 0.2), (0.1,))
_gaussian("workload_gaussian_d6", 6, (0.2,), (0.1,))


@registered("workload_zipf")
def workload_zipf(spark: SparkSession, d: str) -> DataFrame:
    return experiments.zipf(spark, d, 2, SALT)


@registered("workload_zipf_d4")
def workload_zipf_d4(spark: SparkSession, d: str) -> DataFrame:
    return experiments.zipf(spark, d, 4, SALT, skews=(1.2, 2.0))


@registered("workload_ablations")
def workload_ablations(spark: SparkSession, d: str) -> DataFrame:
    return experiments.ablations(spark, d, "clock2", SALT)


@registered("running_times")
def running_times(spark: SparkSession, d: str) -> DataFrame:
    """Seconds of every method on the three cities' matrices."""
    return spark.createDataFrame([(*k.rsplit("_", 1), v) for k, v in experiments.running_times(spark, d, salt=SALT).items()], "method string, matrix string, seconds double")
