"""Registered queries against their DuckDB texts at the smallest scale."""

import math

import pytest

import __spark_entry__ as entry
from privmatrix.plans import catalogue

QUICK = ["cells_price2", "cells_od6", "cells_traj6", "cells_docs2", "cells_conv3", "region_filter", "prefix_rollup", "marginals_cube", "granularity_rules", "level_budgets", "uniform_grid_known_r", "entropy_grid_od4", "log_grid_partsupp2", "cell_noise_small", "one_box", "even_tree_price2", "even_tree_stop", "homogeneous_tree_line3", "objective", "choose_split", "random_queries", "truth_prefix", "answer_even_tree_binned", "answer_uniform_grid_separable", "entropy_measures", "gaussian_points", "zipf_points", "stream_daily_cells", "od_stops"]


def same(a, b):
    if isinstance(a, float) or isinstance(b, float):
        return a == b or (a is not None and b is not None and math.isclose(a, b, rel_tol=1e-9, abs_tol=2e-6))
    return str(a) == str(b)


@pytest.mark.parametrize("name", QUICK)
def test_query_equals_its_sql(spark, duck, small, name):
    df = catalogue.QUERIES[name](spark, small)
    columns = sorted(df.columns)
    got = sorted((tuple(r[c] for c in columns) for r in df.collect()), key=str)
    rel = duck.execute(catalogue.ORACLES[name])
    names = [x[0] for x in rel.description]
    want = sorted((tuple(r[names.index(c)] for c in columns) for r in rel.fetchall()), key=str)
    assert sorted(names) == columns and len(got) == len(want)
    assert all(same(x, y) for r, s in zip(got, want) for x, y in zip(r, s))


def test_every_oracle_has_a_query():
    assert set(catalogue.ORACLES) <= set(catalogue.QUERIES) and set(entry.oracle_sql()) <= set(entry.queries())


def test_entry(spark):
    assert entry.entry(spark).count() > 0
