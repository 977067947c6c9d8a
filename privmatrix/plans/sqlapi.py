"""SQL and fluent surfaces: functions and table functions by name, releases as views, pandas variants, and a facade."""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from privmatrix.functions import boxes
from privmatrix.functions.budget import Releases
from privmatrix.functions.noise import SEPARATOR, release_salt
from privmatrix.operators.answer import answer
from privmatrix.operators.cells import build_cells
from privmatrix.plans import experiments
from privmatrix.sources.spec import MatrixSpec

FUNCTIONS = {
    "keyed_uniform(salt STRING, purpose STRING, key STRING) RETURNS DOUBLE": f"(cast(conv(substring(sha2(concat_ws('{SEPARATOR}', salt, purpose, key), 256), 1, 13), 16, 10) AS BIGINT) + 0.5D) / 4503599627370496.0D",
    "laplace_noise(salt STRING, purpose STRING, key STRING, scale DOUBLE) RETURNS DOUBLE": "-scale * signum(keyed_uniform(salt, purpose, key) - 0.5D) * ln(1 - 2 * abs(keyed_uniform(salt, purpose, key) - 0.5D))",
    "granularity_error(n DOUBLE, eps DOUBLE, d INT) RETURNS DOUBLE": "CASE WHEN d = 1 THEN pow(n * eps / sqrt(2D), 2D / 3) ELSE pow(2D * (d - 1) / d * n * eps / 10D, 2D / (3 * d - 2)) * d * (3 * d - 2) / (3 * d * d - 3 * d + 2) END",
    "granularity_entropy(n DOUBLE, eps DOUBLE, d INT) RETURNS DOUBLE": "pow(n * eps / sqrt(2D), 2D / (3 * d))",
    "even_index(x INT, lo INT, width INT, m INT) RETURNS INT": "cast(((cast(x AS BIGINT) - lo + 1) * m - 1) div width AS INT)",
    "overlap1(lo INT, hi INT, qlo INT, qhi INT) RETURNS INT": "greatest(0, least(hi, qhi) - greatest(lo, qlo))",
}
TABLE_FUNCTIONS = {
    "grid_boxes(m1 INT, w1 INT, m2 INT, w2 INT) RETURNS TABLE (lo1 INT, hi1 INT, lo2 INT, hi2 INT)": """
      SELECT cast(a * w1 div m1 AS INT), cast((a + 1) * w1 div m1 AS INT), cast(b * w2 div m2 AS INT), cast((b + 1) * w2 div m2 AS INT)
      FROM (SELECT explode(sequence(0L, m1 - 1L)) AS a) CROSS JOIN (SELECT explode(sequence(0L, m2 - 1L)) AS b)""",
}


def register(spark: SparkSession) -> None:
    """The SQL functions, as temporary ones that the optimizer inlines, and the table function ``split_box``."""
    for head, body in (FUNCTIONS | TABLE_FUNCTIONS).items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURN {body}")
    spark.udtf.register("split_box", split_box())


def split_box():
    """Python table function (lo, hi, m) -> rows (j, lo, hi) of m equal parts; for a handful of boxes, not for hot paths."""

    @F.udtf(returnType="j: int, lo: int, hi: int")
    class SplitBox:
        def eval(self, lo: int, hi: int, m: int) -> Iterator[tuple[int, int, int]]:
            for j in range(m):
                yield j, lo + j * (hi - lo) // m, lo + (j + 1) * (hi - lo) // m

    return SplitBox


def vectorised_index(curve: Callable[[np.ndarray], np.ndarray]):
    """A pandas UDF that places values by a user's own vectorised curve, for axes that no SQL expression describes."""

    @F.pandas_udf("int")
    def place(values: pd.Series) -> pd.Series:
        at = curve(values.to_numpy(dtype=float))
        return pd.Series(np.where(np.isnan(at), -1, at)).astype("int64").where(~np.isnan(at), None).astype("Int32")

    return place


def error_summary():
    """A pandas aggregate: the mean of the middle 90 % of relative errors."""

    @F.pandas_udf("double")
    def trimmed(errors: pd.Series) -> float:
        kept = errors.dropna().sort_values()
        cut = len(kept) // 20
        kept = kept.iloc[cut : len(kept) - cut] if cut else kept
        return float(kept.mean()) if len(kept) else math.nan

    return trimmed


def grouped_counts(cells: DataFrame, m: int, width: int) -> DataFrame:
    """Counts of m equal parts of the first axis per second coordinate, computed group by group in pandas: a reference for small nodes."""

    def run(part: pd.DataFrame) -> pd.DataFrame:
        j = ((part["x1"].to_numpy().astype(np.int64) + 1) * m - 1) // width
        counts = np.bincount(j, part["f"], m)
        return pd.DataFrame({"x2": int(part["x2"].iloc[0]), "j": np.arange(m), "f": counts.astype(np.int64)}).query("f > 0")

    return cells.groupBy("x2").applyInPandas(run, "x2 int, j int, f long")


def views(partitions: DataFrame, queries: DataFrame, d: int, prefix: str = "") -> str:
    """Registers ``release_boxes`` and ``asked_boxes`` and returns the SQL text that answers the one by the other."""
    partitions.createOrReplaceTempView(f"{prefix}release_boxes")
    queries.createOrReplaceTempView(f"{prefix}asked_boxes")
    cover = " * ".join(f"cast(overlap1(lo{i}, hi{i}, qlo{i}, qhi{i}) AS DOUBLE)" for i in range(1, d + 1))
    meet = " AND ".join(f"lo{i} < qhi{i} AND qlo{i} < hi{i}" for i in range(1, d + 1))
    return f"SELECT /*+ BROADCAST(q) */ q.qid, coalesce(sum(ncount * {cover} / n_entries), 0D) AS est FROM {prefix}asked_boxes q LEFT JOIN {prefix}release_boxes ON {meet} GROUP BY q.qid"


class PrivateMatrix:
    """``PrivateMatrix(records, spec).release("even_tree", eps=0.1, salt=...).answer(queries)``. Only ``release`` reads the records."""

    def __init__(self, records: DataFrame, spec: MatrixSpec):
        self._records, self.spec = records, spec

    def release(self, method: str, eps: float, salt: str, label: str = "", releases: Releases | None = None, **options) -> Released:
        """``label`` names the state of the records; ``releases`` refuses what was released before."""
        if releases:
            releases.claim(release_salt(salt, f"claim:{method}", eps, self.spec.key, sorted(options.items()), label))
        options["label"] = label
        return Released(experiments.release(method, build_cells(self._records, self.spec), self.spec, eps, salt, **options), self.spec)


class Released:
    """Boxes and noisy counts; holds nothing of the records."""

    def __init__(self, partitions: DataFrame, spec: MatrixSpec):
        self.partitions, self.spec = partitions, spec

    def answer(self, queries: DataFrame, strategy: str = "auto") -> DataFrame:
        return answer(self.partitions, queries, self.spec.d, strategy, self.spec.widths)

    def array_view(self) -> DataFrame:
        return boxes.array_view(self.partitions, self.spec.d)
