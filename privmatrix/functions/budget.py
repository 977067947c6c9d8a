"""Privacy budgets: shares of roots, levels and purposes, and the ledger of what was spent."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

ROOT_FRACTION = 0.01
SPLIT_SHARE = 0.3


def root_share(eps: float, fraction: float = ROOT_FRACTION) -> float:
    return eps * fraction


def split(eps_k: Column | float, q: float = SPLIT_SHARE) -> tuple[Column | float, Column | float]:
    """(for choosing the split, for the count)."""
    return eps_k * q, eps_k * (1 - q)


def level_budgets(m0: Column, eps: float, d: int, eps0: float | None = None, base: str = "net") -> Column:
    """array<double> of the budgets of levels 1..d, in proportion to m0 ** (i / 3), which makes the summed noise least.

    base: ``net`` shares what the root left; ``gross`` shares eps itself but gives the last level only the remainder.
    """
    eps0 = root_share(eps) if eps0 is None else eps0
    m0 = F.greatest(F.lit(1.0), m0.cast("double"))
    weights = [F.pow(m0, F.lit(i / 3)) for i in range(1, d + 1)]
    total = sum(weights[1:], weights[0])
    if base == "net":
        return F.array(*[F.lit(eps - eps0) * w / total for w in weights])
    shares = [F.lit(eps) * w / total for w in weights[:-1]]
    rest = F.lit(eps - eps0) - (sum(shares[1:], shares[0]) if shares else F.lit(0.0))
    return F.array(*shares, rest)


def equal_budgets(eps: float, d: int, eps0: float | None = None) -> Column:
    """The same budget for every level; for comparison."""
    eps0 = root_share(eps) if eps0 is None else eps0
    return F.array(*[F.lit((eps - eps0) / d)] * d)


def path_total(spent: DataFrame) -> DataFrame:
    """path, eps, proven: what each root-to-leaf path of a ledger (path, purpose, eps, proven) spends in all."""
    return spent.groupBy("path").agg(F.sum("eps").alias("eps"), F.min("proven").alias("proven"))


class Releases:
    """Releases that were made, as marker files in a folder that all drivers share. A key (see ``noise.release_salt``) is claimed once: the same
    noise on other data, or a second look under one label, is refused."""

    def __init__(self, spark: SparkSession, path: str):
        self._spark, self._path = spark, path

    def claim(self, key: str) -> None:
        file = self._spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{self._path}/{key}")
        if not file.getFileSystem(self._spark.sparkContext._jsc.hadoopConfiguration()).createNewFile(file):
            raise ValueError("this salt, method, budget, matrix and label were released before")


def assert_within(spent: DataFrame, eps: float, tolerance: float = 1e-9) -> None:
    """Raises where a path spends more than eps. Disjoint siblings share a budget, steps of one path add up."""
    worst = path_total(spent).agg(F.max("eps")).first()[0]
    if worst is not None and worst > eps + tolerance:
        raise ValueError(f"a path spends {worst}, the budget is {eps}")
