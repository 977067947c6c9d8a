"""Cost and accuracy measures."""

from __future__ import annotations

import math
import time

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from privmatrix.functions import boxes


def relative_error(truth: Column, est: Column, zero: str = "skip", delta: float = 1.0) -> Column:
    """In percent. A true count of 0 gives null (skip), or the error against ``delta`` (floor)."""
    base = F.nullif(truth, F.lit(0.0)) if zero == "skip" else F.greatest(truth, F.lit(delta))
    return F.abs(truth - est) / base * 100


def errors(truth: DataFrame, answers: DataFrame, zero: str = "skip", delta: float = 1.0) -> DataFrame:
    """qid, truth, est, rel_err."""
    return truth.join(answers, "qid").select("qid", "truth", "est", relative_error(F.col("truth"), F.col("est"), zero, delta).alias("rel_err"))


def mre(answers: DataFrame, *by: str) -> DataFrame:
    """Mean and median relative error, the largest, and how many queries were skipped, of each group."""
    return answers.groupBy(*by).agg(F.avg("rel_err").alias("mre"), F.median("rel_err").alias("median"), F.max("rel_err").alias("largest"), F.count_if(F.col("rel_err").isNull()).alias("skipped"))


def decompose(truth: DataFrame, exact_boxes: DataFrame, answers: DataFrame) -> DataFrame:
    """qid, uniformity, noise: distance of the answer from exact box totals to the truth, and of the noisy answer to that one."""
    three = truth.join(exact_boxes.select("qid", F.col("est").alias("est0")), "qid").join(answers, "qid")
    return three.select("qid", "truth", F.abs(F.col("est0") - F.col("truth")).alias("uniformity"), F.abs(F.col("est") - F.col("est0")).alias("noise"), F.abs(F.col("est") - F.col("truth")).alias("total"))


def entropy(counts: DataFrame, count: str = "f") -> DataFrame:
    """One row: entropy in bits of a partitioning with the given counts. Not private."""
    one = counts.agg(F.sum(count).cast("double").alias("n"))
    p = F.col(count) / F.col("n")
    return counts.join(F.broadcast(one)).where(F.col(count) > 0).agg(F.coalesce(F.sum(-p * F.log2(p)), F.lit(0.0)).alias("entropy"))


def noise_entropy(m: Column, eps: float, d: int) -> Column:
    """Bits of the noise that a grid of m cuts per axis imposes on a query."""
    return F.log2(math.sqrt(2) * F.pow(m, F.lit(d / 2)) / eps)


def approximate_loss(n: Column, m: Column, d: int) -> Column:
    """Information that m cuts per axis lose, taking entries for uniform."""
    return F.log2(n) - d * F.log2(m)


def information_loss(cells: DataFrame, widths: tuple[int, ...], m: int) -> DataFrame:
    """One row: entropy of the entries, of the boxes of m cuts, and their difference."""
    d = len(widths)
    coarse = cells.groupBy(*[boxes.even_index(F.col(f"x{i}"), 0, w, min(m, w)).alias(f"j{i}") for i, w in enumerate(widths, 1)]).agg(F.sum("f").alias("f"))
    both = entropy(cells).select(F.col("entropy").alias("h")).join(F.broadcast(entropy(coarse).select(F.col("entropy").alias("hm"))))
    return both.select(F.lit(m).alias("m"), F.lit(d).alias("d"), "h", "hm", (F.col("h") - F.col("hm")).alias("loss"))


def grid_error_curve(spark: SparkSession, n: float, eps: float, d: int, r: float, c0: float, ms: list[int]) -> DataFrame:
    """m, noise, uniformity, total: the predicted error of a query of share r on a grid of m cuts per axis."""
    m = F.col("m").cast("double")
    listed = spark.createDataFrame([(x,) for x in ms], "m int")
    noise = F.lit(math.sqrt(2 * r) / eps) * F.pow(m, F.lit(d / 2))
    uniformity = F.lit(r ** (1 / d) * n / c0) / F.pow(m, F.lit(float(d - 1)))
    return listed.select("m", noise.alias("noise"), uniformity.alias("uniformity"), (noise + uniformity).alias("total"))


def level_noise(m0: float, eps_levels: list[float]) -> float:
    """The summed noise variance (up to a factor) of a tree of fan-out m0 with these level budgets."""
    return sum(m0**i / e**2 for i, e in enumerate(eps_levels, 1))


def structure(partitions: DataFrame) -> DataFrame:
    """Boxes, smallest and largest box of each depth."""
    return partitions.groupBy("depth").agg(F.count("*").alias("n_boxes"), F.min("n_entries").alias("smallest"), F.max("n_entries").alias("biggest"), F.sum("n_entries").alias("covered"))


def fanouts(nodes: DataFrame) -> DataFrame:
    """Children per node of each depth: nodes is a tree's node list (pid, depth)."""
    parents = nodes.where("depth > 0").groupBy(F.regexp_replace("pid", r"\.[0-9]+$", "").alias("parent"), (F.col("depth") - 1).alias("depth")).agg(F.count("*").alias("children"))
    return parents.groupBy("depth").agg(F.avg("children").alias("mean"), F.min("children").alias("fewest"), F.max("children").alias("most"))


def noise_variance(partitions: DataFrame, queries: DataFrame, d: int, scale: float) -> DataFrame:
    """qid, variance: of the noise in a query's answer when every box has noise of one scale."""
    met = partitions.join(F.broadcast(queries.select("qid", *boxes.bounds(d, "q"))), boxes.overlaps(d))
    share = boxes.overlap(d) / F.col("n_entries")
    return met.groupBy("qid").agg(F.sum(2 * scale**2 * share * share).alias("variance"))


def ranking(results: DataFrame, *by: str, error: str = "mre") -> DataFrame:
    """Rank of each method within a workload and its ratio to the best."""
    w = Window.partitionBy(*by).orderBy(error)
    return results.withColumn("rank", F.rank().over(w)).withColumn("to_best", F.try_divide(error, F.min(error).over(Window.partitionBy(*by))))


def quantile_groups(answers: DataFrame, size: Column, n: int = 4) -> DataFrame:
    """Mean error by quantile of query size."""
    return answers.withColumn("size", size).withColumn("part", F.ntile(n).over(Window.orderBy("size", "qid"))).groupBy("part").agg(F.avg("rel_err").alias("mre"))


def timed(run) -> tuple[float, object]:
    """Seconds of a call, and its result."""
    start = time.perf_counter()
    out = run()
    return time.perf_counter() - start, out
