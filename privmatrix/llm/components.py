"""Connected components of a distributed edge list, by alternating star contraction."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from privmatrix.llm.store import dropped, written


def components(edges: DataFrame, most: int = 60) -> DataFrame:
    """id, label for every end of an edge (a, b: long); the label is the smallest id that is reachable.

    Each round joins every vertex's larger neighbours to its smallest one, then its smaller neighbours too; the number of
    rounds grows with the logarithm of the longest path. Rows per round never exceed twice the edges, and hot vertices only
    meet their own minimum. Self-loops count as vertices; an empty list gives an empty result.
    """
    vertices = edges.select(F.col("a").alias("id")).unionByName(edges.select(F.col("b").alias("id"))).distinct()
    u, v = F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")
    state, print_ = written(edges.where("a <> b").select(u, v).distinct(), "cc"), None
    for _ in range(most):
        both = state.select(F.col("u").alias("x"), F.col("v").alias("y")).unionByName(state.select(F.col("v").alias("x"), F.col("u").alias("y")))
        least = both.groupBy("x").agg(F.least(F.min("y"), F.col("x")).alias("m"))
        large = both.join(least, "x").where("y > x").select(F.col("y").alias("u"), F.col("m").alias("v"))
        small = large.groupBy("u").agg(F.min("v").alias("m"))
        lower = large.join(small, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v")
        after = written(lower.unionByName(small.select("u", F.col("m").alias("v"))).distinct(), "cc")
        now = tuple(after.agg(F.count("*"), F.expr("bit_xor(xxhash64(u, v))")).first())
        dropped(state)
        state = after
        if now == print_:
            break
        print_ = now
    else:
        raise RuntimeError("components did not settle")
    return vertices.join(state, vertices["id"] == state["u"], "left").select("id", F.coalesce("v", "id").alias("label"))
