"""Connected components of an edge table by alternating star contraction.

Every round shuffles the current edges twice and ends with one small aggregate on the driver; edges never
leave the executors. A hub's neighbours are reduced by partial aggregation, and the joins back are plain
shuffled joins whose large partitions adaptive execution can split.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ruleworld.sources.scratch import settle


def _large_star(edges: DataFrame) -> DataFrame:
    both = edges.select("u", "v").unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
    return both.filter("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))


def _small_star(edges: DataFrame) -> DataFrame:
    down = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    least = down.groupBy("u").agg(F.min("v").alias("m"))
    moved = down.join(least, "u").filter("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return moved.unionByName(least.select("u", F.col("m").alias("v")))


def connect(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """``(node, root)`` for every node that has an edge to another; the root is the component's least node.

    ``edges`` has two columns of one orderable type. Loops and nulls are ignored; an empty table gives an
    empty result. Nodes without edges are not listed: they are their own roots.
    """
    a, b = edges.columns[:2]
    now = settle(edges.select(F.col(a).alias("u"), F.col(b).alias("v")).filter("u <> v").distinct())
    mark = None
    for _ in range(max_rounds):
        now = settle(_small_star(_large_star(now).filter("u <> v").distinct()).filter("u <> v").distinct())
        seen = now.agg(F.count("*").alias("n"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")).alias("h")).first()
        if (seen.n, seen.h) == mark:
            break
        mark = (seen.n, seen.h)
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    return now.select(F.col("u").alias("node"), F.col("v").alias("root")).unionByName(
        now.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct()
    )
