"""Connected components of an edge table, by alternating star steps, without rows for pairs."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from channelalign.llm.store import written


def _looked_up(edges: DataFrame, least: DataFrame) -> DataFrame:
    # The least neighbours are joined by a key of another expression, so both sides are exchanged for this join and AQE may split a hot vertex.
    return edges.join(least.select((F.col("u") + 0).alias("_u"), "m"), F.col("u") == F.col("_u")).drop("_u")


def connected(edges: DataFrame, most_rounds: int = 60) -> DataFrame:
    """edges: (u long, v long), either direction. Returns (vertex, component), component the least vertex of each component.

    Every round points larger neighbours at the least neighbour and then smaller ones, which keeps one row per
    vertex and parent at most; rounds grow with the logarithm of the components' size. Each round is written to
    the shared folder. No component comes together in one task, nor at the driver.
    """
    now = written(edges.where("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(), "edges")
    mark = None
    for _ in range(most_rounds):
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = _looked_up(both, least).where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        small = _looked_up(large, least)
        now = written(small.where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(least.select("u", F.col("m").alias("v"))).distinct(), "edges")
        seen = now.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if mark == tuple(seen):
            return now.groupBy(F.col("u").alias("vertex")).agg(F.min("v").alias("component")).unionByName(now.select(F.col("v").alias("vertex"), F.col("v").alias("component")).distinct())
        mark = tuple(seen)
    raise RuntimeError("the components did not settle")
