"""Connected components of a distributed edge list."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from ..sources.tables import cut


def components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """(node, root): root is the smallest node that the node reaches; nodes without an edge are absent.

    Alternates two contractions until nothing changes: every node hands its larger neighbours to its smallest
    neighbour, then its smaller ones. Each keeps connectivity, both are aggregates and equi-joins, and the edge list
    ends as one star per component after about log(n) rounds. Hubs are pre-aggregated before each shuffle (min), and the
    joins are plain inner joins that adaptive execution can split. Nulls and self-links are ignored.
    """
    e = edges.select(F.col(a).alias("u"), F.col(b).alias("v")).where("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct()
    e, seen = cut(e), None
    while True:
        both = e.union(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m")).withColumn("m", F.least("u", "m"))
        # the larger neighbours of u, and u itself where it isn't the smallest, go to m
        big = both.where("v > u").join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).union(low.where("u <> m")).distinct()
        # now v < u on each edge: all smaller neighbours of u, and u, go to the smallest of them
        low2 = big.groupBy("u").agg(F.min("v").alias("m"))
        e = cut(big.join(low2, "u").select(F.when(F.col("v") == F.col("m"), F.col("u")).otherwise(F.col("v")).alias("u"), F.col("m").alias("v")).distinct())
        state = e.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if state == seen:
            return e.select(F.col("u").alias("node"), F.col("v").alias("root")).union(e.select(F.col("v"), F.col("v")).distinct())
        seen = state
