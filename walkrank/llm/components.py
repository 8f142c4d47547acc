"""Connected components of a table of links, by alternating stars."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common


def components(links: DataFrame, most_rounds: int = 60) -> DataFrame:
    """links: a, b (long). For each end of a link its root, the smallest node reachable.

    A round links all larger neighbours of a node to its smallest neighbour, then all smaller ones. Each round is
    written to the shared folder; a node's smallest neighbour is a grouped minimum, so large stars are summed up before
    they are shuffled, and it is a table, so that the join of a large star with it can be split. It ends when all links
    are stars: each node has one link, to a node that has none. Tables of earlier rounds are deleted."""
    edge = lambda a, b: F.struct(F.greatest(a, b).alias("a"), F.least(a, b).alias("b"))
    now = common.written(links.where("a <> b").select(edge(F.col("a"), F.col("b")).alias("e")).select("e.*").distinct(), "links")
    for _ in range(most_rounds):
        both = now.unionByName(now.select(F.col("b").alias("a"), F.col("a").alias("b")))
        lowest = common.written(both.groupBy("a").agg(F.min("b").alias("m")).withColumn("m", F.least("a", "m")), "links-lowest")
        large = both.where("b > a").join(lowest, "a").select(F.col("b").alias("a"), F.col("m").alias("b"))
        large = large.unionByName(lowest.where("m < a").select("a", F.col("m").alias("b"))).where("a <> b").distinct()
        large = common.written(large, "links-large")
        low = common.written(large.groupBy("a").agg(F.min("b").alias("m")), "links-low")
        small = large.join(low, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).unionByName(low.select("a", F.col("m").alias("b")))
        before, now = now, common.written(small.where("a <> b").distinct(), "links")
        common.discard(before, lowest, large, low)
        single = now.groupBy("a").agg(F.count("*").alias("n")).where("n > 1").isEmpty()
        if single and now.join(now.select(F.col("b").alias("_b")).distinct(), F.col("a") == F.col("_b"), "left_semi").isEmpty():
            return now.select(F.col("a").alias("node"), F.col("b").alias("root")).unionByName(now.select(F.col("b").alias("node"), F.col("b").alias("root")).distinct())
    raise RuntimeError("the components did not settle")
