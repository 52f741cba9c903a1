"""Connected components of an arbitrary edge table by alternating stars, all in DataFrame operations.

Each round joins every vertex to the smallest vertex near it: first for larger neighbours, then for smaller ones. The number of
edges never grows, and the rounds follow the logarithm of the diameter. Every round is a staged table, so that lost
executors cost one round at most. Minima are pre-aggregated before the shuffle; joins on hub vertices are ordinary
equi-joins that adaptive execution splits.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hubsplit.shared_dir import drop_path, staged, staged_path


def star_components(edges: DataFrame, max_rounds: int = 1000) -> DataFrame:
    """(vid, component) for each end of an edge (src, dst): the smallest vertex id of its component. Null ends and loops are ignored."""
    spark = edges.sparkSession
    now = staged(edges.where("src <> dst").select(F.greatest("src", "dst").alias("a"), F.least("src", "dst").alias("b")).distinct(), "stars")
    seen = None
    for _ in range(max_rounds):
        mark = now.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if mark == seen or not mark[0]:
            break
        seen = mark
        both = now.union(now.select(F.col("b").alias("a"), F.col("a").alias("b")))
        low = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
        large = both.where("b > a").join(low, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        least = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b")
        after = staged(small.union(least.select("a", F.col("m").alias("b"))).distinct(), "stars")
        drop_path(spark, staged_path(now))
        now = after
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    return now.select(F.col("a").alias("vid"), F.col("b").alias("component")).union(now.select("b", "b").distinct())
