"""Measures of cuts and graphs: aggregates over assigned edges, replicas and degrees."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hubsplit.plans import partition as P


def imbalance(assigned: DataFrame, n: int) -> DataFrame:
    """Largest part over the mean part, counting empty parts."""
    sizes = assigned.groupBy("pid").agg(F.count("*").alias("c"))
    return sizes.agg((F.max("c") / (F.sum("c") / F.lit(float(n)))).alias("imbalance"))


def replication_factor(assigned: DataFrame) -> DataFrame:
    per_vertex = P.replicas_of(assigned).groupBy("vid").agg(F.count("*").alias("copies"))
    return per_vertex.agg((F.sum("copies") / F.count("*")).alias("rf"))


def _per_n(degrees: DataFrame, parts: list[int]) -> DataFrame:
    x = 1 - F.pow(1 - 1 / F.col("n"), F.col("d"))
    return degrees.select("d", F.explode(F.array(*map(F.lit, parts))).alias("n")).withColumn("x", x)


def expected_rf(degrees: DataFrame, parts: list[int]) -> DataFrame:
    """Copies of a vertex under a uniform edge hash, averaged: n (1 - (1 - 1/n)^degree)."""
    return _per_n(degrees, parts).groupBy("n").agg((F.sum(F.col("n") * F.col("x")) / F.count("*")).alias("expected"))


def expected_gain(degrees: DataFrame, parts: list[int]) -> DataFrame:
    """Expected copies under a random vertex-cut and a random edge-cut; the difference is never negative."""
    n, x = F.col("n"), F.col("x")
    return _per_n(degrees, parts).groupBy("n").agg(F.round(F.sum(n * x), 3).alias("vertex_cut"), F.round(F.sum(1 + (n - 1) * x), 3).alias("edge_cut"), F.round(F.sum(1 - x), 3).alias("gain"))


def edge_cut_metrics(edges: DataFrame, placed: DataFrame, n: int) -> DataFrame:
    p, q = placed.select(F.col("vid").alias("src"), F.col("part").alias("ps")), placed.select(F.col("vid").alias("dst"), F.col("part").alias("pd"))
    both = edges.join(p, "src").join(q, "dst")
    cut = both.where("ps <> pd")
    ghosts = cut.select(F.explode(F.array(F.struct(F.col("src").alias("vid"), F.col("pd").alias("part")), F.struct(F.col("dst").alias("vid"), F.col("ps").alias("part")))).alias("g")).distinct()
    share = lambda df, by: df.groupBy(by).agg(F.count("*").alias("c")).agg(F.round(F.max("c") / (F.sum("c") / F.lit(float(n))), 9).alias("x"))
    held = both.select(F.explode(F.array_distinct(F.array("ps", "pd"))).alias("part"))
    out = cut.agg(F.count("*").alias("cut_edges")).join(F.broadcast(ghosts.agg(F.count("*").alias("ghosts"))))
    out = out.withColumn("duplicated_edges", F.col("cut_edges")).join(F.broadcast(share(placed, "part").withColumnRenamed("x", "vertex_imbalance")))
    return out.join(F.broadcast(share(held, "part").withColumnRenamed("x", "edge_imbalance")))


def graph_stats(edges: DataFrame) -> DataFrame:
    """Edges, vertices, edges per vertex, both ends per vertex, largest in and out degree."""
    whole = P.degrees(edges).agg((F.sum("d") / 2).cast("long").alias("n_edges"), F.count("*").alias("n_vertices"), F.max("d_in").alias("max_in"), F.max("d_out").alias("max_out"))
    per = F.col("n_edges") / F.col("n_vertices")
    return whole.select("n_edges", "n_vertices", F.round(per, 9).alias("edges_per_vertex"), F.round(2 * F.col("n_edges") / F.col("n_vertices"), 9).alias("average_degree"), "max_in", "max_out")


def powerlaw_exponent(degrees: DataFrame, dmin: int) -> DataFrame:
    tail = degrees.where(F.col("d") >= dmin)
    return tail.agg(F.round(1 + F.count("*") / F.sum(F.log(F.col("d") / F.lit(dmin - 0.5))), 6).alias("exponent"), F.count("*").alias("tail"))


def hub_share(degrees: DataFrame, k: int) -> DataFrame:
    """Share of edge ends on the k vertices of largest degree (a top-k report)."""
    top = degrees.orderBy(F.desc("d"), "vid").limit(k).agg(F.sum("d").alias("hub_ends"))
    return degrees.agg(F.sum("d").alias("ends")).join(F.broadcast(top)).select("hub_ends", "ends", F.round(F.col("hub_ends") / F.col("ends"), 9).alias("share"))


def storage_overhead(edges: DataFrame, assigned: DataFrame, placed: DataFrame) -> DataFrame:
    copies = P.edge_cut(edges, placed)
    one = lambda df, name: df.agg(F.count("*").cast("double").alias(name))
    r = P.replicas_of(assigned)
    parts = one(assigned, "a").join(F.broadcast(one(edges, "e"))).join(F.broadcast(one(r, "r"))).join(F.broadcast(one(r.select("vid").distinct(), "v")))
    parts = parts.join(F.broadcast(one(copies, "ec"))).join(F.broadcast(one(P.replicas_of(copies), "er")))
    ratio = lambda a, b, name: F.round(F.col(a) / F.col(b), 9).alias(name)
    return parts.select(ratio("a", "e", "vc_edge_copies"), ratio("r", "v", "vc_vertex_copies"), ratio("ec", "e", "ec_edge_copies"), ratio("er", "v", "ec_vertex_copies"))
