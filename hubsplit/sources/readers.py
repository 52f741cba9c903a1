"""Readers and writers of graphs: vertex-oriented records, edge lists, text."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def to_adjacency(edges: DataFrame) -> DataFrame:
    """src and its out-edges in order of target. For export only: a hub becomes one row."""
    return edges.groupBy("src").agg(F.array_sort(F.collect_list(F.struct("dst", "w"))).alias("out"))


def from_adjacency(adjacency: DataFrame) -> DataFrame:
    return adjacency.select("src", F.explode("out").alias("x")).select("src", "x.dst", "x.w")


def edges_to_text(edges: DataFrame, path: str) -> None:
    edges.select(F.concat_ws(" ", "src", "dst", "w").alias("value")).write.text(path)


def edges_from_text(spark: SparkSession, path: str) -> DataFrame:
    """`src dst [w]` lines; blank lines and comments go, a missing weight is 1."""
    lines = spark.read.text(path).where("trim(value) <> '' and not startswith(ltrim(value), '#')")
    parts = F.split(F.trim("value"), r"\s+")
    return lines.select(parts[0].cast("long").alias("src"), parts[1].cast("long").alias("dst"), F.coalesce(F.get(parts, F.lit(2)).cast("long"), F.lit(1).cast("long")).alias("w"))
