"""Parts at rest: one folder per part and a manifest; loading one part reads its folder alone."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession


def save_cut(assigned: DataFrame, path: str, n: int) -> None:
    """Edges as parquet by part, written by one task per part, and a one-row manifest."""
    assigned.repartitionById(n, assigned["pid"]).sortWithinPartitions("src", "dst").write.partitionBy("pid").parquet(f"{path}/edges")
    assigned.sparkSession.range(1).selectExpr(f"{n} AS n").write.json(f"{path}/manifest")


def load_cut(spark: SparkSession, path: str, pids: list[int] | None = None) -> tuple[DataFrame, int]:
    """The edges (of some parts, by partition pruning) and the number of parts."""
    n = int(spark.read.json(f"{path}/manifest").first()["n"])
    edges = spark.read.schema("src long, dst long, w long, pid int").parquet(f"{path}/edges")
    return (edges if pids is None else edges.where(edges["pid"].isin(pids))), n
