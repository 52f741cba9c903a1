"""Arithmetic on run ledgers: breakdown of time, processed edges per second, ratios between contenders."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def breakdown(ledger: DataFrame) -> DataFrame:
    """From (round, pid, compute_ms, network_ms, edges, pairs): a part waits for the round's slowest part."""
    slowest = ledger.groupBy("round").agg(F.max("compute_ms").alias("slowest"))
    both = ledger.join(slowest, "round")
    return both.groupBy("round").agg(
        F.min("compute_ms").alias("compute_min"), F.round(F.avg("compute_ms"), 6).alias("compute_mean"), F.max("compute_ms").alias("compute_max"), F.round(F.avg(F.col("slowest") - F.col("compute_ms")), 6).alias("sync_mean"),
        F.sum("pairs").alias("pairs"), F.round(F.try_divide(F.max("edges"), F.avg("edges")), 6).alias("work_imbalance"), F.round(F.try_divide(F.sum("edges"), F.max("slowest") / 1000), 3).alias("peps"))


def ledger_rows(ledger: list[dict]) -> list[tuple]:
    """(round, pid, compute_ms, network_ms, edges, pairs) of every part that ran in a round."""
    return [(r["round"], p[0], p[1], r["network_ms"], p[2], p[3]) for r in ledger for p in r["parts"]]


def totals(ledger: list[dict]) -> dict:
    """Rounds, pairs and edges of a run."""
    return {"rounds": len(ledger), "pairs_up": sum(r["pairs_up"] for r in ledger), "pairs_down": sum(r["pairs_down"] for r in ledger), "edges_visited": sum(r.get("edges_visited", 0) for r in ledger)}


def peps(edges_visited: int, seconds: float, cores: int = 1) -> tuple[float, float]:
    """Processed edges per second, in all and per core."""
    return edges_visited / seconds, edges_visited / seconds / cores


def ratios(rows: list[dict], base: str, key: str = "contender", measures: tuple[str, ...] = ("run_s", "pairs", "rounds")) -> list[dict]:
    """Each contender's measures over those of ``base``."""
    at = next(r for r in rows if r[key] == base)
    return [{key: r[key], **{m: r[m] / at[m] if at[m] else None for m in measures}} for r in rows]
