"""Running sums in two levels: within a group of rows, and over the groups' totals, so that no task holds all rows."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def running_bases(rows: DataFrame, group: str, order: str, sums: list[str]) -> DataFrame:
    """Adds ``before_<column>`` for each column of ``sums``: its sum over all rows that come earlier by (group, order), a unique pair.

    One task sees a row for each group; a group is what one writing task left behind, so both levels stay small.
    """
    totals = rows.groupBy(group).agg(*[F.sum(c).alias(f"_all_{c}") for c in sums])
    outer, inner = Window.orderBy(group), Window.partitionBy(group).orderBy(order)
    totals = totals.select(group, *[(F.sum(f"_all_{c}").over(outer) - F.col(f"_all_{c}")).alias(f"_base_{c}") for c in sums])
    within = rows.select("*", *[(F.sum(c).over(inner) - F.col(c)).alias(f"_in_{c}") for c in sums])
    joined = within.join(totals, group)
    return joined.select(*rows.columns, *[(F.col(f"_base_{c}") + F.col(f"_in_{c}")).alias(f"before_{c}") for c in sums])
