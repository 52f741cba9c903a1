"""Every query outside the optional training-data subpackage, by name, with its DuckDB twin where there is one."""

from __future__ import annotations

from hubsplit import registry
from hubsplit.operators import graph_ops, relational  # noqa: F401
from hubsplit.plans import partition_queries, program_queries  # noqa: F401  each module registers its queries
from hubsplit.streaming import events  # noqa: F401


def flagship(spark, sf_dir):
    return registry.QUERIES["cc_hybrid_near_copy"](spark, sf_dir)


def queries():
    return dict(registry.QUERIES)


def oracle_sql():
    return dict(registry.SQL)
