"""Comparison of queries with their DuckDB twins."""

from __future__ import annotations

from hubsplit import catalog

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def connect(sf_dir: str):
    """A DuckDB connection with a view for each table."""
    import duckdb

    c = duckdb.connect()
    c.execute("SET TimeZone = 'UTC'")
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf_dir}/{t}.parquet'")
    return c


def differences(spark, duck, sf_dir: str, name: str, queries=None, oracles=None) -> str | None:
    """None where both give the same rows under the same names; else what differs."""
    df = (queries or catalog.queries())[name](spark, sf_dir)
    cols = sorted(df.columns)
    sql = (oracles or catalog.oracle_sql())[name]
    found = duck.execute(f"SELECT * FROM ({sql})")
    if sorted(x[0] for x in found.description) != cols:
        return f"columns {cols} against {sorted(x[0] for x in found.description)}"
    want = duck.execute(f"SELECT {', '.join(cols)} FROM ({sql})").fetchall()
    key = lambda r: tuple((x is None, str(x)) for x in r)
    a, b = sorted(map(tuple, df.select(*cols).collect()), key=key), sorted(want, key=key)
    if a == b:
        return None
    at = next((i for i, (x, y) in enumerate(zip(a, b, strict=False)) if x != y), min(len(a), len(b)))
    return f"{len(a)} rows against {len(b)}; first difference: {a[at] if at < len(a) else None} against {b[at] if at < len(b) else None}"
