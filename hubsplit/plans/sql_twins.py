"""DuckDB text of the fixpoints: components, shortest paths, rounds of PageRank, simulation."""

from __future__ import annotations

from hubsplit.sources.graphs import ctes


def components_sql(view: str) -> str:
    """WITH RECURSIVE ... cc(vid, component)."""
    return f"""WITH RECURSIVE {ctes(view, True)}, cc(vid, component) USING KEY (vid) AS (
        SELECT DISTINCT vid, vid AS component FROM (SELECT src AS vid FROM u UNION SELECT vid FROM v)
        UNION SELECT u.dst, min(cc.component) FROM cc JOIN u ON u.src = cc.vid JOIN recurring.cc r ON r.vid = u.dst WHERE cc.component < r.component GROUP BY u.dst) """


def paths_sql(view: str, source: str, weight: str = "w", symmetric: bool = False) -> str:
    """WITH RECURSIVE ... sp(vid, dist); ``source`` is a scalar query."""
    arcs = "u" if symmetric else "e"
    return f"""WITH RECURSIVE {ctes(view, True)}, sp(vid, dist) USING KEY (vid) AS (
        SELECT CAST(({source}) AS BIGINT) AS vid, CAST(0 AS BIGINT) AS dist
        UNION SELECT x.dst, CAST(min(sp.dist + x.{weight}) AS BIGINT) FROM sp JOIN (SELECT src, dst, CAST(w AS BIGINT) AS w, CAST(1 AS BIGINT) AS one FROM {arcs}) x ON x.src = sp.vid
        LEFT JOIN recurring.sp r ON r.vid = x.dst WHERE r.dist IS NULL OR sp.dist + x.{weight} < r.dist GROUP BY x.dst) """


def pagerank_sql(view: str, rounds: int, damping: float = 0.85) -> str:
    """WITH ... p<rounds>(vid, rank): the synchronous equation, sinks dropped."""
    text = f"WITH {ctes(view)}, vv AS MATERIALIZED (SELECT DISTINCT vid FROM v), nn AS MATERIALIZED (SELECT CAST(count(*) AS DOUBLE) AS n FROM vv), od AS MATERIALIZED (SELECT src, count(*) AS d FROM e GROUP BY src), p0 AS MATERIALIZED (SELECT vid, 1 / n AS rank FROM vv, nn)"
    for k in range(1, rounds + 1):
        text += f""", p{k} AS MATERIALIZED (SELECT vv.vid, (1 - {damping}e0) / n + {damping}e0 * coalesce(s, 0) AS rank FROM nn, vv LEFT JOIN (
            SELECT e.dst, sum(p.rank / od.d) AS s FROM p{k - 1} p JOIN e ON e.src = p.vid JOIN od ON od.src = e.src GROUP BY e.dst) t ON t.dst = vv.vid)"""
    return text + " "


def pagerank_limit_sql(view: str, rounds: int, damping: float = 0.85) -> str:
    """WITH RECURSIVE ... pr(vid, rank): the same after many rounds."""
    return f"""WITH RECURSIVE {ctes(view)}, vv AS MATERIALIZED (SELECT DISTINCT vid FROM v), nn AS MATERIALIZED (SELECT CAST(count(*) AS DOUBLE) AS n FROM vv), od AS MATERIALIZED (SELECT src, count(*) AS d FROM e GROUP BY src),
        a AS MATERIALIZED (SELECT e.src, e.dst, {damping}e0 / d AS share FROM e JOIN od USING (src)), pk AS (SELECT 0 AS k, vid, 1 / n AS rank FROM vv, nn UNION ALL
        SELECT k + 1, vv.vid, (1 - {damping}e0) / n + coalesce(s, 0) FROM nn, (SELECT DISTINCT k FROM pk) kk, vv LEFT JOIN (SELECT a.dst, sum(pk.rank * a.share) AS s FROM pk JOIN a ON a.src = pk.vid GROUP BY a.dst) t ON t.dst = vv.vid
        WHERE k < {rounds}), pr AS (SELECT vid, rank FROM pk WHERE k = {rounds}) """


def fixedpoint_sql(view: str, rounds: int, scale: int = 10**12) -> str:
    """The same in integers: rank in units of 1 / scale, damping 85 %, whole divisions."""
    text = f"WITH {ctes(view)}, vv AS MATERIALIZED (SELECT DISTINCT vid FROM v), nn AS MATERIALIZED (SELECT count(*) AS n FROM vv), od AS MATERIALIZED (SELECT src, count(*) AS d FROM e GROUP BY src), p0 AS MATERIALIZED (SELECT vid, CAST({scale} // n AS BIGINT) AS rank FROM vv, nn)"
    for k in range(1, rounds + 1):
        text += f""", p{k} AS MATERIALIZED (SELECT vv.vid, CAST({scale} * 15 // (100 * n) + 85 * coalesce(s, 0) // 100 AS BIGINT) AS rank FROM nn, vv LEFT JOIN (
            SELECT e.dst, CAST(sum(p.rank // od.d) AS BIGINT) AS s FROM p{k - 1} p JOIN e ON e.src = p.vid JOIN od ON od.src = e.src GROUP BY e.dst) t ON t.dst = vv.vid)"""
    return text + " "


def simulation_sql(view: str, nodes: dict[str, str], arcs: list[tuple[str, str]], rounds: int) -> str:
    """WITH ... s<rounds>(u, vid): pattern nodes and the vertices that simulate them, before the all-or-nothing rule."""
    labels = " UNION ALL ".join(f"SELECT '{u}' AS u, '{label}' AS label" for u, label in nodes.items())
    wants = " UNION ALL ".join(f"SELECT '{a}' AS u, '{b}' AS u2" for a, b in arcs)
    text = f"WITH {ctes(view)}, pn AS ({labels}), pe AS ({wants}), s0 AS MATERIALIZED (SELECT u, vid FROM v JOIN pn USING (label))"
    need = "pc AS (SELECT u, count(*) AS c FROM pe GROUP BY u)"
    text += ", " + need
    for k in range(1, rounds + 1):
        text += f""", s{k} AS MATERIALIZED (SELECT s.u, s.vid FROM s{k - 1} s LEFT JOIN pc ON pc.u = s.u LEFT JOIN (
            SELECT u, vid, count(*) AS c FROM (SELECT DISTINCT c.u, c.vid, pe.u2 FROM s{k - 1} c JOIN pe ON pe.u = c.u JOIN e ON e.src = c.vid JOIN s{k - 1} t ON t.vid = e.dst AND t.u = pe.u2)
            GROUP BY u, vid) m ON m.u = s.u AND m.vid = s.vid WHERE pc.c IS NULL OR m.c = pc.c)"""
    return text + " "
