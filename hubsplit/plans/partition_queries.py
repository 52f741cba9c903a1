"""Queries on cuts, replicas, masters and measures, each with its DuckDB twin. Default view near_copy, four parts."""

from __future__ import annotations

from pyspark.sql import functions as F

from hubsplit.functions.hashing import hash32, hash32_sql
from hubsplit.plans import partition as P
from hubsplit.registry import query
from hubsplit.shared_dir import fresh_path
from hubsplit.sources.graphs import BUILDERS, build, ctes, table

N, VIEW = 4, "near_copy"


def assigned(spark, d, cut="ldch", view=VIEW, n=N):
    return P.CUTS[cut].assign(build(spark, d, view).edges, n)


def with_cut(cut="ldch", view=VIEW, n=N, more=""):
    """WITH ... up to the CTEs e, v, a (assigned edges), r (replicas)."""
    return f"WITH {ctes(view)}, a AS MATERIALIZED ({P.CUTS[cut].sql(n)}), r AS MATERIALIZED ({P.REPLICAS_SQL}){more} "


def _assign_query(cut):
    @query(f"assign_{cut}", with_cut(cut) + "SELECT src, dst, w, pid FROM a")
    def run(spark, d):
        return assigned(spark, d, cut)


for _cut in P.CUTS:
    _assign_query(_cut)


@query("cut_is_partition", with_cut() + "SELECT CAST((SELECT count(*) FROM e) AS BIGINT) AS n_edges, CAST(count(*) AS BIGINT) AS n_assigned, CAST(count(DISTINCT (src, dst)) AS BIGINT) AS n_distinct, CAST(max(c) AS BIGINT) AS most_parts FROM (SELECT src, dst, count(DISTINCT pid) AS c FROM a GROUP BY src, dst)")
def cut_is_partition(spark, d):
    g = build(spark, d, VIEW)
    per_edge = P.CUTS["ldch"].assign(g.edges, N).groupBy("src", "dst").agg(F.countDistinct("pid").alias("c"))
    found = per_edge.agg(F.count("*").alias("n_assigned"), F.count("*").alias("n_distinct"), F.max("c").alias("most_parts"))
    return g.edges.agg(F.count("*").alias("n_edges")).join(F.broadcast(found))


@query("replica_sets", with_cut() + "SELECT pid, vid FROM r")
def replica_sets(spark, d):
    return P.replicas_of(assigned(spark, d))


def _returns_all(spark, d):
    g = build(spark, d, "returns")
    v = table(spark, d, "orders", "o_orderkey").select((2 * F.col("o_orderkey")).alias("vid")).union(table(spark, d, "part", "p_partkey").select(2 * F.col("p_partkey") + 1))
    return type(g)(g.edges, v, False)


@query("isolated_placement", f"WITH {ctes('returns')}, x AS (SELECT 2 * o_orderkey AS vid FROM orders UNION SELECT 2 * p_partkey + 1 FROM part) SELECT CAST({hash32_sql('vid')} % {N} AS INT) AS pid, vid FROM x WHERE vid NOT IN (SELECT src FROM e UNION SELECT dst FROM e)")
def isolated_placement(spark, d):
    return P.place_isolated(_returns_all(spark, d), N)


@query("subgraph_rows", with_cut(view="returns") + "SELECT a.pid, a.src, a.dst, a.w, p.label AS src_label, q.label AS dst_label FROM a JOIN v p ON p.vid = a.src JOIN v q ON q.vid = a.dst")
def subgraph_rows(spark, d):
    g = build(spark, d, "returns")
    v = g.vertices
    return P.CUTS["ldch"].assign(g.edges, N).join(v.select(F.col("vid").alias("src"), F.col("label").alias("src_label")), "src").join(v.select(F.col("vid").alias("dst"), F.col("label").alias("dst_label")), "dst")


@query("replica_lists", with_cut() + "SELECT vid, array_to_string(list_sort(list(pid)), ',') AS parts FROM r GROUP BY vid")
def replica_lists(spark, d):
    return P.replicas_of(assigned(spark, d)).groupBy("vid").agg(F.array_join(F.array_sort(F.collect_set(F.col("pid"))).cast("array<string>"), ",").alias("parts"))


_COPIES = ", c AS (SELECT vid, count(*) AS n FROM r GROUP BY vid)"


@query("frontier_vertices", with_cut(more=_COPIES) + "SELECT r.pid, r.vid, CAST(c.n AS BIGINT) AS copies FROM r JOIN c USING (vid) WHERE n > 1")
def frontier_vertices(spark, d):
    return P.mark_frontier(P.replicas_of(assigned(spark, d))).where("is_frontier").select("pid", "vid", "copies")


@query("internal_vertices", with_cut(more=_COPIES) + "SELECT r.pid, r.vid FROM r JOIN c USING (vid) WHERE n = 1")
def internal_vertices(spark, d):
    return P.mark_frontier(P.replicas_of(assigned(spark, d))).where("not is_frontier").select("pid", "vid")


@query("master_election", with_cut() + P.MASTERS_SQL)
def master_election(spark, d):
    return P.elect_master(P.replicas_of(assigned(spark, d)))


_ROUTE = f", m AS ({P.MASTERS_SQL})"


@query("master_balance", with_cut("ueh", more=_ROUTE) + """SELECT pid, CAST(sum(hashed) AS BIGINT) AS hashed, CAST(sum(lowest) AS BIGINT) AS lowest, CAST(sum(single) AS BIGINT) AS single FROM (
    SELECT m.master_pid AS pid, 1 AS hashed, 0 AS lowest, 0 AS single FROM m UNION ALL SELECT min(pid), 0, 1, 0 FROM r GROUP BY vid UNION ALL SELECT 0, 0, 0, count(DISTINCT vid) FROM r) GROUP BY pid""")
def master_balance(spark, d):
    r = P.replicas_of(assigned(spark, d, "ueh"))
    counted = None
    for policy, name in (("hash", "hashed"), ("min_pid", "lowest"), ("single", "single")):
        own = P.elect_master(r, policy).groupBy(F.col("master_pid").alias("pid")).agg(F.count("*").alias("n")).select("pid", *[(F.col("n") if k == name else F.lit(0).cast("long")).alias(k) for k in ("hashed", "lowest", "single")])
        counted = own if counted is None else counted.union(own)
    return counted.groupBy("pid").agg(*[F.sum(k).alias(k) for k in ("hashed", "lowest", "single")])


@query("routing_table", with_cut(more=_ROUTE) + "SELECT r.pid, r.vid, m.master_pid FROM r JOIN m USING (vid)")
def routing_table(spark, d):
    return P.build_routing(P.replicas_of(assigned(spark, d)))


@query("degrees", f"WITH {ctes('commerce')} {P.DEGREES_SQL}")
def degrees(spark, d):
    return P.degrees(build(spark, d, "commerce").edges)


_TWO_WAY = "e AS (SELECT src, dst, w FROM u)"


@query("ldch_opposite_arcs_colocated", f"""WITH {ctes(VIEW, True).replace("e AS MATERIALIZED", "e0 AS MATERIALIZED").replace("FROM e UNION", "FROM e0 UNION").replace("FROM e)", "FROM e0)")}, e AS MATERIALIZED (SELECT * FROM u),
    a AS MATERIALIZED ({P.CUTS['ldch'].sql(N)}) SELECT CAST(count(*) AS BIGINT) AS pairs, CAST(count(*) FILTER (x.pid = y.pid) AS BIGINT) AS together FROM a x JOIN a y ON x.src = y.dst AND x.dst = y.src WHERE x.src < x.dst""")
def ldch_opposite_arcs_colocated(spark, d):
    a = P.CUTS["ldch"].assign(build(spark, d, VIEW).symmetric(), N)
    back = a.select(F.col("dst").alias("src"), F.col("src").alias("dst"), F.col("pid").alias("back"))
    return a.where("src < dst").join(back, ["src", "dst"]).agg(F.count("*").alias("pairs"), F.count_if(F.col("pid") == F.col("back")).alias("together"))


@query("adjacency_from_edges", f"WITH {ctes('commerce')} SELECT src, array_to_string(list_sort(list(dst)), ',') AS neighbours FROM e GROUP BY src")
def adjacency_from_edges(spark, d):
    from hubsplit.sources.readers import to_adjacency

    return to_adjacency(build(spark, d, "commerce").edges).select("src", F.array_join(F.transform("out", lambda x: x["dst"].cast("string")), ",").alias("neighbours"))


@query("edges_from_adjacency", f"WITH {ctes('commerce')} SELECT src, dst, w FROM e")
def edges_from_adjacency(spark, d):
    from hubsplit.sources.readers import from_adjacency, to_adjacency

    return from_adjacency(to_adjacency(build(spark, d, "commerce").edges))


@query("edges_from_text", f"WITH {ctes('returns')} SELECT src, dst, w FROM e")
def edges_from_text(spark, d):
    from hubsplit.sources.readers import edges_from_text as read, edges_to_text

    path = fresh_path(spark, "edge-text")
    edges_to_text(build(spark, d, "returns").edges, path)
    return read(spark, path)


@query("loader_placement", f"WITH {ctes(VIEW)} SELECT CAST({hash32_sql('vid')} % {N} AS INT) AS worker, CAST(count(*) AS BIGINT) AS n FROM (SELECT DISTINCT vid FROM v) GROUP BY ALL")
def loader_placement(spark, d):
    return build(spark, d, VIEW).vertices.select("vid").distinct().groupBy((hash32("vid") % N).cast("int").alias("worker")).agg(F.count("*").alias("n"))


@query("partition_traffic", with_cut() + f"""SELECT CAST((SELECT count(*) FROM (SELECT DISTINCT {hash32_sql('src')} % {N} AS at, dst FROM e WHERE {hash32_sql('src')} % {N} <> {hash32_sql('dst')} % {N})) AS BIGINT) AS degree_requests,
    CAST((SELECT count(*) FROM a WHERE {hash32_sql('src')} % {N} <> pid) AS BIGINT) AS edge_moves, CAST((SELECT count(*) FROM r) AS BIGINT) AS metadata_rows""")
def partition_traffic(spark, d):
    """Requests for a neighbour's degree held elsewhere, edges that leave their loader, and replica records sent."""
    a = assigned(spark, d)
    home = hash32("src") % N
    requests = a.where(home != hash32("dst") % N).select(home.alias("at"), "dst").distinct().agg(F.count("*").alias("degree_requests"))
    moves = a.agg(F.count_if(home != F.col("pid")).alias("edge_moves"))
    return requests.join(F.broadcast(moves)).join(F.broadcast(P.replicas_of(a).agg(F.count("*").alias("metadata_rows"))))


@query("layout_roundtrip", with_cut() + "SELECT src, dst, w, pid FROM a")
def layout_roundtrip(spark, d):
    from hubsplit.plans.layout import load_cut, save_cut

    path = fresh_path(spark, "layout")
    save_cut(assigned(spark, d), path, N)
    return load_cut(spark, path)[0]


@query("overpartition_balance", with_cut(n=16) + "SELECT CAST(pid % 4 AS INT) AS worker, CAST(count(*) AS BIGINT) AS n_edges, CAST(count(DISTINCT pid) AS BIGINT) AS n_parts FROM a GROUP BY ALL")
def overpartition_balance(spark, d):
    return assigned(spark, d, n=16).groupBy((F.col("pid") % 4).alias("worker")).agg(F.count("*").alias("n_edges"), F.countDistinct("pid").alias("n_parts"))


_PLACED = f", x AS MATERIALIZED (SELECT DISTINCT vid, CAST({hash32_sql('vid')} % {N} AS INT) AS part FROM v)"


@query("assign_vertex_hash", f"WITH {ctes(VIEW)} {_PLACED} SELECT vid, part FROM x")
def assign_vertex_hash(spark, d):
    return P.vertex_hash(build(spark, d, VIEW).vertices, N)


@query("edgecut_to_vertexcut", f"WITH {ctes(VIEW)} {_PLACED}, d AS ({P.DEGREES_SQL}) SELECT src, dst, w, CASE WHEN p.d <= q.d THEN y.part ELSE z.part END AS pid FROM e JOIN d p ON p.vid = src JOIN d q ON q.vid = dst JOIN x y ON y.vid = src JOIN x z ON z.vid = dst")
def edgecut_to_vertexcut(spark, d):
    g = build(spark, d, VIEW)
    return P.edge_cut_to_vertex_cut(P.vertex_hash(g.vertices, N), g.edges, "low_degree")


# --- measures ---------------------------------------------------------------------------------------------------------------------


def _measures(cut):
    views = ("near_copy", "pagelink", "commerce")
    parts = (4, 8, 32)

    sqls = [with_cut(cut, v, n) + f"SELECT '{v}' AS graph, {n} AS n, max(c) / (sum(c) / {n}e0) AS imbalance FROM (SELECT pid, count(*) AS c FROM a GROUP BY pid)" for v in views for n in parts]

    @query(f"imbalance_{cut}", "SELECT graph, CAST(n AS INT) AS n, round(imbalance, 9) AS imbalance FROM (" + " UNION ALL ".join(f"(SELECT * FROM ({s}))" for s in sqls) + ")")
    def imbalance(spark, d):
        from hubsplit.plans.metrics import imbalance as measure

        out = None
        for v in views:
            for n in parts:
                one = measure(assigned(spark, d, cut, v, n), n).select(F.lit(v).alias("graph"), F.lit(n).alias("n"), F.round("imbalance", 9).alias("imbalance"))
                out = one if out is None else out.union(one)
        return out

    sqls_rf = [with_cut(cut, v, n) + f"SELECT '{v}' AS graph, CAST({n} AS INT) AS n, round(count(*) / CAST(count(DISTINCT vid) AS DOUBLE), 9) AS rf FROM r" for v in views for n in parts]

    @query(f"rf_{cut}", " UNION ALL ".join(f"(SELECT * FROM ({s}))" for s in sqls_rf))
    def rf(spark, d):
        from hubsplit.plans.metrics import replication_factor

        out = None
        for v in views:
            for n in parts:
                one = replication_factor(assigned(spark, d, cut, v, n)).select(F.lit(v).alias("graph"), F.lit(n).alias("n"), F.round("rf", 9).alias("rf"))
                out = one if out is None else out.union(one)
        return out


for _cut in ("ueh", "ldch"):
    _measures(_cut)

_DEG = f", g AS ({P.DEGREES_SQL})"


@query("expected_rf", f"WITH {ctes('commerce')} {_DEG} SELECT CAST(n AS INT) AS n, round(sum(n * (1 - pow(1 - 1e0 / n, d))) / count(*), 6) AS expected FROM g, (SELECT unnest([4, 8, 32]) AS n) GROUP BY n")
def expected_rf(spark, d):
    from hubsplit.plans.metrics import expected_rf as measure

    return measure(P.degrees(build(spark, d, "commerce").edges), [4, 8, 32]).select("n", F.round("expected", 6).alias("expected"))


@query("expected_cut", f"WITH {ctes('returns')}, c AS (SELECT count(*) FILTER (src <> dst) AS open, count(*) AS m FROM e) SELECT CAST(n AS INT) AS n, round((1 - 1e0 / n) * open / m, 9) AS cut_fraction, round(1 + (1 - 1e0 / n) * open / m, 9) AS edge_copies FROM c, (SELECT unnest([4, 8, 32]) AS n) WHERE m > 0")
def expected_cut(spark, d):
    """What a random edge-cut of the view cuts: a loop never, any other edge unless both ends meet."""
    c = build(spark, d, "returns").edges.agg(F.count_if(F.col("src") != F.col("dst")).alias("open"), F.count("*").alias("m")).where("m > 0")
    share = (1 - 1 / F.col("n")) * F.col("open") / F.col("m")
    return c.select("open", "m", F.explode(F.array(*map(F.lit, (4, 8, 32)))).alias("n")).select("n", F.round(share, 9).alias("cut_fraction"), F.round(1 + share, 9).alias("edge_copies"))


@query("expected_gain", f"WITH {ctes('commerce')} {_DEG} SELECT CAST(n AS INT) AS n, round(sum(n * x), 3) AS vertex_cut, round(sum(1 + (n - 1) * x), 3) AS edge_cut, round(sum(1 - x), 3) AS gain FROM (SELECT n, 1 - pow(1 - 1e0 / n, d) AS x FROM g, (SELECT unnest([4, 8, 32]) AS n)) GROUP BY n")
def expected_gain(spark, d):
    from hubsplit.plans.metrics import expected_gain as measure

    return measure(P.degrees(build(spark, d, "commerce").edges), [4, 8, 32])


_CUTEDGES = ", b AS (SELECT e.src, e.dst, y.part AS ps, z.part AS pd FROM e JOIN x y ON y.vid = e.src JOIN x z ON z.vid = e.dst)"


@query("edgecut_metrics", f"WITH {ctes(VIEW)} {_PLACED} {_CUTEDGES}" + """, g AS (SELECT DISTINCT vid, part FROM (SELECT src AS vid, pd AS part FROM b WHERE ps <> pd UNION ALL SELECT dst, ps FROM b WHERE ps <> pd))
    SELECT CAST((SELECT count(*) FROM b WHERE ps <> pd) AS BIGINT) AS cut_edges, CAST((SELECT count(*) FROM g) AS BIGINT) AS ghosts, CAST((SELECT count(*) FROM b WHERE ps <> pd) AS BIGINT) AS duplicated_edges,
    round((SELECT max(c) / (sum(c) / 4e0) FROM (SELECT count(*) AS c FROM x GROUP BY part)), 9) AS vertex_imbalance,
    round((SELECT max(c) / (sum(c) / 4e0) FROM (SELECT count(*) AS c FROM (SELECT ps AS part FROM b UNION ALL SELECT pd FROM b WHERE ps <> pd) GROUP BY part)), 9) AS edge_imbalance""")
def edgecut_metrics(spark, d):
    from hubsplit.plans.metrics import edge_cut_metrics

    g = build(spark, d, VIEW)
    return edge_cut_metrics(g.edges, P.vertex_hash(g.vertices, N), N)


def _stats(view, name=None):
    @query(f"stats_{name or view}", f"WITH {ctes(view)} {_DEG} SELECT CAST((SELECT count(*) FROM e) AS BIGINT) AS n_edges, CAST(count(*) AS BIGINT) AS n_vertices, round((SELECT count(*) FROM e) / CAST(count(*) AS DOUBLE), 9) AS edges_per_vertex, round(2 * (SELECT count(*) FROM e) / CAST(count(*) AS DOUBLE), 9) AS average_degree, max(d_in) AS max_in, max(d_out) AS max_out FROM g")
    def run(spark, d):
        from hubsplit.plans.metrics import graph_stats

        return graph_stats(build(spark, d, view).edges)


for _view in ("commerce", "near_copy", "road", "pagelink", "docword"):
    _stats(_view)
_stats("kron_events", "kron")


@query("degree_histogram", f"WITH {ctes('docword')} {_DEG} SELECT d, CAST(count(*) AS BIGINT) AS n FROM g GROUP BY d")
def degree_histogram(spark, d):
    return P.degrees(build(spark, d, "docword").edges).groupBy("d").agg(F.count("*").alias("n"))


@query("kron_degree_histogram", f"WITH {ctes('kron_events')} {_DEG} SELECT d, CAST(count(*) AS BIGINT) AS n FROM g GROUP BY d")
def kron_degree_histogram(spark, d):
    return P.degrees(build(spark, d, "kron_events").edges).groupBy("d").agg(F.count("*").alias("n"))


@query("powerlaw_exponent", f"WITH {ctes('docword')} {_DEG} SELECT round(1 + count(*) / sum(ln(d / 4.5e0)), 6) AS exponent, CAST(count(*) AS BIGINT) AS tail FROM g WHERE d >= 5")
def powerlaw_exponent(spark, d):
    from hubsplit.plans.metrics import powerlaw_exponent as fit

    return fit(P.degrees(build(spark, d, "docword").edges), 5)


@query("hub_share", f"WITH {ctes('docword')} {_DEG} SELECT CAST(sum(CASE WHEN k <= 10 THEN d ELSE 0 END) AS BIGINT) AS hub_ends, CAST(sum(d) AS BIGINT) AS ends, round(sum(CASE WHEN k <= 10 THEN d ELSE 0 END) / CAST(sum(d) AS DOUBLE), 9) AS share FROM (SELECT d, row_number() OVER (ORDER BY d DESC, vid) AS k FROM g)")
def hub_share(spark, d):
    from hubsplit.plans.metrics import hub_share as measure

    return measure(P.degrees(build(spark, d, "docword").edges), 10)


@query("storage_overhead", with_cut("ldch", more=_PLACED + _CUTEDGES) + """SELECT round((SELECT count(*) FROM a) / CAST((SELECT count(*) FROM e) AS DOUBLE), 9) AS vc_edge_copies, round((SELECT count(*) FROM r) / CAST((SELECT count(DISTINCT vid) FROM r) AS DOUBLE), 9) AS vc_vertex_copies,
    round((SELECT sum(CASE WHEN ps <> pd THEN 2 ELSE 1 END) FROM b) / CAST((SELECT count(*) FROM e) AS DOUBLE), 9) AS ec_edge_copies,
    round((SELECT count(*) FROM (SELECT src AS vid, ps AS p FROM b UNION SELECT src, pd FROM b UNION SELECT dst, ps FROM b UNION SELECT dst, pd FROM b)) / CAST((SELECT count(DISTINCT vid) FROM r) AS DOUBLE), 9) AS ec_vertex_copies""")
def storage_overhead(spark, d):
    from hubsplit.plans.metrics import storage_overhead as measure

    g = build(spark, d, VIEW)
    return measure(g.edges, P.CUTS["ldch"].assign(g.edges, N), P.vertex_hash(g.vertices, N))


@query("part_bytes", with_cut() + "SELECT pid, CAST(count(*) AS BIGINT) AS n_edges, CAST(24 * count(*) AS BIGINT) AS bytes FROM a GROUP BY pid")
def part_bytes(spark, d):
    return assigned(spark, d).groupBy("pid").agg(F.count("*").alias("n_edges"), (24 * F.count("*")).alias("bytes"))


@query("kron_edges", f"WITH {ctes('kron_events')} SELECT src, dst, w FROM e")
def kron_edges(spark, d):
    return build(spark, d, "kron_events").edges

