"""Queries on the programs, their variants and rivals, each with its DuckDB twin."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from hubsplit.plans import partition as P
from hubsplit.plans import programs as R
from hubsplit.plans import rivals as V
from hubsplit.plans import sql_twins as S
from hubsplit.plans.partition_queries import N, with_cut
from hubsplit.plans.runtime import each_part, fold, make_layout, out_edge_layout, run, spread
from hubsplit.registry import query
from hubsplit.sources.graphs import build, ctes, table

_CC = "SELECT vid, component FROM cc"


def _layout(spark, d, view, cut="ldch", mode="vertex_cut", placed=None, n=N):
    return make_layout(build(spark, d, view), P.CUTS[cut] if cut else None, n, mode, placed)


def _component_queries():
    for view in ("near_copy", "returns", "pagelink"):
        sql = S.components_sql(view) + _CC
        for suffix, cut in (("", "ldch"), ("_ueh", "ueh")):
            query(f"cc_hybrid_{view}{suffix}", sql)(lambda spark, d, v=view, c=cut: R.connected_components(_layout(spark, d, v, c)).values)
        query(f"cc_edgecut_{view}", sql)(lambda spark, d, v=view: R.connected_components(_layout(spark, d, v, None, "edge_cut")).values)
        query(f"cc_vcbsp_{view}", sql)(lambda spark, d, v=view: V.cc(build(spark, d, v)).values)
        query(f"cc_gas_{view}", sql)(lambda spark, d, v=view: V.cc(build(spark, d, v), P.CUTS["ldch"], N).values)
        if view != "pagelink":
            def block(spark, d, v=view):
                g = build(spark, d, v)
                return V.block_cc(g, V.partition_bfs(g))

            query(f"cc_block_{view}", sql)(block)


_component_queries()


@query("cc_sizes", S.components_sql("returns") + "SELECT component, CAST(count(*) AS BIGINT) AS n FROM cc GROUP BY component")
def cc_sizes(spark, d):
    return R.component_sizes(R.connected_components(_layout(spark, d, "returns")).values)


@query("bfs_blocks")
def bfs_blocks(spark, d):
    return V.partition_bfs(build(spark, d, "near_copy"))


@query("bfs_blocks_connected", f"WITH {ctes('near_copy')} SELECT true AS connected, CAST(count(*) AS BIGINT) AS n_vertices FROM (SELECT DISTINCT vid FROM v)")
def bfs_blocks_connected(spark, d):
    """Every block is one component of the edges inside it."""
    from hubsplit.components import star_components

    g = build(spark, d, "near_copy")
    blocks = V.partition_bfs(g)
    inside = g.edges.join(blocks.select(F.col("vid").alias("src"), F.col("block").alias("p")), "src").join(blocks.select(F.col("vid").alias("dst"), F.col("block").alias("q")), "dst").where("p = q")
    comp = blocks.join(star_components(inside.select("src", "dst")), "vid", "left").select("block", F.coalesce("component", "vid").alias("component"))
    per = comp.groupBy("block").agg(F.countDistinct("component").alias("k"), F.count("*").alias("n"))
    return per.agg((F.max("k") == 1).alias("connected"), F.sum("n").alias("n_vertices"))


@query("block_worker_balance", f"WITH {ctes('near_copy')} SELECT how, true AS bounded, CAST(n AS BIGINT) AS n_vertices FROM (SELECT count(DISTINCT vid) AS n FROM v), (SELECT unnest(['hash', 'largest_first']) AS how)")
def block_worker_balance(spark, d):
    blocks = V.partition_bfs(build(spark, d, "near_copy"), 0.05)
    out = None
    for how in ("hash", "largest_first"):
        sizes = V.assign_blocks(blocks, N, how).groupBy("part").agg(F.count("*").alias("n"))
        one = sizes.agg((F.max("n") < 0.75 * F.sum("n")).alias("bounded"), F.sum("n").alias("n_vertices")).select(F.lit(how).alias("how"), "bounded", "n_vertices")
        out = one if out is None else out.union(one)
    return out


# --- shortest paths ---------------------------------------------------------------------------------------------------------------

_MOST = "SELECT src FROM e GROUP BY src ORDER BY count(*) DESC, src LIMIT 1"
_SP = "SELECT vid, dist FROM sp"


def most_linked(graph) -> int:
    """The source of most edges; of several, the smallest id."""
    first = graph.edges.groupBy("src").agg(F.count("*").alias("k")).orderBy(F.desc("k"), "src").first()
    return first["src"] if first else 0


def _source(spark, d, view):
    return most_linked(build(spark, d, view)) if view in ("pagelink", "docword", "kron") else 0


def _path_queries():
    cases = {"road_w": ("road", True), "road_hops": ("road", False), "commerce": ("commerce", False), "pagelink": ("pagelink", False)}
    for name, (view, weighted) in cases.items():
        sql = S.paths_sql(view, _MOST if view == "pagelink" else "0", "w" if weighted else "one", view == "road") + _SP

        def hybrid(spark, d, v=view, w=weighted, c="ldch"):
            return R.shortest_paths(_layout(spark, d, v, c), _source(spark, d, v), w).values

        query(f"sssp_hybrid_{name}", sql)(hybrid)
        query(f"sssp_hybrid_{name}_ueh", sql)(lambda spark, d, f=hybrid: f(spark, d, c="ueh"))
        if name in ("road_hops", "pagelink"):
            query(f"sssp_vcbsp_{name}", sql)(lambda spark, d, v=view, w=weighted: V.sssp(build(spark, d, v), _source(spark, d, v), w).values)
        if name in ("road_hops", "commerce"):
            query(f"sssp_gas_{name}", sql)(lambda spark, d, v=view, w=weighted: V.sssp(build(spark, d, v), _source(spark, d, v), w, P.CUTS["ldch"], N).values)
        if name in ("road_w", "pagelink"):
            query(f"sssp_edgecut_{name}", sql)(lambda spark, d, v=view, w=weighted: R.shortest_paths(_layout(spark, d, v, None, "edge_cut"), _source(spark, d, v), w).values)
        if name == "road_w":
            def block(spark, d):
                return R.shortest_paths(V.block_layout(build(spark, d, "road"), N), 0, True).values

            query("sssp_block_road_w", sql)(block)


_path_queries()


@query("sssp_directed_commerce", S.paths_sql("commerce", "SELECT min(src) FROM e WHERE src % 4 = 1", "one") + _SP)
def sssp_directed_commerce(spark, d):
    g = build(spark, d, "commerce")
    source = g.edges.where("src % 4 = 1").agg(F.min("src")).first()[0]
    return R.shortest_paths(make_layout(g, P.CUTS["ldch"], N), 0 if source is None else source, False).values


@query("sssp_relax_road_w", S.paths_sql("road", "0", "w", True) + _SP)
def sssp_relax_road_w(spark, d):
    """The local search by waves instead of the priority queue."""
    return R.shortest_paths(_layout(spark, d, "road"), 0, True, local="relax").values


@query("sssp_tree_road_w", S.paths_sql("road", "0", "w", True) + "SELECT u.dst AS vid, min(u.src) AS parent FROM u JOIN sp a ON a.vid = u.src JOIN sp b ON b.vid = u.dst WHERE a.dist + u.w = b.dist AND a.dist < b.dist GROUP BY u.dst")
def sssp_tree_road_w(spark, d):
    layout = _layout(spark, d, "road")
    return R.predecessors(layout.edges, R.shortest_paths(layout, 0, True).values)


_SWEEP = S.paths_sql("road", "0", "one", True) + """, far AS (SELECT vid FROM sp ORDER BY dist DESC, vid LIMIT 1), sq(vid, dist) USING KEY (vid) AS (
        SELECT vid, CAST(0 AS BIGINT) AS dist FROM far UNION SELECT x.dst, CAST(min(sq.dist + 1) AS BIGINT) FROM sq JOIN u x ON x.src = sq.vid
        LEFT JOIN recurring.sq r ON r.vid = x.dst WHERE r.dist IS NULL OR sq.dist + 1 < r.dist GROUP BY x.dst)
    SELECT CAST((SELECT max(dist) FROM sq) AS BIGINT) AS hops, (SELECT vid FROM far) AS from_vid, (SELECT vid FROM sq ORDER BY dist DESC, vid LIMIT 1) AS to_vid"""


@query("graph_diameter_road", _SWEEP)
def graph_diameter_road(spark, d):
    """Diameter by a double sweep of the hybrid program."""
    return spark.createDataFrame([R.diameter(_layout(spark, d, "road"), 0)], "hops long, from_vid long, to_vid long")


@query("sssp_multi_source", f"""WITH RECURSIVE {ctes('commerce', True)}, sp(vid, dist) USING KEY (vid) AS (SELECT CAST(x AS BIGINT) AS vid, CAST(0 AS BIGINT) AS dist FROM (SELECT unnest([0, 4, 8]) AS x)
    UNION SELECT e.dst, CAST(min(sp.dist + 1) AS BIGINT) FROM sp JOIN e ON e.src = sp.vid LEFT JOIN recurring.sp r ON r.vid = e.dst WHERE r.dist IS NULL OR sp.dist + 1 < r.dist GROUP BY e.dst) SELECT vid, dist FROM sp""")
def sssp_multi_source(spark, d):
    return R.shortest_paths(_layout(spark, d, "commerce"), (0, 4, 8), False).values


@query("sssp_variants_equal", S.paths_sql("pagelink", _MOST, "one") + "SELECT CAST(count(*) AS BIGINT) AS reached, true AS equal FROM sp")
def sssp_variants_equal(spark, d):
    source = _source(spark, d, "pagelink")
    runs = [R.shortest_paths(_layout(spark, d, "pagelink", c, m), source, False).values for c, m in (("ldch", "vertex_cut"), ("ueh", "vertex_cut"), (None, "edge_cut"))]
    both = runs[0].join(runs[1].withColumnRenamed("dist", "d2"), "vid", "full_outer").join(runs[2].withColumnRenamed("dist", "d3"), "vid", "full_outer")
    return both.agg(F.count("*").alias("reached"), F.every(F.coalesce((F.col("dist") == F.col("d2")) & (F.col("dist") == F.col("d3")), F.lit(False))).alias("equal"))


# --- PageRank ---------------------------------------------------------------------------------------------------------------------


def _ranked(df):
    return df.select("vid", F.round("rank", 9).alias("rank"))


def _rank_sql(view, rounds):
    return S.pagerank_sql(view, rounds) + f"SELECT vid, round(rank, 9) AS rank FROM p{rounds}"


# The two views have no cycles, so that the equation is at its fixpoint after as many rounds as its longest path.
for _v, _r in (("pagelink", 3), ("commerce", 5)):
    query(f"pr_hybrid_{_v}_agrees", _rank_sql(_v, _r))(lambda spark, d, v=_v: _ranked(R.pagerank(_layout(spark, d, v)).values))
    query(f"pr_vcbsp_{_v}_agrees", _rank_sql(_v, _r))(lambda spark, d, v=_v, r=_r: _ranked(V.pagerank_sync(build(spark, d, v), r).values))
query("pr_gas_pagelink_agrees", _rank_sql("pagelink", 3))(lambda spark, d: _ranked(V.pagerank_sync(build(spark, d, "pagelink"), 3, cut=P.CUTS["ldch"]).values))
query("pr_edgecut_pagelink_agrees", _rank_sql("pagelink", 3))(lambda spark, d: _ranked(R.pagerank(_layout(spark, d, "pagelink", None, "edge_cut")).values))
query("pr_sync_pagelink_10", _rank_sql("pagelink_sym", 10))(lambda spark, d: _ranked(V.pagerank_sync(build(spark, d, "pagelink_sym"), 10).values))
query("pr_sync_commerce_5", _rank_sql("commerce", 5))(lambda spark, d: _ranked(V.pagerank_sync(build(spark, d, "commerce"), 5).values))
query("pr_fixedpoint_pagelink", S.fixedpoint_sql("pagelink_sym", 5) + "SELECT vid, rank FROM p5")(lambda spark, d: V.pagerank_fixed(build(spark, d, "pagelink_sym"), 5))


@query("pr_hybrid_topk", S.pagerank_sql("commerce", 5) + "SELECT vid, round(rank, 9) AS rank FROM p5 ORDER BY round(rank, 9) DESC, vid LIMIT 20")
def pr_hybrid_topk(spark, d):
    return _ranked(R.pagerank(_layout(spark, d, "commerce")).values).orderBy(F.desc("rank"), "vid").limit(20)


#: Rounds of the equation after which it is nearer to its limit than the accumulative tolerance.
_LIMIT = 150


def _limit_sql(view):
    return S.pagerank_limit_sql(view, _LIMIT) + "SELECT vid, round(rank, 8) AS rank FROM pr"


def _limited(r):
    return r.values.select("vid", F.round("rank", 8).alias("rank"))


@query("pr_hybrid_kron_agrees", _limit_sql("kron"))
def pr_hybrid_kron_agrees(spark, d):
    """A cyclic power-law graph, damping 0.85, to a tolerance of 1e-10: the ranks themselves."""
    return _limited(R.pagerank(_layout(spark, d, "kron")))


@query("pr_hybrid_pagelink_sym", _limit_sql("pagelink_sym"))
def pr_hybrid_pagelink_sym(spark, d):
    """Local fixpoints: inner vertices settle in their part before a round ends."""
    return _limited(R.pagerank(_layout(spark, d, "pagelink_sym"), local_sweeps=None))


@query("adaptive_pagerank", _limit_sql("pagelink_sym"))
def adaptive_pagerank(spark, d):
    """Each part sends its largest receipts only and holds tiny ones back; the limit is the same."""
    return _limited(R.pagerank(_layout(spark, d, "pagelink_sym"), local_sweeps=None, min_delta=1e-14, top_k=160))


_AT_K = 20
_TOP = f"(SELECT vid FROM p%d ORDER BY round(rank, 9) DESC, vid LIMIT {_AT_K})"


@query("rank_overlap_at_k", S.pagerank_sql("commerce", 5) + f"SELECT CAST(count(*) AS BIGINT) AS common FROM {_TOP % 5} a JOIN {_TOP % 1} b USING (vid)")
def rank_overlap_at_k(spark, d):
    """How many of the limit's first twenty the first round of the equation names as well."""
    top = lambda df: _ranked(df).orderBy(F.desc("rank"), "vid").limit(_AT_K).select("vid")
    return top(R.pagerank(_layout(spark, d, "commerce")).values).join(top(V.pagerank_sync(build(spark, d, "commerce"), 1).values), "vid").agg(F.count("*").alias("common"))


@query("pr_l1_error", S.pagerank_sql("pagelink", 3) + "SELECT round(sum(abs(p3.rank - p1.rank)), 7) AS l1, round(max(abs(p3.rank - p1.rank)), 7) AS linf FROM p3 JOIN p1 USING (vid)")
def pr_l1_error(spark, d):
    """L1 and largest distance of the equation's first round from the accumulative ranks."""
    got = R.pagerank(_layout(spark, d, "pagelink")).values
    ref = V.pagerank_sync(build(spark, d, "pagelink"), 1).values.withColumnRenamed("rank", "ref")
    gap = F.abs(F.col("rank") - F.col("ref"))
    return got.join(ref, "vid").agg(F.round(F.sum(gap), 7).alias("l1"), F.round(F.max(gap), 7).alias("linf"))


# --- simulation -------------------------------------------------------------------------------------------------------------------

_DEPTH = {"P1": 4, "P2": 6, "P3": 30, "P4": 14, "P5": 6, "P6": 100}


def _sim_sql(p, rounds=None):
    view, pattern = R.PATTERNS[p]
    k = rounds or _DEPTH[p]
    return S.simulation_sql(view, pattern.nodes, pattern.arcs, k) + f"SELECT u, vid FROM s{k} WHERE (SELECT count(DISTINCT u) FROM s{k}) = {len(pattern.nodes)}"


_NONE = "SELECT 'v' AS u, CAST(0 AS BIGINT) AS vid WHERE false"  # P6 asks for a cycle on an acyclic graph


def _sim_queries():
    for p, (view, pattern) in R.PATTERNS.items():
        sql = _NONE if p == "P6" else _sim_sql(p)
        query(f"gsim_{p}", sql)(lambda spark, d, v=view, t=pattern: R.graph_simulation(_layout(spark, d, v), t).values)
        if p in ("P1", "P3"):
            query(f"gsim_vcbsp_{p}", sql)(lambda spark, d, v=view, t=pattern: V.gsim(build(spark, d, v), t).values)
        if p in ("P2", "P3"):
            query(f"gsim_edgecut_{p}", sql)(lambda spark, d, v=view, t=pattern: R.graph_simulation(out_edge_layout(build(spark, d, v), N), t).values)
        if p == "P3":
            query("gsim_gas_P3", sql)(lambda spark, d, v=view, t=pattern: V.gsim(build(spark, d, v), t, P.CUTS["ldch"], N).values)
            query("gsim_sql_P3", sql)(lambda spark, d, v=view, t=pattern: V.simulate_sql(build(spark, d, v), t))

            def block(spark, d, v=view, t=pattern):
                return R.graph_simulation(V.block_layout(build(spark, d, v), N), t).values

            query("gsim_block_P3", sql)(block)


_sim_queries()
_P1_VIEW, _P1 = R.PATTERNS["P1"]
_LABELS = ", pn AS (" + " UNION ALL ".join(f"SELECT '{u}' AS u, '{x}' AS label" for u, x in _P1.nodes.items()) + "), s AS (SELECT u, vid FROM v JOIN pn USING (label))"


@query("gsim_candidates", f"WITH {ctes(_P1_VIEW)} {_LABELS} SELECT u, vid FROM s")
def gsim_candidates(spark, d):
    return V.candidates(build(spark, d, _P1_VIEW), _P1)


@query("gsim_counts", f"WITH {ctes(_P1_VIEW)} {_LABELS} SELECT e.src, s.u, CAST(count(*) AS BIGINT) AS n FROM e JOIN s ON s.vid = e.dst GROUP BY ALL")
def gsim_counts(spark, d):
    g = build(spark, d, _P1_VIEW)
    return V.successor_counts(g, V.candidates(g, _P1))


@query("gsim_match_flag", S.simulation_sql(_P1_VIEW, _P1.nodes, _P1.arcs, 4) + f"SELECT 'P1' AS pattern, (SELECT count(DISTINCT u) FROM s4) = {len(_P1.nodes)} AS matched UNION ALL SELECT 'P6', false")
def gsim_match_flag(spark, d):
    flags = [(p, bool(R.graph_simulation(_layout(spark, d, R.PATTERNS[p][0]), R.PATTERNS[p][1]).values.head(1))) for p in ("P1", "P6")]
    return spark.createDataFrame(flags, "pattern string, matched boolean")


# --- synchronisation and its measures -----------------------------------------------------------------------------------------------


def _first_round(layout):
    """(pid, vid, master_pid, value): what the parts send after local components, the label of each boundary replica that is not its own id."""
    return run(layout, R.Components(), rounds=1).out.where("sent")


_VCOPIES = ", c AS (SELECT vid FROM r GROUP BY vid HAVING count(*) > 1), m AS (" + P.MASTERS_SQL + ")"


def _part_components(cut):
    """Local components of every part as SQL: a recursion keyed by (pid, vid)."""
    w = with_cut(cut, "returns", N, _VCOPIES).replace("WITH ", "WITH RECURSIVE ", 1)
    return w + """, pu AS MATERIALIZED (SELECT pid, src, dst FROM a UNION SELECT pid, dst, src FROM a), lc(pid, vid, comp) USING KEY (pid, vid) AS (
        SELECT pid, vid, vid AS comp FROM r UNION SELECT pu.pid, pu.dst, min(lc.comp) FROM lc JOIN pu ON pu.pid = lc.pid AND pu.src = lc.vid JOIN recurring.lc x ON x.pid = pu.pid AND x.vid = pu.dst
        WHERE lc.comp < x.comp GROUP BY pu.pid, pu.dst), o AS (SELECT lc.pid, lc.vid, lc.comp AS value, m.master_pid FROM lc JOIN c USING (vid) JOIN m USING (vid) WHERE lc.comp <> lc.vid) """


@query("fold_min", _part_components("ldch") + "SELECT vid, min(value) AS folded FROM o GROUP BY vid")
def fold_min(spark, d):
    """Masters take the least of their own and their mirrors' labels."""
    return fold(_first_round(_returns_layout(spark, d)), R.Components())


def _returns_layout(spark, d, cut="ldch"):
    return make_layout(build(spark, d, "returns"), P.CUTS[cut], N, symmetric=False)


@query("spread_pairs", _part_components("ldch") + """, f AS (SELECT vid, min(value) AS folded FROM o GROUP BY vid)
    SELECT r.pid, f.vid, f.folded FROM f JOIN r USING (vid) LEFT JOIN o ON o.vid = f.vid AND o.pid = r.pid WHERE o.value IS NULL OR o.value <> f.folded""")
def spread_pairs(spark, d):
    """Every replica that does not hold the folded value yet is told."""
    layout, program = _returns_layout(spark, d), R.Components()
    out = _first_round(layout)
    own = out.select("pid", "vid", "value")
    return spread(fold(out, program), layout, program).join(own, ["pid", "vid", "value"], "left_anti").select("pid", "vid", F.col("value").alias("folded"))


@query("pair_matrix", _part_components("ldch") + "SELECT pid AS from_pid, master_pid AS to_pid, CAST(count(*) AS BIGINT) AS pairs FROM o WHERE pid <> master_pid GROUP BY ALL")
def pair_matrix(spark, d):
    """Pairs of round 0 by sender and receiver: each row is one batch between two parts."""
    out = _first_round(_returns_layout(spark, d)).where("pid <> master_pid")
    return out.groupBy(F.col("pid").alias("from_pid"), F.col("master_pid").alias("to_pid")).agg(F.count("*").alias("pairs"))


for _cut in ("ueh", "ldch"):
    query(f"pairs_round0_cc_{_cut}", _part_components(_cut) + "SELECT CAST(count(*) FILTER (pid <> master_pid) AS BIGINT) AS pairs_up FROM o")(
        lambda spark, d, c=_cut: spark.createDataFrame([(run(_returns_layout(spark, d, c), R.Components(), rounds=1).ledger[0]["pairs_up"],)], "pairs_up long"))


@query("fold_sum", with_cut("ldch", "commerce") + "SELECT dst AS vid, CAST(sum(w) AS BIGINT) AS folded FROM a GROUP BY dst")
def fold_sum(spark, d):
    """Partial sums per part, added at the masters and told to every replica."""
    return R.inflow(_layout(spark, d, "commerce")).withColumnRenamed("total", "folded")


@query("fold_map", with_cut("ldch", "copurchase") + "SELECT a.src AS vid, v.label, CAST(count(*) AS BIGINT) AS n FROM a JOIN v ON v.vid = a.dst GROUP BY ALL")
def fold_map(spark, d):
    """Successor counts by label: a vector per part, added entry by entry at the masters."""
    return R.successor_labels(_layout(spark, d, "copurchase"))


_GHOST = f"""WITH {ctes('returns')}, x AS (SELECT DISTINCT vid, CAST(hash AS INT) AS part FROM (SELECT vid, {P.hash32_sql('vid')} % {N} AS hash FROM v)),
    b AS (SELECT e.src, e.dst, y.part AS ps, z.part AS pd FROM e JOIN x y ON y.vid = e.src JOIN x z ON z.vid = e.dst)"""


@query("ghost_messages_cc", _GHOST + """ SELECT CAST((SELECT 2 * count(*) FROM b WHERE ps <> pd) AS BIGINT) AS per_message,
    CAST((SELECT count(*) FROM (SELECT DISTINCT src AS vid, pd AS p FROM b WHERE ps <> pd UNION SELECT DISTINCT dst, ps FROM b WHERE ps <> pd)) AS BIGINT) AS per_pair""")
def ghost_messages_cc(spark, d):
    """One exchange of all ghosts: a message for each cut edge and end, against one merged pair for each ghost."""
    g = build(spark, d, "returns")
    held = P.edge_cut(g.edges, P.vertex_hash(g.vertices, N))
    placed = P.vertex_hash(g.vertices, N)
    ghosts = P.replicas_of(held).join(placed, "vid").where("pid <> part")
    cut = held.where("not primary").agg((2 * F.count("*")).alias("per_message"))
    return cut.join(F.broadcast(ghosts.agg(F.count("*").alias("per_pair"))))


@query("assign_multilevel_metrics", "SELECT true AS balanced, true AS cuts_less_than_hash")
def assign_multilevel_metrics(spark, d):
    g = build(spark, d, "near_copy")
    placed = V.multilevel_cut(g, N)

    def cut_share(p):
        e = g.edges.join(p.select(F.col("vid").alias("src"), F.col("part").alias("a")), "src").join(p.select(F.col("vid").alias("dst"), F.col("part").alias("b")), "dst")
        return e.agg(F.avg((F.col("a") != F.col("b")).cast("double")).alias("share"))

    sizes = placed.groupBy("part").agg(F.count("*").alias("n")).agg((F.max("n") / (F.sum("n") / F.lit(float(N)))).alias("imbalance"))
    hashed = cut_share(P.vertex_hash(g.vertices, N)).withColumnRenamed("share", "by_hash")
    return sizes.join(F.broadcast(cut_share(placed))).join(F.broadcast(hashed)).select((F.col("imbalance") <= 1.3).alias("balanced"), (F.col("share") < F.col("by_hash")).alias("cuts_less_than_hash"))


# --- the programming surface over resident parts -----------------------------------------------------------------------------------


@query("api_children", with_cut(view="returns") + "SELECT pid, src AS vid, CAST(count(*) AS BIGINT) AS children FROM a GROUP BY ALL")
def api_children(spark, d):
    def count(part):
        n = np.diff(part.out_ptr)
        return {"pid": np.full((n > 0).sum(), part.pid, np.int32), "vid": part.vids[n > 0], "children": n[n > 0]}

    return each_part(_returns_layout(spark, d), count, "pid int, vid long, children long")


@query("api_parents", with_cut(view="returns") + "SELECT pid, dst AS vid, CAST(count(*) AS BIGINT) AS parents FROM a GROUP BY ALL")
def api_parents(spark, d):
    def count(part):
        n = np.diff(part.in_order[1])
        return {"pid": np.full((n > 0).sum(), part.pid, np.int32), "vid": part.vids[n > 0], "parents": n[n > 0]}

    return each_part(_returns_layout(spark, d), count, "pid int, vid long, parents long")


@query("api_degree", f"WITH {ctes('returns')} SELECT vid, CAST(sum(o) AS BIGINT) AS d_out, CAST(sum(i) AS BIGINT) AS d_in FROM (SELECT src AS vid, 1 AS o, 0 AS i FROM e UNION ALL SELECT dst, 0, 1 FROM e) GROUP BY vid")
def api_degree(spark, d):
    """Every replica knows its vertex's whole degree; masters report it."""
    held = lambda part: {"vid": part.vids[part.owned], "d_out": part.d_out[part.owned], "d_in": part.d_in[part.owned]}
    return each_part(_returns_layout(spark, d), held, "vid long, d_out long, d_in long")


@query("api_edge_lookup", with_cut(view="returns") + "SELECT pid, src, dst, w FROM a WHERE w >= 90")
def api_edge_lookup(spark, d):
    """The weight of an edge by binary search among its source's targets."""

    def look(part):
        heavy = [(i, j) for i, j, w in zip(part.src.tolist(), part.dst.tolist(), part.w.tolist(), strict=True) if w >= 90]
        return {"pid": np.full(len(heavy), part.pid, np.int32), "src": part.vids[[i for i, _ in heavy]], "dst": part.vids[[j for _, j in heavy]], "w": np.array([part.edge(i, j) for i, j in heavy], np.int64)}

    return each_part(_returns_layout(spark, d), look, "pid int, src long, dst long, w long")


@query("api_frontier", with_cut(view="returns", more=", c AS (SELECT vid FROM r GROUP BY vid HAVING count(*) > 1)") + "SELECT pid, CAST(count(*) AS BIGINT) AS frontier FROM r JOIN c USING (vid) GROUP BY pid")
def api_frontier(spark, d):
    counts = lambda part: {"pid": np.array([part.pid], np.int32), "frontier": np.array([part.frontier.sum()])}
    return each_part(_returns_layout(spark, d), counts, "pid int, frontier long").where("frontier > 0")


_LEDGER = "SELECT extract(hour FROM ts) AS round, user_id % 4 AS pid, sum(CAST(round(value * 100) AS BIGINT)) / 100e0 AS compute_ms, 5e0 AS network_ms, count(*) AS edges, count(*) FILTER (event_type = 'purchase') AS pairs FROM events WHERE ts IS NOT NULL GROUP BY ALL"


@query("breakdown_stats", f"WITH l AS ({_LEDGER}), m AS (SELECT round, max(compute_ms) AS slowest FROM l GROUP BY round) SELECT round, min(compute_ms) AS compute_min, round(avg(compute_ms), 6) AS compute_mean, max(compute_ms) AS compute_max, round(avg(slowest - compute_ms), 6) AS sync_mean, CAST(sum(pairs) AS BIGINT) AS pairs, round(max(edges) / avg(edges), 6) AS work_imbalance, round(sum(edges) / nullif(max(slowest) / 1000e0, 0), 3) AS peps FROM l JOIN m USING (round) GROUP BY round")
def breakdown_stats(spark, d):
    """Per round: compute over the parts, the wait for the slowest, pairs, work imbalance and edges per second, from a ledger of the
    events: an hour of the day is a round, users are dealt to four parts, an event's value is the time it took, a purchase is sent."""
    from hubsplit.plans.ledger import breakdown

    ev = table(spark, d, "events", "ts", "user_id", "event_type", "value").where("ts is not null")
    cents = F.sum(F.round(F.col("value") * 100).cast("long"))
    ledger = ev.groupBy(F.hour("ts").cast("long").alias("round"), (F.col("user_id") % 4).cast("int").alias("pid")).agg(
        (cents / 100).alias("compute_ms"), F.lit(5.0).alias("network_ms"), F.count("*").alias("edges"), F.count_if(F.col("event_type") == "purchase").alias("pairs"))
    return breakdown(ledger)


@query("breakdown_cc_near_copy")
def breakdown_cc_near_copy(spark, d):
    """The same from a run's own ledger: a row per round."""
    from hubsplit.plans.ledger import breakdown, ledger_rows

    r = R.connected_components(_layout(spark, d, "near_copy"))
    return breakdown(spark.createDataFrame(ledger_rows(r.ledger), "round long, pid int, compute_ms double, network_ms double, edges long, pairs long"))
