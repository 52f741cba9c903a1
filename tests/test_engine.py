"""Programs on tiny and random graphs: all contenders agree with the sequential references; worked examples; failure cases."""

import random

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from hubsplit import sequential
from hubsplit.components import star_components
from hubsplit.plans import ledger, metrics, programs, rivals, runtime
from hubsplit.plans import partition as P
from hubsplit.plans.runtime import make_layout, open_layout, run
from hubsplit.sources.graphs import Graph


def graph(spark, edges, directed=True, labels=None, more=()):
    rows = [(s, d, w) for s, d, *r in edges for w in [r[0] if r else 1]]
    vids = sorted({x for s, d, _ in rows for x in (s, d)} | set(more))
    e = spark.createDataFrame(rows, "src long, dst long, w long")
    return Graph(e, spark.createDataFrame([(v, (labels or {}).get(v, "x")) for v in vids], "vid long, label string"), directed), vids


def pairs(df, a, b):
    return {r[a]: r[b] for r in df.collect()}


@pytest.fixture(scope="module")
def mixed(spark):
    rng = random.Random(7)
    edges = {(rng.randrange(60), min(59, int(rng.paretovariate(0.8)))) for _ in range(150)}
    edges = sorted((s, d) for s, d in edges if s != d)
    weighted = [(s, d, 1 + (s * 7 + d) % 5) for s, d in edges]
    labels = {v: "abc"[v % 3] for v in range(60)}
    return graph(spark, weighted, labels=labels, more=range(55, 64)), weighted, labels


@pytest.mark.parametrize("n", [1, 3])
def test_components_agree(spark, mixed, n):
    (g, vids), edges, _ = mixed
    want = sequential.cc(vids, [(s, d) for s, d, _ in edges])
    for cut in ("ldch", "ueh"):
        r = programs.connected_components(make_layout(g, P.CUTS[cut], n))
        assert pairs(r.values, "vid", "component") == want
    assert pairs(programs.connected_components(make_layout(g, None, n, "edge_cut")).values, "vid", "component") == want
    if n == 3:
        assert pairs(rivals.cc(g).values, "vid", "component") == want
        assert pairs(rivals.cc(g, P.CUTS["ldch"], n).values, "vid", "component") == want
        assert pairs(rivals.block_cc(g, rivals.partition_bfs(g, 0.2)), "vid", "component") == want


@pytest.mark.parametrize("local", ["unionfind", "bfs", "dfs"])
def test_local_searches(local):
    import numpy as np

    src, dst = np.array([0, 4, 5, 2]), np.array([3, 5, 6, 0])
    assert programs.local_labels(8, src, dst, local).tolist() == [0, 1, 0, 0, 4, 4, 4, 7]


def test_paths_agree(spark, mixed):
    (g, _), edges, _ = mixed
    want = sequential.sssp(edges, 3)
    for cut, local in (("ldch", "relax"), ("ueh", "heap")):
        assert pairs(programs.shortest_paths(make_layout(g, P.CUTS[cut], 3), 3, True, local).values, "vid", "dist") == want
    assert pairs(programs.shortest_paths(make_layout(g, None, 3, "edge_cut"), 3).values, "vid", "dist") == want
    assert pairs(rivals.sssp(g, 3).values, "vid", "dist") == want


def test_pagerank_agrees(spark, mixed):
    (g, vids), edges, _ = mixed
    want = sequential.pagerank(vids, [(s, d) for s, d, _ in edges], damping=0.5)
    for layout in (make_layout(g, P.CUTS["ldch"], 3), make_layout(g, None, 3, "edge_cut")):
        for sweeps in (1, None):
            got = pairs(programs.pagerank(layout, 0.5, 1e-4, sweeps).values, "vid", "rank")
            assert set(got) == set(want) and sum(abs(got[v] - want[v]) for v in want) <= 1e-4


def test_simulation_agrees(spark, mixed):
    (g, _), edges, labels = mixed
    for nodes, arcs in (({"u": "a", "v": "b"}, [("u", "v"), ("v", "u")]), ({"u": "a", "v": "b", "x": "c"}, [("u", "v"), ("v", "x")]), ({"u": "a", "v": "z"}, [("u", "v")])):
        pattern = programs.Pattern(nodes, arcs)
        want = {(u, v) for u, vs in sequential.gsim(labels | {v: "x" for v in range(60, 64)}, [(s, d) for s, d, _ in edges], nodes, arcs).items() for v in vs}
        got = [programs.graph_simulation(make_layout(g, P.CUTS["ldch"], 3), pattern).values, programs.graph_simulation(make_layout(g, None, 3, "edge_cut"), pattern).values, rivals.gsim(g, pattern).values, rivals.simulate_sql(g, pattern)]
        assert [{(r["u"], r["vid"]) for r in x.collect()} for x in got] == [want] * 4


def test_hub_toy(spark):
    """A star with its hub split holds one replicated vertex; the edge-cut copies four vertices and three edges."""
    g, _ = graph(spark, [(0, k) for k in range(1, 6)])
    placed = spark.createDataFrame([(0, 0), (1, 0), (3, 0), (2, 1), (4, 1), (5, 1)], "vid long, part int")
    m = metrics.edge_cut_metrics(g.edges, placed, 2).first()
    assert (m["cut_edges"], m["ghosts"], m["duplicated_edges"]) == (3, 4, 3)
    a = g.edges.withColumn("pid", F.when(F.col("dst").isin(1, 3), 0).otherwise(1))
    assert P.mark_frontier(P.replicas_of(a)).where("is_frontier").select("vid").distinct().count() == 1


class FixedCut(P.VertexCut):
    def __init__(self, where):
        self.where = where

    def assign(self, edges, n):
        col = None
        for (s, d), p in self.where.items():
            hit = (F.least("src", "dst") == min(s, d)) & (F.greatest("src", "dst") == max(s, d))
            col = F.when(hit, p) if col is None else col.when(hit, p)
        return edges.withColumn("pid", col.cast("int"))


def test_seven_vertices_in_three_parts(spark):
    """Local labels meet at the two hubs in round 0 and reach all parts in the next."""
    A, B, C, D, E, FF, G = range(7)
    where = {(A, D): 0, (A, G): 0, (B, D): 1, (B, G): 1, (D, E): 1, (C, G): 2, (C, FF): 2, (FF, G): 2}
    g, _ = graph(spark, list(where), directed=False)
    r = programs.connected_components(make_layout(g, FixedCut(where), 3, symmetric=False))
    assert set(pairs(r.values, "vid", "component").values()) == {A}
    assert r.rounds <= 3 and r.ledger[0]["pairs_up"] > 0 and r.ledger[-1]["pairs_up"] == 0


def test_two_way_arcs_share_a_part(spark):
    g, _ = graph(spark, [x for k in range(100) for x in ((k, 1000 + k), (1000 + k, k))])
    a = {(r["src"], r["dst"]): r["pid"] for r in P.CUTS["ldch"].assign(g.edges, 8).collect()}
    assert all(a[s, d] == a[d, s] for s, d in a)
    assert len(set(a.values())) == 8


def test_every_cut_is_disjoint_and_replicas_have_one_master(spark, mixed):
    (g, _), edges, _ = mixed
    for cut in [*P.CUTS.values(), P.SpillingLowDegreeHash(slack=1.0)]:
        a = cut.assign(g.edges, 4)
        assert a.count() == len(edges) == a.select("src", "dst").distinct().count()
        assert a.where("pid < 0 or pid >= 4").count() == 0
        routing = P.build_routing(P.replicas_of(a))
        assert routing.groupBy("vid").agg(F.countDistinct("master_pid").alias("m"), F.count_if(F.col("pid") == F.col("master_pid")).alias("own")).where("m <> 1 or own <> 1").count() == 0
    grid = P.replicas_of(P.GridHash().assign(g.edges, 4)).groupBy("vid").count().agg(F.max("count")).first()[0]
    assert grid <= 3


def test_pair_bound_and_expected_copies(spark, mixed):
    (g, _), _, _ = mixed
    layout = make_layout(g, P.CUTS["ueh"], 4)
    rf = layout.replicas.count()
    v = layout.replicas.select("vid").distinct().count()
    r = programs.connected_components(layout)
    assert all(x["pairs_up"] + x["pairs_down"] <= 2 * (rf - v) for x in r.ledger)
    gain = metrics.expected_gain(P.degrees(g.edges), [2, 4, 8]).collect()
    assert all(x["gain"] >= 0 and x["vertex_cut"] <= x["edge_cut"] for x in gain)


def test_odd_graphs(spark):
    empty, _ = graph(spark, [])
    assert programs.connected_components(make_layout(empty, P.CUTS["ldch"], 2)).values.count() == 0
    single, _ = graph(spark, [(5, 5)], more=[9])
    assert pairs(programs.connected_components(make_layout(single, P.CUTS["ldch"], 3)).values, "vid", "component") == {5: 5, 9: 9}
    far, _ = graph(spark, [(0, 1), (2, 3)])
    assert pairs(programs.shortest_paths(make_layout(far, P.CUTS["ldch"], 7), 0).values, "vid", "dist") == {0: 0, 1: 1}
    bad, _ = graph(spark, [(0, 1, -2)])
    with pytest.raises(ValueError):
        programs.shortest_paths(make_layout(bad, P.CUTS["ldch"], 2), 0)
    with pytest.raises(ValueError):
        make_layout(far, P.CUTS["ldch"], 1, max_edges_per_part=1)
    with pytest.raises(ValueError):
        rivals.multilevel_cut(far, 2, cap_edges=1)
    chain, _ = graph(spark, [(k, k + 1) for k in range(12)])
    with pytest.raises(RuntimeError):
        run(make_layout(chain, P.CUTS["ueh"], 4), programs.ShortestPaths((0,)), max_rounds=1)


def test_resume_from_a_stored_round(spark):
    """Another driver opens the layout's folder and a run's manifest, and goes on with the rounds that are left."""
    chain, _ = graph(spark, [(k, k + 1) for k in range(12)])
    layout = make_layout(chain, P.CUTS["ueh"], 4)
    folder = layout.save()
    whole = programs.shortest_paths(layout, 0, snapshots="first")
    assert whole.rounds > 3
    again = programs.shortest_paths(open_layout(spark, folder), 0, snapshots="first", resume_from=1)
    assert pairs(again.values, "vid", "dist") == pairs(whole.values, "vid", "dist") == {k: k for k in range(13)}
    assert [x["pairs_up"] for x in again.ledger] == [x["pairs_up"] for x in whole.ledger] and again.rounds == whole.rounds


def same(key: tuple, t: pa.Table) -> pa.Table:
    return t


def test_sleeping_parts_are_neither_read_nor_moved_nor_written(spark):
    """Only parts that are told something leave a new state, and a round's plan reads inbox and routes alone."""
    chain, _ = graph(spark, [(k, k + 1) for k in range(40)])
    where = {(k, k + 1): k // 10 for k in range(40)}
    layout = make_layout(chain, FixedCut(where), 4)
    r = programs.shortest_paths(layout, 0)
    assert [[p[0] for p in x["parts"]] for x in r.ledger] == [[0], [0, 1], [1, 2], [2, 3], [3]] or [x["active"] for x in r.ledger][0] == 1
    assert all(x["active"] <= 2 for x in r.ledger) and sum(x["edges_visited"] for x in r.ledger) == 40
    program = programs.ShortestPaths((0,))
    out = spark.createDataFrame([(0, 10, 1, 5)], "pid int, vid long, master_pid int, value long")
    told = runtime.spread(runtime.fold(out, program), layout, program)
    plan = told.repartitionById(4, F.col("pid")).groupBy("pid").applyInArrow(same, told.schema)._jdf.queryExecution().executedPlan().toString()
    below = plan.split("InMemoryTableScan")[0]
    assert "InMemoryTableScan" in plan and "FileScan" not in below and below.count("REPARTITION_BY_NUM") == 1
    assert "ENSURE_REQUIREMENTS" not in plan.split("FlatMapGroupsInArrow")[1].split("REPARTITION_BY_NUM")[0]  # groups use the placement as it is


def test_routes_stay_where_a_fold_leaves_its_rows(spark, mixed):
    (g, _), _, _ = mixed
    layout = make_layout(g, P.CUTS["ldch"], 3)
    program = programs.Components()
    out = spark.range(1000).selectExpr("cast(id % 3 AS int) AS pid", "id AS vid", "0 AS master_pid", "id AS value")
    old = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        plan = runtime.spread(runtime.fold(out, program), layout, program)._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", old)
    assert plan.split("InMemoryRelation")[0].count("Exchange") == 1  # the fold's own


def test_halting_and_waking(spark):
    """A part halts when nothing is pending and runs again when told; with nothing on its way the run ends."""
    g, _ = graph(spark, [(0, 1), (1, 2), (2, 3), (3, 4)])
    where = {(0, 1): 0, (1, 2): 1, (2, 3): 0, (3, 4): 1}
    r = programs.shortest_paths(make_layout(g, FixedCut(where), 3), 0)
    ran = [[p[0] for p in x["parts"]] for x in r.ledger]
    assert 2 not in {p for x in ran for p in x}  # an empty part never wakes
    assert sum(0 in x for x in ran) >= 2 and sum(1 in x for x in ran) >= 2
    assert r.ledger[-1]["pairs_up"] == 0


def test_programming_surface(spark):
    g, _ = graph(spark, [(0, 1, 5), (0, 2, 6), (1, 2, 7), (2, 0, 8)])

    def look(part):
        v = part.vids
        rows = [(int(v[i]), [int(v[x]) for x in part.children(i)], [int(v[x]) for x in part.parents(i)], part.degree(i)) for i in range(len(v))]
        i, j = part.index_of(np.array([1, 2]))
        return {"vid": [r[0] for r in rows], "children": [r[1] for r in rows], "parents": [r[2] for r in rows], "degree": [list(r[3]) for r in rows], "w12": [part.edge(i, j)] * 3, "w21": pa.array([part.edge(j, i)] * 3, pa.int64())}

    rows = runtime.each_part(make_layout(g, P.CUTS["ldch"], 1), look, "vid long, children array<long>, parents array<long>, degree array<long>, w12 long, w21 long").collect()
    assert sorted(map(tuple, rows)) == [(0, [1, 2], [2], [2, 1], 7, None), (1, [2], [0], [1, 1], 7, None), (2, [0], [0, 1], [1, 2], 7, None)]


def test_all_replicas_are_treated_alike(spark, mixed):
    """After a run every replica holds its master's value: nothing tells a master from a mirror but who folds."""
    (g, _), _, _ = mixed
    layout = make_layout(g, P.CUTS["ldch"], 3)
    r = run(layout, programs.Components())
    held = runtime.part_values(layout, programs.Components(), r.states, lambda part, s: {"vid": part.vids, "label": s["low"][s["root"]]}, "vid long, label long")
    assert held.groupBy("vid").agg(F.countDistinct("label").alias("k")).where("k > 1").count() == 0


def test_star_components(spark):
    rng = random.Random(3)
    edges = [(rng.randrange(300), rng.randrange(300)) for _ in range(180)] + [(1000 + k, 1001 + k) for k in range(70)]
    got = pairs(star_components(spark.createDataFrame(edges, "src long, dst long")), "vid", "component")
    want = sequential.cc({x for e in edges for x in e}, edges)
    assert got == {v: want[v] for s, d in edges if s != d for v in (s, d)}
    assert star_components(spark.createDataFrame([], "src long, dst long")).count() == 0


def test_ledger_arithmetic(spark):
    rows = [(r, p, 10.0 * (p + 1), 1.0, 100, 2) for r in range(4) for p in range(3)]
    out = ledger.breakdown(spark.createDataFrame(rows, "round long, pid int, compute_ms double, network_ms double, edges long, pairs long")).collect()
    assert all((x["compute_min"], x["compute_mean"], x["compute_max"], x["sync_mean"], x["pairs"], x["work_imbalance"], x["peps"]) == (10, 20, 30, 10, 6, 1, 10_000) for x in out)
    assert ledger.peps(100, 2, 5) == (50, 10)
    assert ledger.ratios([{"contender": "a", "run_s": 2, "pairs": 4, "rounds": 0}, {"contender": "b", "run_s": 4, "pairs": 2, "rounds": 3}], "a")[1] == {"contender": "b", "run_s": 2, "pairs": 0.5, "rounds": None}


def test_parts_follow_workers():
    assert P.choose_parts(100, 4) == 4
    assert P.choose_parts(10**9, 4, 64_000_000) == 16


def test_hash_parity(spark):
    from hubsplit.functions.hashing import hash32, hash32_py

    r = spark.range(5).select("id", hash32("id", F.lit(7)).alias("h")).collect()
    assert all(x["h"] == hash32_py(x["id"], 7) for x in r)


def test_state_of_every_round_of_the_walk_through(spark):
    """Seven vertices in three parts: hubs D and G learn A in round 0's fold, and the other two parts relabel in round 1."""
    A, B, C, D, E, FF, G = range(7)
    where = {(A, D): 0, (A, G): 0, (B, D): 1, (B, G): 1, (D, E): 1, (C, G): 2, (C, FF): 2, (FF, G): 2}
    g, _ = graph(spark, list(where), directed=False)
    layout = make_layout(g, FixedCut(where), 3, symmetric=False)
    held = []
    for rounds in (1, 2):
        program = programs.Components()
        r = run(layout, program, rounds=rounds)
        rows = runtime.part_values(layout, program, r.states, lambda part, s: {"pid": np.full(len(part.vids), part.pid, np.int32), "vid": part.vids, "label": s["low"][s["root"]]}, "pid int, vid long, label long").collect()
        held.append({(x["pid"], x["vid"]): x["label"] for x in rows})
    first = {(0, A): A, (0, D): A, (0, G): A, (1, B): B, (1, D): B, (1, E): B, (1, G): B, (2, C): C, (2, FF): C, (2, G): C}
    assert held[0] == first and held[1] == dict.fromkeys(first, A)
    out = run(layout, programs.Components(), rounds=1).out.where("sent")
    assert pairs(runtime.fold(out, programs.Components()), "vid", "folded") == {D: A, G: A}


def test_no_shuffle_meets_the_edges_of_a_hub(spark, monkeypatch):
    """A hub with a third of all edges decides them by broadcast; only the rest is joined by key. The rule is the plain one."""
    monkeypatch.setattr(P, "HUB_FLOOR", 20)
    rng = random.Random(1)
    edges = sorted({(0, k) for k in range(1, 101)} | {(200 + rng.randrange(150), 400 + rng.randrange(150)) for _ in range(200)} | {(k, 200 + k) for k in range(1, 30)})
    g, _ = graph(spark, edges)
    degree = {}
    for e in edges:
        for v in e:
            degree[v] = degree.get(v, 0) + 1
    for canonical in (True, False):
        got = {(r["src"], r["dst"]): r["owner"] for r in P.LowDegreeHash(canonical=canonical).owner_end(g.edges).collect()}
        want = {}
        for s, d in edges:
            a, b = (min(s, d), max(s, d)) if canonical else (s, d)
            want[s, d] = a if degree[a] <= degree[b] else b
        assert got == want
    old = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        df = P.LowDegreeHash().owner_end(g.edges)
        plan = df._jdf.queryExecution().executedPlan().toString()
        df.collect()
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", old)
    hub_side, rest = plan.split("SortMergeJoin", 1)
    assert "BroadcastHashJoin" in hub_side and "Exchange hashpartitioning" not in hub_side
    assert "isnull" in rest.lower()  # only edges without a hub reach the exchange


def test_blocks_by_several_passes(spark):
    """Every vertex is in one connected block, with one pass or many, and a block's name is one of its vertices."""
    rng = random.Random(4)
    edges = sorted({(a, b) for a, b in ((rng.randrange(80), rng.randrange(80)) for _ in range(110)) if a != b})
    g, vids = graph(spark, edges, directed=False, more=range(80, 84))
    for passes in (1, 3):
        block = pairs(rivals.partition_bfs(g, 0.05, max_passes=passes), "vid", "block")
        assert set(block) == set(vids) and all(block[b] == b for b in block.values())
        inner = sequential.cc(vids, [(s, d) for s, d in edges if block[s] == block[d]])
        assert all(len({inner[v] for v in vids if block[v] == b}) == 1 for b in set(block.values()))


def test_blocks_to_workers(spark):
    blocks = spark.createDataFrame([(v, v % 7 if v < 70 else 100 + v % 3) for v in range(130)], "vid long, block long")
    for how in ("hash", "largest_first"):
        part = pairs(rivals.assign_blocks(blocks, 3, how), "vid", "part")
        assert len(part) == 130 and set(part.values()) <= {0, 1, 2}
        assert all(len({part[v] for v in part if (v % 7 if v < 70 else 100 + v % 3) == b}) == 1 for b in (0, 3, 100, 102))
    sizes = [sum(p == k for p in part.values()) for k in range(3)]
    assert max(sizes) - min(sizes) <= 20


def test_block_programs_agree(spark, mixed):
    """Blocks as units of their own give the same answers as the sequential programs."""
    (g, vids), edges, labels = mixed
    layout = rivals.block_layout(g, 2, 3)
    assert layout.n >= 3
    assert pairs(programs.shortest_paths(layout, 3).values, "vid", "dist") == sequential.sssp(edges, 3)
    pattern = programs.Pattern({"u": "a", "v": "b"}, [("u", "v"), ("v", "u")])
    want = {(u, v) for u, vs in sequential.gsim(labels | {v: "x" for v in range(60, 64)}, [(s, d) for s, d, _ in edges], pattern.nodes, pattern.arcs).items() for v in vs}
    assert {(r["u"], r["vid"]) for r in programs.graph_simulation(layout, pattern).values.collect()} == want


def test_pagerank_with_few_messages_a_round(spark, mixed):
    """The largest receipts alone travel, and the limit is the same; rounds rise and pairs a round fall."""
    (g, vids), edges, _ = mixed
    want = sequential.pagerank(vids, [(s, d) for s, d, _ in edges], damping=0.5)
    layout = make_layout(g, P.CUTS["ldch"], 3)
    whole, few = (programs.pagerank(layout, 0.5, 1e-4, None, top_k=k) for k in (None, 4))
    for r in (whole, few):
        got = pairs(r.values, "vid", "rank")
        assert sum(abs(got[v] - want[v]) for v in want) <= 2e-4
    assert few.rounds > whole.rounds and max(x["pairs_up"] for x in few.ledger) <= 12


def test_diameter_and_tree(spark):
    g, _ = graph(spark, [(k, k + 1, 2) for k in range(9)] + [(4, 20, 1), (20, 5, 1)], directed=False)
    layout = make_layout(g, P.CUTS["ldch"], 2)
    assert programs.diameter(layout, 4)[0] == 9
    dist = programs.shortest_paths(layout, 0).values
    assert pairs(programs.predecessors(layout.edges, dist), "vid", "parent") == {1: 0, 2: 1, 3: 2, 4: 3, 20: 4, 5: 4, 6: 5, 7: 6, 8: 7, 9: 8}


def test_long_chains_have_no_round_limit(spark):
    """More rounds than any default would allow per part, all of them counted."""
    n = 60
    chain, _ = graph(spark, [(k, k + 1) for k in range(n)])
    r = programs.shortest_paths(make_layout(chain, FixedCut({(k, k + 1): k % 2 for k in range(n)}), 2), 0)
    assert pairs(r.values, "vid", "dist") == {k: k for k in range(n + 1)} and r.rounds >= n


def test_multilevel_balances_vertices_and_edges(spark):
    rng = random.Random(2)
    edges = sorted({(10 * (k % 8) + rng.randrange(10), 10 * (k % 8) + rng.randrange(10)) for k in range(400)} | {(k, k + 1) for k in range(79)})
    g, vids = graph(spark, [e for e in edges if e[0] != e[1]], directed=False)
    part = pairs(rivals.multilevel_cut(g, 2), "vid", "part")
    assert set(part) == set(vids)
    ends = [sum((part[s] == p) + (part[d] == p) for s, d in edges if s != d) for p in (0, 1)]
    assert max(ends) <= 0.65 * sum(ends) and abs(sum(part.values()) - 40) <= 12
    with pytest.raises(ValueError):
        rivals.multilevel_cut(g, 2, levels=0, coarse_limit=3)


def test_experiment_rows(spark, tmp_path):
    """A row of every kind of contender on a toy folder, with ratios over the first."""
    from hubsplit import experiments

    d = "/root/testdata/sf0.001"
    rows = experiments.with_ratios([experiments.contend(spark, d, "cc", "pagelink", c, 2) for c in ("hybrid-ldch", "twin-multilevel", "vc-bsp", "block")])
    assert [r["contender"] for r in rows] == ["hybrid-ldch", "twin-multilevel", "vc-bsp", "block"]
    assert rows[0]["ratios"]["run_s"] == 1.0 and rows[2]["ratios"]["published_s"] == 2.4
    assert len(rows[0]["trace"]) == rows[0]["rounds"] and rows[0]["pairs"] == sum(x + y for x, y, _ in rows[0]["trace"])
    assert {"compute_mean_s", "network_s", "sync_s", "work_imbalance", "peps", "copies", "imbalance"} <= set(rows[0])
    assert experiments.statistics(spark, d, ("pagelink",))[0]["diameter_at_least"] > 0


def test_shared_folder_has_a_scheme(spark):
    from hubsplit.shared_dir import _qualified, fresh_path

    assert fresh_path(spark, "x").startswith("file:///")
    assert _qualified(spark, "/tmp/a") == _qualified(spark, "file:///tmp/a/") == "file:///tmp/a"
