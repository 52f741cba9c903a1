"""The rivals: vertex-centric message passing, gather/apply/scatter over a vertex-cut, block-centric, and a multilevel edge-cut.

All are DataFrame rounds over staged tables; messages are joined along edges and combined by pre-aggregated minima and sums.
"""

from __future__ import annotations

import time
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hubsplit.components import star_components
from hubsplit.functions.hashing import hash32
from hubsplit.plans import partition as P
from hubsplit.plans.programs import Pattern
from hubsplit.shared_dir import drop_path, staged, staged_path
from hubsplit.sources.graphs import Graph


@dataclass
class Rounds:
    values: DataFrame
    rounds: int
    messages: int
    seconds: float


def _arcs(graph: Graph, cut: P.VertexCut | None, n: int, symmetric: bool) -> DataFrame:
    """Arcs to send along; with a cut they carry the part that holds them (the GAS form)."""
    e = graph.symmetric() if symmetric else graph.edges
    e = e.select("src", "dst", F.col("w").cast("long").alias("w"))
    return staged(cut.assign(e, n) if cut else e.withColumn("pid", F.lit(0)), "arcs")


def _combine(messages: DataFrame, gas: bool, how) -> DataFrame:
    """One value per target: by part first and then at the master (GAS), or straight (BSP); Spark pre-aggregates both."""
    if gas:
        messages = messages.groupBy("pid", "dst").agg(how("m").alias("m"))
    return messages.groupBy("dst").agg(how("m").alias("m"))


def min_propagation(graph: Graph, start: DataFrame, step, symmetric: bool, cut: P.VertexCut | None = None, n: int = 4, max_rounds: int | None = None) -> Rounds:
    """Values (vid, val) that only fall: each round the vertices that fell send ``step`` of their value along their arcs."""
    began = time.time()
    arcs = _arcs(graph, cut, n, symmetric)
    now = staged(start.select("vid", F.col("val").cast("long").alias("val"), F.lit(True).alias("fell")), "values")
    rounds = messages = 0
    while True:
        if max_rounds is not None and rounds >= max_rounds:
            raise RuntimeError(f"not settled after {max_rounds} rounds")
        sent = now.where("fell").join(arcs, now["vid"] == arcs["src"]).select("pid", "dst", step(F.col("val"), F.col("w")).alias("m"))
        best = _combine(sent, cut is not None, F.min)
        met = now.join(best, now["vid"] == best["dst"], "full_outer")
        fell = F.col("m").isNotNull() & (F.col("val").isNull() | (F.col("m") < F.col("val")))
        after = staged(met.select(F.coalesce("vid", "dst").alias("vid"), F.when(fell, F.col("m")).otherwise(F.col("val")).alias("val"), fell.alias("fell")), "values")
        degree = arcs.groupBy(F.col("src").alias("vid")).agg(F.count("*").alias("k")) if rounds == 0 else degree  # noqa: F821
        if rounds == 0:
            degree = staged(degree, "out-degrees")
        fallen = after.where("fell").select("vid").join(degree, "vid", "left").agg(F.count("*").alias("n"), F.sum("k").alias("k")).first()
        rounds += 1
        drop_path(now.sparkSession, staged_path(now))
        now = after
        if not fallen["n"]:
            break
        messages += fallen["k"] or 0
    return Rounds(now.select("vid", "val"), rounds, messages, time.time() - began)


def cc(graph: Graph, cut: P.VertexCut | None = None, n: int = 4) -> Rounds:
    r = min_propagation(graph, graph.vertices.select("vid", F.col("vid").alias("val")).distinct(), lambda v, w: v, True, cut, n)
    r.values = r.values.withColumnRenamed("val", "component")
    return r


def sssp(graph: Graph, source: int, weighted: bool = True, cut: P.VertexCut | None = None, n: int = 4) -> Rounds:
    start = graph.vertices.where(F.col("vid") == source).select("vid", F.lit(0).alias("val")).distinct()
    r = min_propagation(graph, start, lambda v, w: v + (w if weighted else F.lit(1)), not graph.directed, cut, n)
    r.values = r.values.withColumnRenamed("val", "dist")
    return r


def pagerank_sync(graph: Graph, rounds: int | None, damping: float = 0.85, cut: P.VertexCut | None = None, n: int = 4, until: float = 1e-6) -> Rounds:
    """The equation, round by round; weight that reaches a vertex without out-edges is dropped. Without ``rounds``, until the ranks
    are within ``until`` of their limit in sum."""
    began = time.time()
    arcs = _arcs(graph, cut, n, False)
    out = arcs.groupBy("src").agg(F.count("*").alias("d"))
    arcs = staged(arcs.join(out, "src"), "arcs")
    vertices = staged(graph.vertices.select("vid").distinct(), "vertices")
    count = vertices.count()
    now = vertices.select("vid", F.lit(1.0 / count).alias("rank"), F.lit(0.0).alias("moved"))
    done = 0
    while done != rounds:
        sent = now.join(arcs, now["vid"] == arcs["src"]).select("pid", "dst", (F.col("rank") / F.col("d")).alias("m"))
        got = _combine(sent, cut is not None, F.sum)
        rank = F.lit((1 - damping) / count) + F.lit(damping) * F.coalesce("m", F.lit(0.0))
        before, now = now, staged(now.join(got, now["vid"] == got["dst"], "left").select("vid", rank.alias("rank"), F.abs(rank - F.col("rank")).alias("moved")), "ranks")
        if staged_path(before):
            drop_path(now.sparkSession, staged_path(before))
        done += 1
        if rounds is None and (now.agg(F.sum("moved")).first()[0] or 0.0) <= until * (1 - damping):
            break
    return Rounds(now.select("vid", "rank"), done, done * arcs.count(), time.time() - began)


def pagerank_fixed(graph: Graph, rounds: int, scale: int = 10**12) -> DataFrame:
    """PageRank in integers: equal on every engine and for every order of addition; the error is at most edges / scale a round."""
    arcs = graph.edges.select("src", "dst")
    arcs = staged(arcs.join(arcs.groupBy("src").agg(F.count("*").alias("d")), "src"), "arcs")
    vertices = staged(graph.vertices.select("vid").distinct(), "vertices")
    n = vertices.count()
    now = vertices.select("vid", F.lit(scale // n).cast("long").alias("rank"))
    for _ in range(rounds):
        got = now.join(arcs, now["vid"] == arcs["src"]).groupBy("dst").agg(F.sum(F.expr("rank div d")).alias("s"))
        now = staged(vertices.join(got, vertices["vid"] == got["dst"], "left").select("vid", (F.lit(scale * 15 // (100 * n)) + F.expr("85 * coalesce(s, 0) div 100")).cast("long").alias("rank")), "ranks")
    return now


# --- simulation by counters and decrements -----------------------------------------------------------------------------------------


def gsim(graph: Graph, pattern: Pattern, cut: P.VertexCut | None = None, n: int = 4) -> Rounds:
    """(u, vid). Each vertex counts its matching successors per pattern node; a lost match is a decrement to its predecessors."""
    began = time.time()
    names, q = pattern.names, len(pattern.names)
    arcs = _arcs(graph, cut, n, False)
    bits = F.lit(0).cast("long")
    for k, label in enumerate(pattern.nodes.values()):
        bits = bits + F.when(F.col("label") == label, 1 << k).otherwise(0)
    start = staged(graph.vertices.select("vid", bits.alias("mask")), "candidates")

    def along(moved: DataFrame) -> DataFrame:
        """Per predecessor, how many successors carry each bit of ``bits``."""
        sent = moved.join(arcs, moved["vid"] == arcs["dst"])
        one = [F.sum(F.shiftright("bits", k).bitwiseAND(F.lit(1))).alias(f"k{k}") for k in range(q)]
        if cut is not None:
            sent = sent.groupBy("pid", "src").agg(*one)
            one = [F.sum(f"k{k}").alias(f"k{k}") for k in range(q)]
        return sent.groupBy("src").agg(*one).select("src", F.array(*[F.col(f"k{k}") for k in range(q)]).alias("add"))

    zero = F.array_repeat(F.lit(0).cast("long"), q)
    counts = along(start.where("mask <> 0").select("vid", F.col("mask").alias("bits")))
    now = start.join(counts, start["vid"] == counts["src"], "left").select("vid", "mask", F.coalesce("add", zero).alias("z"))
    at = {u: k for k, u in enumerate(names)}
    lost = F.lit(0).cast("long")
    for k, u in enumerate(names):
        wanted = [at[b] for a, b in pattern.arcs if a == u]
        if wanted:
            short = F.lit(False)
            for j in wanted:
                short = short | (F.col("z")[j] <= 0)
            lost = lost + F.when((F.col("mask").bitwiseAND(F.lit(1 << k)) != 0) & short, 1 << k).otherwise(0)
    rounds = messages = 0
    while True:
        now = staged(now.withColumn("lost", lost).withColumn("mask", F.col("mask") - F.col("lost")), "matches")
        gone = now.where("lost <> 0").count()
        rounds += 1
        messages += gone
        if not gone:
            break
        less = along(now.where("lost <> 0").select("vid", F.col("lost").alias("bits")))
        now = now.join(less, now["vid"] == less["src"], "left").select("vid", "mask", F.when(F.col("add").isNull(), F.col("z")).otherwise(F.zip_with("z", "add", lambda x, y: x - y)).alias("z"))
    found = F.array(*[F.when(F.col("mask").bitwiseAND(F.lit(1 << k)) != 0, F.lit(u)) for k, u in enumerate(names)])
    rel = staged(now.select(F.explode(F.array_compact(found)).alias("u"), "vid"), "simulation")
    if rel.agg(F.countDistinct("u")).first()[0] < q:
        rel = rel.where("false")
    return Rounds(rel, rounds, messages, time.time() - began)


def candidates(graph: Graph, pattern: Pattern) -> DataFrame:
    spark = graph.vertices.sparkSession
    nodes = spark.createDataFrame(list(pattern.nodes.items()), "u string, label string")
    return graph.vertices.join(F.broadcast(nodes), "label").select("u", "vid")  # a pattern has a handful of nodes


def successor_counts(graph: Graph, cand: DataFrame) -> DataFrame:
    return graph.edges.join(cand, graph.edges["dst"] == cand["vid"]).groupBy("src", "u").agg(F.count("*").alias("n"))


def simulate_sql(graph: Graph, pattern: Pattern) -> DataFrame:
    """Pruning by semi-joins to the fixpoint: a match stays while each wanted successor has a match."""
    edges = staged(graph.edges.select("src", "dst"), "arcs")
    now = staged(candidates(graph, pattern), "matches")
    before = now.count()
    while True:
        kept = now
        for a, b in pattern.arcs:
            fine = edges.join(now.where(F.col("u") == b).select(F.col("vid").alias("dst")), "dst").select(F.col("src").alias("vid")).distinct()
            kept = kept.where(F.col("u") != a).union(kept.where(F.col("u") == a).join(fine, "vid", "left_semi").select("u", "vid"))
        now = staged(kept, "matches")
        after = now.count()
        if after == before:
            break
        before = after
    return now if now.agg(F.countDistinct("u")).first()[0] == len(pattern.names) else now.where("false")


# --- block-centric -------------------------------------------------------------------------------------------------------------------


def partition_bfs(graph: Graph, rate: float = 0.02, growth: float = 4.0, max_passes: int = 3, max_depth: int = 20, salt: int = 1) -> DataFrame:
    """(vid, block): cells around sampled seeds by breadth-first search, in passes with a growing rate; the rest by its components.

    Seeds are drawn by hash, so that runs agree; a vertex reached by several seeds in one step takes the smallest. Every cell is connected.
    """
    arcs = staged(graph.symmetric().select("src", "dst"), "arcs")
    left = staged(graph.vertices.select("vid").distinct(), "uncovered")
    done: DataFrame | None = None
    for k in range(max_passes):
        p = min(1.0, rate * growth**k)
        wave = staged(left.where(hash32("vid", salt=salt + k) < F.lit(int(p * 4294967296))).select("vid", F.col("vid").alias("block")), "cells")
        cells = wave
        for _ in range(max_depth):
            near = wave.join(arcs, wave["vid"] == arcs["src"]).groupBy(F.col("dst").alias("vid")).agg(F.min("block").alias("block"))
            wave = staged(near.join(left, "vid", "left_semi").join(cells.select("vid"), "vid", "left_anti"), "wave")
            if not wave.head(1):
                break
            cells = staged(cells.union(wave), "cells")
        done = cells if done is None else done.union(cells)
        left = staged(left.join(cells.select("vid"), "vid", "left_anti"), "uncovered")
        if not left.head(1):
            break
    inner = arcs.join(left.select(F.col("vid").alias("src")), "src", "left_semi").join(left.select(F.col("vid").alias("dst")), "dst", "left_semi")
    rest = star_components(inner)
    return staged(done.union(left.join(rest, "vid", "left").select("vid", F.coalesce("component", "vid"))), "blocks")


def block_cc(graph: Graph, blocks: DataFrame) -> DataFrame:
    """Components by merging blocks alone: a block's label is its smallest vertex, and only the block graph iterates."""
    names = blocks.groupBy("block").agg(F.min("vid").alias("label"))
    named = blocks.join(names, "block").select("vid", "label")
    e = graph.edges.join(named.select(F.col("vid").alias("src"), F.col("label").alias("a")), "src").join(named.select(F.col("vid").alias("dst"), F.col("label").alias("b")), "dst")
    merged = star_components(e.where("a <> b").select(F.col("a").alias("src"), F.col("b").alias("dst")).distinct())
    return named.join(merged.select(F.col("vid").alias("label"), "component"), "label", "left").select("vid", F.coalesce("component", "label").alias("component"))


def assign_blocks(blocks: DataFrame, workers: int, how: str = "hash") -> DataFrame:
    """(vid, part): several blocks a worker, by hash or by sizes in descending order laid round the workers."""
    if how == "hash":
        return blocks.select("vid", (hash32("block") % workers).cast("int").alias("part"))
    from pyspark.sql import Window

    sizes = blocks.groupBy("block").agg(F.count("*").alias("size"))
    # One row per block: the running number over sizes is small beside the graph.
    turn = F.row_number().over(Window.orderBy(F.desc("size"), "block")) - 1
    lap = F.pmod(turn, F.lit(2 * workers))
    dealt = sizes.select("block", F.when(lap < workers, lap).otherwise(2 * workers - 1 - lap).cast("int").alias("part"))
    return blocks.join(dealt, "block").select("vid", "part")


def block_layout(graph: Graph, workers: int, per_worker: int = 16):
    """Blocks as units of their own: a program runs inside each block, and blocks of one worker talk by messages like any others.

    The largest ``workers * per_worker`` blocks stand alone; what is left of the small ones is one block a worker.
    """
    from hubsplit.plans.runtime import make_layout

    most = workers * per_worker
    rate = min(0.02, most / max(1, graph.vertices.select("vid").distinct().count()))
    blocks = partition_bfs(graph, rate)
    largest = blocks.groupBy("block").agg(F.count("*").alias("size")).orderBy(F.desc("size"), "block").limit(most).collect()
    named = graph.vertices.sparkSession.createDataFrame([(r["block"], k) for k, r in enumerate(largest)], "block long, nth int")  # at most `most` rows
    placed = blocks.join(F.broadcast(named), "block", "left").select("vid", F.coalesce("nth", (len(largest) + hash32("block") % workers).cast("int")).alias("part"))
    return make_layout(graph, None, len(largest) + workers, "edge_cut", placed)


# --- multilevel edge-cut -------------------------------------------------------------------------------------------------------------


def multilevel_cut(graph: Graph, n: int, levels: int = 40, cap_edges: int = 50_000_000, coarse_limit: int = 100_000, arc_limit: int = 2_000_000, refine: int = 2, balance_edges: bool = True) -> DataFrame:
    """(vid, part): mutual heaviest neighbours are merged level by level, the coarsest graph is split, and boundary vertices move.

    Where that hardly shrinks a graph that is still too large (stars, whose centre merges with one leaf a level, and many components),
    a level gathers vertices instead. Parts are balanced by vertices and, with ``balance_edges``, by edge ends too. Graphs above
    ``cap_edges``, and those that will not shrink to ``coarse_limit`` vertices and ``arc_limit`` arcs, are refused with an error; only
    what is within these limits reaches the driver.
    """
    spark = graph.edges.sparkSession
    arcs = staged(graph.symmetric().where("src <> dst").select("src", "dst", F.lit(1).cast("long").alias("w")), "arcs")
    held = arcs.count()
    if held > 2 * cap_edges:
        raise ValueError("too many edges for the multilevel partitioner")
    names = staged(graph.vertices.select("vid", F.col("vid").alias("coarse")).distinct(), "names")
    size = names.count()
    limit, left, idle, gathers = max(2, size // (4 * n)), size, 0, False
    for level in range(levels):
        weight = staged(names.groupBy(F.col("coarse").alias("c")).agg(F.count("*").alias("size")), "sizes")
        fits = left <= coarse_limit and held <= arc_limit
        if fits or not gathers:
            heavy = _with_sizes(arcs, weight).where(F.col("s1") + F.col("s2") <= limit)
            best = heavy.groupBy("src").agg(F.max_by("dst", F.struct(F.col("w") / F.col("s2"), hash32("dst"))).alias("dst"))
            mutual = best.join(best.select(F.col("dst").alias("src"), F.col("src").alias("dst")), ["src", "dst"]).where("src > dst")
            moved = staged(mutual.select(F.col("src").alias("coarse"), F.col("dst").alias("into")), "merges")
            merged = moved.count()
            if fits and (merged * 50 < left or not merged):
                break
            gathers = merged * 10 < left
        if gathers and not fits:
            moved = staged(_gathered(arcs, weight, limit, level, coarse_limit // 4), "merges")
            merged = moved.count()
            idle = 0 if merged else idle + 1  # another level draws other vertices
            if idle == 3:
                break
        left -= merged
        before = names, arcs, weight, moved
        names = staged(names.join(moved, "coarse", "left").select("vid", F.coalesce("into", "coarse").alias("coarse")), "names")
        up = lambda df, c: df.join(moved.withColumnRenamed("coarse", c), c, "left").withColumn(c, F.coalesce("into", c)).drop("into")
        arcs = staged(up(up(arcs, "src"), "dst").where("src <> dst").groupBy("src", "dst").agg(F.sum("w").alias("w")), "arcs")
        held = arcs.count()
        for done in before:
            drop_path(spark, staged_path(done))
    weight = staged(names.groupBy("coarse").agg(F.count("*").alias("size")), "coarse")
    if weight.count() > coarse_limit or held > arc_limit:
        raise ValueError("the graph will not shrink to a size that one machine can split")
    placed = _split(weight.toArrow(), arcs.toArrow(), n, refine, balance_edges)
    table = spark.createDataFrame(placed, "coarse long, part int")
    return names.join(table, "coarse").select("vid", "part")


def _with_sizes(arcs: DataFrame, weight: DataFrame) -> DataFrame:
    """Arcs with the sizes of both ends."""
    end = lambda c, s: weight.select(F.col("c").alias(c), F.col("size").alias(s))
    return arcs.join(end("src", "s1"), "src").join(end("dst", "s2"), "dst")


def _gathered(arcs: DataFrame, weight: DataFrame, limit: int, level: int, most_alone: int) -> DataFrame:
    """(coarse, into): half of the vertices, drawn by hash, each choose their heaviest neighbour in the other half.

    All that chose one vertex join it if it has room. If not, they are dealt into groups of about half of ``limit``: one group joins the
    vertex if it can, each other becomes one vertex. Vertices without arcs are dealt likewise, about ``most_alone`` of them staying.
    """
    drawn = lambda c: hash32(c, salt=3 * level + 101) % 2
    ends = _with_sizes(arcs.where((drawn("src") == 1) & (drawn("dst") == 0)), weight)
    best = F.max_by(F.struct("dst", "s2"), F.struct(F.col("w") / F.col("s2"), hash32("dst")))
    chosen = staged(ends.groupBy("src").agg(F.first("s1").alias("s1"), best.alias("to")).select("src", "s1", "to.dst", "to.s2"), "chosen")
    asked = chosen.groupBy("dst").agg(F.sum("s1").alias("asked"))
    many = F.when(F.col("asked") + F.col("s2") <= limit, 1).otherwise(F.ceil(2 * F.col("asked") / limit))
    dealt = chosen.join(asked, "dst").withColumn("nth", hash32("src", salt=3 * level + 102) % many)
    groups = dealt.groupBy("dst", "nth").agg(F.sum("s1").alias("total"), F.max("s2").alias("room"), F.min("src").alias("low"))
    joins = F.when((F.col("nth") == 0) & (F.col("total") + F.col("room") <= limit), F.col("dst")).when(F.col("total") <= limit, F.col("low"))
    near = dealt.select("src", "dst", "nth").join(groups, ["dst", "nth"]).select(F.col("src").alias("coarse"), joins.alias("into"))

    alone = staged(weight.join(arcs.select(F.col("src").alias("c")), "c", "left_anti"), "alone")
    found = alone.agg(F.count("*").alias("n"), F.sum("size").alias("size")).first()
    k = max(1, most_alone, -(-2 * (found["size"] or 0) // limit))
    if found["n"] > k:
        alone = alone.withColumn("nth", hash32("c", salt=3 * level + 103) % k)
        groups = alone.groupBy("nth").agg(F.sum("size").alias("total"), F.min("c").alias("into")).where(F.col("total") <= limit)
        near = near.union(alone.join(groups, "nth").select(F.col("c").alias("coarse"), "into"))
    return near.where("coarse <> into")


def _split(vertices: pa.Table, arcs: pa.Table, n: int, refine: int, balance_edges: bool = True) -> list[tuple[int, int]]:
    order = np.argsort(vertices.column("coarse").to_numpy())
    ids, size = (vertices.column(c).to_numpy()[order] for c in ("coarse", "size"))
    src, dst = (np.searchsorted(ids, arcs.column(c).to_numpy()) for c in ("src", "dst"))
    order = np.argsort(src, kind="stable")
    near, pulls = dst[order], arcs.column("w").to_numpy()[order]
    ptr = np.searchsorted(src[order], np.arange(len(ids) + 1))
    ends = np.bincount(src, weights=arcs.column("w").to_numpy(), minlength=len(ids)).astype(np.int64) if balance_edges else np.zeros(len(ids), np.int64)
    cap, most_ends = 1.05 * size.sum() / n, 1.1 * ends.sum() / n
    part = np.full(len(ids), -1)
    load, held = [0] * n, [0] * n
    fits = lambda v, p: load[p] + size[v] <= cap and held[p] + ends[v] <= most_ends
    pull_of = lambda v: np.bincount(part[near[ptr[v] : ptr[v + 1]]] + 1, weights=pulls[ptr[v] : ptr[v + 1]], minlength=n + 1)[1:].tolist()

    def move(v: int, to: int) -> None:
        if part[v] >= 0:
            load[part[v]] -= size[v]
            held[part[v]] -= ends[v]
        part[v] = to
        load[to] += size[v]
        held[to] += ends[v]

    for v in np.lexsort((ids, -size)).tolist():
        pull = pull_of(v)
        open_ = [p for p in range(n) if fits(v, p)] or [min(range(n), key=lambda p: load[p])]
        move(v, max(open_, key=lambda p: (pull[p], -load[p], -p)))
    for _ in range(refine):
        for v in range(len(ids)):
            pull = pull_of(v)
            best = max(range(n), key=lambda p: (pull[p], -p))
            if pull[best] > pull[part[v]] and fits(v, best):
                move(v, best)
    return list(zip(ids.tolist(), part.tolist(), strict=True))
