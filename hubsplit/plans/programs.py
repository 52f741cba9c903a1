"""The four programs on the hybrid model and its edge-cut twin: components, shortest paths, PageRank, simulation."""

from __future__ import annotations

import heapq
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hubsplit.plans.runtime import Inbox, Layout, Part, Program, RunResult, run
from hubsplit.shared_dir import staged

FAR = np.iinfo(np.int64).max // 4

# --- connected components: local components once, then rounds on the contracted boundary --------------------------------------------


def _union_find(n: int, src: np.ndarray, dst: np.ndarray) -> np.ndarray:
    labels = np.arange(n)
    while len(src):
        low = np.minimum(labels[src], labels[dst])
        before = labels.copy()
        np.minimum.at(labels, before[src], low)
        np.minimum.at(labels, before[dst], low)
        while True:
            jumped = labels[labels]
            if np.array_equal(jumped, labels):
                break
            labels = jumped
        if (labels[src] == labels[dst]).all():
            break
    return labels


def _search(n: int, src: np.ndarray, dst: np.ndarray, depth_first: bool) -> np.ndarray:
    near: list[list[int]] = [[] for _ in range(n)]
    for s, d in zip(src.tolist(), dst.tolist(), strict=True):
        near[s].append(d)
        near[d].append(s)
    labels = np.full(n, -1)
    for root in range(n):
        if labels[root] >= 0:
            continue
        labels[root], wait = root, [root]
        at = 0
        while at < len(wait):
            v = wait.pop() if depth_first else wait[at]
            at += not depth_first
            for x in near[v]:
                if labels[x] < 0:
                    labels[x] = root
                    wait.append(x)
            if depth_first and not wait:
                break
    return labels


def local_labels(n: int, src: np.ndarray, dst: np.ndarray, local: str = "unionfind") -> np.ndarray:
    """Smallest index of each local component, by union-find, breadth-first or depth-first search."""
    return _union_find(n, src, dst) if local == "unionfind" else _search(n, src, dst, local == "dfs")


@dataclass
class Components(Program):
    """Round 0 labels every local component; later rounds read vertices alone, never the edges.

    ``low`` is the label of a local component (at its root), ``agreed`` the label last sent or told for a vertex.
    """

    local: str = "unionfind"
    twin: bool = False

    def __post_init__(self):
        self.spread = "master" if self.twin else "all"

    def start(self, part: Part) -> dict[str, np.ndarray]:
        root = local_labels(len(part.vids), part.src, part.dst, self.local)
        part.visited += len(part.src)
        return {"root": root, "low": part.vids.copy(), "agreed": part.vids.copy()}

    def news(self, state, inbox):
        return inbox.value < state["agreed"][inbox.at]

    def compute(self, part: Part, state: dict, inbox: Inbox, round_: int):
        root, low, agreed = state["root"], state["low"], state["agreed"]
        np.minimum.at(agreed, inbox.at, inbox.value)
        np.minimum.at(low, root[inbox.at], inbox.value)
        label = low[root]
        sent = np.flatnonzero(part.frontier & (label < agreed) & (~part.owned if self.twin else True))
        agreed[sent] = label[sent]
        return sent, label[sent], 0.0


def connected_components(layout: Layout, local: str = "unionfind", max_rounds: int | None = None) -> RunResult:
    """(vid, component): the smallest vertex id of each component."""

    def labels(part: Part, state: dict) -> dict:
        return {"vid": part.vids[part.owned], "component": state["low"][state["root"]][part.owned]}

    return run(layout, Components(local, layout.mode == "edge_cut"), max_rounds, values=labels, schema="vid long, component long")


def component_sizes(values: DataFrame) -> DataFrame:
    return values.groupBy("component").agg(F.count("*").alias("n"))


# --- shortest paths ------------------------------------------------------------------------------------------------------------------


@dataclass
class ShortestPaths(Program):
    """Distances from one or several sources, by a priority queue inside each part. Parts without improved vertices sleep.

    ``heap`` settles the vertices of one distance together, in order of distance; ``relax`` goes by waves without an order.
    """

    sources: tuple[int, ...]
    weighted: bool = True
    local: str = "heap"
    twin: bool = False

    all_active_rounds = 0

    def __post_init__(self):
        self.spread = "master" if self.twin else "all"

    def start(self, part: Part) -> dict[str, np.ndarray]:
        return {"dist": np.full(len(part.vids), FAR, np.int64)}

    def first_inbox(self, layout: Layout) -> DataFrame:
        if self.weighted and layout.edges.where("w < 0").head(1):
            raise ValueError("a weight is negative")
        start = layout.replicas.where(F.col("vid").isin(*self.sources))
        if self.twin:
            start = start.where("pid = master_pid")
        return start.select("pid", "vid", "master_pid", F.lit(0).cast("long").alias("value"))

    def news(self, state, inbox):
        return inbox.value < state["dist"][inbox.at]

    def _relax(self, part: Part, dist: np.ndarray, wave: np.ndarray) -> np.ndarray:
        """Vertices that the wave's edges bring nearer."""
        out = part.out_edges(wave)
        part.visited += len(out)
        x = part.dst[out]
        reach = dist[part.src[out]] + (part.w[out] if self.weighted else 1)
        ok = reach < dist[x]
        np.minimum.at(dist, x[ok], reach[ok])
        return np.unique(x[ok])

    def compute(self, part: Part, state: dict, inbox: Inbox, round_: int):
        dist = state["dist"]
        np.minimum.at(dist, inbox.at, inbox.value)
        told = dist.copy()
        wave = np.unique(inbox.at)
        if self.local == "heap":
            _settle_by_distance(part, dist, wave, self.weighted)
        else:
            while len(wave):
                wave = self._relax(part, dist, wave)
        sent = np.flatnonzero((dist < told) & part.frontier & (~part.owned if self.twin else True))
        return sent, dist[sent], 0.0


def _settle_by_distance(part: Part, dist: np.ndarray, wave: np.ndarray, weighted: bool) -> None:
    """Dijkstra's order: a heap of distances, each with the vertices waiting there. Few vertices are stepped one by one, many together."""
    ptr, to, weight = part.out_ptr, part.dst, part.w
    waiting: dict[int, list] = {}
    for v in wave.tolist():
        waiting.setdefault(int(dist[v]), []).append(v)
    keys = list(waiting)
    heapq.heapify(keys)
    while keys:
        d = heapq.heappop(keys)
        now = [v for v in waiting.pop(d) if dist[v] == d]
        if len(now) > 16:
            out = part.out_edges(np.unique(np.array(now)))
            part.visited += len(out)
            x, reach = to[out], d + (weight[out] if weighted else np.ones(len(out), np.int64))
            ok = reach < dist[x]
            x, reach = x[ok], reach[ok]
            np.minimum.at(dist, x, reach)
            ok = dist[x] == reach
            found = zip(x[ok].tolist(), reach[ok].tolist(), strict=True)
        else:
            found = []
            for v in now:
                a, b = int(ptr[v]), int(ptr[v + 1])
                part.visited += b - a
                for x, w in zip(to[a:b].tolist(), weight[a:b].tolist(), strict=True):
                    e = d + (w if weighted else 1)
                    if e < dist[x]:
                        dist[x] = e
                        found.append((x, e))
        for x, e in found:
            if e in waiting:
                waiting[e].append(x)
            else:
                waiting[e] = [x]
                heapq.heappush(keys, e)


def shortest_paths(layout: Layout, sources, weighted: bool = True, local: str = "heap", **kept) -> RunResult:
    """(vid, dist) of the vertices that can be reached."""
    sources = (sources,) if isinstance(sources, int) else tuple(sources)

    def reached(part: Part, state: dict) -> dict:
        got = part.owned & (state["dist"] < FAR)
        return {"vid": part.vids[got], "dist": state["dist"][got]}

    return run(layout, ShortestPaths(sources, weighted, local, layout.mode == "edge_cut"), values=reached, schema="vid long, dist long", **kept)


def predecessors(edges: DataFrame, distances: DataFrame, weighted: bool = True) -> DataFrame:
    """(vid, parent): a tree of shortest paths; of several predecessors the smallest, and none for a source."""
    step = F.col("w") if weighted else F.lit(1)
    near = edges.join(distances.select(F.col("vid").alias("src"), F.col("dist").alias("_a")), "src").join(distances.select(F.col("vid").alias("dst"), F.col("dist").alias("_b")), "dst")
    tight = near.where((F.col("_a") + step == F.col("_b")) & (F.col("_a") < F.col("_b")))
    return tight.groupBy(F.col("dst").alias("vid")).agg(F.min("src").alias("parent"))


def diameter(layout: Layout, start: int) -> tuple[int, int, int]:
    """(hops, end, end): a double sweep, a lower bound of the diameter that trees attain. Ties take the smallest id."""
    far = lambda v: shortest_paths(layout, int(v), False).values.orderBy(F.desc("dist"), "vid").first()
    a = far(start)
    if a is None:
        return 0, start, start
    b = far(a["vid"])
    return int(b["dist"]), int(a["vid"]), int(b["vid"])


# --- accumulative PageRank -----------------------------------------------------------------------------------------------------------


@dataclass
class PageRank(Program):
    """Pending weight is added to the rank, its damped share is pushed along out-edges, and the frontier's receipts are summed.

    A frontier vertex consumes only what the fold returned, and all its replicas consume the same total over their own edges.
    ``min_delta`` holds small receipts back until they have added up, and ``top_k`` lets a part send its largest receipts only: fewer
    pairs a round, the same limit within the tolerance.
    """

    n_vertices: int
    damping: float = 0.85
    tol: float = 1e-10
    local_sweeps: int | None = 1
    min_delta: float = 0.0
    top_k: int | None = None
    twin: bool = False

    kind = "double"
    how = "sum"

    def __post_init__(self):
        self.spread = "master" if self.twin else "all"

    def start(self, part: Part) -> dict[str, np.ndarray]:
        base = (1 - self.damping) / self.n_vertices
        n = len(part.vids)
        return {"pending": np.where(part.owned, base, 0.0) if self.twin else np.full(n, base), "rank": np.zeros(n), "received": np.zeros(n)}

    def select(self, received: np.ndarray, may: np.ndarray) -> np.ndarray:
        """Which receipts are sent now."""
        sent = np.flatnonzero(may & (received > self.min_delta))
        if self.top_k is not None and len(sent) > self.top_k:
            sent = np.sort(sent[np.argsort(-received[sent], kind="stable")[: self.top_k]])
        return sent

    def compute(self, part: Part, state: dict, inbox: Inbox, round_: int):
        pending, rank, received = state["pending"], state["rank"], state["received"]
        np.add.at(pending, inbox.at, inbox.value)
        keeps = part.owned if self.twin else ~part.frontier  # vertices that take in their receipts at once
        eps = self.tol * (1 - self.damping) / max(self.n_vertices, 1) / 10
        for sweep in range(self.local_sweeps or 10_000):
            go = np.flatnonzero(pending > (eps if sweep else 0))
            if not len(go):
                break
            rank[go] += pending[go]
            share = np.zeros(len(pending))
            spreads = go[part.d_out[go] > 0]
            share[spreads] = self.damping * pending[spreads] / part.d_out[spreads]
            pending[go] = 0.0
            if len(spreads) * 4 > len(pending):
                part.visited += len(part.src)
                got = np.bincount(part.dst, weights=share[part.src], minlength=len(pending))
            else:
                out = part.out_edges(spreads)
                part.visited += len(out)
                got = np.bincount(part.dst[out], weights=share[part.src[out]], minlength=len(pending))
            pending[keeps] += got[keeps]
            received[~keeps] += got[~keeps]
        sent = self.select(received, ~keeps)
        values = received[sent]
        received[sent] = 0.0
        waits = float(received[received > self.min_delta].sum()) if self.top_k is not None else 0.0
        return sent, values, float(pending.sum()) + waits

    def settled(self, pending: float) -> bool:
        return pending <= self.tol * (1 - self.damping)


def pagerank(layout: Layout, damping: float = 0.85, tol: float = 1e-10, local_sweeps: int | None = 1, min_delta: float = 0.0, top_k: int | None = None) -> RunResult:
    """(vid, rank), within ``tol`` of the equation's solution in sum."""
    n = layout.replicas.where("pid = master_pid").count()

    def ranks(part: Part, state: dict) -> dict:
        return {"vid": part.vids[part.owned], "rank": (state["rank"] + state["pending"])[part.owned]}

    return run(layout, PageRank(n, damping, tol, local_sweeps, min_delta, top_k, layout.mode == "edge_cut"), values=ranks, schema="vid long, rank double")


# --- sums over the neighbourhood --------------------------------------------------------------------------------------------------------


@dataclass
class Inflow(Program):
    """Weights of the edges that enter a vertex: partial sums in every part, added by the fold."""

    how = "sum"

    def start(self, part: Part) -> dict[str, np.ndarray]:
        part.visited += len(part.dst)
        total = np.zeros(len(part.vids), np.int64)
        np.add.at(total, part.dst, part.w)
        return {"total": total}

    def compute(self, part: Part, state: dict, inbox: Inbox, round_: int):
        total = state["total"]
        if round_:
            total[inbox.at] = inbox.value
            return np.array([], np.int64), np.array([], np.int64), 0.0
        sent = np.flatnonzero(part.frontier & (total != 0))
        return sent, total[sent], 0.0


def inflow(layout: Layout) -> DataFrame:
    """(vid, total) of the vertices that some edge enters."""
    entered = lambda part, state: {"vid": part.vids[part.owned & (part.d_in > 0)], "total": state["total"][part.owned & (part.d_in > 0)]}
    return run(layout, Inflow(), values=entered, schema="vid long, total long").values


@dataclass
class SuccessorLabels(Program):
    """How many successors of each vertex carry each label: a vector per vertex, added entry by entry."""

    names: tuple[str, ...]

    kind = "array<long>"
    how = "vector"

    def __post_init__(self):
        self.width = len(self.names)

    def start(self, part: Part) -> dict[str, np.ndarray]:
        at = {x: k for k, x in enumerate(self.names)}
        code = np.array([at[x] for x in part.labels.tolist()] + [-1], np.int64)[part.code]  # no label: the last entry
        counts = np.zeros((len(part.vids), self.width), np.int64)
        known = code[part.dst] >= 0
        np.add.at(counts, (part.src[known], code[part.dst[known]]), 1)
        return {"counts": counts}

    def compute(self, part: Part, state: dict, inbox: Inbox, round_: int):
        counts = state["counts"]
        if round_:
            counts[inbox.at] = inbox.value
            return np.array([], np.int64), np.zeros((0, self.width), np.int64), 0.0
        sent = np.flatnonzero(part.frontier & counts.any(axis=1))
        return sent, counts[sent], 0.0


def successor_labels(layout: Layout, most_labels: int = 1000) -> DataFrame:
    """(vid, label, n). The labels are the vector's entries, so there may be ``most_labels`` of them."""
    names = tuple(sorted(r["label"] for r in layout.replicas.select("label").where("label is not null").distinct().limit(most_labels + 1).collect()))
    if len(names) > most_labels:
        raise ValueError(f"more than {most_labels} labels")

    def counted(part: Part, state: dict) -> dict:
        row, k = np.nonzero(np.where(part.owned[:, None], state["counts"], 0))
        return {"vid": part.vids[row], "label": np.array(names, object)[k], "n": state["counts"][row, k]}

    return run(layout, SuccessorLabels(names), values=counted, schema="vid long, label string, n long").values


# --- graph simulation ----------------------------------------------------------------------------------------------------------------


@dataclass(frozen=True)
class Pattern:
    nodes: dict[str, str]
    arcs: list[tuple[str, str]]

    @property
    def names(self) -> list[str]:
        return list(self.nodes)


@dataclass
class Simulation(Program):
    """Per replica: which pattern nodes still match (bits of ``a``) and how many successors match each pattern node (``z``).

    Over a vertex-cut, counters of the frontier are summed by the fold, and later the decrements; every replica removes a match in
    the same round because all hold equal counters. Over the edge-cut twin, owners hold all out-edges, so their counters are
    complete and alone in the state, and removals travel from owners to ghosts.
    """

    pattern: Pattern
    twin: bool = False

    def __post_init__(self):
        q = len(self.pattern.names)
        if self.twin:
            self.kind, self.how, self.spread, self.all_active_rounds = "long", "or", "mirrors", 1
        else:
            self.kind, self.how, self.width, self.all_active_rounds = "array<long>", "vector", q, 2
        at = {u: k for k, u in enumerate(self.pattern.names)}
        self.wants = [[at[b] for a, b in self.pattern.arcs if a == u] for u in self.pattern.names]

    def start(self, part: Part) -> dict[str, np.ndarray]:
        names = part.labels.tolist()
        match = np.zeros((len(part.vids), len(self.wants)), bool)
        for k, label in enumerate(self.pattern.nodes.values()):
            if label in names:
                match[:, k] = part.code == names.index(label)
        return {"match": np.packbits(match, axis=1), "counts": np.zeros((part.owned.sum(), len(self.wants)), np.int32) if self.twin else np.zeros(match.shape, np.int64)}

    def match_of(self, state: dict) -> np.ndarray:
        return np.unpackbits(state["match"], axis=1, count=len(self.wants)).astype(bool)

    def compute(self, part: Part, state: dict, inbox: Inbox, round_: int):
        match, counts = self.match_of(state), state["counts"]
        n, q = match.shape
        if self.twin:
            counts = np.zeros((n, q), np.int32)  # a part's edges are far fewer than 2^31
            counts[part.owned] = state["counts"]
        whole = part.owned.copy() if self.twin else (~part.frontier if round_ == 0 else np.ones(n, bool))
        sent = np.zeros((n, q), np.int64)
        gone = np.zeros((n, q), bool)

        def lose(rows: np.ndarray, cols: np.ndarray) -> None:
            """Matches that are no more: predecessors count one successor less."""
            for k in np.unique(cols):
                edges = part.in_edges(rows[cols == k])
                part.visited += len(edges)
                p = part.src[edges]
                if self.twin:
                    np.subtract.at(counts[:, k], p[part.owned[p]], 1)
                else:
                    inner = ~part.frontier[p]
                    np.subtract.at(counts[:, k], p[inner], 1)
                    np.add.at(sent[:, k], p[~inner], 1)

        if round_ == 0:
            for k in range(q):
                np.add.at(counts[:, k], part.src, match[part.dst, k].astype(counts.dtype))
            part.visited += len(part.src)
        elif self.twin:
            told = (inbox.value[:, None] >> np.arange(q)) & 1 == 1
            r, c = np.nonzero(told & match[inbox.at])
            match[inbox.at[r], c] = False
            lose(inbox.at[r], c)
        elif round_ == 1:
            counts[part.frontier] = 0
            counts[inbox.at] = inbox.value
        else:
            counts[inbox.at] -= inbox.value
        while True:
            bad = np.zeros((n, q), bool)
            for k, wanted in enumerate(self.wants):
                if wanted:
                    bad[:, k] = match[:, k] & whole & (counts[:, wanted] <= 0).any(axis=1)
            r, c = np.nonzero(bad)
            if not len(r):
                break
            match &= ~bad
            gone |= bad
            lose(r, c)
        state["match"], state["counts"] = np.packbits(match, axis=1), counts[part.owned] if self.twin else counts
        if self.twin:
            out = np.flatnonzero(gone.any(axis=1) & part.frontier & part.owned)
            return out, (gone[out].astype(np.int64) << np.arange(q)).sum(axis=1), 0.0
        if round_ == 0:
            # partial counters of the frontier, already less what was lost here
            partial = np.where(part.frontier[:, None], counts - sent, 0)
            out = np.flatnonzero(partial.any(axis=1))
            return out, partial[out], 0.0
        out = np.flatnonzero(sent.any(axis=1))
        return out, sent[out], 0.0


def graph_simulation(layout: Layout, pattern: Pattern) -> RunResult:
    """(u, vid): the largest simulation, or nothing when some pattern node has no match."""
    program = Simulation(pattern, layout.mode == "edge_cut")

    def matched(part: Part, state: dict) -> dict:
        row, k = np.nonzero(program.match_of(state) & part.owned[:, None])
        return {"u": np.array(pattern.names, object)[k], "vid": part.vids[row]}

    r = run(layout, program, values=matched, schema="u string, vid long")
    rel = staged(r.values, "simulation")
    r.values = rel if matches(rel, pattern) else rel.where("false")
    return r


def matches(relation: DataFrame, pattern: Pattern) -> bool:
    return relation.agg(F.countDistinct("u")).first()[0] == len(pattern.names)


PATTERNS: dict[str, tuple[str, Pattern]] = {
    "P1": ("commerce", Pattern({"c": "BUILDING", "o": "1-URGENT", "p": "ECONOMY"}, [("c", "o"), ("o", "p")])),
    "P2": ("commerce", Pattern({"c": "BUILDING", "o": "1-URGENT", "o2": "5-LOW", "p": "ECONOMY", "s": "NATION_3"}, [("c", "o"), ("c", "o2"), ("o", "p"), ("o2", "p"), ("p", "s")])),
    "P3": ("copurchase", Pattern({"a": "ECONOMY", "b": "SMALL", "c": "STANDARD"}, [("a", "b"), ("b", "c"), ("c", "a")])),
    "P4": ("copurchase", Pattern({"a": "ECONOMY", "b": "SMALL", "c": "ECONOMY"}, [("a", "b"), ("b", "a"), ("a", "c")])),
    "P5": ("userchain", Pattern({"v": "view", "c": "click", "p": "purchase"}, [("v", "c"), ("c", "p")])),
    "P6": ("userchain", Pattern({"v": "view", "c": "click"}, [("v", "c"), ("c", "v")])),
}
