"""The hybrid model: whole-subgraph programs over a cut, in rounds of local compute, fold and spread.

Parts are resident. ``make_layout`` writes each part once, as arrays in files of the shared folder; a program's state is one file
per part and version. A round is one Spark job over the inbox alone: its rows are dealt to their parts, a part that gets some loads its
arrays, computes, writes its next state under a name of its own and returns what it sends. Parts that get nothing are not
touched: their state is neither read, nor moved, nor written. What is sent is folded by vertex (pre-aggregated by Spark) and spread
along the frontier's routes, which stay cached and partitioned by vertex.

A lost executor costs the tasks it ran: state files of a round are named in its rows, so that a retried task simply writes another file,
and a file is deleted only after the round that replaced it is complete. With ``snapshots`` a run leaves a manifest per round, from
which another driver can resume it. Pairs are counted by their parts' numbers, not by the rows that Spark happens to move.
"""

from __future__ import annotations

import io
import json
import time
import uuid
from collections import OrderedDict
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from hubsplit.plans import partition as P
from hubsplit.shared_dir import drop_path, fresh_path, staged, staged_path
from hubsplit.sources.graphs import Graph

#: Loaded parts that a Python worker keeps for later rounds, in bytes; larger parts are loaded each time.
CACHE_BYTES = 64 << 20
_LOADED: OrderedDict[str, tuple[dict[str, np.ndarray], int]] = OrderedDict()

VERTEX_FIELDS = ("vids", "master_pid", "frontier", "d_out", "d_in", "code", "labels")
#: Integers that files may hold in a narrower type, and the type that kernels see.
WIDE = {"master_pid": np.int32, "d_out": np.int64, "d_in": np.int64, "code": np.int32, "w": np.int64}

# --- files of the shared folder -------------------------------------------------------------------------------------------------------


def _fs(folder: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(folder if "://" in folder else f"file://{folder}")


def save_arrays(folder: str, kind: str, arrays: dict[str, np.ndarray]) -> str:
    """Writes arrays under a fresh name and returns it."""
    fs, root = _fs(folder)
    name = f"{kind}-{uuid.uuid4().hex}.npz"
    held = io.BytesIO()
    np.savez(held, **arrays)
    with fs.open_output_stream(f"{root}/{name}") as out:
        out.write(held.getbuffer())
    return name


def load_arrays(folder: str, name: str) -> dict[str, np.ndarray]:
    fs, root = _fs(folder)
    with fs.open_input_stream(f"{root}/{name}") as f:
        found = np.load(io.BytesIO(f.read()))
    return {k: found[k] for k in found.files}


def narrow(arrays: dict[str, np.ndarray]) -> dict[str, np.ndarray]:
    """The arrays, those of ``WIDE`` in the smallest signed type that holds them."""
    fits = lambda a: next(t for t in (np.int8, np.int16, np.int32, np.int64) if np.iinfo(t).min <= a.min() and a.max() <= np.iinfo(t).max)
    return {k: a.astype(fits(a)) if k in WIDE and len(a) else a for k, a in arrays.items()}


def _kept(folder: str, name: str) -> dict[str, np.ndarray]:
    """Arrays that never change, from this worker's memory if it holds them."""
    key = f"{folder}/{name}"
    if key in _LOADED:
        _LOADED.move_to_end(key)
        return _LOADED[key][0]
    arrays = {k: a.astype(WIDE.get(k, a.dtype), copy=False) for k, a in load_arrays(folder, name).items()}
    for a in arrays.values():
        a.setflags(write=False)
    size = sum(a.nbytes for a in arrays.values())
    if size <= CACHE_BYTES:
        while _LOADED and size + sum(n for _, n in _LOADED.values()) > CACHE_BYTES:
            _LOADED.popitem(last=False)
        _LOADED[key] = (arrays, size)
    return arrays


def _remove(folder: str, name: str) -> None:
    fs, root = _fs(folder)
    try:
        fs.delete_file(f"{root}/{name}")
    except OSError:
        pass  # a retried task finds it gone


# --- layout ---------------------------------------------------------------------------------------------------------------------------


@dataclass
class Layout:
    """Edges by part, one row per replica with its master, and each part's arrays at rest."""

    n: int
    mode: str
    folder: str
    files: dict[int, tuple[str, str]]
    edges: DataFrame
    replicas: DataFrame
    routes: DataFrame
    seconds: float
    spark: SparkSession = field(repr=False, default=None)

    def release(self) -> None:
        self.routes.unpersist()

    def save(self) -> str:
        """Writes the manifest from which ``open_layout`` restores this layout; returns the folder."""
        fs, root = _fs(self.folder)
        kept = {"n": self.n, "mode": self.mode, "files": {str(p): f for p, f in self.files.items()}, "edges": staged_path(self.edges) or staged_path(staged(self.edges, "cut")), "replicas": staged_path(self.replicas) or staged_path(staged(self.replicas, "replicas"))}
        with fs.open_output_stream(f"{root}/layout.json") as out:
            out.write(json.dumps(kept).encode())
        return self.folder


def _routes(replicas: DataFrame) -> DataFrame:
    """The frontier's replicas, kept by vertex as a fold leaves its rows, so that a spread moves only what was folded."""
    many = int(replicas.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    kept = replicas.where("frontier").select("vid", "pid", "master_pid").repartition(many, "vid").persist()
    kept.count()  # adaptive plans know the partitioning of a cached table only once it is filled
    return kept


def open_layout(spark: SparkSession, folder: str) -> Layout:
    """A saved layout, by any driver that reads the shared folder."""
    fs, root = _fs(folder)
    with fs.open_input_stream(f"{root}/layout.json") as f:
        kept = json.loads(f.read())
    edges, replicas = (spark.read.parquet(kept[k]) for k in ("edges", "replicas"))
    edges.staged_path, replicas.staged_path = kept["edges"], kept["replicas"]
    return Layout(kept["n"], kept["mode"], folder, {int(p): tuple(f) for p, f in kept["files"].items()}, edges, replicas, _routes(replicas), 0.0, spark)


def make_layout(graph: Graph, cut: P.VertexCut | None, n: int | None = None, mode: str = "vertex_cut", placed: DataFrame | None = None, symmetric: bool | None = None, max_edges_per_part: int = 64_000_000) -> Layout:
    """Places edges and replicas. ``edge_cut``: a vertex's part owns it, cut edges are held twice, and copies elsewhere are ghosts.

    Without ``n`` there are as many parts as the session has cores, or the multiple of them that keeps parts under the cap.
    """
    began = time.time()
    spark = graph.edges.sparkSession
    both = (not graph.directed) if symmetric is None else symmetric
    edges = staged(graph.symmetric() if both else graph.edges.select("src", "dst", F.col("w").cast("long").alias("w")), "edges")
    codes = staged(graph.vertices.groupBy("vid").agg(F.min("label").alias("label")), "vertices")  # the view is evaluated once
    if n is None:
        n = P.choose_parts(edges.count(), spark.sparkContext.defaultParallelism, max_edges_per_part)
    if mode == "edge_cut":
        placed = staged(placed if placed is not None else P.vertex_hash(codes, n), "placed")
        held = staged(P.edge_cut(edges, placed).select("pid", "src", "dst", "w"), "cut")
        owners = placed.select("vid", F.col("part").alias("master_pid"))
        replicas = P.replicas_of(held).union(owners.select("master_pid", "vid")).distinct().join(owners, "vid")
    else:
        held = staged(cut.assign(edges, n).select("pid", "src", "dst", "w"), "cut")
        replicas = P.build_routing(P.replicas_of(held).union(P.place_isolated(Graph(held, codes), n)))
    largest = held.groupBy("pid").agg(F.count("*").alias("c")).agg(F.max("c")).first()[0] or 0
    if largest > max_edges_per_part:
        raise ValueError(f"a part holds {largest} edges, more than {max_edges_per_part}: raise the number of parts")
    counts = replicas.groupBy("vid").agg(F.count("*").alias("copies"))
    ends = P.degrees(edges).select("vid", "d_out", "d_in")
    # Compressed files and rows are small beside the hash tables made of them: sides that grow with the graph are never broadcast.
    replicas = replicas.join(counts.hint("merge"), "vid").join(ends.hint("merge"), "vid", "left").join(codes.hint("merge"), "vid", "left")
    degree = lambda c: F.coalesce(c, F.lit(0)).cast("long").alias(c)
    replicas = staged(replicas.select("pid", "vid", "master_pid", (F.col("copies") > 1).alias("frontier"), degree("d_out"), degree("d_in"), "label"), "replicas")
    for done in (edges, codes):
        drop_path(spark, staged_path(done))
    folder = fresh_path(spark, "parts")
    fs, root = _fs(folder)
    fs.create_dir(root, recursive=True)

    def write(key: tuple, e: pa.Table, v: pa.Table) -> pa.Table:
        pid = key[0].as_py()
        base = _vertex_arrays(v)
        vids = base["vids"]
        src, dst = (np.searchsorted(vids, e.column(c).to_numpy()).astype(np.int32) for c in ("src", "dst"))
        order = np.lexsort((dst, src))
        arcs = {"src": src[order], "dst": dst[order], "w": e.column("w").to_numpy()[order]}
        return pa.table({"pid": pa.array([pid], pa.int32()), "vertices": [save_arrays(folder, f"vertices-{pid}", base)], "edges": [save_arrays(folder, f"edges-{pid}", arcs)]})

    by_part = lambda df: _deal(df, n).groupBy("pid")
    made = staged(by_part(held).cogroup(by_part(replicas.select("pid", "vid", "master_pid", "frontier", "d_out", "d_in", "label"))).applyInArrow(write, "pid int, vertices string, edges string"), "part-files")
    files = {r["pid"]: (r["vertices"], r["edges"]) for r in made.collect()}  # a row per part
    return Layout(n, mode, folder, files, held, replicas, _routes(replicas), time.time() - began, spark)


def out_edge_layout(graph: Graph, n: int, max_edges_per_part: int = 64_000_000) -> Layout:
    """The edge-cut by vertex hash for programs whose owners read out-edges alone: an edge lies with its source, and a ghost is a target elsewhere.

    A worker gathers a part whole, so there are ``n`` parts, or the multiple of ``n`` that gives a part about ``P.PART_ROWS`` edges and
    vertices. The out-edges of one vertex are never divided. Parts find their ghosts themselves, so no shuffle but the dealing moves edges.
    A target that the view does not list has no label and no owner.
    """
    began = time.time()
    spark = graph.edges.sparkSession
    edges = staged(graph.edges.where("src is not null and dst is not null").select("src", "dst", F.col("w").cast("long").alias("w")), "edges")
    owners = staged(graph.vertices.where("vid is not null").groupBy("vid").agg(F.min("label").cast("string").alias("label")), "vertices")
    n = P.choose_parts(edges.count() + owners.count(), n, P.PART_ROWS)
    held = edges.select(P.vertex_part("src", n).alias("pid"), "src", "dst", "w")
    largest = held.groupBy("pid").agg(F.count("*").alias("c")).agg(F.max("c")).first()[0] or 0
    if largest > max_edges_per_part:
        raise ValueError(f"a part holds {largest} edges, more than {max_edges_per_part}: the out-edges of one vertex cannot be divided")
    folder = fresh_path(spark, "parts")
    fs, root = _fs(folder)
    fs.create_dir(root, recursive=True)

    def write_edges(key: tuple, e: pa.Table, v: pa.Table) -> pa.Table:
        pid = key[0].as_py()
        src, dst, listed = e.column("src").to_numpy(), e.column("dst").to_numpy(), v.column("vid").to_numpy()
        vids = np.unique(np.concatenate([src, dst, listed]))
        label = np.full(len(vids), -1)
        label[np.searchsorted(vids, listed)] = np.arange(len(listed))
        src, dst = np.searchsorted(vids, src).astype(np.int32), np.searchsorted(vids, dst).astype(np.int32)
        order = np.lexsort((dst, src))
        name = save_arrays(folder, f"edges-{pid}", narrow({"src": src[order], "dst": dst[order], "w": e.column("w").to_numpy()[order]}))
        ends = [pa.array(np.bincount(x, minlength=len(vids))) for x in (src, dst)]
        return pa.table([
            pa.array(np.full(len(vids), pid, np.int32)), pa.array(vids), v.column("label").take(pa.array(label, mask=label < 0)), *ends,
            pa.concat_arrays([pa.array([name]), pa.nulls(len(vids) - 1, pa.string())])], names=["pid", "vid", "label", "d_out", "d_in", "edges"])

    by_part = lambda df: _deal(df, n).groupBy("pid")
    listed = owners.select(P.vertex_part("vid", n).alias("pid"), "vid", "label")
    found = staged(by_part(held).cogroup(by_part(listed)).applyInArrow(write_edges, "pid int, vid long, label string, d_out long, d_in long, edges string"), "ends")
    arcs = {r["pid"]: r["edges"] for r in found.where("edges is not null").select("pid", "edges").collect()}  # a row per part
    many = int(spark.conf.get("spark.sql.shuffle.partitions"))
    routes = found.select("vid", "pid", P.vertex_part("vid", n).alias("master_pid"), "label", "d_out", "d_in").repartition(many, "vid").persist()
    routes.count()  # adaptive plans know the partitioning of a cached table only once it is filled
    for done in (edges, owners):
        drop_path(spark, staged_path(done))
    one = Window.partitionBy("vid")  # at most a row per part, where the routes are
    replicas = routes.select(
        "pid", "vid", "master_pid", (F.count("*").over(one) > 1).alias("frontier"), F.sum("d_out").over(one).alias("d_out"), F.sum("d_in").over(one).alias("d_in"), F.max("label").over(one).alias("label"))

    def write_vertices(key: tuple, v: pa.Table) -> pa.Table:
        pid = key[0].as_py()
        return pa.table({"pid": pa.array([pid], pa.int32()), "vertices": [save_arrays(folder, f"vertices-{pid}", narrow(_vertex_arrays(v)))]})

    made = staged(by_part(replicas).applyInArrow(write_vertices, "pid int, vertices string"), "part-files")
    files = {r["pid"]: (r["vertices"], arcs[r["pid"]]) for r in made.collect()}  # a row per part
    layout = Layout(n, "edge_cut", folder, files, None, replicas, routes, 0.0, spark)
    arcs_of = lambda p: {"src": p.vids[p.src], "dst": p.vids[p.dst], "w": p.w, "pid": np.full(len(p.src), p.pid, np.int32)}
    layout.edges = each_part(layout, arcs_of, "src long, dst long, w long, pid int").hint("merge")  # the parts hold them; there is no second copy
    layout.seconds = time.time() - began
    return layout


def _vertex_arrays(v: pa.Table) -> dict[str, np.ndarray]:
    """A part's replicas as arrays, by vertex."""
    order = np.argsort(v.column("vid").to_numpy(), kind="stable")
    label = v.column("label").combine_chunks().dictionary_encode()
    code = label.indices.fill_null(-1).to_numpy(zero_copy_only=False)[order]
    take = lambda c: v.column(c).to_numpy(zero_copy_only=False)[order]
    return {"vids": take("vid"), "master_pid": take("master_pid"), "frontier": take("frontier").astype(bool), "d_out": take("d_out"), "d_in": take("d_in"), "code": code.astype(np.int32), "labels": np.array(label.dictionary.to_pylist(), str)}


def _deal(rows: DataFrame, n: int) -> DataFrame:
    """A task for each part; many small parts (blocks) share tasks by hash."""
    many = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return rows.repartitionById(n, F.col("pid")) if n <= 4 * many else rows.repartition("pid")


class Part:
    """One part inside a kernel: sorted vertex ids, and edges as indexes into them, by source and then target. Edges load when asked for."""

    def __init__(self, pid: int, folder: str, files: tuple[str, str]):
        self.pid, self._folder, self._files = pid, folder, files
        base = _kept(folder, files[0])
        self.vids, self.master_pid, self.frontier, self.d_out, self.d_in, self.code, self.labels = (base[k] for k in VERTEX_FIELDS)
        self.owned = self.master_pid == pid
        self.visited = 0
        self._arcs: dict[str, np.ndarray] | None = None
        self._out: np.ndarray | None = None
        self._in: tuple | None = None

    src = property(lambda self: self._edges["src"])
    dst = property(lambda self: self._edges["dst"])
    w = property(lambda self: self._edges["w"])

    @property
    def _edges(self) -> dict[str, np.ndarray]:
        if self._arcs is None:
            self._arcs = _kept(self._folder, self._files[1])
        return self._arcs

    # the programming surface over a part
    def index_of(self, ids: np.ndarray) -> np.ndarray:
        return np.searchsorted(self.vids, ids)

    @property
    def out_ptr(self) -> np.ndarray:
        """Where each vertex's out-edges begin."""
        if self._out is None:
            self._out = np.searchsorted(self.src, np.arange(len(self.vids) + 1))
        return self._out

    @property
    def in_order(self) -> tuple[np.ndarray, np.ndarray]:
        """Edges by target, and where each vertex's in-edges begin."""
        if self._in is None:
            order = np.argsort(self.dst, kind="stable")
            self._in = order, np.searchsorted(self.dst[order], np.arange(len(self.vids) + 1))
        return self._in

    def children(self, i: int) -> np.ndarray:
        return self.dst[self.out_ptr[i] : self.out_ptr[i + 1]]

    def parents(self, i: int) -> np.ndarray:
        order, ptr = self.in_order
        return self.src[order[ptr[i] : ptr[i + 1]]]

    def degree(self, i: int) -> tuple[int, int]:
        """Out- and in-degree over all parts."""
        return int(self.d_out[i]), int(self.d_in[i])

    def edge(self, i: int, j: int) -> int | None:
        """Weight of an edge held here, by binary search among the source's targets."""
        a, b = self.out_ptr[i], self.out_ptr[i + 1]
        at = a + np.searchsorted(self.dst[a:b], j)
        return int(self.w[at]) if at < b and self.dst[at] == j else None

    def out_edges(self, vertices: np.ndarray) -> np.ndarray:
        """Indexes of the edges that leave any of the vertices."""
        return _spans(self.out_ptr, vertices)

    def in_edges(self, vertices: np.ndarray) -> np.ndarray:
        order, ptr = self.in_order
        return order[_spans(ptr, vertices)]


def _spans(ptr: np.ndarray, vertices: np.ndarray) -> np.ndarray:
    size = ptr[vertices + 1] - ptr[vertices]
    return np.repeat(ptr[vertices] - np.cumsum(size) + size, size) + np.arange(size.sum())


def each_part(layout: Layout, f: Callable[[Part], dict], schema: str) -> DataFrame:
    """The columns that ``f`` gives for every part; only part numbers are dealt, and each task loads its own part."""
    folder, files = layout.folder, layout.files
    names = [x.split()[0] for x in schema.split(", ")]

    def load(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for pid in batch.column(0).to_pylist():
                found = f(Part(pid, folder, files[pid]))
                yield pa.RecordBatch.from_arrays([pa.array(found[c]) for c in names], names=names)

    pids = layout.spark.createDataFrame([(p,) for p in sorted(files)], "pid int") if files else layout.spark.createDataFrame([], "pid int")
    return _deal(pids, layout.n).mapInArrow(load, schema)


# --- programs -------------------------------------------------------------------------------------------------------------------------


@dataclass
class Inbox:
    """What a part was told: indexes of its vertices, the folded values, and which came from another part's master."""

    at: np.ndarray
    value: np.ndarray
    far: np.ndarray


class Program:
    """A whole-subgraph program. ``kind`` and ``how`` name the values sent and their fold, ``spread`` who gets the result.

    ``start`` gives a part's first state, ``compute`` the next: it changes the arrays of ``state``, and returns the indexes it emits, their
    values, and the weight still pending inside the part (a part with any runs again; one without halts until it is told something).
    Both must be pure functions of their arguments, so that a retried task gives the same rows. ``news`` marks the rows of
    an inbox that tell the part something; the others are the part's own values coming back.
    """

    kind = "long"  # long, double, or array<long> of ``width`` numbers
    how = "min"
    spread = "all"  # all replicas, the master, or the mirrors
    width = 0
    all_active_rounds = 1

    def start(self, part: Part) -> dict[str, np.ndarray]:
        raise NotImplementedError

    def first_inbox(self, layout: Layout) -> DataFrame | None:
        """(pid, vid, master_pid, value) told before round 0."""
        return None

    def compute(self, part: Part, state: dict[str, np.ndarray], inbox: Inbox, round_: int) -> tuple[np.ndarray, np.ndarray, float]:
        raise NotImplementedError

    def news(self, state: dict[str, np.ndarray], inbox: Inbox) -> np.ndarray:
        return np.ones(len(inbox.at), bool)

    def settled(self, pending: float) -> bool:
        return False


@dataclass
class RunResult:
    values: DataFrame
    rounds: int
    seconds: float
    ledger: list[dict]
    states: dict[int, str] = field(default_factory=dict)


def _schema(program: Program) -> str:
    return f"sent boolean, pid int, vid long, master_pid int, value {program.kind}, state string, visited long, pending double, ms double, n_out long, n_far long, n_told long, mass double"


def _values(column: pa.ChunkedArray, program: Program) -> np.ndarray:
    if program.width:
        return column.combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(-1, program.width)
    return column.to_numpy()


def _value_array(values: np.ndarray, program: Program) -> pa.Array:
    if program.width:
        flat = np.ascontiguousarray(values, np.int64).reshape(-1)
        return pa.ListArray.from_arrays(pa.array(np.arange(0, len(flat) + 1, program.width, dtype=np.int32)), pa.array(flat))
    return pa.array(values, pa.float64() if program.kind == "double" else pa.int64())


def _kernel(program: Program, round_: int, folder: str, files: dict, states: dict, stale: dict):
    def step(key: tuple, rows: pa.Table) -> pa.Table:
        began = time.perf_counter()
        pid = key[0].as_py()
        part = Part(pid, folder, files[pid])
        state = load_arrays(folder, states[pid]) if pid in states else program.start(part)
        if pid in stale:  # the round that replaced it is complete
            _remove(folder, stale[pid])
        rows = rows.filter(pc.is_valid(rows.column("vid")))
        box = Inbox(part.index_of(rows.column("vid").to_numpy()), _values(rows.column("value"), program), rows.column("master_pid").to_numpy() != pid)
        told = int((box.far & program.news(state, box)).sum())
        out, values, pending = program.compute(part, state, box, round_)
        name = save_arrays(folder, f"state-{pid}-{round_}", state)
        n = len(out)
        far = int((part.master_pid[out] != pid).sum())
        mass = float(values.sum()) if program.how == "sum" else 0.0
        fixed = lambda x, kind: pa.concat_arrays([pa.nulls(n, kind), pa.array([x], kind)])
        stat = [fixed(name, pa.string()), fixed(part.visited, pa.int64()), fixed(float(pending), pa.float64()), fixed((time.perf_counter() - began) * 1000, pa.float64())]
        stat += [fixed(x, pa.int64()) for x in (n, far, told)] + [fixed(mass, pa.float64())]
        value = _value_array(values, program)
        columns = [
            pa.array(np.r_[np.ones(n, bool), False]), pa.array(np.full(n + 1, pid, np.int32)), pa.concat_arrays([pa.array(part.vids[out], pa.int64()), pa.nulls(1, pa.int64())]),
            pa.concat_arrays([pa.array(part.master_pid[out], pa.int32()), pa.nulls(1, pa.int32())]), pa.concat_arrays([value, pa.nulls(1, value.type)]), *stat]
        return pa.Table.from_arrays(columns, names=[f.split()[0] for f in _schema(program).split(", ")])

    return step


def fold(out: DataFrame, program: Program) -> DataFrame:
    """(vid, folded): what the masters make of their own and their mirrors' values."""
    if program.width:
        value = F.array(*[F.sum(F.col("value")[k]) for k in range(program.width)])
    else:
        value = {"min": F.min, "max": F.max, "sum": F.sum, "or": F.bit_or}[program.how]("value")
    return out.groupBy("vid").agg(value.alias("folded"))


def spread(folded: DataFrame, layout: Layout, program: Program) -> DataFrame:
    """(pid, vid, master_pid, value) for the replicas that are told."""
    told = folded.join(layout.routes, "vid")
    if program.spread != "all":
        told = told.where("pid = master_pid" if program.spread == "master" else "pid <> master_pid")
    return told.select("pid", "vid", "master_pid", F.col("folded").alias("value"))


def _snapshot(folder: str, run_id: str, round_: int, kept: dict) -> None:
    fs, root = _fs(folder)
    with fs.open_output_stream(f"{root}/run-{run_id}-{round_:06d}.json") as out:
        out.write(json.dumps(kept).encode())


def run(layout: Layout, program: Program, max_rounds: int | None = None, snapshots: str | None = None, resume_from: int | None = None, values: Callable | None = None, schema: str = "", rounds: int | None = None) -> RunResult:
    """Rounds until nothing is on its way and nothing is pending, or ``rounds`` of them.

    ``snapshots`` names the run and keeps what a restart needs; with ``resume_from`` it goes on after that round of the named run.
    """
    began = time.time()
    spark, schema_out = layout.spark, _schema(program)
    states: dict[int, str] = {}
    stale: dict[int, str] = {}
    waiting: set[int] = set()
    out: DataFrame | None = None
    ledger: list[dict] = []
    round_ = 0
    inbox = program.first_inbox(layout)
    if resume_from is not None:
        fs, root = _fs(layout.folder)
        with fs.open_input_stream(f"{root}/run-{snapshots}-{resume_from:06d}.json") as f:
            kept = json.loads(f.read())
        states, waiting, ledger, round_ = {int(p): s for p, s in kept["states"].items()}, set(kept["waiting"]), kept["ledger"], resume_from + 1
        out = spark.read.schema(schema_out).parquet(kept["out"])
        inbox = spread(fold(out.where("sent"), program), layout, program) if kept["sent"] else None
    elif round_ < program.all_active_rounds:
        waiting = set(layout.files)
    old: list[DataFrame] = []
    while (inbox is not None or waiting) and round_ != rounds:
        if max_rounds is not None and round_ >= max_rounds:
            raise RuntimeError(f"not settled after {max_rounds} rounds")
        t0 = time.time()
        if waiting:
            wake = spark.createDataFrame([(p,) for p in sorted(waiting)], "pid int").select("pid", F.lit(None).cast("long").alias("vid"), F.lit(None).cast("int").alias("master_pid"), F.lit(None).cast(program.kind).alias("value"))
            inbox = wake if inbox is None else inbox.union(wake)
        step = _kernel(program, round_, layout.folder, layout.files, states, stale)
        out = staged(_deal(inbox, layout.n).groupBy("pid").applyInArrow(step, schema_out), "round")
        stats = out.where("not sent").drop("sent", "vid", "master_pid", "value").collect()  # a row per part that ran
        stale = {} if snapshots else {r["pid"]: states[r["pid"]] for r in stats if r["pid"] in states}
        states |= {r["pid"]: r["state"] for r in stats}
        n_out, mass = sum(r["n_out"] for r in stats), sum(r["mass"] for r in stats)
        pending = sum(r["pending"] for r in stats)
        times = [r["ms"] for r in stats] or [0.0]
        if ledger:
            ledger[-1]["pairs_down"] = sum(r["n_told"] for r in stats)
        ledger.append({
            "round": round_, "pairs_up": sum(r["n_far"] for r in stats), "pairs_down": 0, "active": len(stats), "edges_visited": sum(r["visited"] for r in stats), "compute_min_ms": min(times), "compute_mean_ms": sum(times) / len(times),
            "compute_max_ms": max(times), "network_ms": max(0.0, (time.time() - t0) * 1000 - max(times)), "sync_ms": max(times) - min(times), "parts": [[r["pid"], r["ms"], r["visited"], r["n_far"] + r["n_told"]] for r in stats]})
        waiting = {r["pid"] for r in stats if r["pending"]}
        if round_ + 1 < program.all_active_rounds:
            waiting = set(layout.files)
        inbox = spread(fold(out.where("sent"), program), layout, program) if n_out else None
        if snapshots:
            _snapshot(layout.folder, snapshots, round_, {"states": states, "waiting": sorted(waiting), "out": staged_path(out), "sent": n_out, "ledger": ledger})
        else:
            old.append(out)
            if len(old) > 2:
                drop_path(spark, staged_path(old.pop(0)))
        round_ += 1
        if program.settled(pending + mass):
            break
    result = RunResult(None, round_, time.time() - began, ledger, dict(states))
    result.out = out
    if values is not None:
        result.values = part_values(layout, program, states, values, schema)
    return result


def part_values(layout: Layout, program: Program, states: dict[int, str], values: Callable, schema: str) -> DataFrame:
    """Columns that ``values`` takes from each part and its last state.

    The planner takes their size for that of the part numbers they come from; without the hint it would broadcast them through the driver.
    """
    folder = layout.folder
    return each_part(layout, lambda part: values(part, load_arrays(folder, states[part.pid]) if part.pid in states else program.start(part)), schema).hint("merge")
