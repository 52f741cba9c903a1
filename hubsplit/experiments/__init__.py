"""The experiment workloads: every contender's time, rounds, pairs, balance and copies on the stand-in graphs.

``python bench.py --experiments [w2,w4,...]`` prints one JSON line a row (BENCH_SF_DIR, BENCH_CPUS as for the bench). A row that varies
the workers comes from a process of its own with so many cores and parts. Partitioning and running are timed apart.
"""

from __future__ import annotations

import json
import os
import subprocess
import sys
import time
from pathlib import Path

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from hubsplit.plans import ledger as L
from hubsplit.plans import metrics, programs, rivals
from hubsplit.plans import partition as P
from hubsplit.plans.program_queries import most_linked
from hubsplit.plans.runtime import make_layout
from hubsplit.sources.graphs import Graph, build, kron_graph

HYBRIDS = ("hybrid-ldch", "hybrid-ueh")
CONTENDERS = ("hybrid-ldch", "twin-multilevel", "vc-bsp", "vc-gas", "block")
# Published ratios of a rival's time to the hybrid's, by program and rival.
PUBLISHED = {
    ("cc", "vc-bsp"): 2.4, ("cc", "vc-gas"): 2.4, ("cc", "block"): 1.3, ("cc", "twin-multilevel"): 1.4, ("cc", "hybrid-ueh"): 1.96, ("gsim", "twin-multilevel"): 6.7, ("gsim", "block"): 8.5, ("gsim", "vc-bsp"): 12.8,
    ("gsim", "vc-gas"): 13.4, ("sssp", "vc-bsp"): 455.0, ("sssp", "vc-gas"): 413.0, ("sssp", "block"): 6.3, ("sssp", "twin-multilevel"): 1.6, ("sssp", "hybrid-ueh"): 1.2, ("sssp", "twin-hash"): 1.31,
}


def graph(spark: SparkSession, d: str, view: str) -> Graph:
    """A view by name; ``kron:<scale>`` is a Kronecker graph of any scale."""
    return kron_graph(spark, int(view.split(":")[1])) if view.startswith("kron:") else build(spark, d, view)


def place(g: Graph, contender: str, n: int):
    """The contender's layout, and its name: a multilevel cut that refuses the graph is replaced by a random one, and says so."""
    began = time.time()
    if contender in HYBRIDS:
        return make_layout(g, P.CUTS[contender.split("-")[1]], n), contender
    if contender == "block":
        layout = rivals.block_layout(g, n)
    elif contender == "twin-multilevel":
        try:
            layout = make_layout(g, None, n, "edge_cut", rivals.multilevel_cut(g, n))
        except ValueError:
            layout, contender = make_layout(g, None, n, "edge_cut"), "twin-hash (multilevel refused the graph)"
    else:
        layout = make_layout(g, None, n, "edge_cut")
    layout.seconds = time.time() - began
    return layout, contender


def _run(layout, g: Graph, program: str, tol: float):
    if program == "cc":
        return programs.connected_components(layout)
    if program.startswith("sssp"):
        return programs.shortest_paths(layout, most_linked(g) if g.directed else 0, program == "sssp-w")
    if program == "pagerank":
        return programs.pagerank(layout, tol=tol)
    return programs.graph_simulation(layout, programs.PATTERNS[program.split("-")[1]][1])


def _rival(g: Graph, program: str, cut, n: int, tol: float):
    if program == "cc":
        return rivals.cc(g, cut, n)
    if program.startswith("sssp"):
        return rivals.sssp(g, most_linked(g) if g.directed else 0, program == "sssp-w", cut, n)
    if program == "pagerank":
        return rivals.pagerank_sync(g, None, cut=cut, n=n, until=tol)
    return rivals.gsim(g, programs.PATTERNS[program.split("-")[1]][1], cut, n)


def contend(spark: SparkSession, d: str, program: str, view: str, contender: str, n: int, tol: float = 1e-6) -> dict:
    """One contender's row: time to partition and to run, rounds, pairs, and for partitioned models balance, copies, time split and trace."""
    g = graph(spark, d, view)
    row = {"graph": view, "program": program, "contender": contender, "n": n, "cores": spark.sparkContext.defaultParallelism}
    if contender.startswith("vc-"):
        r = _rival(g, program, P.CUTS["ldch"] if contender == "vc-gas" else None, n, tol)
        r.values.write.format("noop").mode("overwrite").save()
        return row | {"partition_s": 0.0, "run_s": round(r.seconds, 2), "rounds": r.rounds, "pairs": r.messages}
    if contender == "block" and program == "cc":  # blocks are merged as vertices of a small graph
        began = time.time()
        blocks = rivals.partition_bfs(g)
        cells = time.time() - began
        rivals.block_cc(g, blocks).write.format("noop").mode("overwrite").save()
        return row | {"partition_s": round(cells, 2), "run_s": round(time.time() - began - cells, 2), "rounds": None, "pairs": None}
    layout, row["contender"] = place(g, contender, n)
    began = time.time()
    r = _run(layout, g, program, tol)
    r.values.write.format("noop").mode("overwrite").save()
    seconds = time.time() - began
    sizes = [x["count"] for x in layout.edges.groupBy("pid").count().collect()]
    copies = layout.replicas.agg(F.count("*").alias("r"), F.countDistinct("vid").alias("v")).first()
    layout.release()
    return row | {"partition_s": round(layout.seconds, 2), "run_s": round(seconds, 2)} | measures(r, layout.n, sizes, copies["r"], copies["v"])


def measures(r, n: int, sizes: list[int], replicas: int, vertices: int) -> dict:
    """What a run's ledger says: pairs, bytes, processed edges, the time split, work imbalance, and the first hundred rounds."""
    t = L.totals(r.ledger)
    split = {f"{k}_s": round(sum(x[f"{k}_ms"] for x in r.ledger) / 1000, 3) for k in ("compute_min", "compute_mean", "compute_max", "network", "sync")}
    total, per_part = L.peps(t["edges_visited"], max(r.seconds, 1e-9), n)
    skew = [max(p[2] for p in x["parts"]) * len(x["parts"]) / sum(p[2] for p in x["parts"]) for x in r.ledger if sum(p[2] for p in x["parts"])]
    return {
        "rounds": r.rounds, "pairs": t["pairs_up"] + t["pairs_down"], "pairs_up": t["pairs_up"], "pairs_down": t["pairs_down"], "bytes": 16 * (t["pairs_up"] + t["pairs_down"]), "peps": round(total), "peps_per_part": round(per_part), **split,
        "work_imbalance": round(max(skew), 3) if skew else None, "imbalance": round(max(sizes) * n / sum(sizes), 4) if sizes else None, "copies": round(replicas / vertices, 4) if vertices else None,
        "trace": [[x["pairs_up"], x["pairs_down"], x["active"]] for x in r.ledger[:100]]}


def with_ratios(rows: list[dict]) -> list[dict]:
    """Adds each contender's time, pairs and rounds over the first one's of its program, graph and n, and the published ratio of times."""
    base: dict[tuple, dict] = {}
    for r in rows:
        key = (r["graph"], r["program"], r["n"], r["cores"])
        first = base.setdefault(key, r)
        over = lambda m, r=r, first=first: round(r[m] / first[m], 3) if r.get(m) and first.get(m) else None
        r["ratios"] = {"run_s": over("run_s"), "pairs": over("pairs"), "rounds": over("rounds"), "published_s": PUBLISHED.get((r["program"].split("-")[0], r["contender"]))}
    return rows


def in_process(d: str, program: str, view: str, contender: str, workers: int) -> dict:
    """The row of a process with so many cores and parts."""
    root = Path(__file__).resolve().parents[2]
    env = os.environ | {"BENCH_SF_DIR": d, "BENCH_CPUS": str(workers), "PYTHONPATH": f"{root}:{os.environ.get('PYTHONPATH', '')}"}
    out = subprocess.run([sys.executable, str(root / "bench.py"), "--row", program, view, contender, str(workers)], env=env, capture_output=True, text=True, check=True).stdout
    return json.loads(out.strip().splitlines()[-1])


def strong_scaling(d: str, program: str, views: tuple[str, ...], contenders: tuple[str, ...], workers: tuple[int, ...] = (1, 2, 4)) -> list[dict]:
    """The same graph with more and more workers."""
    rows = [in_process(d, program, v, c, k) for v in views for k in workers for c in contenders]
    first = {(r["graph"], r["contender"]): r["run_s"] for r in reversed(rows)}
    for r in rows:
        r["speed_up"] = round(first[r["graph"], r["contender"]] / r["run_s"], 3) if r["run_s"] else None
    return with_ratios(rows)


def weak_scaling(d: str, base_scale: int = 12, workers: tuple[int, ...] = (1, 2, 4)) -> list[dict]:
    """Kronecker graphs whose edges grow with the workers; processed edges per second and per part."""
    return [in_process(d, program, f"kron:{base_scale + k}", "hybrid-ldch", w) for program in ("cc", "pagerank") for k, w in enumerate(workers)]


def partition_quality(spark: SparkSession, d: str, views=("near_copy", "pagelink", "commerce", "docword", "kron:15"), parts=(4, 8, 32)) -> list[dict]:
    """Balance and copies of both hashes."""
    out = []
    for v in views:
        g = graph(spark, d, v)
        for n in parts:
            for cut in ("ueh", "ldch"):
                a = P.CUTS[cut].assign(g.edges, n).cache()
                out.append({"graph": v, "n": n, "cut": cut, "imbalance": round(metrics.imbalance(a, n).first()[0], 4), "rf": round(metrics.replication_factor(a).first()[0], 4)})
                a.unpersist()
    return out


def statistics(spark: SparkSession, d: str, views=("near_copy", "pagelink", "commerce", "road", "docword", "kron:15")) -> list[dict]:
    """Size, degrees and diameter (double sweep along both directions) of the graphs."""
    out = []
    for v in views:
        g = graph(spark, d, v)
        row = metrics.graph_stats(g.edges).first().asDict()
        layout = make_layout(g, P.CUTS["ldch"], 4, symmetric=True)
        row["diameter_at_least"] = programs.diameter(layout, most_linked(g))[0]
        layout.release()
        out.append({"graph": v, **row})
    return out


WEB = ("pagelink", "docword", "kron:13")
VARIANTS = ("hybrid-ldch", "hybrid-ueh", "twin-hash")
WORKLOADS = {
    "w1": lambda spark, d: statistics(spark, d),
    "w2": lambda spark, d: partition_quality(spark, d),
    "w3": lambda spark, d: with_ratios([contend(spark, d, "cc", v, c, 8) for v in ("near_copy", "docword", "pagelink") for c in HYBRIDS]),
    "w4": lambda spark, d: strong_scaling(d, "cc", ("near_copy",), CONTENDERS),
    "w5": lambda spark, d: [r for p, (v, _) in programs.PATTERNS.items() for r in strong_scaling(d, f"gsim-{p}", (v,), CONTENDERS, (1, 2, 4) if p == "P1" else (4,))],
    "w6": lambda spark, d: strong_scaling(d, "pagerank", WEB, ("hybrid-ldch", "twin-multilevel", "vc-bsp", "vc-gas"), (4,)) + strong_scaling(d, "pagerank", ("commerce",), ("hybrid-ldch", "twin-hash", "vc-bsp", "vc-gas")),
    "w7": lambda spark, d: strong_scaling(d, "sssp", ("road",), CONTENDERS) + strong_scaling(d, "sssp-w", ("road",), ("hybrid-ldch", "twin-multilevel", "block", "vc-bsp"), (4,)) + strong_scaling(d, "sssp", ("userchain",), ("hybrid-ldch", "twin-multilevel"), (4,)),
    "w8": lambda spark, d: with_ratios([contend(spark, d, "sssp", "road", c, 4) for c in ("hybrid-ldch", "twin-hash", "twin-multilevel")]),
    "w9": lambda spark, d: with_ratios([contend(spark, d, "sssp", v, c, 4) for v in WEB for c in VARIANTS]),
    "w10": lambda spark, d: with_ratios([contend(spark, d, "cc", "near_copy", c, 4) for c in ("hybrid-ldch", "twin-multilevel")]),
    "w11": lambda spark, d: with_ratios([contend(spark, d, p, v, c, 4) for p in ("cc", "sssp") for v in ("docword", "pagelink") for c in VARIANTS]),
    "w12": lambda spark, d: weak_scaling(d),
}


def print_all(spark: SparkSession, d: str, names: list[str] | None = None) -> list[dict]:
    """Runs the workloads and prints a line for each row."""
    out = []
    for name in names or WORKLOADS:
        for row in WORKLOADS[name](spark, d):
            out.append({"work": name, **row})
            print(json.dumps(out[-1]), flush=True)
    return out
