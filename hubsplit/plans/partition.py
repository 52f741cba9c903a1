"""Vertex-cuts, edge-cuts, replicas, masters and routing as DataFrame plans.

Only hash expressions and equi-joins: a cut of any size is one or two shuffles of its edges, and no shuffle meets a hub's edges under
one key. Hubs are the vertices above a degree that no more than ``HUB_LIMIT`` vertices can have; they are broadcast, and decide every edge
they touch at once. Only edges between two other vertices are joined by key.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from hubsplit.functions.hashing import SALT, hash32, hash32_sql
from hubsplit.shared_dir import staged, staged_path
from hubsplit.sources.graphs import Graph

#: At most so many hubs, 16 bytes each, are broadcast; a vertex below the floor is no hub in any graph.
HUB_LIMIT, HUB_FLOOR = 1_000_000, 1_000
#: Edges and vertices of a part that one Python worker gathers whole: at about 100 bytes each, with copies, what an executor's task can hold.
PART_ROWS = 1 << 20

# --- degrees ---------------------------------------------------------------------------------------------------------------------


def degrees(edges: DataFrame) -> DataFrame:
    """vid, d_in, d_out, d of every end, counted over all parts; one pre-aggregated shuffle."""
    ends = edges.select(F.explode(F.array(F.struct(F.col("src").alias("vid"), F.lit(1).alias("o"), F.lit(0).alias("i")), F.struct(F.col("dst").alias("vid"), F.lit(0).alias("o"), F.lit(1).alias("i")))).alias("x"))
    return ends.groupBy("x.vid").agg(F.sum("x.i").alias("d_in"), F.sum("x.o").alias("d_out"), F.count("*").alias("d"))


DEGREES_SQL = "SELECT vid, CAST(sum(i) AS BIGINT) AS d_in, CAST(sum(o) AS BIGINT) AS d_out, CAST(count(*) AS BIGINT) AS d FROM (SELECT src AS vid, 1 AS o, 0 AS i FROM e UNION ALL SELECT dst, 0, 1 FROM e) GROUP BY vid"

# --- vertex-cuts: an owner part for each edge ------------------------------------------------------------------------------------


class VertexCut:
    """Assigns every edge to exactly one part: adds ``pid`` to (src, dst, w)."""

    def __init__(self, salt: int = SALT, fast: bool = False):
        self.salt, self.fast = salt, fast

    def assign(self, edges: DataFrame, n: int) -> DataFrame:
        raise NotImplementedError

    def sql(self, n: int) -> str:
        """SELECT of src, dst, w, pid over the CTE ``e``."""
        raise NotImplementedError

    def _h(self, *parts: Column | str) -> Column:
        return hash32(*parts, salt=self.salt, fast=self.fast)


class UniformEdgeHash(VertexCut):
    """Hash of both ends; the canonical form orders them first, so that both arcs of a pair meet."""

    def __init__(self, canonical: bool = False, **kw):
        super().__init__(**kw)
        self.canonical = canonical

    def assign(self, edges, n):
        ends = (F.least("src", "dst"), F.greatest("src", "dst")) if self.canonical else ("src", "dst")
        return edges.withColumn("pid", (self._h(*ends) % n).cast("int"))

    def sql(self, n):
        ends = ("least(src, dst)", "greatest(src, dst)") if self.canonical else ("src", "dst")
        return f"SELECT src, dst, w, CAST({hash32_sql(*ends, salt=self.salt)} % {n} AS INT) AS pid FROM e"


class LowDegreeHash(VertexCut):
    """Hash of the end of smaller degree. Canonical: the ends are ordered by id before the rule, so a tie takes the smaller id."""

    def __init__(self, canonical: bool = True, degree: str = "d", **kw):
        super().__init__(**kw)
        self.canonical, self.degree = canonical, degree

    def owner_end(self, edges: DataFrame) -> DataFrame:
        edges = edges if staged_path(edges) else staged(edges.select("src", "dst", "w"), "edges")
        deg = staged(degrees(edges).select("vid", F.col(self.degree).alias("deg")), "degrees")
        a, b = (F.least("src", "dst"), F.greatest("src", "dst")) if self.canonical else (F.col("src"), F.col("dst"))
        above = max(HUB_FLOOR, (deg.agg(F.sum("deg")).first()[0] or 0) // HUB_LIMIT)  # fewer than HUB_LIMIT vertices have more
        hubs = deg.where(F.col("deg") > above)
        at = lambda df, end, name: df.select(F.col("vid").alias(end), F.col("deg").alias(name))
        e = edges.withColumns({"_a": a, "_b": b}).join(F.broadcast(at(hubs, "_a", "_ha")), "_a", "left").join(F.broadcast(at(hubs, "_b", "_hb")), "_b", "left")
        # With a hub at one end, the other end has the lower degree.
        near = e.where("_ha is not null or _hb is not null").withColumn("owner", F.when(F.col("_ha").isNull() | (F.col("_ha") <= F.col("_hb")), F.col("_a")).otherwise(F.col("_b")))
        low = deg.where(F.col("deg") <= above).hint("merge")  # it grows with the graph, and its compressed file does not show how much
        rest = e.where("_ha is null and _hb is null").join(at(low, "_a", "_da"), "_a").join(at(low, "_b", "_db"), "_b")
        rest = rest.withColumn("owner", F.when(F.col("_da") <= F.col("_db"), F.col("_a")).otherwise(F.col("_b")))
        return near.select("src", "dst", "w", "owner").union(rest.select("src", "dst", "w", "owner"))

    def assign(self, edges, n):
        return self.owner_end(edges).select("src", "dst", "w", (self._h("owner") % n).cast("int").alias("pid"))

    def sql(self, n):
        a, b = ("least(src, dst)", "greatest(src, dst)") if self.canonical else ("src", "dst")
        return f"""SELECT src, dst, w, CAST({hash32_sql('owner', salt=self.salt)} % {n} AS INT) AS pid FROM (
            SELECT e.src, e.dst, e.w, CASE WHEN p.{self.degree} <= q.{self.degree} THEN p.vid ELSE q.vid END AS owner
            FROM e JOIN ({DEGREES_SQL}) p ON p.vid = {a} JOIN ({DEGREES_SQL}) q ON q.vid = {b})"""


class SourceHash(VertexCut):
    """One-dimensional: all out-edges of a vertex in one part."""

    def assign(self, edges, n):
        return edges.withColumn("pid", (self._h("src") % n).cast("int"))

    def sql(self, n):
        return f"SELECT src, dst, w, CAST({hash32_sql('src', salt=self.salt)} % {n} AS INT) AS pid FROM e"


class GridHash(VertexCut):
    """Two-dimensional: a row by source and a column by target; a vertex has at most rows + columns - 1 copies."""

    @staticmethod
    def shape(n: int) -> tuple[int, int]:
        rows = max(r for r in range(1, int(n**0.5) + 1) if n % r == 0)
        return rows, n // rows

    def assign(self, edges, n):
        r, c = self.shape(n)
        return edges.withColumn("pid", ((self._h("src") % r) * c + self._h("dst") % c).cast("int"))

    def sql(self, n):
        r, c = self.shape(n)
        return f"SELECT src, dst, w, CAST(({hash32_sql('src', salt=self.salt)} % {r}) * {c} + {hash32_sql('dst', salt=self.salt)} % {c} AS INT) AS pid FROM e"


class SpillingLowDegreeHash(LowDegreeHash):
    """LDCH whose overfull parts pass edges above a slack over the mean on by edge hash; one small aggregate per part."""

    def __init__(self, slack: float = 1.1, **kw):
        super().__init__(**kw)
        self.slack = slack

    def assign(self, edges, n):
        first = super().assign(edges, n)
        sizes = first.groupBy("pid").agg(F.count("*").alias("size"))
        mean = sizes.agg((F.sum("size") / n).alias("mean"))
        over = sizes.join(F.broadcast(mean)).select("pid", F.greatest(F.lit(0.0), 1 - self.slack * F.col("mean") / F.col("size")).alias("share"))
        draw = self._h(F.least("src", "dst"), F.greatest("src", "dst"), F.lit("spill")) / F.lit(4294967296.0)
        moved = first.join(F.broadcast(over), "pid")  # one row per part
        again = (self._h(F.least("src", "dst"), F.greatest("src", "dst")) % n).cast("int")
        return moved.select("src", "dst", "w", F.when(draw < F.col("share"), again).otherwise(F.col("pid")).alias("pid"))


CUTS = {"ueh": UniformEdgeHash(), "ueh_canonical": UniformEdgeHash(canonical=True), "ldh": LowDegreeHash(canonical=False), "ldch": LowDegreeHash(), "source_hash": SourceHash(), "grid": GridHash()}

# --- what follows from a cut -----------------------------------------------------------------------------------------------------


def replicas_of(assigned: DataFrame) -> DataFrame:
    return assigned.select("pid", F.explode(F.array("src", "dst")).alias("vid")).distinct()


REPLICAS_SQL = "SELECT DISTINCT pid, vid FROM (SELECT pid, src AS vid FROM a UNION ALL SELECT pid, dst FROM a)"


def place_isolated(graph: Graph, n: int) -> DataFrame:
    ends = graph.edges.select(F.explode(F.array("src", "dst")).alias("vid")).distinct()
    return graph.vertices.select("vid").distinct().join(ends, "vid", "left_anti").select((hash32("vid") % n).cast("int").alias("pid"), "vid")


def mark_frontier(replicas: DataFrame) -> DataFrame:
    """pid, vid, copies and is_frontier; counted by an aggregate and joined back, so a hub's copies are counted before the shuffle."""
    counts = replicas.groupBy("vid").agg(F.count("*").alias("copies"))
    return replicas.join(counts, "vid").select("pid", "vid", "copies", (F.col("copies") > 1).alias("is_frontier"))


def elect_master(replicas: DataFrame, policy: str = "hash") -> DataFrame:
    """vid, master_pid. ``hash``: uniform and repeatable; ``min_pid``; ``single``: the part of smallest number for all, where a vertex has it or not."""
    if policy == "single":
        return replicas.groupBy("vid").agg(F.lit(0).alias("master_pid"))
    if policy == "min_pid":
        return replicas.groupBy("vid").agg(F.min("pid").alias("master_pid"))
    return replicas.groupBy("vid").agg(F.min(F.struct(hash32("vid", "pid").alias("h"), "pid"))["pid"].alias("master_pid"))


MASTERS_SQL = f"SELECT vid, CAST(arg_min(pid, {hash32_sql('vid', 'pid')} * 100000 + pid) AS INT) AS master_pid FROM r GROUP BY vid"


def build_routing(replicas: DataFrame, policy: str = "hash") -> DataFrame:
    """pid, vid, master_pid of every replica: each mirror knows its master, and the rows of a master's vertex name its mirrors."""
    return replicas.join(elect_master(replicas, policy).hint("merge"), "vid").select("pid", "vid", "master_pid")


# --- edge-cuts ---------------------------------------------------------------------------------------------------------------------


def vertex_part(vid: Column | str, n: int, salt: int = SALT) -> Column:
    return (hash32(vid, salt=salt) % n).cast("int")


def vertex_hash(vertices: DataFrame, n: int, salt: int = SALT) -> DataFrame:
    return vertices.select("vid", vertex_part("vid", n, salt).alias("part")).distinct()


def edge_cut(edges: DataFrame, placed: DataFrame) -> DataFrame:
    """Edges held by the parts of both ends: pid, src, dst, w, and whether this copy belongs to the source's part."""
    p, q = placed.select(F.col("vid").alias("src"), F.col("part").alias("ps")), placed.select(F.col("vid").alias("dst"), F.col("part").alias("pd"))
    both = edges.join(p, "src").join(q, "dst")
    return both.select("src", "dst", "w", "ps", F.explode(F.array_distinct(F.array("ps", "pd"))).alias("pid")).select("src", "dst", "w", "pid", (F.col("pid") == F.col("ps")).alias("primary"))


def edge_cut_to_vertex_cut(placed: DataFrame, edges: DataFrame, end: str = "src") -> DataFrame:
    """The owner of an edge is the part of one end: its source, the end of lower degree, or the end in the lighter part."""
    p, q = placed.select(F.col("vid").alias("src"), F.col("part").alias("ps")), placed.select(F.col("vid").alias("dst"), F.col("part").alias("pd"))
    e = edges.join(p, "src").join(q, "dst")
    if end == "low_degree":
        d = degrees(edges).select("vid", "d")
        e = e.join(d.select(F.col("vid").alias("src"), F.col("d").alias("ds")), "src").join(d.select(F.col("vid").alias("dst"), F.col("d").alias("dd")), "dst")
        pick = F.when(F.col("ds") <= F.col("dd"), F.col("ps")).otherwise(F.col("pd"))
    elif end == "lighter":
        weight = placed.groupBy("part").agg(F.count("*").alias("size"))
        e = e.join(F.broadcast(weight.select(F.col("part").alias("ps"), F.col("size").alias("ws"))), "ps").join(F.broadcast(weight.select(F.col("part").alias("pd"), F.col("size").alias("wd"))), "pd")  # one row per part
        pick = F.when((F.col("ws") < F.col("wd")) | ((F.col("ws") == F.col("wd")) & (F.col("ps") <= F.col("pd"))), F.col("ps")).otherwise(F.col("pd"))
    else:
        pick = F.col("ps")
    return e.select("src", "dst", "w", pick.alias("pid"))


def choose_parts(n_edges: int, workers: int, max_edges_per_part: int = 64_000_000) -> int:
    """As many parts as workers, or the smallest multiple of them that keeps a part under the cap."""
    waves = max(1, -(-n_edges // (workers * max_edges_per_part)))
    return workers * waves
