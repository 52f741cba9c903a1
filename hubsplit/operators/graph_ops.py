"""Graph operators around the programs: subgraphs, projections, counts, extension points, results joined back."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
import pyarrow as pa
from pyspark.sql import Window
from pyspark.sql import functions as F

from hubsplit.functions.hashing import hash32_py, hash32_sql
from hubsplit.operators.relational import views
from hubsplit.plans import partition as P
from hubsplit.plans import programs as R
from hubsplit.plans import rivals as V
from hubsplit.plans import sql_twins as S
from hubsplit.plans.partition_queries import N, with_cut
from hubsplit.plans.runtime import make_layout
from hubsplit.registry import query
from hubsplit.shared_dir import staged
from hubsplit.sources.graphs import build, ctes, table

_CO = f"WITH {ctes('copurchase')} "
_COM = f"WITH {ctes('commerce', True)} "


@query("ego_2hop", _COM + ", h1 AS (SELECT dst AS vid FROM u WHERE src = 0), h2 AS (SELECT u.dst AS vid FROM u JOIN h1 ON u.src = h1.vid) SELECT DISTINCT vid FROM (SELECT CAST(0 AS BIGINT) AS vid UNION ALL SELECT vid FROM h1 UNION ALL SELECT vid FROM h2)")
def ego_2hop(spark, d):
    u = build(spark, d, "commerce").symmetric()
    h1 = u.where("src = 0").select(F.col("dst").alias("vid"))
    h2 = u.join(h1, u["src"] == h1["vid"]).select(F.col("dst").alias("vid"))
    return spark.range(1).select(F.col("id").alias("vid")).union(h1).union(h2).distinct()


@query("drop_hubs", f"WITH {ctes('commerce')}, g AS ({P.DEGREES_SQL}), k AS (SELECT vid FROM g WHERE d <= 100) SELECT CAST(count(*) AS BIGINT) AS n_edges FROM e WHERE src IN (SELECT vid FROM k) AND dst IN (SELECT vid FROM k)")
def drop_hubs(spark, d):
    e = build(spark, d, "commerce").edges
    low = P.degrees(e).where("d <= 100").select("vid")
    return e.join(low, e["src"] == low["vid"], "left_semi").join(low, F.col("dst") == low["vid"], "left_semi").agg(F.count("*").alias("n_edges"))


@query("reverse_edges", _CO + "SELECT dst AS src, src AS dst, w FROM e")
def reverse_edges(spark, d):
    return build(spark, d, "copurchase").edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "w")


@query("symmetrise", f"WITH {ctes('copurchase', True)} SELECT src, dst, w FROM u")
def symmetrise(spark, d):
    return build(spark, d, "copurchase").symmetric()


_NEXT = "SELECT l_partkey AS src, lead(l_partkey) OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey) AS dst, CAST(l_quantity AS BIGINT) AS q FROM lineitem"


def _next_lines(spark, d):
    w = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey")
    li = table(spark, d, "lineitem", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity")
    return li.select(F.col("l_partkey").alias("src"), F.lead("l_partkey").over(w).alias("dst"), F.col("l_quantity").cast("long").alias("q"), "l_linenumber")


@query("remove_loops", f"SELECT CAST(count(*) AS BIGINT) AS n, CAST(count(*) FILTER (src <> dst) AS BIGINT) AS without_loops FROM ({_NEXT}) WHERE dst IS NOT NULL")
def remove_loops(spark, d):
    return _next_lines(spark, d).where("dst is not null").agg(F.count("*").alias("n"), F.count_if(F.col("src") != F.col("dst")).alias("without_loops"))


@query("merge_parallel", "SELECT l_orderkey, l_partkey, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS w FROM lineitem GROUP BY ALL")
def merge_parallel(spark, d):
    return table(spark, d, "lineitem", "l_orderkey", "l_partkey", "l_quantity").groupBy("l_orderkey", "l_partkey").agg(F.sum(F.col("l_quantity").cast("long")).alias("w"))


@query("project_bipartite", "WITH s AS (SELECT DISTINCT l_partkey, l_suppkey FROM lineitem) SELECT a.l_suppkey AS a, b.l_suppkey AS b, CAST(count(*) AS BIGINT) AS shared FROM s a JOIN s b ON a.l_partkey = b.l_partkey AND a.l_suppkey < b.l_suppkey GROUP BY ALL HAVING count(*) >= 5")
def project_bipartite(spark, d):
    """Supplier pairs that share parts. A part has at most as many suppliers as it has lines, so a pair list per part stays short."""
    s = table(spark, d, "lineitem", "l_partkey", "l_suppkey").distinct()
    t = s.select("l_partkey", F.col("l_suppkey").alias("b"))
    return s.withColumnRenamed("l_suppkey", "a").join(t, "l_partkey").where("a < b").groupBy("a", "b").agg(F.count("*").alias("shared")).where("shared >= 5")


@query("wedge_selfjoin", _CO + ", i AS (SELECT dst AS vid, count(*) AS n FROM e GROUP BY dst), o AS (SELECT src AS vid, count(*) AS n FROM e GROUP BY src) SELECT i.vid, CAST(i.n * o.n AS BIGINT) AS wedges FROM i JOIN o USING (vid)")
def wedge_selfjoin(spark, d):
    """Two-paths through each centre, counted as the product of its degrees instead of being listed."""
    return P.degrees(build(spark, d, "copurchase").edges).where("d_in > 0 and d_out > 0").select("vid", (F.col("d_in") * F.col("d_out")).alias("wedges"))


@query("triangles_copurchase", _CO + "SELECT CAST(count(*) / 3 AS BIGINT) AS triangles FROM e a JOIN e b ON b.src = a.dst JOIN e c ON c.src = b.dst AND c.dst = a.src")
def triangles_copurchase(spark, d):
    e = build(spark, d, "copurchase").edges.select("src", "dst")
    two = e.join(e.select(F.col("src").alias("dst"), F.col("dst").alias("third")), "dst")
    return two.join(e.select(F.col("src").alias("third"), F.col("dst").alias("src")), ["third", "src"]).agg((F.count("*") / 3).cast("long").alias("triangles"))


def _core_sql(rounds):
    text = f"WITH {ctes('returns', True)}, k0 AS MATERIALIZED (SELECT src, dst FROM u)"
    for k in range(1, rounds + 1):
        text += f", k{k} AS MATERIALIZED (SELECT src, dst FROM k{k - 1} WHERE src IN (SELECT src FROM k{k - 1} GROUP BY src HAVING count(*) >= 2) AND dst IN (SELECT src FROM k{k - 1} GROUP BY src HAVING count(*) >= 2))"
    return text + f" SELECT DISTINCT src AS vid FROM k{rounds}"


@query("kcore_returns", _core_sql(16))
def kcore_returns(spark, d):
    """The 2-core: vertices of degree below two go until none is left."""
    e = staged(build(spark, d, "returns").symmetric().select("src", "dst"), "core")
    n = e.count()
    while True:
        keep = e.groupBy("src").agg(F.count("*").alias("d")).where("d >= 2").select("src")
        after = staged(e.join(keep, "src", "left_semi").join(keep.withColumnRenamed("src", "dst"), "dst", "left_semi").select("src", "dst"), "core")
        m = after.count()
        e = after
        if m == n or m == 0:
            return e.select(F.col("src").alias("vid")).distinct()
        n = m


@query("bfs_levels_road", S.paths_sql("road", "0", "one", True) + "SELECT dist AS level, CAST(count(*) AS BIGINT) AS n FROM sp GROUP BY dist")
def bfs_levels_road(spark, d):
    r = R.shortest_paths(make_layout(build(spark, d, "road"), P.CUTS["ldch"], 2), 0, False).values
    return r.groupBy(F.col("dist").alias("level")).agg(F.count("*").alias("n"))


@query("label_prop_step", f"WITH {ctes('near_copy')}, p AS (SELECT e.dst AS vid, d.source, count(*) AS n FROM e JOIN documents d ON e.src = 2 * d.doc_id GROUP BY ALL) SELECT vid, source FROM p QUALIFY row_number() OVER (PARTITION BY vid ORDER BY n DESC, source) = 1")
def label_prop_step(spark, d):
    docs = table(spark, d, "documents", "doc_id", "source").select((2 * F.col("doc_id")).alias("src"), "source")
    n = build(spark, d, "near_copy").edges.join(docs, "src").groupBy(F.col("dst").alias("vid"), "source").agg(F.count("*").alias("n"))
    return n.withColumn("r", F.row_number().over(Window.partitionBy("vid").orderBy(F.desc("n"), "source"))).where("r = 1").select("vid", "source")


# --- extension points ----------------------------------------------------------------------------------------------------------------


@query("udf_hash_owner", f"WITH {ctes('returns')} SELECT src, dst, CAST({hash32_sql('src', 'dst')} % {N} AS INT) AS pid FROM e")
def udf_hash_owner(spark, d):
    """The owner of an arc as an Arrow-batched function; the Column form is the one to use."""

    @F.pandas_udf("int")
    def owner(a: pd.Series, b: pd.Series) -> pd.Series:
        return pd.Series([hash32_py(x, y) % N for x, y in zip(a, b, strict=True)])

    return build(spark, d, "returns").edges.select("src", "dst", owner("src", "dst").alias("pid"))


@query("udaf_merge_min", f"WITH {ctes('returns')} SELECT dst AS vid, min(src) AS low FROM e GROUP BY dst")
def udaf_merge_min(spark, d):
    @F.pandas_udf("long")
    def merge(v: pd.Series) -> int:
        return v.min()

    return build(spark, d, "returns").edges.groupBy(F.col("dst").alias("vid")).agg(merge("src").alias("low"))


@query("udtf_neighbours", f"WITH {ctes('returns')} SELECT src, dst FROM e")
def udtf_neighbours(spark, d):
    """A table function that unpacks a vertex's packed neighbours, called in SQL."""

    @F.udtf(returnType="dst: bigint")
    class Neighbours:
        def eval(self, packed: str):
            for x in packed.split(","):
                yield (int(x),)

    spark.udtf.register("hubsplit_neighbours", Neighbours)
    e = build(spark, d, "returns").edges
    e.groupBy("src").agg(F.array_join(F.collect_list(F.col("dst").cast("string")), ",").alias("packed")).createOrReplaceTempView("packed_edges")
    return spark.sql("SELECT p.src, n.dst FROM packed_edges p, LATERAL hubsplit_neighbours(p.packed) n")


_SIZES = with_cut(view="returns") + "SELECT pid, CAST(count(*) AS BIGINT) AS n FROM a GROUP BY pid"


def _cut(spark, d):
    return P.CUTS["ldch"].assign(build(spark, d, "returns").edges, N)


@query("grouped_map_parts", _SIZES)
def grouped_map_parts(spark, d):
    def count(key: tuple, t: pa.Table) -> pa.Table:
        return pa.table({"pid": pa.array([key[0].as_py()], pa.int32()), "n": [t.num_rows]})

    return _cut(spark, d).groupBy("pid").applyInArrow(count, "pid int, n long")


@query("cogrouped_map_parts", with_cut(view="returns") + "SELECT a.pid, CAST(count(*) AS BIGINT) AS n_edges, CAST((SELECT count(*) FROM r WHERE r.pid = a.pid) AS BIGINT) AS n_vertices FROM a GROUP BY a.pid")
def cogrouped_map_parts(spark, d):
    def count(key: tuple, e: pa.Table, v: pa.Table) -> pa.Table:
        return pa.table({"pid": pa.array([key[0].as_py()], pa.int32()), "n_edges": [e.num_rows], "n_vertices": [v.num_rows]})

    a = _cut(spark, d)
    return a.groupBy("pid").cogroup(P.replicas_of(a).select(F.col("pid").alias("part"), "vid").groupBy("part")).applyInArrow(count, "pid int, n_edges long, n_vertices long")


@query("map_in_arrow_edges", _SIZES)
def map_in_arrow_edges(spark, d):
    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            c = b.column(0).value_counts()
            yield pa.RecordBatch.from_arrays([c.field(0), c.field(1)], names=["pid", "n"])

    return _cut(spark, d).select("pid").mapInArrow(count, "pid int, n long").groupBy("pid").agg(F.sum("n").alias("n"))


# --- results joined back ----------------------------------------------------------------------------------------------------------------


@query("sql_component_revenue", S.components_sql("returns") + ", m AS (SELECT component, vid FROM cc) SELECT m.component, CAST(sum(CAST(round(l_extendedprice * 100) AS BIGINT)) AS BIGINT) AS cents FROM lineitem JOIN m ON m.vid = 2 * l_orderkey WHERE l_returnflag = 'R' GROUP BY m.component")
def sql_component_revenue(spark, d):
    R.connected_components(make_layout(build(spark, d, "returns"), P.CUTS["ldch"], N)).values.createOrReplaceTempView("components")
    views(spark, d, "lineitem")
    return spark.sql("SELECT c.component, sum(CAST(round(l_extendedprice * 100) AS BIGINT)) AS cents FROM lineitem JOIN components c ON c.vid = 2 * l_orderkey WHERE l_returnflag = 'R' GROUP BY c.component")


@query("sql_rank_by_nation", S.fixedpoint_sql("commerce", 4) + "SELECT n_name, s_suppkey, rank FROM p4 JOIN supplier ON vid = 4 * s_suppkey + 3 JOIN nation ON s_nationkey = n_nationkey QUALIFY row_number() OVER (PARTITION BY n_name ORDER BY rank DESC, s_suppkey) = 1")
def sql_rank_by_nation(spark, d):
    V.pagerank_fixed(build(spark, d, "commerce"), 4).createOrReplaceTempView("ranks")
    views(spark, d, "supplier", "nation")
    return spark.sql("""SELECT n_name, s_suppkey, rank FROM (SELECT n_name, s_suppkey, rank, row_number() OVER (PARTITION BY n_name ORDER BY rank DESC, s_suppkey) AS r
        FROM ranks JOIN supplier ON vid = 4 * s_suppkey + 3 JOIN nation ON s_nationkey = n_nationkey) WHERE r = 1""")

