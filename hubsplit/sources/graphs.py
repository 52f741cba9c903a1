"""Graph views over the given tables: a DataFrame builder and the same view as SQL text, side by side.

Every view gives edges (src, dst, w) and vertices (vid, label); ids of different tables never meet (key * k + tag). Scans name
their columns, so that only those are read.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from hubsplit.functions.hashing import hash32, hash32_sql, text_id, text_id_sql


@dataclass(frozen=True)
class Graph:
    edges: DataFrame
    vertices: DataFrame
    directed: bool = True

    def symmetric(self) -> DataFrame:
        """Both arcs of every edge, once."""
        e = self.edges
        return e.union(e.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "w")).distinct()


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def _long(c: Column) -> Column:
    return c.cast("long")


def _commerce(spark, d):
    orders, lines = table(spark, d, "orders", "o_orderkey", "o_custkey", "o_orderpriority"), table(spark, d, "lineitem", "l_orderkey", "l_partkey", "l_suppkey", "l_quantity")
    one = F.lit(1).cast("long")
    order, part, supp = 4 * F.col("l_orderkey") + 1, 4 * F.col("l_partkey") + 2, 4 * F.col("l_suppkey") + 3
    edges = orders.select((4 * F.col("o_custkey")).alias("src"), (4 * F.col("o_orderkey") + 1).alias("dst"), one.alias("w"))
    edges = edges.union(lines.select(order, part, one)).union(lines.select(part, supp, one)).distinct()
    v = table(spark, d, "customer", "c_custkey", "c_mktsegment").select((4 * F.col("c_custkey")).alias("vid"), F.col("c_mktsegment").alias("label"))
    v = v.union(orders.select(4 * F.col("o_orderkey") + 1, "o_orderpriority")).union(table(spark, d, "part", "p_partkey", "p_type").select(4 * F.col("p_partkey") + 2, "p_type"))
    v = v.union(table(spark, d, "supplier", "s_suppkey", "s_nationkey").select(4 * F.col("s_suppkey") + 3, F.concat(F.lit("NATION_"), F.col("s_nationkey").cast("string"))))
    return Graph(edges, v)


def _ends(edges, label_src, label_dst):
    return edges.select(F.col("src").alias("vid"), F.lit(label_src).alias("label")).union(edges.select("dst", F.lit(label_dst))).distinct()


def _bipartite(name, key, columns, items):
    def build(spark, d):
        rows = table(spark, d, name, key, *columns).select(key, F.explode(items()).alias("item"))
        edges = rows.select((2 * F.col(key)).alias("src"), (2 * text_id(F.col("item")) + 1).alias("dst"), F.lit(1).cast("long").alias("w")).distinct()
        return edges

    return build


_words = _bipartite("documents", "doc_id", ["text"], lambda: F.filter(F.split("text", " "), lambda x: x != ""))
_lines = _bipartite("documents", "doc_id", ["text"], lambda: F.filter(F.split("text", "\n"), lambda x: F.length(x) >= 20))
_hrefs = _bipartite("pages", "page_id", ["html"], lambda: F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1))


def _docword(spark, d):
    e = _words(spark, d)
    return Graph(e, _ends(e, "doc", "word"))


def _near_copy(spark, d):
    e = _lines(spark, d)
    return Graph(e, _ends(e, "doc", "line"), directed=False)


def _pagelink(spark, d):
    e = _hrefs(spark, d)
    return Graph(e, _ends(e, "page", "href"))


def _pagelink_sym(spark, d):
    g = _pagelink(spark, d)
    return Graph(g.symmetric(), g.vertices)


def _chain(events, *by):
    w = Window.partitionBy(*by).orderBy("ts", "event_id")
    gap = F.unix_timestamp(F.lead("ts").over(w)) - F.unix_timestamp("ts")
    return events.select(F.col("event_id").alias("src"), F.lead("event_id").over(w).alias("dst"), gap.alias("w")).where("dst is not null")


def _events(spark, d):
    return table(spark, d, "events", "event_id", "ts", "user_id", "event_type", "props").withColumn("k", F.regexp_extract("props", "([0-9]+)", 1).cast("int"))


def _userchain(spark, d):
    ev = _events(spark, d)
    return Graph(_chain(ev, "user_id"), ev.select(F.col("event_id").alias("vid"), F.col("event_type").alias("label")))


def _road(spark, d):
    ev = _events(spark, d)
    e = _chain(ev, "user_id").union(_chain(ev, "event_type", F.col("k") % 10)).distinct()
    return Graph(e, ev.select(F.col("event_id").alias("vid"), F.col("event_type").alias("label")), directed=False)


def _copurchase(spark, d):
    lines = table(spark, d, "lineitem", "l_orderkey", "l_partkey", "l_suppkey", "l_linenumber")
    w = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey")
    e = lines.select(F.col("l_partkey").alias("src"), F.lead("l_partkey").over(w).alias("dst")).where("dst is not null and src <> dst").distinct()
    return Graph(e.select("src", "dst", F.lit(1).cast("long").alias("w")), table(spark, d, "part", "p_partkey", "p_type").select(F.col("p_partkey").alias("vid"), F.col("p_type").alias("label")))


def _returns(spark, d):
    lines = table(spark, d, "lineitem", "l_orderkey", "l_partkey", "l_quantity", "l_returnflag").where("l_returnflag = 'R'")
    e = lines.groupBy((2 * F.col("l_orderkey")).alias("src"), (2 * F.col("l_partkey") + 1).alias("dst")).agg(F.sum(F.col("l_quantity").cast("long")).alias("w"))
    return Graph(e, _ends(e, "order", "part"), directed=False)


def _transition(spark, d):
    # The order of all events is kept by hour: only an hour's last event looks into the next one, so no task holds the whole stream.
    ev = table(spark, d, "events", "event_id", "ts", "user_id").withColumn("_hour", F.date_trunc("hour", "ts"))
    w = Window.partitionBy("_hour").orderBy("ts", "event_id")
    inner = ev.select(F.col("user_id").alias("src"), F.lead("user_id").over(w).alias("dst"))
    hours = ev.groupBy("_hour").agg(F.min_by("user_id", F.struct("ts", "event_id")).alias("first"), F.max_by("user_id", F.struct("ts", "event_id")).alias("last"))
    borders = hours.select(F.col("last").alias("src"), F.lead("first").over(Window.orderBy("_hour")).alias("dst"))
    e = inner.union(borders).where("dst is not null and src <> dst").groupBy("src", "dst").agg(F.count("*").alias("w"))
    return Graph(e, _ends(e, "user", "user"))


KRON_SCALE = 11  # of the registered view; ``kron_graph`` takes any
# The public Graph500 initiator, as running sums of the first three quadrants, and edges per vertex.
KRON_CUTS, KRON_FACTOR = (0.57, 0.76, 0.95), 16


def kron_edges(spark: SparkSession, scale: int, factor: int = KRON_FACTOR, cuts: tuple[float, float, float] = KRON_CUTS) -> DataFrame:
    """Kronecker arcs by hashing (edge, bit): no state, any order, any number of tasks. Loops and repeats are dropped."""
    return _kron_arcs(spark.range(factor << scale), scale, cuts)


def _kron_arcs(ids: DataFrame, scale: int, cuts: tuple[float, float, float]) -> DataFrame:
    a, b, c = cuts
    src = dst = F.lit(0).cast("long")
    for bit in range(scale):
        u = F.conv(F.substring(F.md5(F.concat(F.col("id").cast("string"), F.lit(f":{bit}"))), 1, 8), 16, 10).cast("double") / F.lit(4294967296.0)
        src = src * 2 + F.when(u >= b, 1).otherwise(0)
        dst = dst * 2 + F.when((u >= a) & (u < b) | (u >= c), 1).otherwise(0)
    e = ids.select(src.alias("src"), dst.alias("dst")).where("src <> dst").distinct()
    return e.select("src", "dst", (1 + hash32("src", "dst") % 10).alias("w"))


def _with_ends(e: DataFrame) -> Graph:
    ends = e.select(F.col("src").alias("vid")).union(e.select("dst")).distinct()
    return Graph(e, ends.select("vid", F.concat(F.lit("K"), F.bit_count("vid").cast("string")).alias("label")))


def kron_graph(spark: SparkSession, scale: int = KRON_SCALE) -> Graph:
    return _with_ends(kron_edges(spark, scale))


def _kron(spark, d):
    return kron_graph(spark)


def _kron_events(spark, d):
    """An arc for each event, drawn by its id; the scale follows their number, so that the edges per vertex stay about ``KRON_FACTOR``."""
    ids = table(spark, d, "events", "event_id").select(F.col("event_id").alias("id"))
    return _with_ends(_kron_arcs(ids, max(1, (ids.count() // KRON_FACTOR).bit_length() - 1), KRON_CUTS))


BUILDERS = {
    "commerce": _commerce, "docword": _docword, "near_copy": _near_copy, "pagelink": _pagelink, "pagelink_sym": _pagelink_sym, "road": _road, "userchain": _userchain,
    "copurchase": _copurchase, "returns": _returns, "transition": _transition, "kron": _kron, "kron_events": _kron_events,
}


def build(spark: SparkSession, sf_dir: str, name: str) -> Graph:
    return BUILDERS[name](spark, sf_dir)


def _bi_sql(name, key, items):
    return f"SELECT DISTINCT 2 * {key} AS src, 2 * {text_id_sql('item')} + 1 AS dst, CAST(1 AS BIGINT) AS w FROM (SELECT {key}, unnest({items}) AS item FROM {name}) WHERE item IS NOT NULL"


_EV = "SELECT event_id, ts, user_id, event_type, CAST(regexp_extract(props, '([0-9]+)', 1) AS INT) AS k FROM events"
_SEC = "(epoch_us(ts) // 1000000)"


def _chain_sql(by):
    w = f"OVER (PARTITION BY {by} ORDER BY ts, event_id)"
    return f"SELECT event_id AS src, lead(event_id) {w} AS dst, lead({_SEC}) {w} - {_SEC} AS w FROM ({_EV}) QUALIFY dst IS NOT NULL"


EDGE_SQL = {
    "commerce": """SELECT DISTINCT * FROM (SELECT 4 * o_custkey AS src, 4 * o_orderkey + 1 AS dst, CAST(1 AS BIGINT) AS w FROM orders
        UNION ALL SELECT 4 * l_orderkey + 1, 4 * l_partkey + 2, 1 FROM lineitem UNION ALL SELECT 4 * l_partkey + 2, 4 * l_suppkey + 3, 1 FROM lineitem)""",
    "docword": _bi_sql("documents", "doc_id", "list_filter(string_split(text, ' '), lambda x: x <> '')"),
    "near_copy": _bi_sql("documents", "doc_id", "list_filter(string_split(text, chr(10)), lambda x: length(x) >= 20)"),
    "pagelink": _bi_sql("pages", "page_id", "regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)"),
    "userchain": _chain_sql("user_id"),
    "road": f"SELECT DISTINCT * FROM ({_chain_sql('user_id')} UNION ALL {_chain_sql('event_type, k % 10')})",
    "copurchase": """SELECT DISTINCT src, dst, CAST(1 AS BIGINT) AS w FROM (SELECT l_partkey AS src, lead(l_partkey) OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey) AS dst
        FROM lineitem) WHERE dst IS NOT NULL AND src <> dst""",
    "returns": """SELECT 2 * l_orderkey AS src, 2 * l_partkey + 1 AS dst, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS w FROM lineitem
        WHERE l_returnflag = 'R' GROUP BY ALL""",
    "transition": """SELECT src, dst, CAST(count(*) AS BIGINT) AS w FROM (SELECT user_id AS src, lead(user_id) OVER (ORDER BY ts, event_id) AS dst FROM events)
        WHERE dst IS NOT NULL AND src <> dst GROUP BY ALL""",
}
EDGE_SQL["pagelink_sym"] = f"SELECT DISTINCT * FROM (SELECT src, dst, w FROM ({EDGE_SQL['pagelink']}) UNION ALL SELECT dst, src, w FROM ({EDGE_SQL['pagelink']}))"


def kron_sql(scale: int) -> str:
    a, b, c = KRON_CUTS
    bits = [f"SELECT i, {k} AS k, CAST(('0x' || substr(md5(CAST(i AS VARCHAR) || ':{k}'), 1, 8)) AS BIGINT) / 4294967296e0 AS u FROM range({KRON_FACTOR << scale}) t(i)" for k in range(scale)]
    return f"""SELECT DISTINCT src, dst, 1 + {hash32_sql('src', 'dst')} % 10 AS w FROM (
        SELECT CAST(sum(CASE WHEN u >= {b}e0 THEN 1 << ({scale} - 1 - k) ELSE 0 END) AS BIGINT) AS src,
               CAST(sum(CASE WHEN u >= {a}e0 AND u < {b}e0 OR u >= {c}e0 THEN 1 << ({scale} - 1 - k) ELSE 0 END) AS BIGINT) AS dst
        FROM ({' UNION ALL '.join(bits)}) GROUP BY i) WHERE src <> dst"""


EDGE_SQL["kron"] = kron_sql(KRON_SCALE)


def _kron_events_sql() -> str:
    a, b, c = KRON_CUTS
    end = lambda when: f"CAST(list_sum(list_transform(us, lambda u, i: CASE WHEN {when} THEN CAST(1 AS BIGINT) << (s - i) ELSE 0 END)) AS BIGINT)"
    return f"""SELECT DISTINCT src, dst, 1 + {hash32_sql('src', 'dst')} % 10 AS w FROM (
        SELECT {end(f'u >= {b}e0')} AS src, {end(f'u >= {a}e0 AND u < {b}e0 OR u >= {c}e0')} AS dst
        FROM (SELECT s, list_transform(range(s), lambda k: CAST(('0x' || substr(md5(CAST(event_id AS VARCHAR) || ':' || k), 1, 8)) AS BIGINT) / 4294967296e0) AS us
            FROM events, (SELECT greatest(1, length(bin(count(*) // {KRON_FACTOR})) - 1) AS s FROM events))) WHERE src <> dst"""


EDGE_SQL["kron_events"] = _kron_events_sql()

VERTEX_SQL = {
    "commerce": """SELECT 4 * c_custkey AS vid, c_mktsegment AS label FROM customer UNION ALL SELECT 4 * o_orderkey + 1, o_orderpriority FROM orders
        UNION ALL SELECT 4 * p_partkey + 2, p_type FROM part UNION ALL SELECT 4 * s_suppkey + 3, 'NATION_' || s_nationkey FROM supplier""",
    "copurchase": "SELECT p_partkey AS vid, p_type AS label FROM part",
    "userchain": "SELECT event_id AS vid, event_type AS label FROM events",
    "road": "SELECT event_id AS vid, event_type AS label FROM events",
}
for _name, (_a, _b) in {"docword": ("doc", "word"), "near_copy": ("doc", "line"), "pagelink": ("page", "href"), "pagelink_sym": ("page", "href"), "returns": ("order", "part"), "transition": ("user", "user")}.items():
    _base = "pagelink" if _name == "pagelink_sym" else _name
    VERTEX_SQL[_name] = f"SELECT DISTINCT src AS vid, '{_a}' AS label FROM ({EDGE_SQL[_base]}) UNION SELECT DISTINCT dst, '{_b}' FROM ({EDGE_SQL[_base]})"
for _name in ("kron", "kron_events"):
    VERTEX_SQL[_name] = f"SELECT DISTINCT vid, 'K' || bit_count(vid) AS label FROM (SELECT src AS vid FROM ({EDGE_SQL[_name]}) UNION SELECT dst FROM ({EDGE_SQL[_name]}))"


def ctes(name: str, symmetric: bool = False) -> str:
    """``e`` (edges), ``v`` (vertices) and, if asked for, ``u`` (both arcs): the view as CTEs, without the word WITH."""
    text = f"e AS MATERIALIZED ({EDGE_SQL[name]}), v AS MATERIALIZED ({VERTEX_SQL[name]})"
    if symmetric:
        text += ", u AS MATERIALIZED (SELECT src, dst, w FROM e UNION SELECT dst, src, w FROM e)"
    return text
