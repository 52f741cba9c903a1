"""Structured Streaming over `events`: the table is replayed as five files, one per micro-batch, and each query ends as a batch table.

Windows and joins carry watermarks, so that state is bounded by their width; results go to files and are read back, so that the
answer can be compared with the batch twin.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hubsplit.components import star_components
from hubsplit.functions.hashing import hash32, hash32_sql
from hubsplit.registry import query
from hubsplit.shared_dir import fresh_path, staged
from hubsplit.sources.graphs import build, ctes, table

ROWS_PER_FILE = 100_000
SCHEMA = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def replay(spark: SparkSession, d: str, batches: int = 5, late: bool = False) -> DataFrame:
    """The events as a stream of one slot of time per trigger, in order; with ``late``, a last slot repeats the first hour's events.

    A slot is written by as many tasks as keep files at ``ROWS_PER_FILE`` rows, the same number for every slot.
    """
    path = fresh_path(spark, "event-files")
    ev = table(spark, d, "events", *[c.split()[0] for c in SCHEMA.split(", ")])
    ends = ev.agg(F.min(F.unix_timestamp("ts")).alias("a"), F.max(F.unix_timestamp("ts")).alias("b")).first()
    if ends["a"] is None:
        ends = {"a": 0, "b": 0}
    width = (ends["b"] - ends["a"]) // batches + 1
    slot = F.floor((F.unix_timestamp("ts") - ends["a"]) / width)
    sizes = [r["n"] for r in ev.groupBy(slot.alias("slot")).agg(F.count("*").alias("n")).collect()]  # a row per slot
    files = max(1, min(sizes, default=0) // ROWS_PER_FILE)
    for k in range(batches):  # the source takes files by age: they are written one after another, in time order
        ev.where(slot == k).repartition(files).write.parquet(f"{path}/{k}")
    if late:
        ev.where(F.unix_timestamp("ts") < ends["a"] + 3600).repartition(files).write.parquet(f"{path}/late")
    return spark.readStream.schema(SCHEMA).option("maxFilesPerTrigger", files).option("recursiveFileLookup", "true").option("pathGlobFilter", "*.parquet").parquet(path)


def settle(df: DataFrame, mode: str = "append") -> DataFrame:
    """Run the stream to its end and read the result back."""
    spark = df.sparkSession
    out = fresh_path(spark, "stream-out")
    q = df.writeStream.outputMode(mode).option("checkpointLocation", fresh_path(spark, "stream-state")).trigger(availableNow=True)
    if mode == "append":
        q.format("parquet").option("path", out).start().awaitTermination()
    else:
        def keep(batch: DataFrame, n: int) -> None:
            batch.withColumn("_batch", F.lit(n)).write.mode("overwrite").parquet(f"{out}/b={n}")

        q.foreachBatch(keep).start().awaitTermination()
    return spark.read.parquet(out)




_US = "epoch_us(ts) // 1000000"


@query("st_tumbling", f"SELECT ({_US}) // 3600 * 3600 AS start, event_type, CAST(count(*) AS BIGINT) AS n FROM events GROUP BY ALL")
def st_tumbling(spark, d):
    """Hourly counts by type, complete mode: the last batch holds all windows."""
    counts = replay(spark, d).withWatermark("ts", "2 hours").groupBy(F.window("ts", "1 hour"), "event_type").agg(F.count("*").alias("n"))
    done = settle(counts, "complete")
    last = done.agg(F.max("_batch")).first()[0]
    return done.where(F.col("_batch") == last).select(F.unix_timestamp("window.start").alias("start"), "event_type", "n")


@query("st_sliding", f"SELECT s AS start, CAST(count(*) AS BIGINT) AS n FROM (SELECT unnest([({_US}) // 900 * 900, ({_US}) // 900 * 900 - 900, ({_US}) // 900 * 900 - 1800, ({_US}) // 900 * 900 - 2700]) AS s FROM events) GROUP BY s")
def st_sliding(spark, d):
    counts = replay(spark, d).withWatermark("ts", "2 hours").groupBy(F.window("ts", "1 hour", "15 minutes")).agg(F.count("*").alias("n"))
    done = settle(counts, "complete")
    last = done.agg(F.max("_batch")).first()[0]
    return done.where(F.col("_batch") == last).select(F.unix_timestamp("window.start").alias("start"), "n")


@query("st_session", f"WITH g AS (SELECT user_id, ts, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER w >= 1800000000 OR lag(ts) OVER w IS NULL THEN 1 ELSE 0 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)), s AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, min({_US}) AS start, CAST(count(*) AS BIGINT) AS n FROM s GROUP BY user_id, k")
def st_session(spark, d):
    """Sessions with a gap of half an hour; the replay is in time order, so a long watermark keeps every session open till its end."""
    counts = replay(spark, d).withWatermark("ts", "1 hour").groupBy(F.session_window("ts", "30 minutes"), "user_id").agg(F.count("*").alias("n"))
    done = settle(counts, "complete")
    last = done.agg(F.max("_batch")).first()[0]
    return done.where(F.col("_batch") == last).select("user_id", F.unix_timestamp("session_window.start").alias("start"), "n")


@query("st_dedup", "SELECT CAST(count(DISTINCT event_id) AS BIGINT) AS n FROM events")
def st_dedup(spark, d):
    """Each event arrives twice within the watermark and is kept once."""
    ev = replay(spark, d).withColumn("copy", F.explode(F.array(F.lit(1), F.lit(2)))).withWatermark("ts", "1 hour")
    return settle(ev.dropDuplicatesWithinWatermark(["event_id"]).select("event_id")).agg(F.count("*").alias("n"))


@query("st_static_join", "SELECT label, CAST(count(*) AS BIGINT) AS n FROM events JOIN (SELECT unnest(['click', 'purchase', 'view']) AS event_type, unnest(['warm', 'hot', 'cold']) AS label) USING (event_type) GROUP BY label")
def st_static_join(spark, d):
    labels = spark.createDataFrame([("click", "warm"), ("purchase", "hot"), ("view", "cold")], "event_type string, label string")
    return settle(replay(spark, d).join(F.broadcast(labels), "event_type").select("event_id", "label")).groupBy("label").agg(F.count("*").alias("n"))


@query("st_stream_join", "SELECT c.event_id AS click, p.event_id AS purchase FROM events c JOIN events p ON c.user_id = p.user_id AND p.ts > c.ts AND p.ts <= c.ts + INTERVAL 1 HOUR WHERE c.event_type = 'click' AND p.event_type = 'purchase'")
def st_stream_join(spark, d):
    """Click and purchase within an hour: an equi-join on the user with a time bound, both sides under a watermark."""
    c = replay(spark, d).where("event_type = 'click'").withWatermark("ts", "2 hours").select(F.col("user_id").alias("cu"), F.col("event_id").alias("click"), F.col("ts").alias("ct"))
    p = replay(spark, d).where("event_type = 'purchase'").withWatermark("ts", "2 hours").select(F.col("user_id").alias("pu"), F.col("event_id").alias("purchase"), F.col("ts").alias("pt"))
    return settle(c.join(p, F.expr("cu = pu AND pt > ct AND pt <= ct + interval 1 hour")).select("click", "purchase"))


@query("st_running_degree", "SELECT user_id, CAST(count(*) AS BIGINT) AS degree FROM events GROUP BY user_id")
def st_running_degree(spark, d):
    """Events per user so far, as custom state; the last value of each user stands."""
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def step(key, frames: Iterator[pd.DataFrame], state: GroupState):
        n = (state.get[0] if state.exists else 0) + sum(len(f) for f in frames)
        state.update((n,))
        yield pd.DataFrame({"user_id": [key[0]], "degree": [n]})

    running = replay(spark, d).groupBy("user_id").applyInPandasWithState(step, "user_id long, degree long", "n long", "update", GroupStateTimeout.NoTimeout)
    return settle(running, "update").groupBy("user_id").agg(F.max("degree").alias("degree"))


@query("st_edge_placement", f"SELECT event_id AS src, user_id AS dst, CAST({hash32_sql('event_id', 'user_id')} % 4 AS INT) AS pid FROM events")
def st_edge_placement(spark, d):
    """Arriving arcs get their part by edge hash, without state, and are appended to the part's folder."""
    arcs = replay(spark, d).select(F.col("event_id").alias("src"), F.col("user_id").alias("dst")).withColumn("pid", (hash32("src", "dst") % 4).cast("int"))
    out = fresh_path(spark, "stream-parts")
    arcs.writeStream.format("parquet").partitionBy("pid").option("path", out).option("checkpointLocation", fresh_path(spark, "stream-state")).trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema("src long, dst long, pid int").parquet(out)


@query("st_incremental_cc", f"""WITH RECURSIVE {ctes('userchain', True)}, cc(vid, component) USING KEY (vid) AS (SELECT DISTINCT src, src FROM u
    UNION SELECT u.dst, min(cc.component) FROM cc JOIN u ON u.src = cc.vid JOIN recurring.cc r ON r.vid = u.dst WHERE cc.component < r.component GROUP BY u.dst) SELECT vid, component FROM cc""")
def st_incremental_cc(spark, d):
    """Components after each batch: the labels so far are a forest, and the batch's arcs are merged into it."""
    path = fresh_path(spark, "arc-files")
    build(spark, d, "userchain").edges.select("src", "dst").repartitionByRange(3, "src").write.parquet(path)
    arcs = spark.readStream.schema("src long, dst long").option("maxFilesPerTrigger", 1).parquet(path)
    state: dict[str, DataFrame] = {}

    def merge(batch: DataFrame, n: int) -> None:
        new = batch.select("src", "dst")
        if "labels" in state:
            new = new.union(state["labels"].select("vid", "component"))
        state["labels"] = staged(star_components(new), "labels")

    arcs.writeStream.foreachBatch(merge).option("checkpointLocation", fresh_path(spark, "stream-state")).trigger(availableNow=True).start().awaitTermination()
    return state["labels"]


@query("st_late_data", "SELECT true AS dropped, CAST(count(*) AS BIGINT) AS kept FROM events")
def st_late_data(spark, d):
    """A last file repeats the first hour long after the watermark has passed it: none of it is counted again."""
    counts = replay(spark, d, late=True).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 hour")).agg(F.count("*").alias("n"))
    done = settle(counts, "update")
    latest = done.groupBy("window").agg(F.max_by("n", "_batch").alias("n"))
    total = table(spark, d, "events", "event_id").count()
    return latest.agg(F.sum("n").alias("kept")).select((F.col("kept") == total).alias("dropped"), "kept")
