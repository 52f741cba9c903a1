"""Mixing sources to target weights by systematic sampling.

Every document of a source expects target / source size copies. Documents are laid out in order of size, so the prefix sum of
the expected copies is that ratio times a document's rank; with one random offset per source, a document is taken once for each
integer its interval crosses. Ordering by size makes the taken words follow the target closely. Ranks are built from counts
per (source, size) and per (source, size, hash bucket), so a source with a third of all rows is never ordered by one task.

Defined results: null text has size 0, a null source is a source of its own and the last one, repeated rows each take their
own turn, a source without words takes nothing, an empty table gives no rows. Equal inputs give equal results on every run.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from hubsplit.shared_dir import staged

WORD = r"[^\x20\x09-\x0D]+"
SEED = 7
CEILING = 3


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def source_targets(sizes: DataFrame, weights: tuple[int, ...] = (1, 2, 3), ceiling: int = CEILING) -> DataFrame:
    """source_size and target of each source of a table (source, source_size): shares by weight, levelled under the ceiling.

    A target is the smaller of ceiling times the size and level times the weight; the level is found where the capped
    sources, taken in order of cap per weight, leave enough for the rest. One row per source.
    """
    w = F.element_at(F.array(*[F.lit(float(x)) for x in weights]), (F.pmod(F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())) - 1, F.lit(len(weights))) + 1).cast("int"))
    t = sizes.select("source", "source_size", w.alias("_w"), (F.lit(float(ceiling)) * F.col("source_size")).alias("_cap"))
    by_fill = Window.orderBy(F.col("_cap") / F.col("_w"), F.col("source").asc_nulls_last())
    whole = Window.partitionBy()
    t = t.select(
        "*", F.sum("source_size").over(whole).cast("double").alias("_total"), (F.sum("_cap").over(by_fill) - F.col("_cap")).alias("_filled"),
        (F.sum("_w").over(whole) - F.sum("_w").over(by_fill) + F.col("_w")).alias("_open"))
    level = (F.col("_total") - F.col("_filled")) / F.col("_open")
    t = t.withColumn("_level", F.when(level * F.col("_w") <= F.col("_cap"), level))
    t = t.withColumn("_level", F.min_by("_level", F.when(F.col("_level").isNotNull(), F.col("_filled"))).over(whole))
    return t.select("source", "source_size", F.least("_cap", F.col("_level") * F.col("_w")).alias("target"))


def draw_copies(docs: DataFrame, seed: int = SEED, counted: DataFrame | None = None, ties: tuple[str, ...] = ()) -> DataFrame:
    """All columns of ``docs`` (doc_id, source, size and any other) with source_size, target and copies.

    ``ties`` orders rows of equal doc_id, source and size, so that reruns agree on which of them is taken. ``counted`` may hold doc_id, source and size of the same rows, staged, so that counting need not read the rest.
    """
    key = F.coalesce(F.concat(F.lit("="), F.col("source")), F.lit("-"))
    bucket = F.substring(F.md5(F.coalesce(F.col("doc_id").cast("string"), F.lit(""))), 1, 4)
    rows = docs.withColumns({"_key": key, "_bucket": bucket})
    buckets = (rows if counted is None else counted.withColumns({"_key": key, "_bucket": bucket})).groupBy("_key", "source", "size", "_bucket").agg(F.count("*").alias("_n"))
    by_size = buckets.groupBy("_key", "source", "size").agg(F.sum("_n").alias("_n"))
    lower = by_size.select("_key", "size", (F.sum("_n").over(Window.partitionBy("_key").orderBy("size")) - F.col("_n")).alias("_lower"))
    targets = source_targets(by_size.groupBy("source").agg(F.sum(F.col("_n") * F.col("size")).alias("source_size")))
    targets = targets.select(key.alias("_key"), "source_size", "target")
    inner = Window.partitionBy("_key", "size").orderBy("_bucket")
    base = (
        buckets.select("_key", "size", "_bucket", (F.sum("_n").over(inner) - F.col("_n")).alias("_inner"))
        .join(lower, ["_key", "size"]).join(targets, "_key")
        .select("_key", "size", "_bucket", (F.col("_inner") + F.col("_lower")).alias("_base"), "source_size", "target"))
    ranked = rows.withColumn("_row", F.row_number().over(Window.partitionBy("_key", "size", "_bucket").orderBy("doc_id", *ties)) - 1)
    joined = ranked.join(base, ["_key", "size", "_bucket"])
    offset = F.conv(F.substring(F.md5(F.concat(F.col("_key"), F.lit(f"|{seed}"))), 1, 8), 16, 10).cast("double") / F.lit(4294967296.0)
    ratio = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(F.lit(0.0))
    rank = (F.col("_base") + F.col("_row")).cast("double")
    copies = F.floor(ratio * (rank + F.lit(1.0)) + offset) - F.floor(ratio * rank + offset)
    return joined.select(*docs.columns, "source_size", "target", copies.cast("long").alias("copies"))


def op4_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "source", word_count(F.col("text")).alias("size"))
    drawn = draw_copies(staged(docs, "sizes"))
    return drawn.select("doc_id", "size", "source_size", "target", (F.col("copies") * F.col("size")).alias("taken"))


OP4_SQL = r"""
WITH d AS (SELECT doc_id, source, CAST(coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0) AS BIGINT) AS size,
                  coalesce('=' || source, '-') AS k FROM documents),
s AS (SELECT source, k, CAST(sum(size) AS BIGINT) AS source_size FROM d GROUP BY source, k),
w AS (SELECT *, CAST((row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1 AS DOUBLE) AS w, 3e0 * source_size AS cap FROM s),
f AS (SELECT *, CAST(sum(source_size) OVER () AS DOUBLE) AS total,
             sum(cap) OVER (ORDER BY cap / w, source NULLS LAST ROWS UNBOUNDED PRECEDING) - cap AS filled,
             sum(w) OVER () - sum(w) OVER (ORDER BY cap / w, source NULLS LAST ROWS UNBOUNDED PRECEDING) + w AS rest FROM w),
l AS (SELECT arg_min((total - filled) / rest, filled) AS level FROM f WHERE (total - filled) / rest * w <= cap),
t AS (SELECT k, source_size, least(cap, level * w) AS target FROM f, l),
r AS (SELECT d.doc_id, d.size, t.source_size, t.target, d.k,
             CAST(row_number() OVER (PARTITION BY d.k ORDER BY d.size, substr(md5(CAST(d.doc_id AS VARCHAR)), 1, 4), d.doc_id) - 1 AS DOUBLE) AS rank
      FROM d JOIN t USING (k)),
o AS (SELECT *, CAST(('0x' || substr(md5(k || '|7'), 1, 8)) AS BIGINT) / 4294967296e0 AS u,
             CASE WHEN source_size > 0 THEN target / source_size ELSE 0e0 END AS ratio FROM r)
SELECT doc_id, size, source_size, target,
       CAST(floor(ratio * (rank + 1e0) + u) - floor(ratio * rank + u) AS BIGINT) * size AS taken FROM o
"""
