"""Stages of the corpus pipeline: (spark, docs, sf_dir) -> DataFrame, each applying one operator to all it is given.

Every stage but packing returns exactly the columns it was given, in their order; columns of any other name pass through untouched.
Null texts, empty tables, ties and repeated rows are treated as the operators' modules state.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hubsplit.llm import mixing as mix
from hubsplit.llm import packing as pack
from hubsplit.llm import near_copies, quality, suffix_dedup
from hubsplit.shared_dir import staged


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that pass the base rule and that no learned rule rejects."""
    rules = quality.fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return quality.with_stats(docs, docs.columns).where(~quality.base_failed() & quality.verdict(rules)).select(*docs.columns)


def simhash_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document of smallest doc_id of each group of near copies (five-word shingles, similarity 0.8); rows without a doc_id stay."""
    classed, copies = near_copies.near_copies(docs)
    return classed.join(copies, ["doc_id", "_hs_class"], "left_anti").select(*docs.columns)


def suffix_array_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document with its repeated strings removed from its text; n_chars, where there is one, follows the text."""
    others = [c for c in docs.columns if c != "text"]
    new = {"text": F.col("_hs_kept_text")}
    if "n_chars" in others:
        new["n_chars"] = F.when(F.size("_hs_spans") > 0, F.length("_hs_kept_text").cast(docs.schema["n_chars"].dataType)).otherwise(F.col("n_chars"))
    return suffix_dedup.deduplicate(docs, others).select(*[new.get(c, F.col(c)).alias(c) for c in docs.columns])


def mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """A row for each copy the mix takes; a document with no copy goes."""
    size = mix.word_count(F.col("text")).alias("size")
    counted = staged(docs.select("doc_id", "source", size), "sizes")
    tie = F.xxhash64(*[F.to_json(F.struct(c)) if dict(docs.dtypes)[c].startswith("map") else F.col(c) for c in docs.columns]).alias("_hs_tie")
    inner = docs.select(F.struct(*docs.columns).alias("_hs_row"), "doc_id", "source", size, tie)
    drawn = mix.draw_copies(inner, counted=counted, ties=("_hs_tie",)).where("copies > 0")
    taken = drawn.select("_hs_row", F.explode(F.sequence(F.lit(1), F.col("copies").cast("int"))).alias("_hs_copy"))
    return taken.select(*[F.col("_hs_row")[c].alias(c) for c in docs.columns])


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces with the sequence and the offset they are packed at."""
    pieces = staged(pack.token_pieces(docs), "pieces")
    return pack.pack_pieces(pieces).select("doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset")
