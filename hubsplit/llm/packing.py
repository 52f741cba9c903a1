"""Best-fit packing of token pieces into sequences, by large-item matching over the histogram of lengths.

Lengths are integers up to the sequence length, so a packing is decided for the histogram: pieces above a third of the capacity
are matched greedily, two to a sequence at most; smaller ones go, longest first, each to the tightest gap. Every decision places a
run of equal pieces in a run of equal sequences, and there are a few thousand runs whatever the number of documents. The
pieces then look up their run by their rank within their length. Ranks come from counts per (length, hash bucket), so a length
that holds a third of all pieces is never ordered by one task.

Defined results: null text is empty (one end id), repeated rows are packed as often as they occur, an empty table gives no rows.
"""

from __future__ import annotations

import struct
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from hubsplit.llm.encoder import Encoder, default_tokenizer, slices
from hubsplit.shared_dir import staged

CAPACITY = 1024
ROWS_PER_BUCKET = 100_000


def token_pieces(docs: DataFrame, capacity: int = CAPACITY, tokenizer_path: str | None = None, end_id: int = 2) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32: only documents beyond the capacity are cut, and their first piece takes the remainder."""
    path = tokenizer_path or default_tokenizer()

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder, end = Encoder.shared(path), struct.pack("<I", end_id)
        for batch in batches:
            ids, texts = batch.column(0).to_pylist(), batch.column(1)
            for a, b in slices(texts):
                rows = []
                for doc_id, encoded in zip(ids[a:b], encoder.encode(texts.slice(a, b - a)), strict=True):
                    encoded += end
                    n = len(encoded) // 4
                    at, piece = 0, 0
                    length = n % capacity or capacity
                    while at < n:
                        rows.append((doc_id, piece, at, length, zlib.crc32(encoded[4 * at : 4 * (at + length)])))
                        at, piece, length = at + length, piece + 1, capacity
                kinds = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64())
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True)], names=["doc_id", "piece", "start", "length", "ids_crc32"])

    return docs.select("doc_id", "text").mapInArrow(cut, "doc_id long, piece int, start long, length long, ids_crc32 long")


def plan_runs(counts: dict[int, int], capacity: int) -> tuple[list[tuple[int, int, int, int, int, int]], int]:
    """Runs (length, first rank, end rank, first sequence, pieces per sequence, offset) and the number of sequences."""
    left = {n: c for n, c in counts.items() if c}
    runs: list[tuple[int, int, int, int, int, int]] = []
    used = dict.fromkeys(left, 0)
    by_gap: list[list[tuple[int, int]]] = [[] for _ in range(capacity + 1)]
    opened = 0

    def put(length: int, first: int, bins: int, each: int, offset: int) -> None:
        runs.append((length, used[length], used[length] + bins * each, first, each, offset))
        used[length] += bins * each
        left[length] -= bins * each

    def keep(first: int, bins: int, gap: int) -> None:
        if bins and gap:
            by_gap[gap].append((first, bins))

    large = sorted((n for n in left if 3 * n > capacity), reverse=True)
    for a in large:
        while left[a]:
            b = next((n for n in large if n + a <= capacity and left[n] > (n == a)), None)
            if b is None:
                bins = left[a]
                put(a, opened, bins, 1, 0)
                keep(opened, bins, capacity - a)
            elif b == a:
                bins = left[a] // 2
                put(a, opened, bins, 2, 0)
                keep(opened, bins, capacity - 2 * a)
            else:
                bins = min(left[a], left[b])
                put(a, opened, bins, 1, 0)
                put(b, opened, bins, 1, a)
                keep(opened, bins, capacity - a - b)
            opened += bins
    for s in sorted((n for n in left if 3 * n <= capacity), reverse=True):
        while left[s]:
            gap = next((g for g in range(s, capacity + 1) if by_gap[g]), None)
            if gap is None:
                first, bins, gap = opened, -(-left[s] // (capacity // s)), capacity
                opened += bins
            else:
                first, bins = by_gap[gap].pop()
            each = gap // s
            full = min(bins, left[s] // each)
            if full:
                put(s, first, full, each, capacity - gap)
                keep(first, full, gap - each * s)
                first, bins = first + full, bins - full
            if bins and left[s]:
                rest = left[s]
                put(s, first, 1, rest, capacity - gap)
                keep(first, 1, gap - rest * s)
                first, bins = first + 1, bins - 1
            keep(first, bins, gap)
    return runs, opened


def pack_pieces(pieces: DataFrame, capacity: int = CAPACITY) -> DataFrame:
    """Adds sequence_id and offset to a staged table of pieces with doc_id, piece, start, length."""
    spark = pieces.sparkSession
    histogram = {r["length"]: r["n"] for r in pieces.groupBy("length").agg(F.count("*").alias("n")).collect()}  # at most `capacity` rows
    runs, _ = plan_runs(histogram, capacity)
    if not runs:
        return pieces.select("*", F.lit(0).cast("long").alias("sequence_id"), F.lit(0).cast("long").alias("offset"))
    buckets = max(1, -(-max(histogram.values()) // ROWS_PER_BUCKET))
    keyed = pieces.withColumn("_bucket", F.pmod(F.xxhash64("doc_id", "piece"), F.lit(buckets)))
    before = keyed.groupBy("length", "_bucket").agg(F.count("*").alias("_n")).select(
        "length", "_bucket", (F.sum("_n").over(Window.partitionBy("length").orderBy("_bucket")) - F.col("_n")).alias("_before"))
    order = Window.partitionBy("length", "_bucket").orderBy("doc_id", "piece", "start", "ids_crc32")
    ranked = keyed.withColumn("_row", F.row_number().over(order) - 1).join(before, ["length", "_bucket"])
    ranked = ranked.withColumn("_rank", F.col("_row") + F.col("_before"))
    table = spark.createDataFrame(runs, "length long, _lo long, _hi long, _first long, _each long, _offset long")
    # The plan has a few thousand runs for any corpus: its size follows the capacity alone.
    placed = ranked.join(F.broadcast(table), (ranked["length"] == table["length"]) & (F.col("_rank") >= F.col("_lo")) & (F.col("_rank") < F.col("_hi")))
    at = F.col("_rank") - F.col("_lo")
    return placed.select(
        *[ranked[c] for c in pieces.columns], (F.col("_first") + F.floor(at / F.col("_each")).cast("long")).alias("sequence_id"),
        (F.col("_offset") + F.pmod(at, F.col("_each")) * ranked["length"]).alias("offset"),
    )


def op2_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    pieces = staged(token_pieces(spark.read.parquet(f"{sf_dir}/documents.parquet")), "pieces")
    return pack_pieces(pieces).select("doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset")
