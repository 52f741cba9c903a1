"""Token counts of documents in flat, unindexed token files, by a vectorised scan for the end-of-document id.

The files of a folder, in order of name, are one stream of little-endian unsigned ids, 16 bits wide where the vocabulary allows
and else 32; a document ends at each separator and may run over block and file borders. Each block yields its size, its separators and where the last one stands; a running
sum and a running maximum over these few numbers per block give every block the ordinal of its first document and the place of
the separator before it, which stitches the lengths; both run in two levels, so that no task holds all blocks. The token files are the only input of the scan.

Defined results: a document without ids has length 1 (its separator), ids after the last separator belong to no document, an empty
folder has no documents. The separator must not occur inside a text: the default is the vocabulary's own end-of-text id, and
special strings inside a text are encoded as ordinary text.
"""

from __future__ import annotations

import struct
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from hubsplit.llm.encoder import Encoder, default_tokenizer, slices
from hubsplit.llm.prefix import running_bases
from hubsplit.llm.token_output import _narrow, id_width, move_file, open_fs
from hubsplit.shared_dir import fresh_path, staged

END_OF_TEXT = 50256
#: Files are closed at this size; a scanning task reads blocks of so many ids, whatever the size of a file.
FILE_BYTES, BLOCK_IDS = 128 << 20, 1 << 20


def write_flat(docs: DataFrame, folder: str, tokenizer_path: str | None = None, separator: int = END_OF_TEXT) -> DataFrame:
    """Flat token files in the order of the input's partitions, without a shuffle; returns the staged order of the documents (file, place in it, doc_id)."""
    path = tokenizer_path or default_tokenizer()
    fs, root = open_fs(folder)
    fs.create_dir(root, recursive=True)

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, root = open_fs(folder)
        at = TaskContext.get()
        encoder, end = Encoder.shared(path, plain_specials=True), struct.pack("<I", separator)
        width = id_width(encoder.vocabulary)
        temporary = f"{root}/.attempt-{at.taskAttemptId()}"  # a retried or speculative task leaves whole files alone
        out, size, place, made = None, 0, 0, 0
        name = f"part-{at.partitionId():07d}-{made:05d}.bin"
        for batch in batches:
            ids, texts = batch.column(0), batch.column(1)
            for a, b in slices(texts):
                if out is None:
                    out, size, place, name = fs.open_output_stream(temporary), 0, 0, f"part-{at.partitionId():07d}-{made:05d}.bin"
                data = _narrow(b"".join(x + end for x in encoder.encode(texts.slice(a, b - a))), width)
                out.write(data)
                yield pa.RecordBatch.from_pydict({"file": pa.array([name] * (b - a), pa.string()), "place": pa.array(range(place, place + b - a), pa.int64()), "doc_id": ids.slice(a, b - a)})
                size, place = size + len(data), place + b - a
                if size >= FILE_BYTES:
                    out.close()
                    move_file(fs, temporary, f"{root}/{name}")
                    out, made = None, made + 1
        if out is not None:
            out.close()
            move_file(fs, temporary, f"{root}/{name}")

    return staged(docs.select("doc_id", "text").mapInArrow(write, "file string, place long, doc_id long"), "flat-order")


def scan_flat(spark: SparkSession, folder: str, separator: int = END_OF_TEXT, block_ids: int = BLOCK_IDS, width: int = 2) -> DataFrame:
    """ordinal, start, n_tokens (with the separator), file and place of the separator, for every document of the stream."""

    def blocks(batches: Iterator[pa.RecordBatch], whole: bool) -> Iterator[pa.RecordBatch]:
        fs, root = open_fs(folder)
        for batch in batches:
            for name, k in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                with fs.open_input_file(f"{root}/{name}") as f:
                    ids = np.frombuffer(f.read_at(min(width * block_ids, f.size() - width * block_ids * k), width * block_ids * k), f"<u{width}")
                ends = np.flatnonzero(ids == separator)
                if whole:
                    yield pa.RecordBatch.from_pydict({"file": pa.array([name]), "block": pa.array([k], pa.int32()), "n_ids": pa.array([len(ids)], pa.int64()), "n_ends": pa.array([len(ends)], pa.int64()), "last_end": pa.array([int(ends[-1]) if len(ends) else None], pa.int64())})
                elif len(ends):
                    gaps = np.diff(ends, prepend=-1)
                    yield pa.RecordBatch.from_pydict({
                        "file": pa.array([name] * len(ends)), "block": pa.array(np.full(len(ends), k, np.int32)), "nth": pa.array(np.arange(len(ends))), "end": pa.array(ends.astype(np.int64)), "gap": pa.array(gaps.astype(np.int64))})

    # Names and sizes alone come from the listing; a task opens its blocks by itself.
    listed = spark.read.format("binaryFile").option("pathGlobFilter", "*.bin").load(folder).select(F.element_at(F.split("path", "/"), -1).alias("file"), "length")
    last = F.greatest(F.ceil(F.col("length") / (width * block_ids)) - 1, F.lit(0))
    files = listed.select("file", F.explode(F.sequence(F.lit(0), last.cast("int"))).alias("block")).repartition("file", "block")
    summary = staged(files.mapInArrow(lambda it: blocks(it, True), "file string, block int, n_ids long, n_ends long, last_end long"), "flat-blocks")
    # A row per block: sums and the latest separator run within a writing task's files, and over the tasks' totals.
    keyed = summary.withColumns({"part": F.substring_index("file", "-", 2), "nth_block": F.concat("file", F.format_string("/%010d", F.col("block")))})
    placed = running_bases(keyed, "part", "nth_block", ["n_ids", "n_ends"]).withColumnsRenamed({"before_n_ids": "at", "before_n_ends": "before"})
    placed = placed.withColumn("stands", F.col("at") + F.col("last_end"))
    earlier = lambda w: w.rowsBetween(Window.unboundedPreceding, -1)
    groups = placed.groupBy("part").agg(F.max("stands").alias("stands"))
    groups = groups.select("part", F.max("stands").over(earlier(Window.orderBy("part"))).alias("_outer"))
    placed = placed.withColumn("_inner", F.max("stands").over(earlier(Window.partitionBy("part").orderBy("nth_block")))).join(groups, "part")
    placed = placed.withColumn("previous", F.coalesce(F.greatest("_inner", "_outer"), F.lit(-1)))
    ends = files.mapInArrow(lambda it: blocks(it, False), "file string, block int, nth long, end long, gap long")
    joined = ends.hint("merge").join(placed.select("file", "block", "at", "before", "previous"), ["file", "block"])
    length = F.when(F.col("nth") == 0, F.col("at") + F.col("end") - F.col("previous")).otherwise(F.col("gap"))
    return joined.select((F.col("before") + F.col("nth")).alias("ordinal"), (F.col("at") + F.col("end") + 1 - length).alias("start"), length.alias("n_tokens"), "file", "block", "nth")


def op8_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, ordinal, start and n_tokens (with the separator) of every document, from the flat files alone."""
    folder = fresh_path(spark, "flat")
    order = write_flat(spark.read.parquet(f"{sf_dir}/documents.parquet"), folder)
    if not order.head(1):
        return spark.createDataFrame([], "doc_id long, ordinal long, start long, n_tokens long")
    counts = scan_flat(spark, folder)
    per_file = order.groupBy("file").agg(F.count("*").alias("_n")).withColumn("part", F.substring_index("file", "-", 2))
    base = running_bases(per_file, "part", "file", ["_n"]).select("file", F.col("before__n").alias("_base"))
    # Compressed, the order looks small enough to broadcast; it has a row for every document.
    named = order.hint("merge").join(base, "file").select((F.col("_base") + F.col("place")).alias("ordinal"), "doc_id")
    return named.hint("merge").join(counts, "ordinal").select("doc_id", "ordinal", "start", "n_tokens")
