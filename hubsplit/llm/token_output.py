"""Token ids in binary files: per-document zstandard frames under one shared dictionary.

A folder holds ``dictionary.zdict`` and shard files in ascending document order. A shard is: a 16-byte head (mark, version,
width of an id in bytes), the frames one after another, the index (valid flag, document id, frame offsets, token counts),
and a foot (index offset, document count, SHA-256 of the dictionary, CRC-32 of the index, mark). A document is read by
its index entry alone: one frame is decompressed, never the shard.

Defined results: null text is empty (one end id), a null doc_id sorts first and stays null, repeated rows are written as often
as they occur, an empty table gives no shard, extra columns are ignored. A text of any length becomes one frame.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hubsplit.llm.encoder import Encoder, default_tokenizer, slices
from hubsplit.llm.prefix import running_bases
from hubsplit.shared_dir import fresh_path, staged

MARK = b"HSZIDS01"
HEAD = struct.Struct("<8sII")
FOOT = struct.Struct("<QQ32sI8s")
#: A shard is closed at this many bytes of frames.
SHARD_BYTES = 32 << 20
#: The dictionary is trained on the rows with the smallest hashed id, this many at most, and on one window of so many characters of each,
#: whose place in the whole text a hash of the id draws. A bound on the training alone: every id is written whatever the dictionary.
SAMPLE_ROWS, SAMPLE_CHARS, DICTIONARY_BYTES = 2000, 16_384, 64 << 10


def open_fs(uri: str):
    """The pyarrow filesystem and path of a folder that all executors share."""
    from pyarrow import fs

    return fs.FileSystem.from_uri(uri if "://" in uri else f"file://{uri}")


def put_file(fs, path: str, data: bytes) -> None:
    """Write under a name of this attempt, then move: a retried or speculative task leaves one whole file."""
    at = TaskContext.get()
    temporary = f"{path}.attempt-{at.taskAttemptId() if at else 0}"
    with fs.open_output_stream(temporary) as out:
        out.write(data)
    move_file(fs, temporary, path)


def move_file(fs, temporary: str, path: str) -> None:
    """Put a whole file in its place; an earlier attempt's file is the same and goes."""
    try:
        fs.move(temporary, path)
    except OSError:
        fs.delete_file(path)
        fs.move(temporary, path)


def id_width(vocabulary: int) -> int:
    return 2 if vocabulary <= 1 << 16 else 4


def _narrow(ids: bytes, width: int) -> bytes:
    return ids if width == 4 else np.frombuffer(ids, "<u4").astype("<u2").tobytes()


def _widen(data: bytes, width: int) -> bytes:
    return data if width == 4 else np.frombuffer(data, "<u2").astype("<u4").tobytes()


def train_dictionary(docs: DataFrame, tokenizer_path: str, end_id: int) -> bytes:
    """A zstandard dictionary from a bounded sample; empty when the sample is too small to train on."""
    import zstandard

    encoder = Encoder.shared(tokenizer_path)
    ids = docs.select("doc_id").where("doc_id is not null").distinct().orderBy(F.xxhash64("doc_id"), "doc_id").limit(SAMPLE_ROWS)
    place = F.pmod(F.xxhash64("doc_id", F.lit("window")), F.greatest(F.lit(1), F.length("text") - SAMPLE_CHARS + 1)).cast("int") + 1
    sampled = docs.join(F.broadcast(ids), "doc_id").select("doc_id", F.substring(F.col("text"), place, F.lit(SAMPLE_CHARS)).alias("text"))  # SAMPLE_ROWS ids
    rows = sampled.orderBy("doc_id", "text").limit(SAMPLE_ROWS).collect()
    width = id_width(encoder.vocabulary)
    end = struct.pack("<I", end_id)
    samples = [_narrow(ids + end, width) for ids in encoder.encode([r["text"] for r in rows])]
    try:
        return zstandard.train_dictionary(DICTIONARY_BYTES, samples).as_bytes()
    except zstandard.ZstdError:
        return b""


class ShardWriter:
    def __init__(self, dictionary: bytes, width: int, level: int = 3):
        import zstandard

        used = zstandard.ZstdCompressionDict(dictionary) if dictionary else None
        self.compressor = zstandard.ZstdCompressor(level=level, dict_data=used, write_content_size=True)
        self.digest, self.width = hashlib.sha256(dictionary).digest(), width
        self.clear()

    def clear(self) -> None:
        self.frames: list[bytes] = []
        self.valid, self.ids, self.sizes, self.counts, self.held = [], [], [0], [], 0

    def add(self, doc_id: int | None, ids: bytes) -> None:
        frame = self.compressor.compress(_narrow(ids, self.width))
        self.frames.append(frame)
        self.held += len(frame)
        self.valid.append(doc_id is not None)
        self.ids.append(doc_id or 0)
        self.sizes.append(len(frame))
        self.counts.append(len(ids) // 4)

    def finish(self) -> bytes:
        head = HEAD.pack(MARK, 1, self.width)
        index = b"".join((
            np.array(self.valid, "u1").tobytes(), np.array(self.ids, "<i8").tobytes(),
            (np.cumsum(np.array(self.sizes, "<u8"), dtype="<u8") + np.uint64(HEAD.size)).astype("<u8").tobytes(), np.array(self.counts, "<u8").tobytes(),
        ))
        foot = FOOT.pack(HEAD.size + self.held, len(self.ids), self.digest, zlib.crc32(index), MARK)
        return b"".join((head, *self.frames, index, foot))


class Shard:
    """Random access to the documents of one shard."""

    def __init__(self, data, dictionary: bytes):
        import zstandard

        at, n, digest, crc, mark = FOOT.unpack_from(data, len(data) - FOOT.size)
        _, _, self.width = HEAD.unpack_from(data)
        data = memoryview(data)
        index = data[at : len(data) - FOOT.size]
        if mark != MARK or zlib.crc32(index) != crc:
            raise ValueError("damaged shard")
        if digest != hashlib.sha256(dictionary).digest():
            raise ValueError("the shard was written with another dictionary")
        self.valid = np.frombuffer(index, "u1", n)
        self.doc_ids = np.frombuffer(index, "<i8", n, n)
        self.offsets = np.frombuffer(index, "<u8", n + 1, 9 * n)
        self.counts = np.frombuffer(index, "<u8", n, 9 * n + 8 * (n + 1))
        self.data = data
        self.decompressor = zstandard.ZstdDecompressor(dict_data=zstandard.ZstdCompressionDict(dictionary) if dictionary else None)

    def __len__(self) -> int:
        return len(self.doc_ids)

    def ids(self, i: int) -> bytes:
        """Ids of the i-th document, little-endian unsigned 32-bit, with the end id."""
        return _widen(self.decompressor.decompress(self.data[int(self.offsets[i]) : int(self.offsets[i + 1])]), self.width)


def write_tokens(docs: DataFrame, folder: str, tokenizer_path: str | None = None, end_id: int = 2) -> DataFrame:
    """Encode every text and write shards in ascending doc_id order; returns the staged manifest (shard, n_docs, n_tokens, n_bytes)."""
    spark = docs.sparkSession
    path = tokenizer_path or default_tokenizer()
    docs = docs.select("doc_id", "text")
    dictionary = train_dictionary(docs, path, end_id)
    fs, root = open_fs(folder)
    fs.create_dir(root, recursive=True)
    put_file(fs, f"{root}/dictionary.zdict", dictionary)

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, root = open_fs(folder)
        encoder, end, part = Encoder.shared(path), struct.pack("<I", end_id), TaskContext.get().partitionId()
        writer, made = ShardWriter(dictionary, id_width(encoder.vocabulary)), []

        def close() -> None:
            name = f"part-{part:07d}-{len(made):05d}.zids"
            data = writer.finish()
            put_file(fs, f"{root}/{name}", data)
            made.append((name, len(writer.ids), sum(writer.counts), len(data)))
            writer.clear()

        for batch in batches:
            ids, texts = batch.column(0).to_pylist(), batch.column(1)
            for a, b in slices(texts):
                for doc_id, encoded in zip(ids[a:b], encoder.encode(texts.slice(a, b - a)), strict=True):
                    writer.add(doc_id, encoded + end)
                    if writer.held >= SHARD_BYTES:
                        close()
        if writer.ids:
            close()
        yield pa.RecordBatch.from_pydict({
            "shard": pa.array([m[0] for m in made], pa.string()), "n_docs": pa.array([m[1] for m in made], pa.int64()),
            "n_tokens": pa.array([m[2] for m in made], pa.int64()), "n_bytes": pa.array([m[3] for m in made], pa.int64()),
        })

    # by text as well, so that rows of one id need not fall to one task
    ordered = docs.repartitionByRange("doc_id", F.xxhash64("text")).sortWithinPartitions("doc_id", F.xxhash64("text"))
    return staged(ordered.mapInArrow(write, "shard string, n_docs long, n_tokens long, n_bytes long"), "tokens-manifest")


def read_tokens(spark: SparkSession, folder: str, manifest: DataFrame, with_ids: bool = False) -> DataFrame:
    """One row per document from the shard files: doc_id, start, n_tokens, ids_crc32, shard, and the ids if asked for."""
    fs, root = open_fs(folder)
    with fs.open_input_stream(f"{root}/dictionary.zdict") as f:
        dictionary = f.read()

    def parse(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for name, data in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                shard = Shard(data.as_buffer(), dictionary)
                for a in range(0, len(shard), 20_000):
                    span = range(a, min(a + 20_000, len(shard)))
                    ids = [shard.ids(i) for i in span]
                    before = int(shard.counts[:a].sum())
                    counts = shard.counts[a : span.stop].astype(np.int64)
                    columns = {
                        "doc_id": pa.array(shard.doc_ids[a : span.stop], pa.int64(), mask=shard.valid[a : span.stop] == 0),
                        "within": pa.array(before + np.cumsum(counts) - counts, pa.int64()), "n_tokens": pa.array([len(x) // 4 for x in ids], pa.int64()),
                        "ids_crc32": pa.array([zlib.crc32(x) for x in ids], pa.int64()), "shard": pa.array([name] * len(ids), pa.string()),
                    }
                    if with_ids:
                        columns["ids"] = pa.array([np.frombuffer(x, "<u4").astype(np.int64) for x in ids], pa.list_(pa.int64()))
                    yield pa.RecordBatch.from_pydict(columns)

    files = spark.read.format("binaryFile").option("pathGlobFilter", "*.zids").load(folder) if manifest.head(1) else None
    schema = "doc_id long, within long, n_tokens long, ids_crc32 long, shard string" + (", ids array<long>" if with_ids else "")
    if files is None:
        parsed = spark.createDataFrame([], schema)
    else:
        parsed = files.select(F.element_at(F.split("path", "/"), -1).alias("shard"), "content").mapInArrow(parse, schema)
    bases = running_bases(manifest.select("shard", F.substring_index("shard", "-", 2).alias("part"), "n_tokens"), "part", "shard", ["n_tokens"]).select("shard", F.col("before_n_tokens").alias("base"))
    kept = [F.col("doc_id"), (F.col("base") + F.col("within")).alias("start"), F.col("n_tokens"), F.col("ids_crc32"), F.col("shard")]
    return parsed.hint("merge").join(bases, "shard").select(*kept, *([F.col("ids")] if with_ids else []))


def op5_token_output(spark: SparkSession, sf_dir: str) -> DataFrame:
    folder = fresh_path(spark, "tokens")
    manifest = write_tokens(spark.read.parquet(f"{sf_dir}/documents.parquet"), folder)
    return read_tokens(spark, folder, manifest).select("doc_id", "start", "n_tokens", "ids_crc32")
