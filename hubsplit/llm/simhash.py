"""SimHash near-duplicates: tiled exact comparison by exclusive-or and bit counts.

Fingerprints that differ in at most r bits agree on some r of r+2 blocks: equal blocks are the tile key, so that only
fingerprints of one tile group meet. Inside a group they are ordered by population count and compared tile by tile with
numpy; a tile pair is skipped when its population counts differ beyond the radius, since each differing bit changes the count
by one. The comparison is exact and complete. Equal fingerprints are one class before anything is compared, and a tile group
reports a spanning forest, so that a large group of copies costs its size and not its square.

Defined results: null text and text without words have fingerprint zero and link like any other; fewer words than a shingle hash
as one sequence; null doc_ids are never the name of a component unless no member has one; repeated rows come back as often as
they occur; an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations, islice, repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from hubsplit.components import star_components
from hubsplit.shared_dir import staged

SHINGLE, RADIUS, SEED = 3, 2, 42
TILE = 1024
#: A tile group above so many fingerprints is dealt to several tasks.
GROUP = 1 << 17


def fingerprint(text: str | None, shingle: int = SHINGLE) -> int:
    """64 bits, each set where more than half of the shingle hashes have it."""
    import xxhash

    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return 0
    if len(words) <= shingle:
        return xxhash.xxh64_intdigest(b" ".join(words), SEED)
    hashes = map(xxhash.xxh64_intdigest, map(b" ".join, zip(*(islice(words, k, None) for k in range(shingle)))), repeat(SEED))
    return majority_bits(np.fromiter(islice(hashes, 65_536), np.uint64) for _ in repeat(None))


def majority_bits(parts: Iterator[np.ndarray]) -> int:
    """The bits that more than half of the hashes have; an empty part ends the sequence."""
    ones, n = np.zeros(64, np.int64), 0
    for part in parts:
        if not len(part):
            break
        ones += np.unpackbits(part.astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
        n += len(part)
    return int(np.packbits(2 * ones > n, bitorder="little").view("<u8")[0])


def fingerprints(docs: DataFrame, shingle: int = SHINGLE, carry: list[str] | None = None) -> DataFrame:
    """doc_id (and the columns to carry) with ``_hs_fp``, the fingerprint's bits as a signed long."""
    columns = carry or ["doc_id"]

    def hashed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            fps = np.array([fingerprint(t.as_py(), shingle) for t in batch.column(len(columns))], np.uint64)
            yield pa.RecordBatch.from_arrays([*batch.columns[: len(columns)], pa.array(fps.view(np.int64))], names=[*columns, "_hs_fp"])

    fields = ", ".join(f"`{c}` {docs.schema[c].dataType.simpleString()}" for c in columns)
    return docs.select(*columns, F.col("text").alias("_hs_text")).mapInArrow(hashed, f"{fields}, _hs_fp long")


def hex_of(fp: Column) -> Column:
    return F.lower(F.lpad(F.hex(fp), 16, "0"))


def tile_keys(fp: Column, radius: int = RADIUS) -> Column:
    """Keys of the groups a fingerprint belongs to: every choice of two of radius + 2 blocks, with the blocks' bits."""
    n = radius + 2
    edges = [64 * k // n for k in range(n + 1)]
    block = lambda k: F.shiftrightunsigned(fp, edges[k]).bitwiseAND(F.lit((1 << (edges[k + 1] - edges[k])) - 1))
    return F.array(*[
        F.struct(F.lit(t).cast("int").alias("table"), (F.shiftleft(block(i), 32).bitwiseOR(block(j))).alias("bits"))
        for t, (i, j) in enumerate(combinations(range(n), 2))])


def _settle(labels: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Smallest index reachable over the links (a, b), starting from labels."""
    while len(a):
        low = np.minimum(labels[a], labels[b])
        before = labels.copy()
        np.minimum.at(labels, before[a], low)
        np.minimum.at(labels, before[b], low)
        labels = labels[labels]
        labels = labels[labels]
        if np.array_equal(labels, before) and (labels[a] == labels[b]).all():
            break
    return labels


def link_group(fps: np.ndarray, radius: int = RADIUS, tile: int = TILE) -> np.ndarray:
    """Index of the forest root of each fingerprint of one group; fps are ordered by population count."""
    ones = np.bitwise_count(fps).astype(np.int64)
    labels = np.arange(len(fps))
    for i in range(0, len(fps), tile):
        for j in range(i, len(fps), tile):
            if ones[j] - ones[min(i + tile, len(fps)) - 1] > radius:
                break  # later tiles have larger counts still
            near = np.bitwise_count(fps[i : i + tile, None] ^ fps[None, j : j + tile]) <= radius
            a, b = np.nonzero(near)
            keep = a + i < b + j
            labels = _settle(labels, a[keep] + i, b[keep] + j)
    return labels


def link_tiles(classes: DataFrame, radius: int = RADIUS, most: int = GROUP) -> DataFrame:
    """Links (src, dst) between distinct fingerprints (column fp) within the radius: a spanning forest of each tile group.

    A group above ``most`` fingerprints is dealt as pairs of its cells: a fingerprint goes to one of k cells by hash, and to the k
    tasks that compare its cell with another, so that no task holds the group.
    """

    def linked(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[np.ndarray] = []
        key = None

        def close(parts: list[np.ndarray]) -> list[tuple[np.ndarray, np.ndarray]]:
            if sum(map(len, parts)) < 2:
                return []
            fps = np.concatenate(parts)
            root = link_group(fps.view(np.uint64), radius)
            moved = np.flatnonzero(root != np.arange(len(fps)))
            return [(fps[moved], fps[root[moved]])] if len(moved) else []

        for batch in batches:
            group, bits, fps = (batch.column(k).to_numpy(zero_copy_only=False) for k in range(3))
            found: list[tuple[np.ndarray, np.ndarray]] = []
            starts = np.flatnonzero(np.r_[True, (group[1:] != group[:-1]) | (bits[1:] != bits[:-1])]) if len(group) else np.array([], int)
            ends = np.r_[starts[1:], len(group)]
            last = len(starts) - 1
            several = [k for k in range(len(starts)) if k in (0, last) or ends[k] - starts[k] > 1] if len(starts) < 3 else [0, *(np.flatnonzero(ends[1:-1] - starts[1:-1] > 1) + 1).tolist(), last]
            for k in several:
                s, e = starts[k], ends[k]
                at = (int(group[s]), int(bits[s]))
                if at != key:
                    found += close(held)
                    held, key = [], at
                held.append(fps[s:e])
            if found:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(x)) for x in zip(*found, strict=True)], names=["src", "dst"])
        for a, b in close(held):
            yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b)], names=["src", "dst"])

    keyed = classes.select("fp", F.explode(tile_keys(F.col("fp"), radius)).alias("k")).select(F.col("k.table").alias("table"), F.col("k.bits").alias("bits"), "fp")
    # Groups above `most` are at most tables * fingerprints / most, each one row of metadata.
    large = keyed.groupBy("table", "bits").agg(F.count("*").alias("n")).where(F.col("n") > most).select("table", "bits", F.ceil(F.col("n") / (most // 2)).cast("int").alias("cells"))
    dealt = keyed.join(large, ["table", "bits"], "left")
    cell = F.pmod(F.xxhash64("fp"), F.col("cells")).cast("int")
    # the pair of cells (i, j), i <= j, as one number; a cell meets every cell, itself included
    pair = F.transform(F.sequence(F.lit(0), F.col("cells") - 1), lambda j: F.least(cell, j) * F.col("cells") + F.greatest(cell, j) + 1)
    dealt = dealt.select("table", "bits", "fp", F.explode(F.when(F.col("cells").isNull(), F.array(F.lit(0))).otherwise(pair)).alias("pair"))
    dealt = dealt.select((F.col("pair").cast("long") * 1000 + F.col("table")).alias("group"), "bits", "fp")
    dealt = dealt.repartition("group", "bits").sortWithinPartitions("group", "bits", F.bit_count("fp"), "fp")
    return dealt.mapInArrow(linked, "src long, dst long")


def near_groups(prints: DataFrame, radius: int = RADIUS) -> DataFrame:
    """Adds component_id to a staged table of fingerprints: the smallest doc_id reachable over links within the radius."""
    classes = prints.groupBy(F.col("_hs_fp").alias("fp")).agg(F.min("doc_id").alias("rep"))
    links = staged(link_tiles(classes.select("fp"), radius), "links")
    roots = star_components(links).select(F.col("vid").alias("fp"), F.col("component").alias("root"))
    rooted = classes.join(roots, "fp", "left").select("fp", "rep", F.coalesce("root", "fp").alias("root"))
    names = rooted.groupBy("root").agg(F.min("rep").alias("component_id"))
    named = rooted.join(names, "root").select(F.col("fp").alias("_hs_fp"), "component_id")
    return prints.join(named, "_hs_fp")


def op9_simhash_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    prints = staged(fingerprints(spark.read.parquet(f"{sf_dir}/documents.parquet")), "prints")
    return near_groups(prints).select("doc_id", hex_of(F.col("_hs_fp")).alias("fingerprint"), "component_id")
