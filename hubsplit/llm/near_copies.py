"""Near copies: all pairs of texts whose sets of five-word shingles have a Jaccard similarity of at least 0.8.

The SimHash operator comes first: five-word fingerprints within ``REACH`` bits are linked by its tiled comparison, and each link is
decided on the whole sets. Fingerprints cannot promise every pair (pairs at 0.8 differ by any number of bits), so what they cannot reach
comes from prefixes: when all sets are sorted by one common order, two sets that are similar enough share one of their first
n - ceil(0.8 n) + 1 elements. The order puts shingles that are frequent in a sample last; it decides what a run costs and not what it
finds. Candidates are narrowed by bounds that hold for every similar pair (sizes, positions, parities of 1024 buckets), and each
is then decided on the whole sets.

Equal sets are one class before anything is compared. A first round of prefixes compares the nearest rows of a key only; the second
compares what is not in one component by then, so that a large group of near copies costs its size. Texts without words are one class.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce
from itertools import islice, repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from hubsplit.components import star_components
from hubsplit.llm import simhash
from hubsplit.shared_dir import drop_path, staged, staged_path

SHINGLE, SEED, BUCKETS = 5, 42, 1024
SAMPLE, FREQUENT, MOST_FREQUENT = 16_384, 3, 50_000
NEIGHBOURS, ROWS = 32, 500
#: Pairs whose sets are brought together at once, and in how many rounds at most: a set takes about twice the disk of its text.
ROUND_PAIRS, MOST_ROUNDS = 16_384, 8
#: Differing bits of five-word fingerprints that the first links allow; whole sets decide them.
REACH = 3


def shingle_hashes(text: str | None) -> np.ndarray:
    """Hashes of the five-word shingles, repeats included; fewer words hash as one sequence, no words give none."""
    import xxhash

    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return np.array([], np.int64)
    if len(words) <= SHINGLE:
        return np.array([xxhash.xxh64_intdigest(b" ".join(words), SEED)], np.uint64).view(np.int64)
    grams = map(b" ".join, zip(*(islice(words, k, None) for k in range(SHINGLE))))
    return np.fromiter(map(xxhash.xxh64_intdigest, grams, repeat(SEED)), np.uint64).view(np.int64)


def shingles(text: str | None) -> np.ndarray:
    """The same as a set: sorted and distinct."""
    return np.unique(shingle_hashes(text))


def parities(found: np.ndarray) -> bytes:
    """A bit for each bucket with an odd number of elements: two sets differ in at least as many elements as bits."""
    return np.packbits((np.bincount(found & (BUCKETS - 1), minlength=BUCKETS) & 1).astype(np.uint8)).tobytes()


def possible(n: np.ndarray, m: np.ndarray, i: np.ndarray | None = None, j: np.ndarray | None = None) -> np.ndarray:
    """Whether sets of n and m elements can reach 0.8, given the places of their first common element."""
    fits = 5 * np.minimum(n, m) >= 4 * np.maximum(n, m)
    if i is not None:
        fits &= 9 * (1 + np.minimum(n - i - 1, m - j - 1)) >= 4 * (n + m)
    return fits


def among(found: np.ndarray, listed: np.ndarray) -> np.ndarray:
    """Which elements the sorted list has."""
    return listed[np.minimum(np.searchsorted(listed, found), len(listed) - 1)] == found if len(listed) else np.zeros(len(found), bool)


def few_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The batches in pieces, so that only so many sets are held at once."""
    return (b.slice(k, ROWS) for b in batches for k in range(0, b.num_rows, ROWS))


def with_classes(docs: DataFrame) -> DataFrame:
    """docs with the name of the set of shingles, its size, its parities, and the fingerprint of all shingles."""
    at = docs.columns.index("text")

    def hashed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import xxhash

        for batch in few_rows(batches):
            hashes = [shingle_hashes(t.as_py()) for t in batch.column(at)]
            sets = [np.unique(h) for h in hashes]
            prints = np.array([simhash.majority_bits(iter([h.view(np.uint64)])) for h in hashes], np.uint64).view(np.int64)
            names = np.array([xxhash.xxh3_64_intdigest(s.tobytes(), SEED) for s in sets], np.uint64).view(np.int64)
            new = [pa.array(names), pa.array([len(s) for s in sets], pa.int32()), pa.array([parities(s) for s in sets], pa.binary()), pa.array(prints)]
            yield pa.RecordBatch.from_arrays([*batch.columns, *new], names=[*batch.schema.names, "_hs_class", "_hs_n", "_hs_odd", "_hs_fp"])

    new = [T.StructField("_hs_class", T.LongType()), T.StructField("_hs_n", T.IntegerType()), T.StructField("_hs_odd", T.BinaryType()), T.StructField("_hs_fp", T.LongType())]
    return docs.mapInArrow(hashed, T.StructType([*docs.schema.fields, *new]))


def frequent_shingles(classed: DataFrame) -> np.ndarray:
    """The most frequent shingles of about SAMPLE classes, sorted."""
    share = min(1 << 20, (SAMPLE << 20) // max(1, classed.count()) + 1)

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for t in batch.column(0):
                yield pa.RecordBatch.from_arrays([pa.array(shingles(t.as_py()))], names=["h"])

    drawn = classed.where(F.pmod(F.xxhash64("_hs_class"), F.lit(1 << 20)) < share).dropDuplicates(["_hs_class"]).select("text")
    counts = drawn.mapInArrow(each, "h long").groupBy("h").count().where(F.col("count") >= FREQUENT)
    return np.sort(np.array([r["h"] for r in counts.orderBy(F.desc("count"), "h").limit(MOST_FREQUENT).collect()], np.int64))


def prefixes(classed: DataFrame, frequent: np.ndarray) -> DataFrame:
    """(key, class, n, pos): the prefix of each class, at least once."""

    def keyed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[int] = set()
        for batch in few_rows(batches):
            keys, names, sizes = [], [], []
            for name, t in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                if name in seen:
                    continue
                seen.add(name)
                s = shingles(t.as_py())
                if not len(s):
                    continue
                late = among(s, frequent)
                keys.append(np.concatenate([s[~late], s[late]])[: len(s) + (-4 * len(s)) // 5 + 1])
                names.append(name)
                sizes.append(len(s))
            if keys:
                k = [len(x) for x in keys]
                cols = [np.concatenate(keys), np.repeat(np.array(names, np.int64), k), np.repeat(np.array(sizes, np.int32), k), np.concatenate([np.arange(x, dtype=np.int32) for x in k])]
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in cols], names=["key", "class", "n", "pos"])

    return classed.select("_hs_class", "text").mapInArrow(keyed, "key long, class long, n int, pos int")


def whole_keys(batches: Iterator[pa.RecordBatch]) -> Iterator[list[np.ndarray]]:
    """Columns of sorted batches, cut between keys and without repeated rows (key, class)."""
    held: list[np.ndarray] | None = None
    for batch in batches:
        if not batch.num_rows:
            continue
        cols = [c.to_numpy(zero_copy_only=False) for c in batch.columns]
        if held is not None:
            cols = [np.concatenate(x) for x in zip(held, cols, strict=True)]
        new = np.r_[True, (cols[0][1:] != cols[0][:-1]) | (cols[1][1:] != cols[1][:-1])]
        cols = [c[new] for c in cols]
        cut = int(np.searchsorted(cols[0], cols[0][-1]))
        if cut:
            yield [c[:cut] for c in cols]
        held = [c[cut:] for c in cols]
    if held is not None:
        yield held


def shared_keys(rows: DataFrame) -> DataFrame:
    """The rows of keys that several classes have."""

    def several(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for cols in whole_keys(batches):
            same = cols[0][1:] == cols[0][:-1]
            keep = np.r_[False, same] | np.r_[same, False]
            yield pa.RecordBatch.from_arrays([pa.array(c[keep]) for c in cols], names=["key", "class", "n", "pos"])

    return rows.repartition("key").sortWithinPartitions("key", "class").mapInArrow(several, rows.schema)


def candidates(shared: DataFrame, reach: int | None = None) -> DataFrame:
    """Pairs (a, b) of classes with a common key that may be similar, not in one component yet; with reach, among neighbours only."""

    def paired(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for key, name, n, pos, comp in whole_keys(batches):
            left, step = np.arange(len(key) - 1), 0
            while len(left) and step != reach:
                step += 1
                left = left[left + step < len(key)]
                left = left[key[left] == key[left + step]]
                right = left + step
                good = possible(n[left], n[right], pos[left], pos[right]) & (comp[left] != comp[right])
                if good.any():
                    yield pa.RecordBatch.from_arrays([pa.array(name[left[good]]), pa.array(name[right[good]])], names=["a", "b"])

    dealt = shared.repartition("key").sortWithinPartitions("key", "class")
    return dealt.mapInArrow(paired, "a long, b long").distinct()


def _round(end: str, rounds: int) -> Column:
    """The round in which a pair is decided, from its first class."""
    return F.pmod(F.xxhash64(end), F.lit(rounds))


def asked_in(kept: DataFrame, rounds: int) -> DataFrame:
    """(_hs_class, asked): the ends of pairs, and a bit for each round that a class is the second end in; no other round moves its set for that."""
    ends = kept.select(F.col("a").alias("_hs_class"), F.lit(0).cast("long").alias("asked"))
    ends = ends.union(kept.select("b", F.expr(f"shiftleft(1L, cast(pmod(xxhash64(a), {rounds}) AS int))")))
    return ends.groupBy("_hs_class").agg(F.bit_or("asked").alias("asked"))


def similar(pairs: DataFrame, classed: DataFrame) -> DataFrame:
    """The candidates (a, b) whose sets have a Jaccard similarity of at least 0.8, staged."""

    def narrowed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            odd = [np.frombuffer(b"".join(batch.column(k).to_pylist()), np.uint64).reshape(batch.num_rows, -1) for k in (4, 5)]
            differ = np.bitwise_count(odd[0] ^ odd[1]).sum(axis=1, dtype=np.int64)
            total = batch.column(2).to_numpy().astype(np.int64) + batch.column(3).to_numpy()
            yield batch.select([0, 1]).filter(pa.array(9 * differ <= total))

    def hashed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for name, text, asked in zip(*batch.columns, strict=True):
                cols = [pa.array([name.as_py()], pa.int64()), pa.array([asked.as_py()], pa.int64()), pa.array([shingles(text.as_py())], pa.list_(pa.int64()))]
                yield pa.RecordBatch.from_arrays(cols, names=["class", "asked", "found"])

    side = lambda end: classed.select(F.col("_hs_class").alias(end), F.col("_hs_n").alias(f"n_{end}"), F.col("_hs_odd").alias(f"odd_{end}")).dropDuplicates([end])
    met = pairs.join(side("a"), "a").join(side("b"), "b").select("a", "b", "n_a", "n_b", "odd_a", "odd_b")
    kept = staged(met.mapInArrow(narrowed, "a long, b long"), "pairs")
    rounds = min(MOST_ROUNDS, 1 + kept.count() // ROUND_PAIRS)
    ends = staged(asked_in(kept, rounds), "ends")  # staged, so that its size is known to the join
    texts = classed.select("_hs_class", "text").join(ends, "_hs_class").dropDuplicates(["_hs_class"])
    sets = staged(texts.select("_hs_class", "text", "asked").mapInArrow(hashed, "class long, asked long, found array<long>"), "sets")
    common = F.size(F.array_intersect("of_a", "of_b"))
    found = []
    for k in range(rounds):  # what a round shuffles is gone when the next begins
        of_a = sets.where(_round("class", rounds) == k).select(F.col("class").alias("a"), F.col("found").alias("of_a"))
        of_b = sets.where(F.col("asked").bitwiseAND(F.lit(1 << k)) != 0).select(F.col("class").alias("b"), F.col("found").alias("of_b"))
        both = kept.where(_round("a", rounds) == k).join(of_a, "a").join(of_b, "b")
        found.append(staged(both.where(9 * common >= 4 * (F.size("of_a") + F.size("of_b"))).select("a", "b"), "links"))
    links = found[0] if rounds == 1 else staged(reduce(DataFrame.union, found), "links")
    for done in (kept, ends, sets, *(found if rounds > 1 else ())):
        drop_path(classed.sparkSession, staged_path(done))
    return links


def by_fingerprint(classed: DataFrame) -> DataFrame:
    """Pairs (a, b) of classes from the SimHash operator: a forest of fingerprints within ``REACH`` bits, and classes of one fingerprint."""
    classes = classed.where("_hs_n > 0").select("_hs_class", "_hs_fp").distinct()
    named = staged(classes.groupBy(F.col("_hs_fp").alias("fp")).agg(F.min("_hs_class").alias("first")), "fingerprints")
    links = simhash.link_tiles(named.select("fp"), REACH)
    end = lambda column, name: named.select(F.col("fp").alias(column), F.col("first").alias(name))
    apart = links.join(end("src", "a"), "src").join(end("dst", "b"), "dst").select("a", "b")
    alike = classes.join(end("_hs_fp", "a"), "_hs_fp").where("a <> _hs_class").select("a", F.col("_hs_class").alias("b"))
    return apart.union(alike).distinct()


def near_copies(docs: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Staged docs with their class, and the copies (doc_id, _hs_class): all but the smallest doc_id of each component."""
    classed = staged(with_classes(docs), "classed")
    rows = prefixes(classed, frequent_shingles(classed))
    shared = staged(shared_keys(rows), "shared")
    near = staged(similar(by_fingerprint(classed), classed).union(similar(candidates(shared.withColumn("comp", F.col("class")), NEIGHBOURS), classed)), "near")
    roots = star_components(near.toDF("src", "dst")).toDF("class", "root")
    rooted = shared.join(roots, "class", "left").select("key", "class", "n", "pos", F.coalesce("root", "class").alias("comp"))
    rest = similar(candidates(rooted), classed)
    roots = staged(star_components(near.union(rest).toDF("src", "dst")).toDF("_hs_class", "root"), "roots")
    for done in (shared, near, rest):
        drop_path(docs.sparkSession, staged_path(done))
    # Staged, so that the last join is dealt by itself: a group of thousands of copies is split among tasks like any skewed key.
    ids = staged(classed.select("doc_id", "_hs_class").distinct().join(roots, "_hs_class", "left").withColumn("root", F.coalesce("root", "_hs_class")), "members")
    names = staged(ids.groupBy("root").agg(F.min("doc_id").alias("first"), F.count("*").alias("many")).where("many > 1").select("root", "first"), "firsts")
    return classed, ids.join(names, "root").where(F.col("doc_id") != F.col("first")).select("doc_id", "_hs_class")
