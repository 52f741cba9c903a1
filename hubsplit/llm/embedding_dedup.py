"""Embedding near-duplicates: PCA-ordered tiled comparison with suffix-norm bounds.

Equal vectors of a label are one class. Class vectors are scaled to length one and turned into the axes of the second-moment matrix,
largest first. Two vectors with cosine >= t are at most delta = sqrt(2 - 2t) apart, so cells of width delta along the leading
axes meet only their neighbours; a cell is cut into tiles of a bounded number of vectors, and a label that fits in one tile is sent
once. Only the given vectors travel: a task turns its tiles itself, orders them along the first axis, and goes through them square by
square. A square whose sides lie too far apart there is skipped; another adds up products of the leading dimensions first, bounds the
rest by the product of the suffix norms, and stops when no pair can reach t. Pairs that survive are decided by the cosine of the given
vectors in double precision.

A tile pair reports how many vectors each class is linked to and a spanning forest of its links, never the pairs, so output
follows the number of vectors. Work inside one label is quadratic in what the cells leave together; that is the method's nature.

Defined results: vectors that are null, zero, or hold null or non-finite components, and vectors of null label, link with nothing;
vectors of different dimension do not link; a null vec_id names a component only if all of its members are null; repeated rows
are copies of each other; an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from hubsplit.components import star_components
from hubsplit.llm.simhash import _settle
from hubsplit.shared_dir import staged

THRESHOLD, TILE, SQUARE, AXES, STEP = 0.98, 8192, 1024, 6, 8


def usable(v: Column) -> Column:
    """Not null, finite throughout, and not all zero."""
    bad = F.exists(v, lambda x: x.isNull() | F.isnan(x) | (F.abs(x.cast("double")) == F.lit(float("inf"))))
    return F.coalesce(v.isNotNull() & ~bad & F.exists(v, lambda x: x != 0), F.lit(False))


def classes_of(vectors: DataFrame) -> DataFrame:
    """One row per distinct (label, vector): class number, how many, smallest vec_id. Staged, so that the numbers hold."""
    good = vectors.where(usable(F.col("embedding")) & F.col("label").isNotNull())
    grouped = good.groupBy("label", "embedding").agg(F.count("*").alias("many"), F.min("vec_id").alias("first_id"))
    return staged(grouped.select(F.monotonically_increasing_id().alias("class"), "label", F.size("embedding").alias("dim"), "embedding", "many", "first_id"), "vector-classes")


def _unit(batch_column, dim: int) -> np.ndarray:
    x = np.asarray(batch_column.flatten().to_numpy(zero_copy_only=False), np.float64).reshape(-1, dim)
    x = x / np.abs(x).max(axis=1, keepdims=True)
    return x / np.sqrt((x * x).sum(axis=1, keepdims=True))


def principal_axes(classes: DataFrame) -> dict[int, np.ndarray]:
    """Axes (columns, largest first) for each dimension. Moments are summed by Spark: dim * dim numbers reach the driver."""

    def moments(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[int, np.ndarray] = {}
        for batch in batches:
            dims = batch.column(0).to_numpy()
            for d in np.unique(dims):
                x = _unit(batch.column(1).filter(pa.array(dims == d)), int(d))
                sums[int(d)] = sums.get(int(d), 0) + x.T @ x
        for d, m in sums.items():
            yield pa.RecordBatch.from_pydict({"dim": pa.array(np.full(d * d, d, np.int32)), "i": pa.array(np.arange(d * d)), "v": pa.array(m.ravel())})

    rows = classes.select("dim", "embedding").mapInArrow(moments, "dim int, i long, v double").groupBy("dim", "i").agg(F.sum("v").alias("v")).toPandas()
    axes = {}
    for d, own in rows.groupby("dim"):
        m = np.zeros(d * d)
        m[own["i"].to_numpy()] = own["v"].to_numpy()
        _, vectors = np.linalg.eigh(m.reshape(d, d))
        axes[int(d)] = vectors[:, ::-1].copy()
    return axes


def celled(classes: DataFrame, axes: dict[int, np.ndarray], delta: float, tile: int = TILE) -> DataFrame:
    """Adds each vector's cell along the leading axes."""
    sent = classes.sparkSession.sparkContext.broadcast(axes)

    def turn(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            dims = batch.column(2).to_numpy()
            for d in np.unique(dims):
                own = batch.filter(pa.array(dims == d))
                cells = np.floor(_unit(own.column(3), int(d)) @ sent.value[int(d)][:, :AXES] / delta).astype(np.int32)
                cells = np.pad(cells, ((0, 0), (0, AXES - cells.shape[1])))
                columns = [*(own.column(k) for k in range(5)), pa.array(list(cells), pa.list_(pa.int32()))]
                yield pa.RecordBatch.from_arrays(columns, names=["class", "label", "dim", "embedding", "many", "cell"])

    label = classes.schema["label"].dataType.simpleString()
    kind = classes.schema["embedding"].dataType.simpleString()
    points = classes.select("class", "label", "dim", "embedding", "many").mapInArrow(turn, f"class long, label {label}, dim int, embedding {kind}, many long, cell array<int>")
    # A label uses as many axes as leave about a tile in a cell, so that small labels are one cell and large ones many.
    sizes = classes.groupBy("label", "dim").agg(F.count("*").alias("n"))
    axes_used = F.least(F.lit(AXES), F.greatest(F.lit(0), F.ceil(F.log(F.col("n") / tile) / F.log(F.lit(4.0))))).cast("int")
    sizes = staged(sizes.select("label", "dim", axes_used.alias("used")), "label-sizes")  # a row for each label
    cut = F.transform("cell", lambda x, k: F.when(k < F.col("used"), x).otherwise(0))
    return points.join(sizes, ["label", "dim"]).withColumn("cell", cut).drop("used")


def compare(a: dict, b: dict, same: bool, threshold: float, square: int = SQUARE) -> tuple[np.ndarray, np.ndarray]:
    """Index pairs of two tiles with cosine at or above the threshold; of one tile with itself, each pair once.

    Tiles are ordered along the first axis; squares that lie further apart there than two near vectors can are skipped.
    """
    delta, out_i, out_j = np.sqrt(max(0.0, 2 - 2 * threshold)) + 1e-6, [], []
    for p in range(0, len(a["turned"]), square):
        x = a["turned"][p : p + square]
        for q in range(p if same else 0, len(b["turned"]), square):
            y = b["turned"][q : q + square]
            if y[0, 0] - x[-1, 0] > delta:
                break  # later squares lie further still
            if x[0, 0] - y[-1, 0] > delta:
                continue
            i, j = _compare_square(x, y, same and p == q, threshold)
            for s in range(0, len(i), 100_000):
                m, n = i[s : s + 100_000] + p, j[s : s + 100_000] + q
                u, v = a["given"][m], b["given"][n]
                near = (u * v).sum(axis=1) / (a["norm"][m] * b["norm"][n]) >= threshold
                out_i.append(m[near])
                out_j.append(n[near])
    return (np.concatenate(out_i), np.concatenate(out_j)) if out_i else (np.array([], int), np.array([], int))


def _compare_square(x: np.ndarray, y: np.ndarray, same: bool, threshold: float) -> tuple[np.ndarray, np.ndarray]:
    """Pairs that may reach the threshold: products of leading dimensions, and the suffix norms' product for the rest."""
    dim, slack = x.shape[1], 1e-9
    done = min(STEP, dim)
    products = x[:, :done] @ y[:, :done].T
    while done < dim:
        rest = np.sqrt((x[:, done:] ** 2).sum(axis=1))[:, None] * np.sqrt((y[:, done:] ** 2).sum(axis=1))[None, :]
        alive = products + rest >= threshold - slack
        if same:
            alive &= np.tri(len(x), k=-1, dtype=bool).T
        i, j = np.nonzero(alive)
        if len(i) * 8 < products.size:
            return i, j
        more = min(2 * done, dim)
        products += x[:, done:more] @ y[:, done:more].T
        done = more
    i, j = np.nonzero(products >= threshold - slack)
    return (i[i < j], j[i < j]) if same else (i, j)


def tile_pairs(points: DataFrame, tile: int = TILE) -> DataFrame:
    """(pair, cell key, sub, side) for each tile in each pair of tiles that may hold a link; one row of metadata per cell is joined."""
    cells = points.groupBy("label", "dim", "cell").agg(F.count("*").alias("n")).withColumn("subs", F.ceil(F.col("n") / tile).cast("int"))
    a = cells.select("label", "dim", F.col("cell").alias("ca"), F.col("subs").alias("sa"), F.explode(F.array(F.element_at("cell", 1), F.element_at("cell", 1) + 1)).alias("lead"))
    b = cells.select("label", "dim", F.col("cell").alias("cb"), F.col("subs").alias("sb"), F.element_at("cell", 1).alias("lead"))
    close = F.forall(F.zip_with("ca", "cb", lambda p, q: F.abs(p - q) <= 1), lambda t: t)
    ordered = (F.element_at("ca", 1) < F.col("lead")) | (F.col("ca") <= F.col("cb"))
    met = a.join(b, ["label", "dim", "lead"]).where(close & ordered)
    subs = met.withColumn("i", F.explode(F.sequence(F.lit(0), F.col("sa") - 1))).withColumn("j", F.explode(F.sequence(F.lit(0), F.col("sb") - 1)))
    subs = subs.where((F.col("ca") != F.col("cb")) | (F.col("i") <= F.col("j")))
    return subs.select("label", "dim", "ca", "i", "cb", "j")


def links(points: DataFrame, axes: dict[int, np.ndarray], threshold: float = THRESHOLD, tile: int = TILE) -> DataFrame:
    """(class, linked, root) from every tile pair: vectors linked to a class there, and the class its forest hangs it on."""
    pairs = staged(tile_pairs(points, tile).withColumn("pair", F.monotonically_increasing_id()), "tile-pairs")
    sides = pairs.select("label", "dim", F.col("ca").alias("cell"), F.col("i").alias("sub"), "pair", F.when((F.col("ca") == F.col("cb")) & (F.col("i") == F.col("j")), 2).otherwise(0).alias("side")).union(
        pairs.where("ca <> cb or i <> j").select("label", "dim", "cb", "j", "pair", F.lit(1)))
    # Staged: a row for each cell, whose size is known when the join is planned.
    cells = staged(points.groupBy("label", "dim", "cell").agg(F.ceil(F.count("*") / tile).alias("subs")), "cells")
    cut = points.join(cells, ["label", "dim", "cell"]).withColumn("sub", F.pmod(F.xxhash64("class"), F.col("subs")).cast("int"))
    sent = cut.join(sides, ["label", "dim", "cell", "sub"]).select("pair", "side", "class", "many", "embedding")
    dealt = sent.repartition("pair").sortWithinPartitions("pair", "side", "class")
    known = points.sparkSession.sparkContext.broadcast(axes)  # dim * dim numbers

    def linked(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def tile_of(part: pa.Table) -> dict:
            n = part.num_rows
            given = np.asarray(part.column("embedding").combine_chunks().flatten().to_numpy(zero_copy_only=False), np.float64).reshape(n, -1)
            given = given / np.abs(given).max(axis=1, keepdims=True)
            norm = np.sqrt((given * given).sum(axis=1))
            turned = (given / norm[:, None]) @ known.value[given.shape[1]]
            order = np.argsort(turned[:, 0], kind="stable")
            return {"class": part.column("class").to_numpy()[order], "many": part.column("many").to_numpy()[order], "given": given[order], "norm": norm[order], "turned": turned[order]}

        def close(parts: list[pa.RecordBatch]) -> pa.RecordBatch | None:
            if not parts:
                return None
            table = pa.Table.from_batches(parts)
            side = table.column("side").to_numpy()
            same = bool((side == 2).any())
            if not same and (not (side == 0).any() or not (side == 1).any()):
                return None  # a tile without vectors
            a = tile_of(table.filter(pa.array(side != 1)))
            b = a if same else tile_of(table.filter(pa.array(side == 1)))
            i, j = compare(a, b, same, threshold)
            if not len(i):
                return None
            names = a["class"] if same else np.concatenate([a["class"], b["class"]])
            far = j if same else j + len(a["class"])
            linked = np.zeros(len(names), np.int64)
            np.add.at(linked, i, b["many"][j])
            np.add.at(linked, far, a["many"][i])
            root = _settle(np.arange(len(names)), i, far)
            used = np.flatnonzero(linked)
            return pa.RecordBatch.from_pydict({"class": pa.array(names[used]), "linked": pa.array(linked[used]), "root": pa.array(names[root[used]])})

        key, held = None, []
        for batch in batches:
            pair = batch.column(0).to_numpy()
            starts = np.flatnonzero(np.r_[True, pair[1:] != pair[:-1]]) if len(pair) else np.array([], int)
            for s, e in zip(starts, [*starts[1:], len(pair)], strict=True):
                if pair[s] != key:
                    if (out := close(held)) is not None:
                        yield out
                    key, held = pair[s], []
                held.append(batch.slice(s, e - s))
        if (out := close(held)) is not None:
            yield out

    return dealt.mapInArrow(linked, "class long, linked long, root long")


def near_vectors(vectors: DataFrame, threshold: float = THRESHOLD, tile: int = TILE) -> DataFrame:
    """vec_id, n_links, component_id and kept for every row of (vec_id, label, embedding)."""
    vectors = vectors.select("vec_id", "label", "embedding")
    classes = classes_of(vectors)
    axes = principal_axes(classes)
    points = staged(celled(classes, axes, float(np.sqrt(2 - 2 * threshold)) + 1e-6, tile), "celled")
    found = staged(links(points, axes, threshold, tile), "vector-links")
    linked = found.groupBy("class").agg(F.sum("linked").alias("linked"))
    roots = star_components(found.select(F.col("class").alias("src"), F.col("root").alias("dst"))).withColumnRenamed("vid", "class")
    table = classes.join(linked, "class", "left").join(roots, "class", "left").withColumn("component", F.coalesce("component", "class"))
    names = table.groupBy("component").agg(F.min("first_id").alias("component_id"))
    table = table.join(names, "component").select("label", "embedding", (F.coalesce("linked", F.lit(0)) + F.col("many") - 1).alias("n_links"), "component_id")
    keyed = vectors.withColumn("_usable", usable(F.col("embedding")))
    joined = keyed.where("_usable and label is not null").join(table, ["label", "embedding"]).select("vec_id", "n_links", "component_id")
    alone = keyed.where("not _usable or label is null").select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"))
    return joined.union(alone).withColumn("kept", F.col("vec_id").eqNullSafe(F.col("component_id")))


def op7_embedding_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_vectors(spark.read.parquet(f"{sf_dir}/embeddings.parquet"))
