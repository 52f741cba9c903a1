import random
import zlib
from array import array

import pytest
from pyspark.sql import functions as F

from hubsplit.llm import packing, token_counts, token_output
from hubsplit.llm.encoder import Encoder, default_tokenizer
from hubsplit.shared_dir import fresh_path


def reference(texts, end=2):
    t = Encoder(default_tokenizer()).tokenizer
    return [array("I", [*t.encode(x or "", add_special_tokens=False).ids, end]).tobytes() for x in texts]


def test_chunked_encoding_equals_whole_texts():
    texts = ["  a  b", " a b ", "a \n b", "　x y", "it's 's a", "a \x1cb", "<|endoftext|> x <|endoftext|>", None, "", " ", "\n", "12 34  5", "\x85 a", "a᠎ b c", "foo, bar. baz.\nQux é,", "a.\n\nb", "x\n y", "tab\tx y", "naïve ça.\nÉté"]
    rng = random.Random(0)
    alphabet = ["a", "Be", " ", "  ", "\n", ".", ",", "é", "'s", "9", "\t", "中", " ", "!"]
    texts += ["".join(rng.choice(alphabet) for _ in range(rng.randrange(40))) for _ in range(400)]
    e = Encoder(default_tokenizer(), memo_bytes=2000)
    for _ in range(2):  # the second pass meets a full memo
        assert [x + array("I", [2]).tobytes() for x in e.encode(texts)] == reference(texts)


def test_token_files_round_trip(spark, odd_docs):
    folder = fresh_path(spark, "t")
    manifest = token_output.write_tokens(odd_docs, folder)
    got = token_output.read_tokens(spark, folder, manifest, with_ids=True).orderBy("start").collect()
    rows = sorted(odd_docs.select("doc_id", "text").collect(), key=lambda r: (r["doc_id"] is not None, r["doc_id"] or 0))
    want = reference([r["text"] for r in rows])
    assert [r["doc_id"] for r in got] == [r["doc_id"] for r in rows]
    at = 0
    for r, ids in zip(got, want, strict=True):
        assert (r["start"], r["n_tokens"], r["ids_crc32"]) == (at, len(ids) // 4, zlib.crc32(ids))
        assert array("I", r["ids"]).tobytes() == ids
        at += len(ids) // 4


def test_shard_reads_one_document_and_refuses_another_dictionary(spark, odd_docs):
    w = token_output.ShardWriter(b"", 2)
    ids = reference(["one two", "three"])
    for k, x in enumerate(ids):
        w.add(k, x)
    data = w.finish()
    assert token_output.Shard(data, b"").ids(1) == ids[1]
    with pytest.raises(ValueError):
        token_output.Shard(data, b"other")
    with pytest.raises(ValueError):
        token_output.Shard(data[:40] + b"x" + data[41:], b"") if data[40:41] == b"x" else token_output.Shard(data[:-60] + bytes([data[-60] ^ 1]) + data[-59:], b"")


def test_token_files_of_an_empty_table(spark, no_docs):
    folder = fresh_path(spark, "t")
    assert token_output.read_tokens(spark, folder, token_output.write_tokens(no_docs, folder)).count() == 0


def test_flat_counts_stitch_over_blocks_and_files(spark, odd_docs, saved):
    docs = odd_docs.where("doc_id is not null").dropDuplicates(["doc_id"])
    folder = fresh_path(spark, "f")
    token_counts.write_flat(docs.repartition(3), folder)
    counts = sorted(token_counts.scan_flat(spark, folder, block_ids=7).collect(), key=lambda r: r["ordinal"])
    assert [r["ordinal"] for r in counts] == list(range(docs.count()))
    at = 0
    for r in counts:
        assert r["start"] == at
        at += r["n_tokens"]
    got = {r["doc_id"]: r["n_tokens"] for r in token_counts.op8_token_counts(spark, saved(documents=docs.select("doc_id", "text"))).collect()}
    rows = docs.select("doc_id", "text").collect()
    assert got == {r["doc_id"]: len(x) // 4 for r, x in zip(rows, reference([r["text"] for r in rows]), strict=True)}


def test_flat_counts_of_an_empty_table(spark, no_docs, saved):
    assert token_counts.op8_token_counts(spark, saved(documents=no_docs)).count() == 0


def check_packing(rows, capacity):
    bins = {}
    for r in rows:
        bins.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for held in bins.values():
        at = 0
        for offset, length in sorted(held):
            assert offset == at
            at += length
        assert at <= capacity
    return len(bins)


def test_packing_of_documents(spark, odd_docs):
    from hubsplit.shared_dir import staged

    pieces = staged(packing.token_pieces(odd_docs, 64), "p")
    rows = packing.pack_pieces(pieces, 64).collect()
    assert len(rows) == pieces.count()
    used = check_packing(rows, 64)
    assert used <= -(-sum(r["length"] for r in rows) // 64) + 3
    texts = {r["doc_id"]: r["text"] for r in odd_docs.collect()}
    for doc_id in (1, 2, 3, 4):
        ids = reference([texts[doc_id]])[0]
        own = sorted((r["piece"], r["start"], r["length"], r["ids_crc32"]) for r in rows if r["doc_id"] == doc_id)
        assert sum(p[2] for p in own) == len(ids) // 4
        assert all(p[2] == 64 for p in own[1:])
        assert [p[3] for p in own] == [zlib.crc32(ids[4 * p[1] : 4 * (p[1] + p[2])]) for p in own]


def test_packing_of_nothing(spark, no_docs):
    from hubsplit.shared_dir import staged

    assert packing.pack_pieces(staged(packing.token_pieces(no_docs), "p")).count() == 0


def test_histogram_plan_places_every_piece_once():
    rng = random.Random(3)
    for _ in range(60):
        capacity = rng.choice([5, 10, 64])
        counts = {n: rng.randrange(0, 40) for n in range(1, capacity + 1)}
        runs, opened = packing.plan_runs(dict(counts), capacity)
        fill = {}
        ranks = {n: set() for n in counts}
        for length, lo, hi, first, each, offset in runs:
            for k in range(lo, hi):
                assert k not in ranks[length]
                ranks[length].add(k)
                fill.setdefault(first + (k - lo) // each, []).append((offset + (k - lo) % each * length, length))
        assert all(ranks[n] == set(range(c)) for n, c in counts.items())
        for held in fill.values():
            at = 0
            for offset, length in sorted(held):
                assert offset == at
                at += length
            assert at <= capacity
            assert sum(3 * n > capacity for _, n in held) <= 2
        assert set(fill) == set(range(opened))
        large = sum(c for n, c in counts.items() if 2 * n > capacity)
        assert opened <= max(large, -(-sum(n * c for n, c in counts.items()) * 11 // (9 * capacity)) + 2)



def test_queries_on_odd_documents(spark, odd_docs, saved):
    """The registered queries over nulls, repeated rows, clashing names, and a text of some megabytes."""
    from hubsplit.llm import embedding_dedup

    huge = spark.createDataFrame([(50, "alpha beta, gamma. " * 150_000)], "doc_id long, text string")
    docs = odd_docs.unionByName(huge, allowMissingColumns=True)
    d = saved(documents=docs)
    rows = docs.select("doc_id", "text").collect()
    want = reference([r["text"] for r in rows])
    key = lambda x: (x[0] is not None, x[0] or 0, x[1:])
    got = [(r["doc_id"], r["n_tokens"], r["ids_crc32"]) for r in token_output.op5_token_output(spark, d).collect()]
    assert sorted(got, key=key) == sorted([(r["doc_id"], len(x) // 4, zlib.crc32(x)) for r, x in zip(rows, want, strict=True)], key=key)
    pieces = packing.op2_best_fit_packing(spark, d).collect()
    assert sum(r["length"] for r in pieces) == sum(len(x) // 4 for x in want)
    check_packing(pieces, 1024)
    counts = [(r["doc_id"], r["n_tokens"]) for r in token_counts.op8_token_counts(spark, d).collect()]
    assert sorted(counts, key=key) == sorted([(r["doc_id"], len(x) // 4) for r, x in zip(rows, want, strict=True)], key=key)
    vectors = spark.createDataFrame([(1, [1.0, 0.0], 1), (2, [1.0, 0.01], 1), (2, [1.0, 0.01], 1), (3, None, 1), (None, [0.0, 1.0], None)], "vec_id long, embedding array<float>, label int").withColumn("kept", F.lit("clash"))
    out = embedding_dedup.op7_embedding_dedup(spark, saved(embeddings=vectors)).collect()
    assert sorted((r["vec_id"] or 0, r["n_links"], r["component_id"] or 0, r["kept"]) for r in out) == [(0, 0, 0, True), (1, 2, 1, True), (2, 2, 1, False), (2, 2, 1, False), (3, 0, 3, True)]


def test_running_sums_in_two_levels(spark):
    from hubsplit.llm.prefix import running_bases

    rng = random.Random(2)
    rows = [(f"g{k % 5}", f"g{k % 5}-{k:04d}", rng.randrange(9)) for k in range(200)]
    got = {r["name"]: r["before_n"] for r in running_bases(spark.createDataFrame(rows, "part string, name string, n long"), "part", "name", ["n"]).collect()}
    at = 0
    for _, name, n in sorted(rows):
        assert got[name] == at
        at += n
