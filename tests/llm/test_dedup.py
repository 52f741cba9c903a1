import hashlib
import random

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from hubsplit.llm import embedding_dedup, simhash, suffix_dedup

WS = " \t\n\x0b\x0c\r"


def slow_fingerprint(text, k=3):
    words, at = [], ""
    for c in text or "":
        c = c.lower() if "A" <= c <= "Z" else c
        if c in WS:
            words += [at] if at else []
            at = ""
        else:
            at += c
    words += [at] if at else []
    if not words:
        return 0
    grams = [" ".join(words[i : i + k]) for i in range(len(words) - k + 1)] or [" ".join(words)]
    hs = [xxhash.xxh64_intdigest(g.encode(), 42) for g in grams]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > len(hs))


def components(n, links):
    label = list(range(n))
    changed = True
    while changed:
        changed = False
        for a, b in links:
            low = min(label[a], label[b])
            if label[a] != low or label[b] != low:
                label[a] = label[b] = low
                changed = True
    return label


def test_fingerprints(odd_docs):
    for r in odd_docs.select("text").collect():
        assert simhash.fingerprint(r["text"]) == slow_fingerprint(r["text"])
    assert simhash.fingerprint("A É\x1cb c d e") == slow_fingerprint("A É\x1cb c d e")


def test_simhash_components(spark, odd_docs, saved):
    rng = random.Random(5)
    base = [rng.randrange(1 << 64) for _ in range(30)]
    fps = [b ^ sum(1 << x for x in rng.sample(range(64), rng.randrange(4))) for b in base for _ in range(12)] + base[:3] * 4
    signed = [f - (1 << 64) if f >> 63 else f for f in fps]
    prints = spark.createDataFrame([(i, f) for i, f in enumerate(signed)], "doc_id long, _hs_fp long")
    got = {r["doc_id"]: r["component_id"] for r in simhash.near_groups(prints).collect()}
    links = [(i, j) for i in range(len(fps)) for j in range(i) if (fps[i] ^ fps[j]).bit_count() <= 2]
    assert got == dict(enumerate(components(len(fps), links)))
    out = simhash.op9_simhash_dedup(spark, saved(documents=odd_docs)).collect()
    assert len(out) == odd_docs.count()
    by = {r["doc_id"]: r for r in out}
    assert by[2]["fingerprint"] == "0" * 16 and by[2]["component_id"] == by[3]["component_id"] == by[8]["component_id"] == 2
    assert by[5]["component_id"] == by[7]["component_id"] == 5


def test_tiles_are_compared_exactly():
    rng = np.random.default_rng(1)
    fps = rng.integers(0, 1 << 12, 3000, dtype=np.uint64)
    fps = np.unique(fps)
    fps = fps[np.argsort(np.bitwise_count(fps), kind="stable")]
    root = simhash.link_group(fps, 1, tile=64)
    near = np.bitwise_count(fps[:, None] ^ fps[None, :]) <= 1
    a, b = np.nonzero(np.triu(near, 1))
    assert root.tolist() == components(len(fps), list(zip(a.tolist(), b.tolist(), strict=True)))


def test_simhash_of_nothing(spark, no_docs, saved):
    assert simhash.op9_simhash_dedup(spark, saved(documents=no_docs)).count() == 0


# --- repeated strings ---------------------------------------------------------------------------------------------------------------


def test_suffix_array():
    rng = random.Random(1)
    for _ in range(2000):
        s = [rng.randrange(rng.choice([1, 2, 3, 6])) for _ in range(rng.randrange(40))]
        assert suffix_dedup.suffix_array(s) == sorted(range(len(s)), key=lambda i: s[i:])


def slow_removal(rows, length=50):
    """(doc_id, text) rows: for each row the bytes kept and the maximal removed runs."""
    owner = {}
    for doc_id, text in rows:
        b = (text or "").encode()
        if doc_id is not None:
            for i in range(len(b) - length + 1):
                w = b[i : i + length]
                owner[w] = min(owner.get(w, doc_id), doc_id)
    out = []
    for doc_id, text in rows:
        b = (text or "").encode()
        gone = [False] * len(b)
        if doc_id is not None:
            for i in range(len(b) - length + 1):
                if owner[b[i : i + length]] < doc_id:
                    gone[i : i + length] = [True] * length
        runs = sum(g and not (i and gone[i - 1]) for i, g in enumerate(gone))
        out.append((doc_id, len(b), sum(gone), runs, hashlib.sha256(bytes(c for c, g in zip(b, gone, strict=True) if not g)).hexdigest()))
    return out


def removal(spark, folder):
    return [tuple(r) for r in suffix_dedup.op6_suffix_dedup(spark, folder).select("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256").collect()]


KEY = lambda r: (r[0] is not None, r[0] or 0, r[1:])


def test_repeated_strings_of_odd_documents(spark, odd_docs, saved):
    rows = [(r["doc_id"], r["text"]) for r in odd_docs.collect()]
    assert sorted(removal(spark, saved(documents=odd_docs)), key=KEY) == sorted(slow_removal(rows), key=KEY)


@pytest.mark.parametrize("hot", [False, True])
def test_repeated_strings_of_random_mixtures(spark, saved, monkeypatch, hot):
    rng = random.Random(11)
    parts = ["".join(rng.choice("abc é") for _ in range(rng.randrange(20, 160))) for _ in range(14)] + ["ab" * 60, "z" * 90]
    rows = []
    for k in range(120):
        text = "".join(rng.choice(parts) if rng.random() < 0.7 else "".join(rng.choice("xyz \n") for _ in range(rng.randrange(60))) for _ in range(rng.randrange(1, 6)))
        if rng.random() < 0.3 and len(text) > 10:
            at = rng.randrange(len(text))
            text = text[:at] + "#" + text[at + 1 :]
        rows.append((rng.randrange(100) if k % 9 else k, text))
    if hot:  # anchors with two entries and more are dealt string by string
        monkeypatch.setattr(suffix_dedup, "HOT_SHARE", 10**9)
        monkeypatch.setattr(suffix_dedup, "HOT_FLOOR", 1)
    df = spark.createDataFrame(rows, "doc_id long, text string")
    assert (suffix_dedup.shared_anchors(tagged(df), 4).where("doc_id is null").count() > 0) == hot
    assert sorted(removal(spark, saved(documents=df)), key=KEY) == sorted(slow_removal(rows), key=KEY)


def tagged(docs):
    return docs.withColumn("tag", F.xxhash64("text").bitwiseAND(F.lit((1 << suffix_dedup.TAG_BITS) - 1)))


def test_many_texts_under_one_doc_id(spark, saved):
    rng = random.Random(5)
    passage = "".join(rng.choice("abcdefgh ") for _ in range(90))
    rows = [(7 if k else 1, f"{k} " + passage + "x" * (k % 4)) for k in range(60)] + [(7, "0 " + passage)] * 3 + [(9, passage)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    assert sorted(removal(spark, saved(documents=df)), key=KEY) == sorted(slow_removal(rows), key=KEY)


def test_the_array_decides_between_contexts(monkeypatch):
    """Two contexts of one anchor that agree to the left of a byte: its classes alone say which strings are shared."""
    asked = []
    whole = suffix_dedup.equal_strings
    monkeypatch.setattr(suffix_dedup, "equal_strings", lambda pieces, *a: asked.append(len(pieces)) or whole(pieces, *a))
    one = np.frombuffer(b"q" * 30 + b"abcdefghijklmnopqrst" + b"z" * 30, np.uint8)
    two = one.copy()
    two[60] = 1
    flank = np.full(2, 30, np.uint8)
    found = list(suffix_dedup._owned(np.array([5, 5], np.uint64), np.array([1, 2]), np.zeros(2, np.int64), np.array([100, 200]), flank, flank, np.stack([one, two]), 50, 20))
    assert asked == [1] and [x.tolist() for x in found[0]] == [[2], [0], [170], [230]]


def test_text_is_exchanged_once(spark, saved, odd_docs):
    """The exchange that brings texts to their anchors is used again for the removal."""
    docs = spark.read.parquet(saved(documents=odd_docs) + "/documents.parquet").select("doc_id", "text")
    old = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        out = suffix_dedup.deduplicate(docs)
        out.collect()
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", old)
    final = out._jdf.queryExecution().executedPlan().toString().split("Initial Plan")[0]
    assert "ReusedExchange" in final


def test_hot_anchors_are_dealt_string_by_string(spark):
    """The same spans when every anchor counts as hot."""
    rng = random.Random(2)
    passage = "".join(rng.choice("abcdefgh ") for _ in range(140))
    rows = [(k, "".join(rng.choice("klmnop ") for _ in range(30)) + passage[rng.randrange(40) : 100 + rng.randrange(40)]) for k in range(40)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    docs = tagged(docs)
    anchors = suffix_dedup.shared_anchors(docs, 4).cache()
    data = passage.encode()
    h = suffix_dedup.gram_hashes(np.frombuffer(data, np.uint8), suffix_dedup.GRAM)
    hot = suffix_dedup._name(h, 4) * np.uint64(4) + h % np.uint64(4)

    def spans(hot):
        found = {}
        for r in suffix_dedup.removed_spans(docs, anchors, hot, 4).collect():
            found.setdefault(r["doc_id"], []).append((r["start"], r["end"]))
        return {k: suffix_dedup.merge_spans(v) for k, v in found.items()}

    assert spans(hot) == spans(np.array([], np.uint64)) != {}


def test_spans_are_joined_before_they_leave_their_task(spark):
    """each task sent a row for every context it met, so that the rows grew with the number of tasks."""
    rng = random.Random(3)
    passage = "".join(rng.choice("abcdefgh ") for _ in range(2000))
    docs = tagged(spark.createDataFrame([(k, f"{k} {passage}") for k in range(20)], "doc_id long, text string").repartition(20)).cache()
    anchors = suffix_dedup.shared_anchors(docs, 16).cache()
    rows = suffix_dedup.removed_spans(docs, anchors, np.array([], np.uint64), 16).collect()
    assert len(rows) == 19 and {r["end"] - r["start"] for r in rows} == {2001}


def test_grams_that_meet_by_chance_are_not_kept(spark):
    """op6: every anchor whose 20 bytes stood in two documents was sent with its context; such grams grow in number faster than the corpus."""
    rng = random.Random(8)
    letters = lambda n: "".join(rng.choice("abcdefghijklmnop ") for _ in range(n))
    phrase, passage = letters(26), letters(60)
    docs = tagged(spark.createDataFrame([(k, letters(90) + phrase + letters(90)) for k in range(60)], "doc_id long, text string").repartition(3))
    assert suffix_dedup.shared_anchors(docs, 4).where("tag >= 0").count() == 0
    docs = docs.union(tagged(spark.createDataFrame([(k, letters(70) + passage) for k in (100, 101)] + [(7, letters(40) + passage[5:57] + letters(40))], "doc_id long, text string")))
    found = suffix_dedup.shared_anchors(docs, 4).where("tag >= 0").collect()
    assert sorted(r["doc_id"] for r in found) == [7, 100, 101]  # one row a text


def test_contexts_of_a_corpus_of_copies_take_turns(spark, saved, monkeypatch):
    """op6: where everything repeats, contexts of all anchors stood on the disk at once, some five times the text."""
    rng = random.Random(12)
    texts = ["".join(rng.choice("abcdefgh é") for _ in range(400)) for _ in range(12)]
    rows = [(k, texts[k % 12] + texts[(k + k // 12) % 12][100:300]) for k in range(48)]
    asked = []
    whole = suffix_dedup.removed_spans
    monkeypatch.setattr(suffix_dedup, "TURN_FLOOR", 1)
    monkeypatch.setattr(suffix_dedup, "removed_spans", lambda *a: asked.append(a[6:]) or whole(*a))
    got = removal(spark, saved(documents=spark.createDataFrame(rows, "doc_id long, text string")))
    assert asked[1:] == [(0, 3), (1, 3), (2, 3)]
    assert sorted(got, key=KEY) == sorted(slow_removal(rows), key=KEY)


@pytest.mark.parametrize(("length", "gram"), [(50, 20), (50, 49), (50, 50), (30, 9)])
def test_equal_strings_have_an_equal_side(length, gram):
    """Wherever its anchor stands in it, a string fixes one of the anchor's two digests."""
    rng = np.random.default_rng(3)
    string = rng.integers(0, 256, length, dtype=np.uint8)
    for at in range(length - gram + 1):
        sides = []
        for lead, trail in ((0, 0), (45, 3), (2, 70), (90, 90)):
            text = np.concatenate([rng.integers(0, 256, lead, dtype=np.uint8), string, rng.integers(0, 256, trail, dtype=np.uint8)])
            sides.append([int(x[0]) for x in suffix_dedup.side_digests(text, np.array([lead + at]), length, gram)])
        left, right = zip(*sides, strict=True)
        assert len(set(left)) == 1 or len(set(right)) == 1


def test_repeated_strings_of_nothing(spark, no_docs, saved):
    assert removal(spark, saved(documents=no_docs)) == []


# --- embeddings ------------------------------------------------------------------------------------------------------------------------


@pytest.mark.parametrize("tile", [4, 2048])
def test_near_vectors(spark, tile):
    rng = np.random.default_rng(4)
    centres = rng.normal(size=(12, 16))
    rows = []
    for i in range(300):
        v = centres[rng.integers(12)] + rng.normal(size=16) * rng.choice([0.02, 0.12, 1.0])
        rows.append((i, [float(np.float32(x)) for x in v], int(rng.integers(2))))
    rows += [(300 + k, rows[k][1], rows[k][2]) for k in range(40)] + [(340, [2 * x for x in rows[0][1]], rows[0][2])]
    odd = [(400, None, 1), (401, [0.0] * 16, 1), (402, [float("nan")] * 16, 1), (403, [None, *rows[0][1][1:]], 0), (404, rows[0][1], None), (405, [1.0, 2.0], 0), (406, [1.0, 2.0], 0), (None, rows[1][1], rows[1][2]), (407, [float("inf")] * 16, 0)]
    df = spark.createDataFrame(rows + odd, "vec_id long, embedding array<float>, label int").withColumn("class", F.lit("clash")).withColumn("n_links", F.lit(-1))
    got = {r["vec_id"]: r for r in embedding_dedup.near_vectors(df, tile=tile).collect()}
    good = [r for r in rows + odd if r[1] and all(x is not None and np.isfinite(x) for x in r[1]) and any(r[1]) and r[2] is not None]
    x = [np.array(r[1], np.float64) for r in good]
    links = [(i, j) for i in range(len(good)) for j in range(i) if good[i][2] == good[j][2] and len(x[i]) == len(x[j]) and x[i] @ x[j] / (np.linalg.norm(x[i]) * np.linalg.norm(x[j])) >= 0.98]
    ids = [r[0] for r in good]
    label = components(len(good), links)
    count = np.bincount([k for link in links for k in link], minlength=len(good))
    members = {}
    for i, root in enumerate(label):
        members.setdefault(root, []).append(ids[i])
    for i, r in enumerate(good):
        low = min(m for m in members[label[i]] if m is not None)
        assert (got[r[0]]["n_links"], got[r[0]]["component_id"], got[r[0]]["kept"]) == (count[i], low, r[0] == low), r[0]
    for r in odd:
        if r[0] in (400, 401, 402, 403, 404, 407):
            assert (got[r[0]]["n_links"], got[r[0]]["component_id"], got[r[0]]["kept"]) == (0, r[0], True)


def test_near_vectors_of_nothing(spark):
    assert embedding_dedup.near_vectors(spark.createDataFrame([], "vec_id long, embedding array<float>, label int")).count() == 0


def test_large_tile_groups_are_dealt_as_pairs_of_cells(spark):
    """The same components when every group above eight fingerprints is split."""
    rng = random.Random(6)
    base = [rng.getrandbits(64) for _ in range(12)]
    fps = sorted({b ^ (1 << rng.randrange(40)) ^ (1 << rng.randrange(40)) for b in base for _ in range(30)})
    df = spark.createDataFrame([(x - (1 << 64) if x >> 63 else x,) for x in fps], "fp long")
    label = components(len(fps), [(i, j) for i in range(len(fps)) for j in range(i) if (fps[i] ^ fps[j]).bit_count() <= 2])
    for most in (8, 1 << 17):
        found = [(r["src"], r["dst"]) for r in simhash.link_tiles(df, 2, most).collect()]
        at = {x - (1 << 64) if x >> 63 else x: k for k, x in enumerate(fps)}
        assert components(len(fps), [(at[a], at[b]) for a, b in found]) == label
