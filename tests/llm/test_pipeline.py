import random

import pytest

import corpus_pipeline
from hubsplit.llm import near_copies, simhash, stages
from tests.llm.test_dedup import components


def labels(spark):
    return spark.createDataFrame([(1, 1, 0), (11, 0, 0)], "doc_id long, quality int, toxic int")


def test_stages_keep_columns_and_take_effect(spark, odd_docs, saved):
    d = saved(labels=labels(spark), documents=odd_docs)
    docs = spark.read.parquet(f"{d}/documents.parquet")
    assert [s[0] for s in corpus_pipeline.STAGES] == ["quality rules", "SimHash near-dedup", "suffix-array dedup", "mixing to target weights", "best-fit packing"]
    for f in (stages.quality_rules, stages.simhash_dedup, stages.suffix_array_dedup, stages.mixing):
        out = f(spark, docs, d)
        assert out.columns == docs.columns and [x.dataType for x in out.schema] == [x.dataType for x in docs.schema]
        out.count()
    near = {r["doc_id"] for r in stages.simhash_dedup(spark, docs, d).collect()}
    assert 5 in near and 7 not in near and 1 in near
    cut = {r["doc_id"]: r["text"] for r in stages.suffix_array_dedup(spark, docs, d).collect()}
    assert cut[6] == "before " and cut[1].startswith("plain words")
    assert stages.packing(spark, docs, d).count() > 0


def test_pipeline_runs_whole_and_over_nothing(spark, odd_docs, no_docs, saved):
    assert corpus_pipeline.run(spark, saved(labels=labels(spark), documents=odd_docs)).count() > 0
    assert corpus_pipeline.run(spark, saved(labels=labels(spark), documents=no_docs)).count() == 0


def shingle_set(text):
    words = (text or "").lower().split()
    return {tuple(words[i : i + 5]) for i in range(len(words) - 4)} or {tuple(words)}


@pytest.mark.parametrize("sample", [0, 16_384])
def test_near_dedup_finds_every_pair_of_similarity_eighty(spark, monkeypatch, sample):
    """Against brute force: chains, exact copies, a passage that many unlike texts share, texts shorter than a shingle."""
    monkeypatch.setattr(near_copies, "SAMPLE", sample)
    rng = random.Random(3)
    word = lambda: f"w{rng.randrange(4000)}"
    passage = [word() for _ in range(30)]
    texts = []
    for k in range(60):
        base = [word() for _ in range(rng.randrange(8, 260))] + passage * (k % 3 == 0)
        for _ in range(rng.randrange(1, 6)):
            texts.append(" ".join(base))
            for _ in range(rng.choice([0, 1, 1, 2, 3, 5])):
                base[rng.randrange(len(base))] = word()
            if rng.random() < 0.3:
                base = base[: rng.randrange(len(base) * 4 // 5, len(base)) + 1]
    texts += ["one two", "One  TWO", "three", "", None, " \n"]
    rng.shuffle(texts)
    sets = [shingle_set(t) for t in texts]
    links = [(i, j) for i in range(len(texts)) for j in range(i) if 9 * len(sets[i] & sets[j]) >= 4 * (len(sets[i]) + len(sets[j]))]
    wide = [(i, j) for i, j in links if sets[i] != sets[j] and (simhash.fingerprint(texts[i]) ^ simhash.fingerprint(texts[j])).bit_count() > simhash.RADIUS]
    assert len(wide) > 20  # pairs that fingerprints within two bits miss
    label = components(len(texts), links)
    docs = spark.createDataFrame([(i, t, "en", "a", 1) for i, t in enumerate(texts)], "doc_id long, text string, lang string, source string, n_chars long")
    assert sorted(r["doc_id"] for r in stages.simhash_dedup(spark, docs, "").collect()) == sorted(set(label))


def test_near_dedup_of_rows_without_or_with_the_same_doc_id(spark, no_docs):
    a, b = " ".join(f"a{k}" for k in range(40)), " ".join(f"b{k}" for k in range(40))
    docs = spark.createDataFrame([(1, a), (2, a), (2, b), (None, b)], "doc_id long, text string")
    assert sorted(map(str, stages.simhash_dedup(spark, docs, "").collect())) == sorted(map(str, docs.where("doc_id is null or doc_id = 1 or text = '%s'" % b).collect()))
    assert stages.simhash_dedup(spark, no_docs, "").count() == 0


def test_mixing_takes_the_same_of_tied_rows_on_every_run(spark):
    docs = spark.createDataFrame([(1, f"tie {k} {'x ' * 9}", "en", "a" if k % 2 else "b", k) for k in range(90)], "doc_id long, text string, lang string, source string, n_chars long")
    runs = [sorted(map(tuple, stages.mixing(spark, docs.repartition(k), "").collect())) for k in (1, 3, 7)]
    assert runs[0] == runs[1] == runs[2] != []


def test_near_dedup_goes_through_the_simhash_operator(spark, monkeypatch):
    """Pairs that fingerprints reach are linked by the tiled comparison, before any prefix is looked at."""
    asked = []
    whole = simhash.link_tiles
    monkeypatch.setattr(simhash, "link_tiles", lambda *a: asked.append(1) or whole(*a))
    text = " ".join(f"w{k}" for k in range(300))
    docs = spark.createDataFrame([(1, text), (2, text + " end"), (3, "other words that nobody shares with them at all")], "doc_id long, text string")
    classed = near_copies.with_classes(docs).cache()
    assert near_copies.by_fingerprint(classed).count() == 1 and asked
    assert sorted(r["doc_id"] for r in stages.simhash_dedup(spark, docs, "").collect()) == [1, 3]


def test_pipeline_against_stages_by_hand(spark, saved):
    """Every row of a run, from brute-force versions of the five stages' decisions."""
    import re

    from hubsplit.llm import mixing, packing, quality
    from tests.llm.test_dedup import slow_removal
    from tests.llm.test_tokens import check_packing, reference

    rng = random.Random(12)
    word = lambda: "".join(rng.choice("abcdefghijk") for _ in range(rng.randrange(3, 9)))
    passage = " ".join(word() for _ in range(20))
    rows = []
    for k in range(40):
        text = " ".join(word() for _ in range(rng.randrange(10, 90)))
        text = f"{text} {passage} {word()}" if k % 6 == 0 else text
        rows.append((k, text, "en", "ab"[k % 2], len(text)))
        if k % 7 == 0:
            rows.append((100 + k, text + (" tail" if k % 2 else ""), "en", "a", 0))
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    d = saved(documents=docs, labels=labels(spark))
    out = corpus_pipeline.run(spark, d).collect()
    kept = [r for r in rows if len(r[1].split()) >= quality.MIN_WORDS]
    sets = [shingle_set(r[1]) for r in kept]
    links = [(i, j) for i in range(len(kept)) for j in range(i) if 9 * len(sets[i] & sets[j]) >= 4 * (len(sets[i]) + len(sets[j]))]
    label = components(len(kept), links)
    least = {}
    for r, c in zip(kept, label, strict=True):
        least[c] = min(least.get(c, r[0]), r[0])
    kept = [r for r, c in zip(kept, label, strict=True) if r[0] == least[c]]
    owner, cut = {}, []
    for r in kept:
        b = r[1].encode()
        for i in range(len(b) - 49):
            owner[b[i : i + 50]] = min(owner.get(b[i : i + 50], r[0]), r[0])
    for r in kept:
        b = r[1].encode()
        gone = [False] * len(b)
        for i in range(len(b) - 49):
            if owner[b[i : i + 50]] < r[0]:
                gone[i : i + 50] = [True] * 50
        cut.append((r[0], bytes(c for c, g in zip(b, gone, strict=True) if not g).decode(), r[3]))
    assert sum(removed for _, _, removed, _, _ in slow_removal([(r[0], r[1]) for r in kept])) > 0
    size = {i: len(re.findall(mixing.WORD, t)) for i, t, _ in cut}
    words, total = {}, sum(size.values())
    for i, _, s in cut:
        words[s] = words.get(s, 0) + size[i]
    target = {s: min(3 * words[s], total * w / 3) for s, w in (("a", 1), ("b", 2))}
    copies = {}
    for r in out:
        if r["piece"] == 0:
            copies[r["doc_id"]] = copies.get(r["doc_id"], 0) + 1
    texts = {i: (t, s) for i, t, s in cut}
    assert set(copies) <= set(texts) and all(n <= 3 for n in copies.values())
    for s in words:
        taken = sum(n * size[i] for i, n in copies.items() if texts[i][1] == s)
        assert abs(taken - target[s]) <= max(size.values())
    ids = dict(zip(copies, reference([texts[i][0] for i in copies]), strict=True))
    assert sum(r["length"] for r in out) == sum(copies[i] * len(ids[i]) // 4 for i in copies)
    assert check_packing(out, packing.CAPACITY) <= -(-sum(r["length"] for r in out) // packing.CAPACITY) + 1


def test_a_staged_table_leaves_no_shuffle_files(spark):
    """what a write had shuffled stayed on the disks until the driver happened to collect its garbage."""
    import time

    from pyspark.sql import functions as F

    from hubsplit.shared_dir import staged

    blocks = spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager()
    held = lambda: {x for x in blocks.getAllFiles().mkString("\n").split("\n") if "shuffle_" in x}
    before = held()
    assert staged(spark.range(1000).groupBy((F.col("id") % 10).alias("k")).count(), "counts").count() == 10
    for _ in range(50):
        if not any(x.endswith(".data") for x in held() - before):
            break
        time.sleep(0.1)
    # the count above may still hold a shuffle of its own, of one row a task
    assert sum(x.endswith(".data") for x in held() - before) <= 1


def test_pairs_are_decided_in_rounds(spark, monkeypatch):
    """the sets of all pairs were brought together at once, which takes about twice the disk of their texts."""
    words = [f"w{i}" for i in range(60)]
    texts = [" ".join([*words[:k], f"other{k}", *words[k + 1 :]]) if k else " ".join(words) for k in range(0, 60, 3)] + ["quite another text of few words"]
    classed = near_copies.with_classes(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).cache()
    names = [r["_hs_class"] for r in classed.orderBy("doc_id").collect()]
    pairs = spark.createDataFrame([(a, b) for i, a in enumerate(names) for b in names[:i]], "a long, b long").cache()
    links = lambda: sorted(map(tuple, near_copies.similar(pairs, classed).collect()))
    whole = links()
    made = []
    stage = near_copies.staged
    monkeypatch.setattr(near_copies, "staged", lambda df, name, *a: made.append(name) or stage(df, name, *a))
    monkeypatch.setattr(near_copies, "ROUND_PAIRS", 20)
    assert links() == whole and 0 < len(whole) < pairs.count()
    assert made.count("links") >= 3


def test_a_round_moves_the_sets_of_its_pairs_alone(spark, monkeypatch):
    """Every round moved all sets, so that a corpus with more rounds shuffled more than its share."""
    from hubsplit.llm import near_copies

    pairs = [(a, a + b) for a in range(60) for b in (1, 7)]
    kept = spark.createDataFrame(pairs, "a long, b long")
    asked = {r["_hs_class"]: r["asked"] for r in near_copies.asked_in(kept, 8).collect()}
    held = {(r["a"], r["b"]): r["k"] for r in kept.select("a", "b", near_copies._round("a", 8).alias("k")).collect()}
    assert set(asked) == {x for p in pairs for x in p}
    assert {c: {k for k in range(8) if m >> k & 1} for c, m in asked.items()} == {c: {k for (_, b), k in held.items() if b == c} for c in asked}
    text = lambda k: " ".join(f"w{j + 3 * k}" for j in range(60))
    classed = near_copies.with_classes(spark.createDataFrame([(k, text(k)) for k in range(20)], "doc_id long, text string")).cache()
    names = [r[0] for r in classed.orderBy("doc_id").select("_hs_class").collect()]
    ends = spark.createDataFrame([tuple(sorted((names[i], names[j]))) for i in range(20) for j in range(i)], "a long, b long")
    want = {(r["a"], r["b"]) for r in near_copies.similar(ends, classed).collect()}
    assert want == {tuple(sorted((names[i], names[i - step]))) for step in (1, 2) for i in range(step, 20)}  # 53 of 59, 50 of 62; at three steps 47 of 65
    monkeypatch.setattr(near_copies, "ROUND_PAIRS", 2)
    assert {(r["a"], r["b"]) for r in near_copies.similar(ends, classed).collect()} == want
