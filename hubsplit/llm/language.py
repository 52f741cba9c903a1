"""Language identification of mixed-language text: script ranges, per-word scores, and a Viterbi path with a switching penalty.

Training counts hashed character sequences of one to four characters per language. A word's score in a language is the
mean log probability of its sequences, taken as a posterior over the languages whose letters share the word's script. The best path over
the words of a text pays a penalty for each change of language; its runs are the labelled spans, and the language with the
most letters names the text. Paths of many texts are stepped together with numpy, longest first.

Training reads texts and languages of ``SAMPLE_ROWS`` documents with the smallest hashed id, a documented bound on the fit alone.

Defined results: null text, and text without a letter, gives ``und`` with score 0 and no spans; nothing learned gives ``und`` too; a
tie takes the language that sorts first; repeated rows come back as often as they occur; extra columns are ignored.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

SAMPLE_ROWS, BUCKET_BITS, SMOOTHING, SWITCH, SHARPNESS = 6000, 17, 0.5, 3.0, 4.0
_WORD = re.compile(r"[^\W\d_]+")
# First code point of each script range, and the script's name.
SCRIPT_RANGES = (
    (0x0000, "latin"), (0x0370, "greek"), (0x0400, "cyrillic"), (0x0530, "armenian"), (0x0590, "hebrew"), (0x0600, "arabic"), (0x0900, "devanagari"), (0x0980, "bengali"),
    (0x0A00, "gurmukhi"), (0x0A80, "gujarati"), (0x0B00, "oriya"), (0x0B80, "tamil"), (0x0C00, "telugu"), (0x0C80, "kannada"), (0x0D00, "malayalam"), (0x0D80, "sinhala"),
    (0x0E00, "thai"), (0x0E80, "lao"), (0x0F00, "tibetan"), (0x1000, "myanmar"), (0x10A0, "georgian"), (0x1100, "hangul"), (0x1200, "ethiopic"), (0x1780, "khmer"), (0x1800, "mongolian"),
    (0x1E00, "latin"), (0x1F00, "greek"), (0x2000, "latin"), (0x2E80, "han"), (0x3040, "kana"), (0x3100, "han"), (0x3130, "hangul"), (0x3190, "han"), (0xA000, "other"), (0xAC00, "hangul"),
    (0xD7B0, "other"), (0xF900, "han"), (0xFB00, "other"), (0xFF00, "latin"), (0x10000, "other"), (0x20000, "han"), (0x40000, "other"),
)
_STARTS = np.array([s for s, _ in SCRIPT_RANGES], np.uint32)
SCRIPTS = sorted({n for _, n in SCRIPT_RANGES})
_SCRIPT_OF = np.array([SCRIPTS.index(n) for _, n in SCRIPT_RANGES])
_ODD = tuple(np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x27D4EB2F165667C5))


def scripts_of(points: np.ndarray) -> np.ndarray:
    return _SCRIPT_OF[np.searchsorted(_STARTS, points, side="right") - 1]


def sequences(words: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hashed sequences of each word (bucket and word index), and the script of each word's first letter."""
    points = np.frombuffer((" " + " ".join(words) + " ").encode("utf-32-le", "surrogatepass"), "<u4").astype(np.uint64)
    space = points == 32
    word = np.cumsum(space) - 1
    first = np.flatnonzero(space)[:-1] + 1
    buckets, owners = [], []
    at = [points * _ODD[k] for k in range(4)]
    shift = np.uint64(64 - BUCKET_BITS)
    for n in range(1, 5):
        m = len(points) - n + 1
        if m < 1:
            break
        inner = np.ones(m, bool)
        for k in range(n):
            if n == 1 or 0 < k < n - 1:
                inner &= ~space[k : k + m]
        if n == 2:
            inner &= ~(space[:m] & space[1 : 1 + m])
        h = np.full(m, n, np.uint64) * _ODD[3]
        for k in range(n):
            h = (h ^ at[k][k : k + m]) * _ODD[0]
            h ^= h >> np.uint64(29)
        own = word[(1 if n > 2 else 0) : (1 if n > 2 else 0) + m] if n != 2 else np.where(space[:m], word[1 : 1 + m], word[:m])
        buckets.append((h[inner] * _ODD[1]) >> shift)
        owners.append(own[inner])
    return np.concatenate(buckets).astype(np.int64), np.concatenate(owners), scripts_of(points[first].astype(np.uint32))


class Model:
    """Learned languages, a log probability per bucket and language, and which languages each script may stand for."""

    def __init__(self, languages: list[str], counts: np.ndarray, script_letters: np.ndarray):
        self.languages = languages
        total = counts.sum(axis=1, keepdims=True)
        self.table = np.log((counts + SMOOTHING) / (total + SMOOTHING * counts.shape[1])).astype(np.float32)
        share = script_letters / np.maximum(script_letters.sum(axis=1, keepdims=True), 1)
        allowed = (share >= 0.01).T
        allowed[~allowed.any(axis=1)] = True
        self.allowed = allowed  # [script, language]

    def word_scores(self, words: list[str]) -> np.ndarray:
        """Log posterior [word, language], with excluded languages far below the rest."""
        buckets, owners, script = sequences(words)
        n = np.maximum(np.bincount(owners, minlength=len(words)), 1)
        raw = np.stack([np.bincount(owners, weights=row[buckets], minlength=len(words)) for row in self.table], axis=1) / n[:, None]
        raw = raw * SHARPNESS * np.sqrt(n)[:, None] / 2
        raw = np.where(self.allowed[script], raw, -1e4)
        top = raw.max(axis=1, keepdims=True)
        return (raw - top - np.log(np.exp(raw - top).sum(axis=1, keepdims=True))).astype(np.float32)


def best_paths(scores: np.ndarray, lengths: np.ndarray, switch: float = SWITCH) -> np.ndarray:
    """Language index of every word: paths that maximise the sum of scores less the penalty of each switch.

    Texts stand one after another in ``scores``. They are stepped together, longest first, so that the texts still
    running are a prefix of the columns.
    """
    order = np.argsort(-lengths, kind="stable")
    starts = (np.cumsum(lengths) - lengths)[order]
    sizes = lengths[order]
    steps = int(sizes[0]) if len(sizes) else 0
    running = np.searchsorted(-sizes, -np.arange(steps), side="left")
    begin = np.cumsum(running) - running  # a step's rows in the arrays below
    came = np.empty(int(running.sum()), np.int16)
    stayed = np.empty((len(came), scores.shape[1]), bool)
    best = np.zeros((len(sizes), scores.shape[1]))
    for t in range(steps):
        n = int(running[t])
        now = scores[starts[:n] + t]
        if t:
            before = best[:n]
            top = before.argmax(axis=1)
            jump = before[np.arange(n), top][:, None] - switch
            keep = before >= jump
            came[begin[t] : begin[t] + n] = top
            stayed[begin[t] : begin[t] + n] = keep
            best[:n] = np.where(keep, before, jump) + now
        else:
            best[:n] = now
    final = best.argmax(axis=1)
    out = np.zeros(int(lengths.sum()), np.int16)
    state = final.copy()
    for t in range(steps - 1, -1, -1):
        n = int(running[t])
        out[starts[:n] + t] = state[:n]
        if t:
            # texts that begin to run at an earlier step keep their final state until then
            m = np.arange(n)
            state[:n] = np.where(stayed[begin[t] + m, state[:n]], state[:n], came[begin[t] : begin[t] + n])
    return out


def spans_of(text: str, words: list[str], path: list[int]) -> list[tuple[int, int, int]]:
    """(start, end, state) of each run of equal states over the words of a text."""
    if not words:
        return []
    if path.count(path[0]) == len(path):
        last = words[-1]
        return [(_WORD.search(text).start(), text.rfind(last) + len(last), path[0])]
    out: list[tuple[int, int, int]] = []
    for m, state in zip(_WORD.finditer(text), path, strict=True):
        if out and out[-1][2] == state:
            out[-1] = (out[-1][0], m.end(), state)
        else:
            out.append((m.start(), m.end(), state))
    return out


def label_batch(model: Model, texts: list[str | None], with_spans: bool = True) -> list[tuple[str, float, list[dict] | None]]:
    """Language, share of its letters, and the labelled spans of each text."""
    words = [_WORD.findall(t) if t else [] for t in texts]
    lengths = np.array([len(w) for w in words], np.int64)
    if not lengths.sum() or not model.languages:
        return [("und", 0.0, [] if with_spans else None)] * len(texts)
    names: dict[str, int] = {}
    codes = np.array([names.setdefault(w, len(names)) for ws in words for w in ws], np.int64)
    unique = list(names)
    scores = model.word_scores([u.lower() for u in unique])
    size = np.array([len(u) for u in unique], np.float64)[codes]
    path = best_paths(scores[codes], lengths)
    n_lang, owner = len(model.languages), np.repeat(np.arange(len(texts)), lengths)
    letters = np.bincount(owner * n_lang + path, weights=size, minlength=len(texts) * n_lang).reshape(-1, n_lang)
    totals = letters.sum(axis=1)
    top = letters.argmax(axis=1)
    share = letters.max(axis=1) / np.maximum(totals, 1)
    out, at, states = [], 0, path.tolist()
    for i, own in enumerate(words):
        spans = [{"start": s, "end": e, "lang": model.languages[k]} for s, e, k in spans_of(texts[i], own, states[at : at + len(own)])] if with_spans else None
        at += len(own)
        out.append((model.languages[top[i]], float(min(1.0, share[i])), spans) if totals[i] else ("und", 0.0, spans))
    return out


def held_out() -> Column:
    return F.pmod(F.crc32(F.coalesce(F.col("doc_id").cast("string"), F.lit("")).cast("binary")), F.lit(5)) == 0


def train(docs: DataFrame, sample_rows: int = SAMPLE_ROWS) -> Model:
    """A model from at most ``sample_rows`` texts with a language; held-out documents are left out."""
    ids = docs.where(~held_out() & F.col("lang").isNotNull() & F.col("text").isNotNull()).select("doc_id").distinct().orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample_rows)
    rows = docs.select("doc_id", "text", "lang").where("lang is not null").join(F.broadcast(ids), "doc_id")  # at most sample_rows ids

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts, langs = batch.column(0).to_pylist(), batch.column(1).to_pylist()
            for lang in sorted(set(langs)):
                words = [w.lower() for t, x in zip(texts, langs, strict=True) if x == lang and t for w in _WORD.findall(t)]
                for a in range(0, len(words), 200_000):
                    part = words[a : a + 200_000]
                    buckets, _, script = sequences(part)
                    counts = np.bincount(buckets, minlength=1 << BUCKET_BITS)
                    used = np.flatnonzero(counts)
                    letters = np.bincount(script, weights=[len(w) for w in part], minlength=len(SCRIPTS)).astype(np.int64)
                    keys = np.concatenate([used, -1 - np.arange(len(SCRIPTS))])
                    yield pa.RecordBatch.from_pydict({"lang": pa.array([lang] * len(keys)), "bucket": pa.array(keys, pa.int64()), "n": pa.array(np.concatenate([counts[used], letters]), pa.int64())})

    # At most languages x buckets rows come back, whatever the corpus.
    found = rows.select("text", "lang").mapInArrow(count, "lang string, bucket long, n long").groupBy("lang", "bucket").agg(F.sum("n").alias("n")).toPandas()
    languages = sorted(found["lang"].unique())
    counts, letters = np.zeros((len(languages), 1 << BUCKET_BITS)), np.zeros((len(languages), len(SCRIPTS)))
    for k, lang in enumerate(languages):
        own = found[found["lang"] == lang]
        grams = own[own["bucket"] >= 0]
        counts[k, grams["bucket"].to_numpy()] = grams["n"].to_numpy()
        script = own[own["bucket"] < 0]
        letters[k, -1 - script["bucket"].to_numpy()] = script["n"].to_numpy()
    return Model(languages, counts, letters)


def identify(docs: DataFrame, model: Model, with_spans: bool = True) -> DataFrame:
    """doc_id, lang_pred, score and, if asked for, the spans of each whole text."""
    from hubsplit.llm.encoder import slices

    sent = docs.sparkSession.sparkContext.broadcast(model)  # languages x 2**17 floats

    def predict(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch.column(1)
            for a, b in slices(texts):
                rows = label_batch(sent.value, texts.slice(a, b - a).to_pylist(), with_spans)
                columns = {"doc_id": batch.column(0).slice(a, b - a), "lang_pred": pa.array([r[0] for r in rows], pa.string()), "score": pa.array([r[1] for r in rows], pa.float64())}
                if with_spans:
                    columns["spans"] = pa.array([r[2] for r in rows], pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64()), ("lang", pa.string())])))
                yield pa.RecordBatch.from_pydict(columns)

    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", "text").mapInArrow(predict, f"doc_id {kind}, lang_pred string, score double" + (", spans array<struct<start: long, end: long, lang: string>>" if with_spans else ""))


def op1_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return identify(docs, train(docs)).select("doc_id", held_out().alias("held_out"), "lang_pred", "score", "spans")
