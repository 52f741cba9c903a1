"""Quality rules: an ordered decision list learned by sequential covering from labelled statistics.

Rules are conjunctions of thresholds on statistics of a text. They are learned on the labelled rows that pass the base rule, since
the base rule decides the others alone. Each is grown on two thirds of them, one condition at a time by information gain on
the bad rows still uncovered, then pruned from its end on the other third. It is accepted while chance would hardly find so many bad
rows there (the hypergeometric tail) and nearly all rows it covers are bad; those are then set aside. The list becomes an ordered chain
of Spark conditional expressions: the first rule that fits rejects, and a text that none fits is kept.

The list is fitted on the ``SAMPLE_ROWS`` labelled rows with the smallest hashed id. It is a documented bound on the fit alone; the
statistics and verdicts cover every text whole.

Defined results: null and empty texts have no words and fail the base rule; without labelled rows of both kinds the list is
empty and the base rule decides alone; of repeated labels of a document the worst counts; repeated rows come back as often as
they occur; an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

SAMPLE_ROWS = 20_000
MIN_WORDS, MAX_REPEAT_PERCENT, WINDOW = 20, 30, 8
#: A rule's chance on the pruning rows, its precision on all rows it covers, and how many bad rows it must cover while it grows.
CHANCE, PRECISION, SUPPORT, MAX_RULES, MAX_CONDITIONS = 1e-3, 0.9, 5, 24, 4
STATS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines", "n_upper", "n_digits", "n_marks")
_SPACE, _SYMBOLS, _UPPER, _DIGITS, _MARKS = b" \t\n\r\x0b\x0c", b"#*$%&|<>", b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"0123456789", b"!?.,;:'\"()-_/\\@~^`=+[]{}"


def repeat_words(words: list[bytes], window: int = WINDOW) -> int:
    """Words that lie in a window of ``window`` words which occurs twice or more in the text."""
    n = len(words) - window + 1
    if n < 2:
        return 0
    names: dict[bytes, int] = {}
    grams = np.array([names.setdefault(w, len(names)) for w in words], np.int64)
    width, seen = 1, len(names)
    while width < window:  # names of longer and longer sequences: each is a pair of shorter ones, so that equal names mean equal words
        step = min(width, window - width)
        pairs = grams[:-step] * np.int64(seen) + grams[step:]
        ordered = np.sort(pairs)
        if not (ordered[1:] == ordered[:-1]).any():
            return 0
        _, grams = np.unique(pairs, return_inverse=True)
        width, seen = width + step, int(grams.max()) + 1
    counts = np.bincount(grams)
    repeated = np.flatnonzero(counts[grams] > 1)
    if not len(repeated):
        return 0
    edge = np.zeros(len(words) + 1, np.int64)
    np.add.at(edge, repeated, 1)
    np.add.at(edge, repeated + window, -1)
    return int((np.cumsum(edge)[:-1] > 0).sum())


def text_stats(text: str | None) -> tuple[int, ...]:
    data = (text or "").encode("utf-8", "surrogatepass")
    words = data.split()
    without = lambda drop: len(data) - len(data.translate(None, drop))
    lines = [x for x in data.split(b"\n") if x.strip(_SPACE)]
    return (
        len(words), len(text or "") - without(_SPACE), without(_SYMBOLS), len(lines) - len(set(lines)), repeat_words(words),
        len(lines), without(_UPPER), without(_DIGITS), without(_MARKS))


def with_stats(docs: DataFrame, carry: list[str]) -> DataFrame:
    """The carried columns and the statistics, named ``_hs_<statistic>``, of each row's text."""

    at = carry.index("text") if "text" in carry else len(carry)

    def measured(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in (b.slice(k, 1000) for b in batches for k in range(0, b.num_rows, 1000)):
            rows = np.array([text_stats(t.as_py()) for t in batch.column(at)], np.int64).reshape(-1, len(STATS))
            yield pa.RecordBatch.from_arrays([*batch.columns[: len(carry)], *(pa.array(rows[:, k]) for k in range(len(STATS)))], names=[*carry, *(f"_hs_{s}" for s in STATS)])

    fields = [f"`{c}` {docs.schema[c].dataType.simpleString()}" for c in carry] + [f"_hs_{s} long" for s in STATS]
    sent = docs.select(*carry) if "text" in carry else docs.select(*carry, F.col("text").alias("_hs_text_in"))
    return sent.mapInArrow(measured, ", ".join(fields))


def features() -> dict[str, Column]:
    s = {k: F.col(f"_hs_{k}").cast("double") for k in STATS}
    words, chars = F.greatest(s["n_words"], F.lit(1.0)), F.greatest(s["word_chars"], F.lit(1.0))
    return {
        "words": s["n_words"], "word_length": s["word_chars"] / words, "symbols_per_word": s["n_symbols"] / words, "dup_line_share": s["n_dup_lines"] / F.greatest(s["n_lines"], F.lit(1.0)),
        "repeat_share": s["n_repeat_words"] / words, "upper_share": s["n_upper"] / chars, "digit_share": s["n_digits"] / chars, "mark_share": s["n_marks"] / chars,
        "words_per_line": s["n_words"] / F.greatest(s["n_lines"], F.lit(1.0)),
    }


Condition = tuple[int, bool, float]


def _fits(rule: list[Condition], x: np.ndarray) -> np.ndarray:
    out = np.ones(len(x), bool)
    for feature, above, threshold in rule:
        out &= (x[:, feature] > threshold) if above else (x[:, feature] <= threshold)
    return out


def _best_condition(x: np.ndarray, bad: np.ndarray) -> tuple[float, Condition | None]:
    """The condition of most information gain on the bad rows; thresholds lie halfway between neighbouring values."""
    p0, n0 = bad.sum(), len(bad) - bad.sum()
    best: tuple[float, Condition | None] = (1e-9, None)
    for f in range(x.shape[1]):
        order = np.argsort(x[:, f], kind="stable")
        v, b = x[order, f], np.cumsum(bad[order])
        cut = np.flatnonzero(v[1:] > v[:-1])
        for above in (False, True):
            p = (p0 - b[cut]) if above else b[cut]
            total = (len(v) - cut - 1) if above else cut + 1
            with np.errstate(divide="ignore", invalid="ignore"):
                gain = np.where(p >= SUPPORT, p * (np.log2(p / total) - np.log2(p0 / (p0 + n0))), -1.0)
            if len(gain) and gain.max() > best[0]:
                k = int(gain.argmax())
                best = (float(gain[k]), (f, above, float((v[cut[k]] + v[cut[k] + 1]) / 2)))
    return best


def chance_of(total: int, bad: int, drawn: int, hit: int) -> float:
    """Probability that ``drawn`` of ``total`` rows taken at random hold at least ``hit`` of the ``bad`` ones."""
    ways = math.comb(total, drawn)
    return sum(math.comb(bad, k) * math.comb(total - bad, drawn - k) for k in range(hit, min(bad, drawn) + 1)) / ways


def learn_rules(x: np.ndarray, bad: np.ndarray, precision: float = PRECISION) -> list[list[Condition]]:
    """An ordered list of rejecting rules. Rows come in a fixed order; every third one prunes."""
    prunes = np.arange(len(bad)) % 3 == 2
    open_rows, rules = np.ones(len(bad), bool), []
    while len(rules) < MAX_RULES and (bad & open_rows & ~prunes).sum() >= SUPPORT:
        grow = open_rows & ~prunes
        gx, gb, rule = x[grow], bad[grow], []
        while len(rule) < MAX_CONDITIONS and gb.any() and not gb.all():
            _, condition = _best_condition(gx, gb)
            if condition is None:
                break
            rule.append(condition)
            inside = _fits([condition], gx)
            gx, gb = gx[inside], gb[inside]
        if not rule:
            break
        held = open_rows & prunes
        worth = []
        for n in range(len(rule), 0, -1):
            inside = _fits(rule[:n], x[held])
            p, total = int((inside & bad[held]).sum()), int(inside.sum())
            worth.append(((p - (total - p)) / total if total else -1.0, p, total, n))
        _, p, total, n = max(worth, key=lambda w: (w[0], w[1]))
        covered = _fits(rule[:n], x) & open_rows
        if total == 0 or chance_of(int(held.sum()), int(bad[held].sum()), total, p) > CHANCE or p / total < precision or bad[covered].mean() < precision:
            break
        rules.append(rule[:n])
        open_rows &= ~covered
    return rules


def fit(docs: DataFrame, labels: DataFrame, sample_rows: int = SAMPLE_ROWS) -> list[list[Condition]]:
    """Rules from the bounded sample of labelled rows; the sample's ids are at most ``sample_rows``, so that they may be broadcast."""
    wanted = labels.where("doc_id is not null and quality is not null").groupBy("doc_id").agg(F.min("quality").alias("_hs_quality"))
    wanted = wanted.orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample_rows)
    named = {c: F.col(c) for c in ("doc_id", "text")}
    rows = with_stats(docs.select(*named.values()).join(F.broadcast(wanted), "doc_id"), ["doc_id", "_hs_quality"])
    rows = rows.dropDuplicates().orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample_rows)
    data = rows.where(~base_failed()).select((F.col("_hs_quality") == 0).alias("bad"), *[f.alias(k) for k, f in features().items()]).toPandas()
    if not len(data) or data["bad"].nunique() < 2:
        return []
    return learn_rules(data[list(features())].to_numpy(float), data["bad"].to_numpy(bool))


def verdict(rules: list[list[Condition]]) -> Column:
    """True where the first rule that fits is none: an ordered chain of conditions over the feature columns."""
    columns = list(features().values())
    chain = None
    for rule in rules:
        fits = F.lit(True)
        for f, above, threshold in rule:
            fits = fits & ((columns[f] > threshold) if above else (columns[f] <= threshold))
        chain = F.when(fits, F.lit(False)) if chain is None else chain.when(fits, F.lit(False))
    return F.lit(True) if chain is None else chain.otherwise(F.lit(True))


def base_failed() -> Column:
    return (F.col("_hs_n_words") < MIN_WORDS) | (100 * F.col("_hs_n_repeat_words") > MAX_REPEAT_PERCENT * F.col("_hs_n_words"))


def op3_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = (spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in ("documents", "labels"))
    rules = fit(docs, labels)
    base = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
    return with_stats(docs, ["doc_id"]).select(
        "doc_id", *[F.col(f"_hs_{s}").alias(s) for s in base], base_failed().alias("base_failed"), (~base_failed() & verdict(rules)).alias("kept"))
