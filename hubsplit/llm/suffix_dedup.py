"""Removal of repeated byte strings, exact, with suffix arrays built by linear grouping.

A byte goes when a string of ``length`` bytes over it also starts in a document with a smaller doc_id. Suffixes cannot be sorted
over a whole corpus in one place, so strings that may be equal are brought together first: every string of ``length`` bytes
contains an anchor, the gram of smallest hash among its grams, and equal strings have equal anchors at equal places.

1. Anchors of all texts go to their hash's task, each with a digest of the bytes on either side. An equal string reaches over half of
   what is beside its anchor on one side at least, so that an anchor is kept when one of its sides is seen in two documents; grams
   that meet by chance, ever more of them as the corpus grows, are not. A task of the scan sends one entry for the anchors of equal sides
   that it already saw in two documents. The places of kept anchors go to their document's task, which makes them one row a text.
2. For each kept anchor, its context (all strings around it) goes to the anchor's task. A context that the scan's task
   saw in a smaller document is settled there; of equal contexts one is sent. Anchors that alone would fill a task are
   replaced by the single strings around them, so that no task holds an unbounded group. A context is some five times the text
   between two anchors: where more than ``TURN_SHARE`` of all anchors are kept, they take turns by their hash, so that a turn's
   contexts leave the disk before the next one's come.
3. There, the strings that several contexts may share are cut out, the distinct pieces of an anchor are joined, and their suffix array
   groups equal strings; each group's smallest doc_id is its owner. Occurrences in larger documents become removed spans, which go
   to their document's task and are joined there.
   An anchor with one distinct context has nothing to order: that context's smallest document owns it. (With these in the array as
   well, the check tool asks 1,415 CPU seconds a GB where 960 are allowed.)

What is dealt goes as packed payloads, one for each task that gets some. The more tasks there are, the more is gathered before it is
packed (``PAYLOAD_ROWS`` a payload, ``MOST_ROWS`` in all), so that payloads do not shrink to nothing on large corpora.

The suffix array is built in two phases without renaming: groups of suffixes with equal Lyndon prefix, taken in descending
order, extend the prefix of the previous smaller suffix they stand after; then suffixes in ascending order place the suffixes
that end their Lyndon prefix before them. Buckets order everything, so that the work is linear; an array holds the pieces of as many
anchors as make ``ARRAY_SYMBOLS`` symbols, which bounds its memory.

Rows are joined by doc_id and some bits of the text's hash, so that many texts under one doc_id are as many keys.

Defined results: null text is empty; a text shorter than ``length`` loses nothing; documents of null doc_id are neither sources nor
changed; rows with the same doc_id do not remove from each other; an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import math
import struct
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hubsplit.shared_dir import staged

LENGTH, GRAM = 50, 20
SLICE_BYTES = 2_000_000
#: Anchors (or contexts, or spans) a payload is meant to hold, and how many of each a task gathers at most before it packs them.
PAYLOAD_ROWS = 2048
MOST_ROWS = {"anchors": 700_000, "contexts": 300_000, "spans": 1_500_000}
#: Rows hashed at once: eight bytes for each of their bytes, several times over.
ROWS = 8192
BLOCK = 1 << 16
#: An anchor is hot when it has more entries than this, and than its task's divided by HOT_SHARE.
HOT_FLOOR, HOT_SHARE = 20_000, 8
ARRAY_SYMBOLS = 60_000
#: The share of all anchors that may be dealt with their contexts in one turn, and how many may be in any case.
TURN_SHARE, TURN_FLOOR = 0.4, 4_000_000
#: A text's place is one number with some bits of its hash above.
PLACE_BITS, TAG_BITS = 44, 16
#: Bytes of the digest of an anchor's side: sides that meet by chance only bring contexts together that then differ.
SIDE_BYTES = 3
_C, _M = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xD6E8FEB86659FD93)
_TABLE = (np.arange(256, dtype=np.uint64) + np.uint64(1)) * np.uint64(0xC2B2AE3D27D4EB4F)
_TABLE ^= _TABLE >> np.uint64(31)
_TABLE *= _M


def gram_hashes(data: np.ndarray, n: int) -> np.ndarray:
    """Hash of every run of n bytes along the last axis, built from runs of powers of two."""
    power, width, run = _C, 1, _TABLE[data]
    out, done = None, 0
    with np.errstate(over="ignore"):
        while True:
            if n & width:
                if out is None:
                    out = run
                else:
                    step = np.uint64(pow(int(_C), width, 1 << 64))
                    m = min(out.shape[-1], run.shape[-1] - done)
                    out = out[..., :m] * step + run[..., done : done + m]
                done += width
            width *= 2
            if width > n:
                break
            run = run[..., : -(width // 2)] * power + run[..., width // 2 :]
            power = np.uint64(pow(int(_C), width, 1 << 64))
        out = out ^ (out >> np.uint64(32))
        out = out * _M
        return out ^ (out >> np.uint64(29))


def row_hashes(rows: np.ndarray, n: int) -> np.ndarray:
    """``gram_hashes`` of every row, some rows at a time."""
    if len(rows) <= ROWS:
        return gram_hashes(rows, n)
    return np.concatenate([gram_hashes(rows[a : a + ROWS], n) for a in range(0, len(rows), ROWS)])


def anchor_positions(data: np.ndarray, starts: np.ndarray, ends: np.ndarray, length: int = LENGTH, gram: int = GRAM) -> tuple[np.ndarray, np.ndarray]:
    """Positions and hashes of the anchors of texts that stand one after another in ``data``; the last smallest gram of a string wins."""
    marked = np.zeros(len(data), bool)
    inside = np.zeros(len(data) + 1, np.int32)
    long = ends - starts >= length
    np.add.at(inside, starts[long], 1)
    np.add.at(inside, ends[long] - length + 1, -1)
    valid = np.cumsum(inside) > 0
    found, hashes = [], []
    for a in range(0, len(data) - length + 1, BLOCK):  # blocks that stay in a core's cache
        b = min(a + BLOCK, len(data) - length + 1)
        if not valid[a:b].any():
            continue
        h = gram_hashes(data[a : b + length - 1], gram)
        at = _last_smallest(h, length - gram + 1)[: b - a][valid[a:b]]
        marked[a : b + length - 1] = False
        marked[a + at] = True
        here = np.flatnonzero(marked[a : b + length - 1])
        found.append(here + a)
        hashes.append(h[here])
    if not found:
        return np.array([], np.int64), np.array([], np.uint64)
    at, first = np.unique(np.concatenate(found), return_index=True)
    return at, np.concatenate(hashes)[first]


def _digest(rows: np.ndarray) -> np.ndarray:
    """``SIDE_BYTES`` that tell rows of bytes apart."""
    wide = np.pad(rows, ((0, 0), (0, -rows.shape[1] % 8))).view("<u8")
    out = np.full(len(rows), _C)
    for k in range(wide.shape[1]):
        out = (out ^ wide[:, k]) * _M
        out ^= out >> np.uint64(32)
    return (out * _C >> np.uint64(64 - 8 * SIDE_BYTES)).astype(np.uint32)


def side_digests(data: np.ndarray, at: np.ndarray, length: int = LENGTH, gram: int = GRAM) -> tuple[np.ndarray, np.ndarray]:
    """Digests of the bytes to the left and to the right of each anchor; every string around it holds all bytes of one of them.

    What stands outside an anchor's text is digested with the rest: no string reaches there.
    """
    flank = length - gram
    before = flank // 2
    after = flank - before + (before > 0)  # a string with fewer than ``before`` bytes to the left has so many to the right
    padded = np.pad(data, (before, after))
    side = lambda p, n: _digest(np.lib.stride_tricks.sliding_window_view(padded, n)[p] if n else np.zeros((len(p), 0), np.uint8))
    return side(at, before), side(at + before + gram, after)


def _met(key: np.ndarray, owner: np.ndarray, place: np.ndarray) -> np.ndarray:
    """Whether an entry's key is that of two documents, or of an entry settled before."""
    order = np.argsort(key, kind="stable")
    k, doc = key[order], owner[order]
    head = np.flatnonzero(np.r_[True, k[1:] != k[:-1]])
    both = (np.minimum.reduceat(doc, head) < np.maximum.reduceat(doc, head)) | (np.minimum.reduceat(place[order], head) < 0)
    out = np.empty(len(key), bool)
    out[order] = np.repeat(both, np.diff(np.r_[head, len(k)]))
    return out


def _shared(h: np.ndarray, left: np.ndarray, right: np.ndarray, owner: np.ndarray, place: np.ndarray) -> np.ndarray:
    """Whether one of an anchor's sides occurs in two documents. Entries are in order of ``h``."""
    out = np.zeros(len(h), bool)
    several = np.flatnonzero(np.r_[False, h[1:] == h[:-1]] | np.r_[h[1:] == h[:-1], False])
    if len(several):
        name, doc, at = h[several] * _M, owner[several], place[several]
        out[several] = _met(name ^ left[several], doc, at) | _met(name ^ right[several], doc, at)
    # an entry settled before stands for documents elsewhere, whose own places are known there
    return out | (place < 0)


def _narrow(x: np.ndarray, width: int) -> np.ndarray:
    return np.ascontiguousarray(x.astype("<u8").view("u1").reshape(-1, 8)[:, :width])


def _widened(x: np.ndarray, width: int) -> np.ndarray:
    return np.pad(x.view("u1").reshape(-1, width), ((0, 0), (0, 8 - width))).view("<u8").reshape(-1)


def _last_smallest(h: np.ndarray, window: int) -> np.ndarray:
    """Place of the smallest value of each window, the last of equal ones."""
    low, at, width = h, np.arange(len(h), dtype=np.int32), 1
    while 2 * width <= window:
        right = low[width:] <= low[:-width]
        low, at = np.where(right, low[width:], low[:-width]), np.where(right, at[width:], at[:-width])
        width *= 2
    if width < window:
        d = window - width
        at = np.where(low[d:] <= low[:-d], at[d:], at[:-d])
    return at


def suffix_array(text: list[int]) -> list[int]:
    """Start positions of all suffixes in ascending order; a suffix that is a prefix of another is smaller. Linear time.

    Symbols are small integers, so that buckets order them; nothing is sorted by comparison and nothing renamed.
    """
    n = len(text)
    if n < 2:
        return list(range(n))
    low = min(text) - 1
    seq = [c - low for c in text]
    seq.append(0)
    n += 1
    # Groups form a list from lowest to highest; a new group is entered after the group that it leaves.
    used = bytearray(max(seq) + 1)
    for c in seq:
        used[c] = 1
    first_of, kinds = [0] * len(used), 0
    for c, there in enumerate(used):
        if there:
            first_of[c] = kinds
            kinds += 1
    group = [first_of[c] for c in seq]
    members: list[list[int]] = [[] for _ in range(kinds)]
    for i, g in enumerate(group):
        members[g].append(i)
    size = [len(m) for m in members]
    below, above = list(range(-1, kinds - 1)), [*range(1, kinds), -1]
    previous = [-1] * n
    final = [False] * n  # belongs to the group in hand or to a higher one
    g = kinds - 1
    while g >= 0:
        own = [s for s in members[g] if group[s] == g]
        if len(own) == 1:
            s = own[0]
            final[s] = True
            p = s - 1
            while p >= 0 and final[p]:
                p = previous[p]
            previous[s] = p
            if p < 0 or size[group[p]] == 1:
                g = below[g]
                continue
            levels = [[], [p]]
        else:
            # A member's walk back may stop at a member before it, whose own walk goes on from there.
            for s in own:
                p = s - 1
                while p >= 0 and final[p]:
                    p = previous[p]
                previous[s] = p
            for s in own:
                final[s] = True
            counts: dict[int, int] = {}
            for s in own:
                p = previous[s]
                if p >= 0 and final[p]:
                    chain = [s]
                    while p >= 0 and final[p]:
                        chain.append(p)
                        p = previous[p]
                    for x in chain:
                        previous[x] = p
                if p >= 0:
                    counts[p] = counts.get(p, 0) + 1
            levels = [[] for _ in range(max(counts.values(), default=0) + 1)]
            for p, k in counts.items():
                levels[k].append(p)
        # The previous smaller suffix extends its prefix by this group's, as often as counted; more often ranks higher.
        for level in reversed(levels):
            if not level:
                continue
            moves: dict[int, list[int]] = {}
            for p in level:
                moves.setdefault(group[p], []).append(p)
            for old, moved in moves.items():
                if len(moved) == size[old]:
                    continue  # the whole group moves, and nothing stands between its old place and its new one
                new = len(members)
                members.append(moved)
                size.append(len(moved))
                size[old] -= len(moved)
                nxt = above[old]
                below.append(old)
                above.append(nxt)
                if nxt >= 0:
                    below[nxt] = new
                above[old] = new
                for p in moved:
                    group[p] = new
        g = below[g]
    starts, at, g = [0] * len(members), 0, 0
    order = [0] * n
    while g >= 0:
        starts[g] = at
        at += size[g]
        g = above[g]
    placed = [False] * n
    order[0], placed[n - 1] = n - 1, True
    for i in range(n):
        j = order[i] - 1
        while j >= 0 and not placed[j]:
            order[starts[group[j]]] = j
            starts[group[j]] += 1
            placed[j] = True
            j = previous[j]
    return order[1:]


def equal_strings(pieces: list[bytes], lengths: list[int], cores: list[tuple[int, int, int]], groups: list[int] | None = None) -> list[np.ndarray]:
    """For each piece, the class of the string of ``length`` bytes at each place; equal strings of a group have equal classes.

    All strings of a piece share the bytes from ``core`` start to end, which stand as one symbol: (start, end, symbol's name).
    Strings are only equal when their cores are, so the folded text has the same equal strings and is far shorter. Pieces of
    one group stand together, in ascending groups, and share an array; several groups fill one.
    """
    groups = groups or [0] * len(pieces)
    out: list[np.ndarray] = []
    first, symbols, seen = 0, 0, 0
    for k in range(len(pieces) + 1):
        if k == len(pieces) or (symbols >= ARRAY_SYMBOLS and groups[k] != groups[k - 1]):
            if k > first:
                out += _classes(pieces[first:k], lengths[first:k], cores[first:k], seen)
                seen += sum(len(p) - n + 1 for p, n in zip(pieces[first:k], lengths[first:k], strict=True))
            first, symbols = k, 0
        if k < len(pieces):
            symbols += len(pieces[k]) - (cores[k][1] - cores[k][0]) + 2
    return out


def _classes(pieces: list[bytes], lengths: list[int], cores: list[tuple[int, int, int]], base: int) -> list[np.ndarray]:
    text: list[int] = []
    begin, count, span = [], [], []
    least = min(name for _, _, name in cores)
    for piece, length, (lo, hi, name) in zip(pieces, lengths, cores, strict=True):
        begin.append(len(text))
        text += piece[:lo]
        text.append(256 + name - least)
        text += piece[hi:]
        text.append(-1)
        count.append(len(piece) - length + 1)
        span.append(length - (hi - lo) + 1)
    order = np.array(suffix_array(text), np.int64)
    data = np.array(text, np.int64)
    size = np.zeros(len(text), np.int64)  # symbols of the string that starts here
    for b, n, k in zip(begin, count, span, strict=True):
        size[b : b + n] = k
    order = order[size[order] > 0]
    new = np.ones(len(order), bool)
    steps = np.arange(max(span))
    data = np.pad(data, (0, len(steps)), constant_values=-2)
    for a in range(1, len(order), 50_000):
        e = min(a + 50_000, len(order))
        x, y = order[a:e], order[a - 1 : e - 1]
        differs = (data[x[:, None] + steps] != data[y[:, None] + steps]) & (steps < size[x][:, None])
        new[a:e] = differs.any(axis=1) | (size[x] != size[y])
    classes = np.zeros(len(text), np.int64)
    classes[order] = base + np.cumsum(new) - 1
    return [classes[b : b + n] for b, n in zip(begin, count, strict=True)]


def _name(h: np.ndarray, parts: int) -> np.ndarray:
    """48 bits that name an anchor within its task; names that meet by chance only bring strings together that then differ."""
    return (h // np.uint64(parts)) & np.uint64((1 << 48) - 1)


def _pack(*columns: np.ndarray) -> bytes:
    """Columns of equal length, byte planes apart, compressed."""
    import zstandard

    planes = [np.ascontiguousarray(np.ascontiguousarray(c).view(np.uint8).reshape(len(c), -1).T).tobytes() for c in columns]
    return zstandard.ZstdCompressor(level=1).compress(struct.pack("<Q", len(columns[0])) + b"".join(planes))


def _unpack(data: bytes, *kinds: str) -> list[np.ndarray]:
    import zstandard

    raw = zstandard.ZstdDecompressor().decompress(data)
    (n,), at, out = struct.unpack_from("<Q", raw), 8, []
    for kind in kinds:
        width = np.dtype(kind).itemsize
        planes = np.frombuffer(raw, np.uint8, n * width, at).reshape(width, n)
        out.append(np.ascontiguousarray(planes.T).reshape(-1).view(kind) if n else np.array([], kind))
        at += n * width
    return out


def _text_slices(batches: Iterator[pa.RecordBatch]):
    """(batch, first row, end row, bytes of the texts one after another, where each begins and ends) of bounded size; a longer text stands alone.

    The bytes are the batch's own buffer, so that no text is copied.
    """
    for batch in batches:
        column = batch.column(1).cast(pa.large_string()).fill_null("")
        n = len(column)
        _, places, values = column.buffers()
        edge = np.frombuffer(places, np.int64)[column.offset : column.offset + n + 1] if n else np.zeros(1, np.int64)
        data = np.frombuffer(values, np.uint8) if values is not None else np.zeros(0, np.uint8)
        a = 0
        while a < n:
            b = max(a + 1, int(np.searchsorted(edge, edge[a] + SLICE_BYTES, side="right")) - 1)
            b = min(b, n)
            yield batch, a, b, data[edge[a] : edge[b]], edge[a : b + 1] - edge[a]
            a = b


def _gathered(kind: str, parts: int) -> int:
    """How many rows of a kind are gathered before they are packed for ``parts`` tasks."""
    return min(MOST_ROWS[kind], PAYLOAD_ROWS * parts)


def _document_task(owner: np.ndarray, mark: np.ndarray, parts: int) -> np.ndarray:
    return (((owner ^ mark).view(np.uint64) * _M >> np.uint64(32)) % np.uint64(parts)).astype(np.int64)


def _cuts(bucket: np.ndarray) -> list[tuple[int, int]]:
    """Where each run of a sorted array begins and ends."""
    if not len(bucket):
        return []
    edge = np.r_[np.flatnonzero(np.r_[True, bucket[1:] != bucket[:-1]]), len(bucket)].tolist()
    return list(zip(edge[:-1], edge[1:], strict=True))


def _rows(buckets: list[int], payloads: list[bytes], kinds: list[int]) -> pa.RecordBatch:
    return pa.RecordBatch.from_pydict({"bucket": pa.array(buckets, pa.int32()), "kind": pa.array(kinds, pa.int32()), "payload": pa.array(payloads, pa.binary())})


def shared_anchors(docs: DataFrame, parts: int, length: int = LENGTH, gram: int = GRAM) -> DataFrame:
    """(doc_id, tag, places) of the anchors that strings of two documents may have, of a table (doc_id, text, tag): a row for each text, ``places`` being its
    ascending places as differences of four bytes. Rows with null doc_id carry a hot anchor's hash in ``tag``, those of tag -1 a number of all anchors in ``doc_id``."""
    most, most_places = _gathered("anchors", parts), _gathered("spans", parts)

    def packed(found: list[tuple[np.ndarray, ...]]) -> pa.RecordBatch:
        h, left, right, owner, place = (np.concatenate(c) for c in zip(*found, strict=True))
        order = np.argsort(h, kind="stable")
        h, left, right, owner, place = (x[order] for x in (h, left, right, owner, place))
        seen = _shared(h, left, right, owner, place)
        # one entry for anchors of equal sides that are settled here: its place is minus the number of its occurrences
        known = np.flatnonzero(seen)
        known = known[np.lexsort((right[known], left[known], h[known]))]
        same = lambda x: x[known][1:] == x[known][:-1]
        head = np.flatnonzero(np.r_[True, ~(same(h) & same(left) & same(right))]) if len(known) else known
        one = known[head]
        h_out, left_out, right_out = (np.concatenate([x[~seen], x[one]]) for x in (h, left, right))
        owner_out = np.concatenate([owner[~seen], owner[one]])
        place_out = np.concatenate([place[~seen], -np.diff(np.r_[head, len(known)])])
        bucket = (h_out % np.uint64(parts)).astype(np.int64)
        order = np.lexsort((h_out, bucket))
        bucket, h_out, left_out, right_out, owner_out, place_out = (x[order] for x in (bucket, h_out, left_out, right_out, owner_out, place_out))
        columns = _narrow(_name(h_out, parts), 6), _narrow(left_out, SIDE_BYTES), _narrow(right_out, SIDE_BYTES), owner_out.astype(np.int64), place_out.astype(np.int64)
        made = [(int(bucket[s]), _pack(*(x[s:e] for x in columns)), 0) for s, e in _cuts(bucket)]
        if seen.any():  # settled: any task may carry them
            made.append((int(h[0] % np.uint64(parts)), _pack(owner[seen].astype(np.int64), place[seen].astype(np.int64)), 1))
        return _rows([m[0] for m in made], [m[1] for m in made], [m[2] for m in made])

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, ...]] = []
        for batch, a, b, data, edge in _text_slices(batches):
            ids = batch.column(0).slice(a, b - a)
            doc = ids.fill_null(0).to_numpy()
            starts, ends = edge[:-1], edge[1:]
            known = ids.is_valid().to_numpy(zero_copy_only=False)
            at, h = anchor_positions(data, starts[known], ends[known], length, gram)
            if not len(at):
                continue
            row = np.searchsorted(ends, at, side="right")
            tag = batch.column(2).slice(a, b - a).to_numpy()
            held.append((h, *side_digests(data, at, length, gram), doc[row], (at - starts[row]).astype(np.int64) | (tag[row] << PLACE_BITS)))
            if sum(len(x[0]) for x in held) >= most:
                yield packed(held)
                held = []
        if held:
            yield packed(held)

    def dealt_places(found: list[tuple[np.ndarray, ...]]) -> pa.RecordBatch:
        """Places to the tasks of their documents, in order of document and place."""
        owner, place = (np.concatenate(c) for c in zip(*found, strict=True))
        bucket = _document_task(owner, place >> PLACE_BITS, parts)
        order = np.lexsort((place, owner, bucket))
        owner, place, bucket = owner[order], place[order], bucket[order]
        at = _cuts(bucket)
        return _rows([int(bucket[s]) for s, _ in at], [_pack(owner[s:e], place[s:e]) for s, e in at], [0] * len(at))

    def gather(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list] = {}
        found: list[tuple[np.ndarray, ...]] = []
        many = 0

        def add(owner: np.ndarray, place: np.ndarray) -> Iterator[pa.RecordBatch]:
            nonlocal found, many
            if len(owner):
                found.append((owner, place))
                many += len(owner)
            if many >= most_places:
                yield dealt_places(found)
                found, many = [], 0

        for batch in batches:
            for bucket, kind, payload in zip(*(batch.column(k).to_pylist() for k in range(3)), strict=True):
                if kind == 1:
                    yield from add(*_unpack(payload, "<i8", "<i8"))
                else:
                    held.setdefault(bucket, []).append(_unpack(payload, "V6", f"V{SIDE_BYTES}", f"V{SIDE_BYTES}", "<i8", "<i8"))
        total = sum(len(x[0]) for xs in held.values() for x in xs)
        seen = 0
        while held:
            bucket, entries = held.popitem()
            h, left, right, doc, pos = (np.concatenate(c) for c in zip(*entries, strict=True))
            del entries
            h = _widened(h, 6)
            order = np.argsort(h, kind="stable")
            h, left, right, doc, pos = h[order], _widened(left, SIDE_BYTES).astype(np.uint32)[order], _widened(right, SIDE_BYTES).astype(np.uint32)[order], doc[order], pos[order]
            shared = _shared(h, left, right, doc, pos)
            keep = shared & (pos >= 0)
            yield from add(doc[keep], pos[keep])
            head = np.flatnonzero(np.r_[True, h[1:] != h[:-1]])
            weight = np.add.reduceat(np.where(pos < 0, -pos, shared), head)
            hot = h[head][weight > max(HOT_FLOOR, total // HOT_SHARE)] * np.uint64(parts) + np.uint64(bucket)
            if len(hot):
                yield _rows([bucket], [_pack(hot)], [2])
            seen += int(np.where(pos < 0, -pos, 1).sum())
        if seen:
            yield _rows([0], [_pack(np.array([seen]))], [3])
        if found:
            yield dealt_places(found)

    def texts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names, found = ["doc_id", "tag", "places"], []
        for batch in batches:
            for kind, payload in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist(), strict=True):
                if kind == 2:
                    (hot,) = _unpack(payload, "<i8")
                    yield pa.RecordBatch.from_arrays([pa.nulls(len(hot), pa.int64()), pa.array(hot), pa.nulls(len(hot), pa.binary())], names=names)
                elif kind == 3:
                    yield pa.RecordBatch.from_arrays([pa.array(_unpack(payload, "<i8")[0]), pa.array([-1], pa.int64()), pa.nulls(1, pa.binary())], names=names)
                else:
                    found.append(_unpack(payload, "<i8", "<i8"))
        if not found:
            return
        owner, place = (np.concatenate(c) for c in zip(*found, strict=True))
        order = np.lexsort((place, owner))
        owner, place = owner[order], place[order]
        new = np.r_[True, (owner[1:] != owner[:-1]) | (place[1:] != place[:-1])]  # repeated rows have the same places
        owner, tag, place = owner[new], place[new] >> PLACE_BITS, place[new] & ((1 << PLACE_BITS) - 1)
        first = np.r_[True, (owner[1:] != owner[:-1]) | (tag[1:] != tag[:-1])]
        step = np.where(first, place, np.diff(place, prepend=0)).astype("<u4")
        edge = np.r_[np.flatnonzero(first), len(place)]
        for a in range(0, len(edge) - 1, 10_000):
            at = edge[a : a + 10_001]
            places = pa.Array.from_buffers(pa.binary(), len(at) - 1, [None, pa.py_buffer(((at - at[0]) * 4).astype(np.int32)), pa.py_buffer(step[at[0] : at[-1]])])
            yield pa.RecordBatch.from_arrays([pa.array(owner[at[:-1]]), pa.array(tag[at[:-1]]), places], names=names)

    payloads = "bucket int, kind int, payload binary"
    dealt = docs.select("doc_id", "text", "tag").mapInArrow(scan, payloads).repartitionById(parts, F.col("bucket"))
    known = dealt.mapInArrow(gather, payloads).repartitionById(parts, F.col("bucket"))
    return known.mapInArrow(texts, "doc_id long, tag long, places binary")


def _own_reach(h: np.ndarray, p: np.ndarray, flank: int) -> tuple[np.ndarray, np.ndarray]:
    """How far strings may reach to each side of the anchors at ``p`` while no other gram in them, of hash ``h``, is their anchor."""
    near = h[p[:, None] + np.arange(2 * flank + 1)]
    mine = near[:, flank : flank + 1]
    lower, beats = near[:, flank - 1 :: -1] < mine, near[:, flank + 1 :] <= mine
    reach = lambda x: np.where(x.any(axis=1), x.argmax(axis=1), flank)
    return reach(lower), reach(beats)


def _joined(owner: np.ndarray, mark: np.ndarray, start: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, ...]:
    """The same spans with those that touch made one, per document."""
    if not len(owner):
        return tuple(np.zeros(0, np.int64) for _ in range(4))
    order = np.lexsort((start, mark, owner))
    owner, mark, start, end = (x[order].astype(np.int64) for x in (owner, mark, start, end))
    fresh = np.r_[True, (owner[1:] != owner[:-1]) | (mark[1:] != mark[:-1])]
    base = np.cumsum(fresh) << 40
    far = np.maximum.accumulate(end + base)
    head = np.flatnonzero(np.r_[True, start[1:] + base[1:] > far[:-1]])
    last = np.r_[head[1:], len(order)] - 1
    return owner[head], mark[head], start[head], far[last] - base[last]


def _string_key(ctx: np.ndarray, anchor: np.ndarray) -> np.ndarray:
    """The key of a string that is dealt by itself."""
    return row_hashes(ctx, ctx.shape[1])[:, 0] ^ anchor


def _send(owner, mark, place, left, right, ctx) -> bytes:
    """Contexts of one task: documents once, then per context its document, place, reach and bytes. Keys follow from the bytes."""
    import zstandard

    whose, which = np.unique(np.stack([owner, mark], axis=1).astype(np.int64), axis=0, return_inverse=True)
    docs = _pack(np.ascontiguousarray(whose[:, 0]), np.ascontiguousarray(whose[:, 1]))
    flat = _pack(which.reshape(-1).astype("<u4"), place.astype(np.int64), left.astype(np.uint8), right.astype(np.uint8))
    return struct.pack("<II", len(docs), len(flat)) + docs + flat + zstandard.ZstdCompressor(level=5).compress(ctx.tobytes())


def _receive(payload: bytes, width: int, flank: int, gram: int) -> tuple[np.ndarray, ...]:
    import zstandard

    n, m = struct.unpack_from("<II", payload)
    whose, marks = _unpack(payload[8 : 8 + n], "<i8", "<i8")
    which, place, left, right = _unpack(payload[8 + n : 8 + n + m], "<u4", "<i8", "u1", "u1")
    ctx = np.frombuffer(zstandard.ZstdDecompressor().decompress(payload[8 + n + m :]), np.uint8).reshape(-1, width)
    key = row_hashes(ctx[:, flank : flank + gram], gram)[:, 0]
    alone = right >= 128
    if alone.any():
        key[alone] = _string_key(ctx[alone], key[alone])
    return key, whose[which], marks[which], place, left, right & 127, ctx


def removed_spans(docs: DataFrame, anchors: DataFrame, hot: np.ndarray, parts: int, length: int = LENGTH, gram: int = GRAM, turn: int = 0, turns: int = 1) -> DataFrame:
    """(doc_id, text_hash, start, end) of strings that start in a smaller document as well; spans that touch are one. Strings of the turn's anchors alone."""
    flank = length - gram
    width = length + flank
    most, most_spans = _gathered("contexts", parts), _gathered("spans", parts)

    def packed(found: list[tuple[np.ndarray, ...]]) -> pa.RecordBatch | None:
        ctx, key, alone, owner, mark, place, left, right = (np.concatenate(c) for c in zip(*found, strict=True))
        # of equal contexts, those in larger documents are settled here
        reach = np.stack([left, right], axis=1).astype(np.uint8)
        order = np.lexsort((owner, row_hashes(ctx, width)[:, 0] ^ (left.astype(np.uint64) << np.uint64(8)) ^ right.astype(np.uint64)))
        same = np.zeros(len(order), bool)
        for a in range(1, len(order), ROWS):
            x, y = order[a : a + ROWS], order[a - 1 : a - 1 + ROWS]
            y = y[: len(x)]
            same[a : a + ROWS] = (ctx[x] == ctx[y]).all(axis=1) & (reach[x] == reach[y]).all(axis=1)
        head = np.flatnonzero(~same)
        least = np.repeat(owner[order][head], np.diff(np.r_[head, len(order)]))
        settled = np.zeros(len(owner), bool)
        settled[order] = owner[order] > least
        settled &= left + gram + right >= length
        made = []
        if settled.any():
            made.append((int(key[0] % np.uint64(parts)), _pack(*_joined(*(x[settled] for x in (owner, mark, place - left, place + gram + right)))), 1))
        sent = np.flatnonzero(~settled & (left + gram + right >= length))
        bucket = (key[sent] % np.uint64(parts)).astype(np.int64)
        order = np.lexsort((key[sent], bucket))
        sent, bucket = sent[order], bucket[order]
        for s, e in _cuts(bucket):
            k = sent[s:e]
            made.append((int(bucket[s]), _send(owner[k], mark[k], place[k], left[k], right[k].astype(np.uint8) | alone[k], ctx[k]), 0))
        return _rows([m[0] for m in made], [m[1] for m in made], [m[2] for m in made]) if made else None

    def contexts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, ...]] = []
        for batch, a, b, data, edge in _text_slices(batches):
            doc, digest, wanted = (batch.column(k).slice(a, b - a) for k in (0, 2, 3))
            doc, digest = doc.to_numpy(), digest.to_numpy()
            parts_of = []
            for i in range(b - a):
                text = data[edge[i] : edge[i + 1]]
                p = np.cumsum(np.frombuffer(wanted[i].as_buffer(), "<u4"), dtype=np.int64)
                p = p[p + gram <= len(text)]
                padded = np.zeros(len(text) + 2 * flank, np.uint8)
                padded[flank : flank + len(text)] = text
                if not len(p):
                    continue
                h = gram_hashes(padded, gram)
                if turns > 1:
                    p = p[(h[p + flank] >> np.uint64(40)) % np.uint64(turns) == np.uint64(turn)]
                m = len(p)
                if not m:
                    continue
                left, right = _own_reach(h, p, flank)
                left, right = np.minimum(left, p), np.minimum(right, len(text) - p - gram)
                column = np.arange(width)
                ctx = np.where((column >= (flank - left)[:, None]) & (column < (flank + gram + right)[:, None]), padded[p[:, None] + column], 0).astype(np.uint8)
                parts_of.append((ctx, np.full(m, doc[i]), np.full(m, digest[i]), p, left, right))
            if not parts_of:
                continue
            ctx, owner, mark, place, left, right = (np.concatenate(c) for c in zip(*parts_of, strict=True))
            if not len(place):
                continue
            key = row_hashes(ctx[:, flank : flank + gram], gram)[:, 0]
            alone = np.zeros(len(key), np.uint8)
            wide = np.isin(_name(key, parts) * np.uint64(parts) + key % np.uint64(parts), hot)
            if wide.any():  # a hot anchor's strings are dealt one by one
                pick, shift = np.nonzero(wide[:, None] & (np.arange(flank + 1) <= left[:, None]) & (flank - np.arange(flank + 1) <= right[:, None]))
                column = np.arange(width)
                single = np.zeros((len(pick), width), np.uint8)
                for r in range(0, len(pick), ROWS):
                    some = slice(r, r + ROWS)
                    inside = (column >= (flank - shift[some])[:, None]) & (column < (flank - shift[some] + length)[:, None])
                    single[some] = ctx[pick[some]] * inside
                keep = ~wide
                ctx, key = np.concatenate([ctx[keep], single]), np.concatenate([key[keep], _string_key(single, key[pick])])
                alone = np.r_[np.zeros(keep.sum(), np.uint8), np.full(len(pick), 128, np.uint8)]
                owner, mark, place = (np.concatenate([c[keep], c[pick]]) for c in (owner, mark, place))
                left, right = np.concatenate([left[keep], shift]), np.concatenate([right[keep], flank - shift])
            held.append((ctx, key, alone, owner, mark, place, left, right))
            if sum(len(x[1]) for x in held) >= most:
                made, held = packed(held), []
                if made is not None:
                    yield made
        made = packed(held) if held else None
        if made is not None:
            yield made

    def dealt_spans(found: list[tuple[np.ndarray, ...]]) -> pa.RecordBatch:
        """Spans to the tasks of their documents, in order of document and place."""
        owner, mark, start, end = _joined(*(np.concatenate(c) for c in zip(*found, strict=True)))
        bucket = _document_task(owner, mark, parts)
        order = np.argsort(bucket, kind="stable")
        owner, mark, start, end, bucket = owner[order], mark[order], start[order], end[order], bucket[order]
        at = _cuts(bucket)
        payloads = []
        for s, e in at:
            new = np.r_[True, (owner[s + 1 : e] != owner[s : e - 1]) | (mark[s + 1 : e] != mark[s : e - 1])]
            docs = _pack(owner[s:e][new], mark[s:e][new], np.diff(np.r_[np.flatnonzero(new), e - s]).astype("<i8"))
            payloads.append(struct.pack("<I", len(docs)) + docs + _pack(start[s:e].astype("<i8"), (end - start)[s:e].astype("<i8")))
        return _rows([int(bucket[s]) for s, _ in at], payloads, [0] * len(at))

    def resolve(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list] = {}
        found: list[tuple[np.ndarray, ...]] = []
        many = 0

        def add(spans: tuple[np.ndarray, ...]) -> Iterator[pa.RecordBatch]:
            nonlocal found, many
            if len(spans[0]):
                found.append(spans)
                many += len(spans[0])
            if many >= most_spans:
                yield dealt_spans(found)
                found, many = [], 0

        for batch in batches:
            for bucket, kind, payload in zip(*(batch.column(k).to_pylist() for k in range(3)), strict=True):
                if kind == 1:
                    yield from add(tuple(_unpack(payload, "<i8", "<i8", "<i8", "<i8")))
                    continue
                held.setdefault(bucket, []).append(_receive(payload, width, flank, gram))
        while held:
            _, entries = held.popitem()
            for spans in _owned(*(np.concatenate(c) for c in zip(*entries, strict=True)), length, gram):
                yield from add(spans)
        if found:
            yield dealt_spans(found)

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found = []
        for batch in batches:
            for payload in batch.column(2).to_pylist():
                (n,) = struct.unpack_from("<I", payload)
                owner, mark, times = _unpack(payload[4 : 4 + n], "<i8", "<i8", "<i8")
                start, size = _unpack(payload[4 + n :], "<i8", "<i8")
                found.append((np.repeat(owner, times), np.repeat(mark, times), start, start + size))
        if found:
            whole = _joined(*(np.concatenate(c) for c in zip(*found, strict=True)))
            for a in range(0, len(whole[0]), 100_000):
                yield pa.RecordBatch.from_arrays([pa.array(c[a : a + 100_000], pa.int64()) for c in whole], names=["doc_id", "text_hash", "start", "end"])

    found = anchors.where("places is not null").withColumnRenamed("places", "_hs_at")
    joined = docs.join(found, ["doc_id", "tag"]).select("doc_id", "text", F.xxhash64("text").alias("_hs_hash"), "_hs_at")
    dealt = joined.mapInArrow(contexts, "bucket int, kind int, payload binary").repartitionById(parts, F.col("bucket"))
    owned = dealt.mapInArrow(resolve, "bucket int, kind int, payload binary").repartitionById(parts, F.col("bucket"))
    return owned.mapInArrow(merge, "doc_id long, text_hash long, start long, end long")


def _owned(key, owner, mark, place, left, right, ctx, length: int, gram: int) -> Iterator[tuple[np.ndarray, ...]]:
    """Spans of the occurrences, of one task's contexts, whose strings belong to a smaller document."""
    flank = length - gram
    whole = np.concatenate([key[:, None].view(np.uint8).reshape(-1, 8), ctx, left[:, None], right[:, None]], axis=1)
    _, first, which = np.unique(np.ascontiguousarray(whole).view(f"V{whole.shape[1]}").reshape(-1), return_index=True, return_inverse=True)
    m = len(first)
    low = np.full(m, np.iinfo(np.int64).max)
    np.minimum.at(low, which, owner)
    _, group = np.unique(key[first], return_inverse=True)
    offsets = np.arange(flank + 1)  # a string that starts `offset` bytes before the anchor
    fits = (offsets <= left[first][:, None]) & (flank - offsets <= right[first][:, None])
    owners = np.where(fits, low[:, None], np.iinfo(np.int64).max)
    # An anchor with one context has nothing to order, and strings that occur in one context only, by their hash, have no equal.
    strings = row_hashes(ctx[first], length)[:, ::-1]  # column: offset
    r, o = np.nonzero(fits & (np.bincount(group) > 1)[group][:, None])
    value = strings[r, o] ^ (key[first[r]] * _M)
    order = np.argsort(value, kind="stable")
    run = np.cumsum(np.r_[True, value[order][1:] != value[order][:-1]]) - 1 if len(value) else np.array([], np.int64)
    twice = np.zeros(len(value), bool)
    twice[order] = (np.bincount(run) > 1)[run] if len(value) else False
    maybe = np.zeros((m, flank + 1), bool)
    maybe[r, o] = twice
    # Pieces: runs of strings that may be shared. Distinct pieces alone are sorted, an anchor's together.
    edge = np.diff(np.pad(maybe.astype(np.int8), ((0, 0), (1, 1))), axis=1)
    rows, begin = np.nonzero(edge == 1)
    _, end = np.nonzero(edge == -1)
    if len(rows):
        by = np.argsort(group[rows], kind="stable")
        rows, begin, end = rows[by], begin[by], end[by]
        anchors = group[rows]
        # The bytes that every shared string of an anchor holds: its core.
        widest_b, widest_e = np.full(group.max() + 1, flank + 1), np.zeros(group.max() + 1, np.int64)
        np.minimum.at(widest_b, anchors, begin)
        np.maximum.at(widest_e, anchors, end)
        core_lo, core_hi = flank - widest_b[anchors], flank - (widest_e[anchors] - 1) + length
        names: dict[tuple, int] = {}
        cores: dict[tuple, int] = {}
        pieces, folds, groups = [], [], []
        piece_of = np.empty(len(rows), np.int64)
        at_row = first[rows]
        for k, (row, g, b, e, lo, hi) in enumerate(zip(at_row.tolist(), anchors.tolist(), begin.tolist(), end.tolist(), core_lo.tolist(), core_hi.tolist(), strict=True)):
            from_ = flank - e + 1
            piece = ctx[row, from_ : flank - b + length].tobytes()
            got = names.setdefault((g, from_, piece), len(names))
            if got == len(pieces):
                pieces.append(piece)
                groups.append(g)
                folds.append((lo - from_, hi - from_, cores.setdefault((g, piece[lo - from_ : hi - from_]), len(cores))))
            piece_of[k] = got
        classes = equal_strings(pieces, [length] * len(pieces), folds, groups)
        sizes = end - begin
        cells = np.concatenate([classes[k] for k in piece_of.tolist()])
        owner_row = np.repeat(rows, sizes)
        step = np.arange(len(owner_row)) - np.repeat(np.cumsum(sizes) - sizes, sizes)
        offset = np.repeat(end - 1, sizes) - step
        best = np.full(1 + int(cells.max()), np.iinfo(np.int64).max)
        np.minimum.at(best, cells, low[owner_row])
        owners[owner_row, offset] = best[cells]
    for a in range(0, len(owner), 200_000):
        e = min(a + 200_000, len(owner))
        gone = owners[which[a:e]] < owner[a:e, None]
        edge = np.diff(np.pad(gone.astype(np.int8), ((0, 0), (1, 1))), axis=1)
        row, b = np.nonzero(edge == 1)
        _, f = np.nonzero(edge == -1)
        row = row + a
        yield _joined(owner[row], mark[row], place[row] - (f - 1), place[row] - b + length)


def merge_spans(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    out: list[tuple[int, int]] = []
    for s, e in sorted(spans):
        if out and s <= out[-1][1]:
            out[-1] = (out[-1][0], max(e, out[-1][1]))
        else:
            out.append((s, e))
    return out


def deduplicate(docs: DataFrame, carry: list[str] | None = None, length: int = LENGTH, gram: int = GRAM) -> DataFrame:
    """The carried columns of each row with ``_hs_kept`` (remaining bytes), ``_hs_kept_text`` (the same without characters cut in
    two) and ``_hs_spans`` (maximal removed runs)."""
    spark = docs.sparkSession
    carry = carry or ["doc_id"]
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    tag = F.xxhash64("text").bitwiseAND(F.lit((1 << TAG_BITS) - 1))
    base = docs.where("doc_id is not null").select("doc_id", "text", tag.alias("tag"))
    anchors = staged(shared_anchors(base, parts, length, gram), "anchors")
    hot = np.array([r["tag"] for r in anchors.where("doc_id is null").select("tag").collect()], np.int64).view(np.uint64)  # at most HOT_SHARE a task
    kept, every = anchors.where("doc_id is not null").agg(F.sum(F.when(F.col("tag") >= 0, F.octet_length("places") / 4)), F.sum(F.when(F.col("tag") < 0, F.col("doc_id")))).first()
    turns = 1 if (kept or 0) <= TURN_FLOOR else math.ceil(kept / (TURN_SHARE * every))
    spans = removed_spans(base, anchors, hot, parts, length, gram)
    if turns > 1:
        spans = reduce(DataFrame.union, [staged(removed_spans(base, anchors, hot, parts, length, gram, k, turns), "spans") for k in range(turns)])
    per_doc = spans.groupBy(F.col("doc_id").alias("_hs_id"), F.col("text_hash").bitwiseAND(F.lit((1 << TAG_BITS) - 1)).alias("_hs_tag")).agg(F.collect_list(F.struct("text_hash", "start", "end")).alias("_hs_found"))

    def apply(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n = len(carry)
        for batch in (b.slice(k, 500) for b in batches for k in range(0, b.num_rows, 500)):
            kept, spans = [], []
            for text, digest, found in zip(batch.column(n), batch.column(n + 1).to_pylist(), batch.column(n + 2), strict=True):
                data = (text.as_py() or "").encode("utf-8", "surrogatepass")
                own = []
                if found.is_valid:
                    v = found.values
                    own = merge_spans([(s, e) for h, s, e in zip(*(v.field(k).to_pylist() for k in range(3)), strict=True) if h == digest])
                edges = [0, *(x for span in own for x in span), len(data)]
                kept.append(b"".join(data[s:e] for s, e in zip(edges[::2], edges[1::2], strict=True)))
                spans.append([{"start": s, "end": e} for s, e in own])
            clean = pa.array([k.decode("utf-8", "ignore") for k in kept], pa.string())
            yield pa.RecordBatch.from_arrays([*batch.columns[:n], pa.array(kept, pa.binary()), clean, pa.array(spans, pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())])))], names=[*carry, "_hs_kept", "_hs_kept_text", "_hs_spans"])

    fields = ", ".join(f"`{c}` {docs.schema[c].dataType.simpleString()}" for c in carry)
    # With doc_id alone to carry, this side is the one that met the anchors, and its exchange is used again.
    more = [c for c in carry if c != "doc_id"]
    known = base if not more else docs.where("doc_id is not null").select(*[F.col(c).alias(f"_hs_in_{c}") for c in more], "doc_id", "text", tag.alias("tag"))
    joined = known.join(per_doc, (known["doc_id"] == F.col("_hs_id")) & (known["tag"] == F.col("_hs_tag")), "left")
    own = lambda c: F.col("doc_id") if c == "doc_id" else F.col(f"_hs_in_{c}").alias(c)
    joined = joined.select(*[own(c) for c in carry], F.col("text").alias("_hs_text"), F.xxhash64("text").alias("_hs_hash"), "_hs_found")
    nameless = docs.where("doc_id is null").select(*carry, F.col("text").alias("_hs_text"), F.lit(0).cast("long").alias("_hs_hash"))
    joined = joined.union(nameless.withColumn("_hs_found", F.lit(None).cast(joined.schema["_hs_found"].dataType)))
    return joined.mapInArrow(apply, f"{fields}, _hs_kept binary, _hs_kept_text string, _hs_spans array<struct<start: long, end: long>>")


def op6_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    removed = F.aggregate("_hs_spans", F.lit(0).cast("long"), lambda total, s: total + s["end"] - s["start"])
    return deduplicate(docs).select(
        "doc_id", (F.length("_hs_kept") + removed).cast("long").alias("n_bytes"), removed.alias("n_removed"), F.size("_hs_spans").cast("long").alias("n_spans"),
        F.sha2("_hs_kept", 256).alias("kept_sha256"))
