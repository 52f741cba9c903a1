"""Token ids of whole texts: each distinct word of a slice of texts is encoded once.

Byte-level BPE splits a text into pieces before it merges, and a single space between two characters that are not white
space always starts a piece. Chunks between such spaces therefore encode independently, and the ids of a text are the
ids of its chunks in order. A slice of texts is split and its chunks numbered by Arrow; the tokenizers library encodes the distinct
ones, and numpy lays their ids out in the order of the texts. A memo of at most ``MEMO_BYTES`` keeps words that came up more than once.
"""

from __future__ import annotations

import json
import os
import re
from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: A space next to other white space does not start a chunk. U+180E counts as white space in older Unicode tables.
_WIDE = "\x85\xa0 ᠎ -     　"
_LONE_SPACE = re.compile(r"(?<=[^\s᠎]) (?=[^\s᠎])")
#: Byte-level vocabularies name a printable byte by its own character and the others, in order, by those from U+0100 on.
_PRINTABLE = {*range(33, 127), *range(161, 173), *range(174, 256)}
_BYTE_NAMES = {b: chr(256 + k) for k, b in enumerate(b for b in range(256) if b not in _PRINTABLE)}
_SPACE_NAME, _LINE_NAME = _BYTE_NAMES[32], _BYTE_NAMES[10]
#: Texts in which some space has white space or nothing beside it; all others are split at every space.
_NARROW = "\\t\\n\\v\\f\\r\\x1c\\x1d\\x1e\\x1f"
_UNEVEN = f"^ | $|  | [{_NARROW}]|[{_NARROW}] |[{_WIDE}]"
#: A bound on the memo: its words, their ids, and the objects that hold them.
MEMO_BYTES, _ENTRY_BYTES = 96 << 20, 180
SLICE_BYTES, SLICE_ROWS = 6_000_000, 10_000


def default_tokenizer() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


class Encoder:
    """Encodes texts to little-endian unsigned 32-bit ids; one instance per Python worker and tokenizer file."""

    _made: dict[tuple, Encoder] = {}

    def __init__(self, path: str, memo_bytes: int = MEMO_BYTES, plain_specials: bool = False):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        if plain_specials:
            self.tokenizer.encode_special_tokens = True
        self.plain_specials = plain_specials
        self.specials = [t.content for t in self.tokenizer.get_added_tokens_decoder().values()]
        self.room = memo_bytes
        self.memo: dict[str, bytes] = {}
        self.seen = np.zeros(1 << 22, bool)  # of words that came up in an earlier slice, by hash
        self.vocabulary = self.tokenizer.get_vocab_size()
        line_end = self.tokenizer.encode("\n", add_special_tokens=False).ids
        self.line_end = line_end[0] if len(line_end) == 1 else None
        self.letters = self._letters_only()

    @classmethod
    def shared(cls, path: str, plain_specials: bool = False) -> Encoder:
        key = (path, plain_specials)
        if key not in cls._made:
            cls._made[key] = cls(path, plain_specials=plain_specials)
        return cls._made[key]

    def _run(self, texts: list[str]) -> list[bytes]:
        return [array("I", e.ids).tobytes() for e in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]

    def _letters_only(self):
        """The same model behind a bare split at spaces, for words of letters alone: they are one piece whatever the pattern says."""
        from tokenizers import Tokenizer, pre_tokenizers

        parts = json.loads(self.tokenizer.to_str())
        if parts["model"]["type"] != "BPE" or (parts["pre_tokenizer"] or {}).get("type") != "ByteLevel" or parts["normalizer"]:
            return None
        bare = Tokenizer(self.tokenizer.model)
        bare.pre_tokenizer = pre_tokenizers.WhitespaceSplit()
        return bare

    def _run_letters(self, words: list[str]) -> tuple[np.ndarray, np.ndarray] | None:
        """Number of ids of each word of letters alone that follows a space, and all ids one after another.

        Byte-level names of the words, and of a line end between them, go straight to the model.
        """
        if not self.letters or self.line_end is None:
            return None
        names = [w if w.isascii() else w.encode().decode("latin-1").translate(_BYTE_NAMES) for w in words]
        texts = [_SPACE_NAME + f" {_LINE_NAME} {_SPACE_NAME}".join(names[i : i + 128]) + f" {_LINE_NAME}" for i in range(0, len(words), 128)]
        held = array("I")
        for e in self.letters.encode_batch_fast(texts, add_special_tokens=False):
            held.extend(e.ids)
        ids = np.frombuffer(held, "<u4")
        ends = np.flatnonzero(ids == self.line_end)
        return (np.diff(ends, prepend=-1) - 1, np.delete(ids, ends)) if len(ends) == len(words) else None

    def _run_words(self, words: list[str]) -> list[bytes]:
        """Ids of words that follow a space. Plain words share a text, a line each: the line end is a piece of its own there."""
        if self.line_end is None:
            return self._run([f" {w}" for w in words])
        found: dict[str, bytes] = {}
        plain = [w for w in words if w and w not in found and w.isprintable()]
        groups = [plain[i : i + 256] for i in range(0, len(plain), 256)]
        texts = [" " + "\n ".join(g) + "\n" for g in groups]
        for group, ids in zip(groups, self._run(texts), strict=True):
            ends = np.flatnonzero(np.frombuffer(ids, "<u4") == self.line_end).tolist()
            if len(ends) == len(group):
                found.update(zip(group, (ids[4 * a : 4 * b] for a, b in zip([0, *(e + 1 for e in ends)], ends, strict=False)), strict=True))
        rest = [w for w in words if w not in found]
        found.update(zip(rest, self._run([f" {w}" for w in rest]), strict=True))
        return [found[w] for w in words]

    def _resolve(self, words: list[str]) -> dict[str, bytes]:
        """Ids of words that the memo lacks. A full stop or comma after letters, and a line end between two words, start pieces too."""
        memo, made = self.memo, {}
        stems: dict[str, tuple[str, str, str]] = {}
        heads, tails = {}, {}
        for w in words:
            stem, line, tail = w.partition("\n")
            if line and not (stem and tail and stem.isprintable() and tail.isprintable()):
                heads[w] = None
                continue
            mark = stem[-1:]
            if mark in (".", ",") and stem[:-1].isalpha():
                stem = stem[:-1]
            else:
                mark = ""
            if not mark and not line:
                heads[w] = None
                continue
            stems[w] = (stem, mark, tail)
            if stem not in memo:
                heads[stem] = None
            if line:
                tails[tail] = None
        made.update(zip(heads, self._run_words(list(heads)), strict=True))
        if stems:
            marks = dict(zip(("", ".", ","), self._run(["", ".", ","]), strict=True))
            after = dict(zip(tails, self._run_starts(list(tails)), strict=True))
            end = self._run(["\n"])[0]
            for w, (stem, mark, tail) in stems.items():
                ids = memo.get(stem)
                made[w] = (made[stem] if ids is None else ids) + marks[mark] + (end + after[tail] if tail else b"")
        return made

    def _run_starts(self, words: list[str]) -> list[bytes]:
        """Ids of words at the start of a line."""
        joined = [words[i : i + 256] for i in range(0, len(words), 256)]
        out: list[bytes] = []
        for group, ids in zip(joined, self._run(["\n".join(g) + "\n" for g in joined]), strict=True):
            ends = np.flatnonzero(np.frombuffer(ids, "<u4") == self.line_end).tolist()
            if self.line_end is not None and len(ends) == len(group):
                out += [ids[4 * a : 4 * b] for a, b in zip([0, *(e + 1 for e in ends)], ends, strict=False)]
            else:
                out += self._run(group)
        return out

    def encode(self, texts: list[str | None] | pa.Array) -> list[bytes]:
        """Ids of each text as bytes; a null text has none. For slices of bounded size, see ``slices``."""
        column = texts if isinstance(texts, pa.Array) else pa.array(texts, pa.large_string())
        flat, ends = self._encode(column.cast(pa.large_string()).fill_null(""))
        view = memoryview(flat).cast("B")
        return [bytes(view[4 * a : 4 * b]) for a, b in zip([0, *ends[:-1]], ends, strict=False)]

    def _lists(self, texts: pa.Array) -> tuple[pa.Array, np.ndarray]:
        """Chunks of every text, those of uneven texts last, and each list's row."""
        uneven = pc.match_substring_regex(texts, _UNEVEN)
        whole = pa.array(np.zeros(len(texts), bool))
        if not self.plain_specials:  # special strings are found before spaces are
            for s in self.specials:
                whole = pc.or_(whole, pc.match_substring(texts, s))
        odd = pc.or_(uneven, whole)
        rows = np.r_[np.flatnonzero(pc.invert(odd).to_numpy(zero_copy_only=False)), np.flatnonzero(odd.to_numpy(zero_copy_only=False))]
        lists = [pc.split_pattern(texts.filter(pc.invert(odd)), " ")]
        if pc.any(odd).as_py():
            chunks = [[t] if keep else _LONE_SPACE.split(t) for t, keep in zip(texts.filter(odd).to_pylist(), whole.filter(odd).to_pylist(), strict=True)]
            lists.append(pa.array(chunks, lists[0].type))
        return pa.concat_arrays(lists), rows

    def _encode(self, texts: pa.Array) -> tuple[np.ndarray, list[int]]:
        """The ids of all texts one after another, and where each text ends."""
        n = len(texts)
        if not n:
            return np.array([], np.uint32), []
        lists, rows = self._lists(texts)
        edge = lists.offsets.to_numpy()
        first = np.zeros(edge[-1] - edge[0], bool)
        first[edge[:-1] - edge[0]] = True
        words = lists.flatten()
        named = words.filter(pa.array(~first)).dictionary_encode()
        body, mark, pieces = self._pieces(named.dictionary, np.bincount(named.indices.to_numpy(), minlength=len(named.dictionary)))
        pieces.append(self._run(words.filter(pa.array(first)).to_pylist()))
        size, ids = pieces.whole()
        # every word is one piece, or one and a mark
        place = np.empty((len(first), 2), np.int32)
        place[~first, 0], place[~first, 1] = body[named.indices.to_numpy()], mark[named.indices.to_numpy()]
        place[first, 0], place[first, 1] = len(size) - n + np.arange(n), -1
        count = np.diff(edge)
        if not np.array_equal(rows, np.arange(n)):  # lists stand in the order of `rows`
            back = np.argsort(rows)
            begin = edge[:-1] - edge[0]
            place = place[np.repeat(begin[back] - np.cumsum(count[back]) + count[back], count[back]) + np.arange(len(place))]
            count = count[back]
        long = np.where(place >= 0, size[place], 0)
        ends = np.cumsum(long.sum(axis=1))[np.cumsum(count) - 1]
        code = place[place >= 0]
        long, start = size[code], (np.cumsum(size) - size)[code]
        total = np.cumsum(long)
        out = ids[np.repeat(start - total + long, long) + np.arange(total[-1])] if total[-1] else ids[:0]
        return np.ascontiguousarray(out), ends.tolist()

    def _pieces(self, words: pa.Array, times: np.ndarray) -> tuple[np.ndarray, np.ndarray, Pieces]:
        """For distinct words that follow a space: the piece of each, the piece of the full stop or comma after it (or -1), and the pieces.

        Words of letters alone, with or without that mark, share their pieces; any others are resolved by themselves.
        """
        marked = pc.match_substring_regex(words, "[.,]$")
        stems = pc.if_else(marked, pc.utf8_slice_codeunits(words, 0, -1), words)
        plain = pc.utf8_is_alpha(stems).to_numpy(zero_copy_only=False)
        if self.letters is None:
            plain = np.zeros(len(words), bool)
        atoms = stems.filter(pa.array(plain)).dictionary_encode()
        names, which = atoms.dictionary.to_pylist(), atoms.indices.to_numpy()
        held = list(map(self.memo.get, names))
        new = np.fromiter((x is None for x in held), bool, len(held))
        pieces, at = Pieces(), np.empty(len(names), np.int64)
        at[~new] = pieces.append([x for x in held if x is not None])
        fresh = [names[i] for i in np.flatnonzero(new).tolist()]
        got = self._run_letters(fresh) if fresh else None
        if got is None:
            at[new] = pieces.append(self._run([f" {w}" for w in fresh]))
        else:
            at[new] = pieces.extend(*got)
            slot = np.fromiter(map(hash, fresh), np.int64, len(fresh)) & (len(self.seen) - 1)
            often = (np.bincount(which, weights=times[plain], minlength=len(names))[new] > 1) | self.seen[slot]
            self.seen[slot] = True
            self._remember(fresh, *got, often)
        body, mark = np.empty(len(words), np.int32), np.full(len(words), -1, np.int32)
        body[plain] = at[which]
        signs = pieces.append(self._run([".", ","]))
        both = plain & marked.to_numpy(zero_copy_only=False)
        mark[both] = np.where(pc.ends_with(words.filter(pa.array(both)), ".").to_numpy(zero_copy_only=False), signs[0], signs[1])
        odd = words.filter(pa.array(~plain)).to_pylist()
        held = list(map(self.memo.get, odd))
        rest = [w for w, x in zip(odd, held, strict=True) if x is None]
        made = self._resolve(rest)
        body[~plain] = pieces.append([made[w] if x is None else x for w, x in zip(odd, held, strict=True)])
        for w, k in zip(odd, times[~plain].tolist(), strict=True):
            if k > 1 and w in made:
                self._keep(w, made[w])
        return body, mark, pieces

    def _remember(self, words: list[str], size: np.ndarray, ids: np.ndarray, often: np.ndarray) -> None:
        """Words that came up more than once enter the memo while there is room."""
        ends = 4 * np.cumsum(size)
        data = ids.tobytes()
        for i in np.flatnonzero(often).tolist():
            if self.room <= 0:
                return
            self._keep(words[i], data[ends[i] - 4 * size[i] : ends[i]])

    def _keep(self, word: str, ids: bytes) -> None:
        if self.room > 0:
            self.memo[word] = ids
            self.room -= len(word) * (1 if word.isascii() else 2) + len(ids) + _ENTRY_BYTES


class Pieces:
    """Sequences of ids, numbered in the order they are given."""

    def __init__(self):
        self.sizes: list[np.ndarray] = []
        self.ids: list[np.ndarray] = []
        self.count = 0

    def extend(self, size: np.ndarray, ids: np.ndarray) -> np.ndarray:
        self.sizes.append(size)
        self.ids.append(ids)
        self.count += len(size)
        return np.arange(self.count - len(size), self.count)

    def append(self, given: list[bytes]) -> np.ndarray:
        return self.extend(np.fromiter(map(len, given), np.int64, len(given)) // 4, np.frombuffer(b"".join(given), "<u4"))

    def whole(self) -> tuple[np.ndarray, np.ndarray]:
        return np.concatenate(self.sizes), np.concatenate(self.ids)


def slices(texts: pa.Array, most_bytes: int = SLICE_BYTES, most_rows: int = SLICE_ROWS) -> Iterator[tuple[int, int]]:
    """Row ranges of a column that hold about ``most_bytes``, so that memory stays bounded; a longer text stands alone."""
    if not len(texts):
        return
    ends = np.cumsum(pc.fill_null(pc.binary_length(texts), 0).to_numpy(zero_copy_only=False).astype(np.int64))
    begin, before = 0, 0
    while begin < len(ends):
        end = min(max(int(np.searchsorted(ends, before + most_bytes, side="right")), begin + 1), begin + most_rows)
        yield begin, min(end, len(ends))
        begin = min(end, len(ends))
        before = int(ends[begin - 1])
