"""Token ids of whole Arrow columns, exactly the library's, without a Python object for each word.

For the word-level file (lower-cased, white space dropped, every word closed by an end-of-word token) a text's ids are
those of its white-space separated words in order. Words are taken apart on their bytes, all at once: a run of Latin-1
letters (lower-cased here, as the tokenizer does) and the run of ASCII marks after it are looked up apart, so case and
punctuation share entries. Known pieces are an Arrow table; the merges of unknown plain pieces are done in numpy, a merge
of every piece in each round, as the algorithm orders them; other pieces go to the library. What is known is bounded:
when it is full, only the pieces of the latest slice stay. Any other tokenizer file goes to the library text by text.
"""

from __future__ import annotations

import json
import os
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from .common import text_slices, worker_slot

#: Pieces remembered by a worker (some 30 bytes each); characters encoded at once.
KEEP, SLICE_CHARS = 400_000, 4_000_000
#: The normaliser and splitter steps of tokenizers whose words can be encoded one by one.
_NORMALIZERS = [("NFC", None), ("Replace", "\\s+"), ("Lowercase", None)]
_SPLIT = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"

#: Of every byte: 1 in Latin-1 letters of UTF-8, 2 in ASCII marks.
_KIND = np.zeros(256, np.uint8)
_KIND[[*range(65, 91), *range(97, 123), 0xC3, *range(0x80, 0xC0)]] = 1
_KIND[[*range(33, 48), *range(58, 65), *range(91, 97), *range(123, 127)]] = 2
#: Longest plain pieces (bytes) of the numpy merges, by group; beyond them the library.
_WIDTHS = (4, 8, 12, 16, 24, 40)
_NO_ID, _NO_RANK = 0xFFFF, 1 << 30


def word_level(spec: dict) -> bool:
    """Whether a tokenizer file lower-cases, drops white space and closes every word, with ids of 16 bits."""
    steps = (spec.get("normalizer") or {}).get("normalizers") or []
    splits = (spec.get("pre_tokenizer") or {}).get("pretokenizers") or []
    model = spec.get("model") or {}
    return (
        [(s["type"], (s.get("pattern") or {}).get("Regex")) for s in steps] == _NORMALIZERS
        and [s["type"] for s in splits] == ["Split", "ByteLevel"]
        and splits[0]["pattern"].get("Regex") == _SPLIT
        and splits[0]["behavior"] == "Removed"
        and splits[0]["invert"]
        and not splits[1]["add_prefix_space"]
        and model.get("type") == "BPE"
        and model.get("end_of_word_suffix") == "</w>"
        and not model.get("dropout")
        and max([*model["vocab"].values(), *(t["id"] for t in spec["added_tokens"])]) < _NO_ID
    )


def _bytes_of(words: pa.StringArray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The bytes of a string array, with the start and end of every word in them."""
    at = np.frombuffer(words.buffers()[1], np.int32)[words.offset : words.offset + len(words) + 1]
    raw = np.frombuffer(words.buffers()[2], np.uint8)[at[0] : at[-1]] if words.buffers()[2] is not None else np.zeros(0, np.uint8)
    return raw, at[:-1] - at[0], at[1:] - at[0]


def _counts(raw: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Running counts of the bytes of letters and of marks, and where two-byte letters begin."""
    kind = _KIND[raw]
    lead = np.flatnonzero(raw == 0xC3)
    kind[lead[np.isin(raw[lead + 1], (0x97, 0xB7))]] = 0  # the two signs among the letters
    letters, marks = (np.concatenate([[0], np.cumsum(kind == k, dtype=np.int32)]) for k in (1, 2))
    return letters, marks, lead


def _pieces(words: pa.StringArray) -> pa.StringArray:
    """Two pieces of every word: its letters, lower-cased, and the marks after them; any other word whole, and nothing."""
    raw, start, end = _bytes_of(words)
    letters, marks, lead = _counts(raw)
    n = letters[end] - letters[start]
    plain = (n > 0) & (n + marks[end] - marks[start] == end - start) & (letters[start + n] - letters[start] == n)
    low = raw.copy()
    for up in (np.flatnonzero((raw >= 65) & (raw <= 90)), lead[(raw[lead + 1] >= 0x80) & (raw[lead + 1] <= 0x9E)] + 1):
        low[up[plain[np.searchsorted(start, up, "right") - 1]]] += 32
    cuts = np.empty(2 * len(start) + 1, np.int32)
    cuts[0:-1:2], cuts[1::2], cuts[-1] = start, start + np.where(plain, n, end - start), len(raw)
    return pa.StringArray.from_buffers(2 * len(start), pa.py_buffer(cuts), pa.py_buffer(low))


def _is_plain(pieces: pa.StringArray) -> np.ndarray:
    """Whether a piece is letters alone (lower-cased by ``_pieces``) or marks alone, and short."""
    raw, start, end = _bytes_of(pieces)
    letters, marks, _ = _counts(raw)
    size = end - start
    return ((letters[end] - letters[start] == size) | (marks[end] - marks[start] == size)) & (size <= _WIDTHS[-1])


def _byte_letters() -> list[str]:
    """The visible character that stands for each byte in byte-level vocabularies (a rule they all share)."""
    shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
    hidden = [b for b in range(256) if b not in shown]
    names = {b: chr(b) for b in shown} | {b: chr(256 + n) for n, b in enumerate(hidden)}
    return [names[b] for b in range(256)]


def _binary(blob: np.ndarray, sizes: np.ndarray) -> pa.Array:
    """Binary values that lie side by side."""
    offsets = np.concatenate([[0], np.cumsum(sizes)]).astype(np.int32)
    return pa.Array.from_buffers(pa.binary(), len(sizes), [None, pa.py_buffer(offsets), pa.py_buffer(np.ascontiguousarray(blob))])


class Merges:
    """The merges of a word-level vocabulary, looked up in an open hash table, for many words at once."""

    def __init__(self, vocabulary: dict[str, int], merges: list):
        letters = _byte_letters()
        self.inner = np.array([vocabulary[c] for c in letters], np.int64)
        self.last = np.array([vocabulary[c + "</w>"] for c in letters], np.int64)
        pairs = [m if isinstance(m, (list, tuple)) else m.split(" ") for m in merges]
        keys = np.array([vocabulary[a] << 16 | vocabulary[b] for a, b in pairs], np.int64)
        self.made = np.array([vocabulary[a + b] for a, b in pairs], np.int64)
        self.mask = (1 << max(4, (4 * len(keys)).bit_length())) - 1
        self.keys, self.ranks = np.full(self.mask + 1, -1, np.int64), np.full(self.mask + 1, _NO_RANK, np.int64)
        left = np.arange(len(keys))
        at = self._home(keys)
        while len(left):  # the first of those that want a free place gets it, the others move on
            free = left[self.keys[at[left]] < 0]
            places, first = np.unique(at[free], return_index=True)
            self.keys[places], self.ranks[places] = keys[free[first]], free[first]
            left = np.setdiff1d(left, free[first])
            at[left] = at[left] + 1 & self.mask

    def _home(self, keys: np.ndarray) -> np.ndarray:
        return (keys * 0x9E3779B1 >> 13) & self.mask

    def rank(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """The rank of every pair; _NO_RANK for those that never merge."""
        keys = a << 16 | b
        at = self._home(keys)
        met = self.keys[at]
        out = np.where(met == keys, self.ranks[at], _NO_RANK)
        open_ = np.nonzero((met != keys) & (met >= 0))
        while len(open_[0]):
            at[open_] = at[open_] + 1 & self.mask
            met = self.keys[at[open_]]
            same = met == keys[open_]
            out[tuple(x[same] for x in open_)] = self.ranks[at[open_][same]]
            open_ = tuple(x[~same & (met >= 0)] for x in open_)
        return out

    def _group(self, raw: np.ndarray, start: np.ndarray, size: np.ndarray, width: int) -> np.ndarray:
        """Ids of words of at most ``width`` bytes, a row a word, closed by _NO_ID."""
        column = np.arange(width)
        there = column < size[:, None]
        letter = raw[np.minimum(start[:, None] + column, len(raw) - 1)]
        ids = np.where(there, np.where(column == size[:, None] - 1, self.last[letter], self.inner[letter]), _NO_ID)
        out, rows = ids.copy(), np.arange(len(ids))
        ranks = np.concatenate([self.rank(ids[:, :-1], ids[:, 1:]), np.full((len(ids), 1), _NO_RANK)], axis=1)
        while len(rows):
            at = ranks.argmin(axis=1)
            best = ranks[np.arange(len(rows)), at]
            go = best < _NO_RANK
            if not go.all():
                out[rows[~go]] = ids[~go]
                rows, ids, ranks, at, best = rows[go], ids[go], ranks[go], at[go], best[go]
                if not len(rows):
                    break
            line = np.arange(len(rows))
            later = column > at[:, None]
            ids[:, :-1] = np.where(later[:, :-1], ids[:, 1:], ids[:, :-1])
            ids[:, -1] = _NO_ID
            ids[line, at] = self.made[best]
            ranks[:, :-1] = np.where(later[:, :-1], ranks[:, 1:], ranks[:, :-1])
            ranks[:, -1] = _NO_RANK
            after = np.where(at + 1 < width, ids[line, np.minimum(at + 1, width - 1)], _NO_ID)
            ranks[line, at] = self.rank(ids[line, at], after)
            prior = np.flatnonzero(at > 0)
            ranks[prior, at[prior] - 1] = self.rank(ids[prior, at[prior] - 1], ids[prior, at[prior]])
        return out

    def encode(self, pieces: pa.StringArray) -> pa.Array:
        """Ids (16 bits each, as binary) of pieces of at most the greatest width."""
        raw, start, end = _bytes_of(pieces)
        size = end - start
        order = np.argsort(size, kind="stable")
        found, lo = [], 0
        for width in _WIDTHS:
            hi = int(np.searchsorted(size[order], width, "right"))
            for a in range(lo, hi, 50_000):
                some = order[a : min(a + 50_000, hi)]
                ids = self._group(raw, start[some], size[some], width) if len(raw) else np.full((len(some), 1), _NO_ID)
                found.append(_binary(ids[ids != _NO_ID].astype("<u2"), 2 * (ids != _NO_ID).sum(axis=1)))
            lo = hi
        back = np.empty(len(order), np.int64)
        back[order] = np.arange(len(order))
        return pa.concat_arrays(found).take(pa.array(back)) if found else pa.array([], pa.binary())


class Encoder:
    """Ids of texts by one tokenizer file, without special tokens added."""

    def __init__(self, path: str, keep: int = KEEP):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        with open(path, encoding="utf-8") as file:
            spec = json.load(file)
        self.library, self.keep = Tokenizer.from_file(path), keep
        self.by_word = word_level(spec)
        self.kind = np.dtype("<u2") if self.by_word else np.dtype("<u4")
        if self.by_word:
            self.merges = Merges(spec["model"]["vocab"], spec["model"]["merges"])
        self._known, self._ids = pa.array([], pa.string()), pa.array([], pa.binary())

    @classmethod
    def of(cls, path: str) -> Encoder:
        """The encoder of this worker, kept from task to task."""
        return worker_slot(("tokens", path), lambda: cls(path))

    def _learn(self, pieces: pa.StringArray) -> pa.Array:
        plain = _is_plain(pieces)
        rest = pieces.filter(pa.array(~plain)).to_pylist()
        by_library = [np.array(e.ids, self.kind).tobytes() for e in self.library.encode_batch_fast(rest, add_special_tokens=False)]
        both = pa.concat_arrays([self.merges.encode(pieces.filter(pa.array(plain))), pa.array(by_library, pa.binary())])
        return both.take(pa.array(np.where(plain, np.cumsum(plain) - 1, int(plain.sum()) + np.cumsum(~plain) - 1)))

    def _ids_of(self, pieces: pa.StringArray) -> pa.Array:
        """Ids of distinct pieces."""
        at = pc.index_in(pieces, value_set=self._known)
        if at.null_count:
            new = np.asarray(at.is_null())
            missing = pieces.filter(pa.array(new))
            place = pc.fill_null(at, 0).to_numpy()
            if len(self._known) + len(missing) > self.keep:
                used = pa.array(place[~new])
                self._known, self._ids = self._known.take(used), self._ids.take(used)
                place = np.cumsum(~new) - 1
            at = pa.array(np.where(new, len(self._known) + np.cumsum(new) - 1, place))
            self._known = pa.concat_arrays([self._known, missing])
            self._ids = pa.concat_arrays([self._ids, self._learn(missing)])
        return self._ids.take(at)

    def slices(self, column: pa.Array, chars: int = SLICE_CHARS) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
        """lo, hi, ids, edges: the ids of texts lo to hi, those of text lo + i between edges i and i + 1. Null counts as empty."""
        column = pc.fill_null(column.cast(pa.string()), "")
        for lo, hi in text_slices(column, chars):
            yield lo, hi, *(self._by_words if self.by_word else self._by_texts)(column.slice(lo, hi - lo))

    def _by_texts(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        found = [e.ids for e in self.library.encode_batch_fast(texts.to_pylist(), add_special_tokens=False)]
        return np.array([i for ids in found for i in ids], self.kind), np.concatenate([[0], np.cumsum([len(ids) for ids in found])]).astype(np.int64)

    def _by_words(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        words = pc.ascii_split_whitespace(texts)
        coded = pc.dictionary_encode(_pieces(words.flatten()))
        whole = self._ids_of(coded.dictionary).take(coded.indices)
        ends = np.frombuffer(whole.buffers()[1], np.int32)[: len(whole) + 1].astype(np.int64) // 2
        ids = np.frombuffer(whole.buffers()[2], self.kind)[: ends[-1]] if whole.buffers()[2] is not None else np.zeros(0, self.kind)
        offsets = words.offsets.to_numpy()
        return ids, ends[2 * (offsets - offsets[0])]

    def closed(self, column: pa.Array, end_id: int, chars: int = SLICE_CHARS) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
        """As ``slices``, with the end id after every text, as unsigned 32-bit ids."""
        for lo, hi, ids, edges in self.slices(column, chars):
            edges = edges + np.arange(hi - lo + 1)
            body = np.ones(edges[-1], bool)
            body[edges[1:] - 1] = False
            out = np.full(edges[-1], end_id, "<u4")
            out[body] = ids
            yield lo, hi, out, edges

    def encode(self, text: str | None) -> np.ndarray:
        return next(self.slices(pa.array([text], pa.string())))[2]
