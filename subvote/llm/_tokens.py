"""Whole-text encoding with the tokenizers library, once per distinct piece of text.

Both vocabularies split a text at white space before they merge, so a text encodes to the
concatenation of its white-space-bounded pieces.  Pieces of a batch are found and hashed
with numpy, distinct ones go through the library, and a bounded memo keeps what recent
batches needed.  Texts for which a piece could depend on its surroundings (control
characters, white space outside ASCII, letters beyond Latin Extended-B, special-token
strings) are encoded whole.  Pieces are looked up by a 64-bit hash and compared by their
whole identity (the bytes, or a 128-bit digest of long ones); a text with a piece whose
hash belongs to another piece is encoded whole as well.
"""

from __future__ import annotations

import os
from itertools import chain

import numpy as np
import pyarrow as pa

from subvote.llm._text import U64, Spans, Words, ragged, text_slices

_UNSAFE = np.ones(256, dtype=bool)
_UNSAFE[[9, 10, 13]] = False
_UNSAFE[32:127] = False
_UNSAFE[0x80:0xC0] = False  # continuation bytes
_UNSAFE[0xC3:0xCA] = False  # lead bytes of U+00C0 to U+027F
_loaded: dict[str, object] = {}


def tokenizer(path: str):
    """The tokenizer of a vocabulary file, loaded once per process."""
    if path not in _loaded:
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        _loaded[path] = Tokenizer.from_file(path)
    return _loaded[path]


class Memo:
    """Values of distinct pieces by hash: a sorted main run and a recent one, merged in steps."""

    def __init__(self, limit: int = 1 << 20):
        self.limit = limit
        self.clear()

    def clear(self) -> None:
        self.runs = [(np.empty(0, U64), np.empty(0, np.int64))] * 2
        self.used = 0

    def find(self, keys: np.ndarray) -> np.ndarray:
        """Slot of each key, -1 where there is none."""
        out = np.full(len(keys), -1, np.int64)
        for have, slots in self.runs:
            if len(have):
                at = np.minimum(np.searchsorted(have, keys), len(have) - 1)
                hit = have[at] == keys
                out[hit] = slots[at[hit]]
        return out

    def add(self, keys: np.ndarray) -> np.ndarray:
        """New slots, in order, for sorted keys that are not there yet."""
        slots = np.arange(self.used, self.used + len(keys))
        self.used += len(keys)
        main, recent = self.runs
        recent = self._merge(recent, (keys, slots))
        if len(recent[0]) * 4 > len(main[0]):
            main, recent = self._merge(main, recent), (np.empty(0, U64), np.empty(0, np.int64))
        self.runs = [main, recent]
        return slots

    @staticmethod
    def _merge(a, b):
        keys, slots = np.concatenate([a[0], b[0]]), np.concatenate([a[1], b[1]])
        order = np.argsort(keys, kind="stable")
        return keys[order], slots[order]


def unsafe_docs(buf: np.ndarray, offs: np.ndarray) -> np.ndarray:
    bad = _UNSAFE[buf]
    if len(buf) > 1:  # "<|" may start a special token
        bad[:-1] |= (buf[:-1] == 60) & (buf[1:] == 124)
    out = np.zeros(len(offs) - 1, dtype=bool)
    at = np.flatnonzero(bad)
    out[np.searchsorted(offs, at, "right") - 1] = True
    return out


def pieces(words: Words, spaced: bool) -> tuple[np.ndarray, np.ndarray]:
    """Byte bounds of the pieces, in text order.

    Without `spaced`, the words.  With it, every byte is in a piece: a word takes a blank
    before it along, other white space stands alone, and the last byte of a run that ends
    in something else than a blank before a word stands apart from the rest of the run.
    """
    if not spaced:
        return words.starts, words.ends
    buf, offs, first = words.buf, words.offs, words.first
    lead = np.zeros(len(words.starts), dtype=bool)
    at = words.starts > offs[:-1][words.doc]
    lead[at] = buf[words.starts[at] - 1] == 32
    starts = words.starts - lead
    previous = np.empty(len(starts), np.int64)
    previous[1:] = words.ends[:-1]
    heads = first[:-1][words.counts > 0]
    previous[heads] = offs[:-1][words.counts > 0]
    gap = starts - previous
    loose = (gap > 1) & ~lead
    gaps = [(previous[gap > 0], np.where(loose, starts - 1, starts)[gap > 0]), (starts[loose] - 1, starts[loose])]
    # White space behind the last word of a text, or all of a text without words.
    tail = offs[:-1].copy()
    full = words.counts > 0
    tail[full] = words.ends[first[1:][full] - 1]
    some = offs[1:] > tail
    gaps.append((tail[some], offs[1:][some]))
    s = np.concatenate([starts, *[g[0] for g in gaps]])
    e = np.concatenate([words.ends, *[g[1] for g in gaps]])
    order = np.argsort(s, kind="stable")
    return s[order], e[order]


class Encoder:
    """Ids of every text of a column, slice by slice.

    `measure(texts, whole)` returns the number of values per text and all values as one
    array; whole texts may hold anything, the others are single pieces of Latin text.
    """

    def __init__(self, measure, spaced: bool, limit: int = 1 << 20):
        self.measure, self.spaced, self.memo = measure, spaced, Memo(limit)
        self._reset()

    def _reset(self) -> None:
        self.memo.clear()
        self.at = np.zeros(1, np.int64)
        self.flat = np.empty(0, np.int32)
        self.known = [np.empty(0, U64), np.empty(0, U64), np.empty(0, np.int64)]

    def _append(self, sizes: np.ndarray, flat: np.ndarray) -> None:
        self.at = np.concatenate([self.at, self.at[-1] + np.cumsum(sizes)])
        self.flat = np.concatenate([self.flat, flat])

    def slices(self, column: pa.Array, limit: int = 2 << 20):
        """Yields (first row, row after the last, ids per document, all ids)."""
        for lo, hi, buf, offs in text_slices(column, limit):
            yield lo, hi, *self.encode(buf, offs)

    def encode(self, buf: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        if self.memo.used > self.memo.limit:
            self._reset()
        words = Words(buf, offs)
        all_starts, all_ends = pieces(words, self.spaced)
        owner = np.searchsorted(offs, all_starts, "right") - 1
        bad = unsafe_docs(buf, offs)
        while True:
            fine = ~bad[owner]
            starts, ends, doc = all_starts[fine], all_ends[fine], owner[fine]
            spans = Spans(buf, starts, ends)
            keys, index, back = np.unique(spans.hash(), return_index=True, return_inverse=True)
            slots = self.memo.find(keys)
            known = np.flatnonzero(slots >= 0)
            have, other = [], np.zeros(len(starts), dtype=bool)
            for mine, stored in zip((spans.low, spans.high, spans.size), self.known, strict=True):
                first = mine[index]
                first[known] = stored[slots[known]]
                have.append(first)
                other |= mine != first[back]
            if not other.any():
                break
            bad[doc[other]] = True
        new = np.flatnonzero(slots < 0)
        if len(new):
            raw = buf.tobytes()
            texts = [raw[s:e].decode() for s, e in zip(starts[index[new]].tolist(), ends[index[new]].tolist(), strict=True)]
            self._append(*self.measure(texts, False))
            slots[new] = self.memo.add(keys[new])
            self.known = [np.concatenate([old, more[new]]) for old, more in zip(self.known, have, strict=True)]
        at, size = self.at[slots], self.at[slots + 1] - self.at[slots]
        flat, at, size = self.flat, at[back], size[back]
        if bad.any():
            raw, which = buf.tobytes(), np.flatnonzero(bad)
            sizes, found = self.measure([raw[offs[d] : offs[d + 1]].decode() for d in which], True)
            more = len(flat) + np.cumsum(sizes) - sizes
            flat = np.concatenate([flat, found])
            order = np.argsort(np.concatenate([doc, which]), kind="stable")
            at, size, doc = np.concatenate([at, more])[order], np.concatenate([size, sizes])[order], np.concatenate([doc, which])[order]
        per_doc = np.bincount(doc, weights=size, minlength=len(offs) - 1).astype(np.int64)
        return per_doc, flat[np.repeat(at, size) + ragged(size)]


_encoders: dict[tuple[str, bool], Encoder] = {}


def id_encoder(path: str, spaced: bool) -> Encoder:
    """Encoder of a vocabulary file into ids, kept by the worker process between tasks."""
    if (path, spaced) not in _encoders:
        library = tokenizer(path)

        _encoders[path, spaced] = Encoder(lambda texts, whole: library_ids(library, texts), spaced)
    return _encoders[path, spaced]


def library_ids(library, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """(ids per text, all ids) as the library gives them."""
    found = [x.ids for x in library.encode_batch_fast(texts, add_special_tokens=False)]
    sizes = np.fromiter(map(len, found), np.int64, len(found))
    return sizes, np.fromiter(chain.from_iterable(found), np.int32, int(sizes.sum()))


