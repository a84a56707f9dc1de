"""Token counts by rank-synchronous merging of batched symbol arrays.

The distinct pieces of a batch become one ragged array of symbols.  In every round each
sequence finds the lowest merge rank among its neighbouring pairs, and all sequences apply
their pair at once, left to right without overlap; ranks are looked up again only beside
merged symbols.  A sequence that has no pair with a rank is finished, and the number of
its symbols is its count.  Normaliser and splitter are those of the vocabulary file.

Defined cases: null and empty texts have 0 tokens and 0 bytes; special strings count as
one token each, as the library takes them; texts of any length are merged whole; repeated
rows are counted each; other columns are ignored.
"""

from __future__ import annotations

import json
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from subvote.llm._tokens import Encoder, tokenizer
from subvote.llm._worker import tidied

NONE = np.int64(1) << 40


class Merger:
    """Merge rules of a vocabulary file and the ragged-array loop over them."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as source:
            spec = json.load(source)
        model = spec["model"]
        self.suffix = model.get("end_of_word_suffix") or ""
        self.vocab: dict[str, int] = model["vocab"]
        self.size = len(self.vocab)
        rules = [tuple(m) if isinstance(m, list) else tuple(m.split(" ")) for m in model["merges"]]
        left = np.array([self.vocab[a] for a, _ in rules], np.int64)
        right = np.array([self.vocab[b] for _, b in rules], np.int64)
        keys = left * self.size + right
        order = np.argsort(keys, kind="stable")
        self.keys, self.ranks = keys[order], order.astype(np.int64)
        self.made = np.array([self.vocab[a + b] for a, b in rules], np.int64)
        self.specials = [t["content"] for t in spec["added_tokens"]]
        self.special = regex.compile("|".join(regex.escape(s) for s in sorted(self.specials, key=len, reverse=True))) if self.specials else None
        self.library = tokenizer(path)

    def rank(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        key = a * self.size + b
        at = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
        return np.where(self.keys[at] == key, self.ranks[at], NONE)

    def merge(self, symbols: np.ndarray, lengths: np.ndarray) -> np.ndarray:
        """Symbols left of every sequence."""
        out = lengths.copy()
        live = np.flatnonzero(lengths > 1)
        keep = np.repeat(lengths > 1, lengths)
        sym, size = symbols[keep], lengths[live]
        rank = np.full(len(sym), NONE)
        if len(sym) > 1:
            rank[:-1] = self.rank(sym[:-1], sym[1:])
            rank[np.cumsum(size) - 1] = NONE
        while len(live):
            starts = np.cumsum(size) - size
            best = np.minimum.reduceat(rank, starts)
            open_ = best < NONE
            if not open_.all():
                out[live[~open_]] = size[~open_]
                inside = np.repeat(open_, size)
                live, sym, rank, size, best = live[open_], sym[inside], rank[inside], size[open_], best[open_]
                if not len(live):
                    break
                starts = np.cumsum(size) - size
            hit = rank == np.repeat(best, size)
            at = np.flatnonzero(hit)
            # In a run of overlapping pairs (a a a) every second one counts.
            head = np.ones(len(at), dtype=bool)
            head[1:] = np.diff(at) > 1
            run = np.cumsum(head) - 1
            at = at[(np.arange(len(at)) - np.flatnonzero(head)[run]) % 2 == 0]
            owner = np.searchsorted(starts, at, "right") - 1
            sym[at] = self.made[best[owner]]
            gone = np.zeros(len(sym), dtype=bool)
            gone[at + 1] = True
            moved = at - np.arange(len(at))  # places after the second halves are taken out
            sym, rank = sym[~gone], rank[~gone]
            size = size - np.bincount(owner, minlength=len(size))
            last = np.zeros(len(sym), dtype=bool)
            last[np.cumsum(size) - 1] = True
            near = np.unique(np.concatenate([moved, moved - 1]))
            near = near[near >= 0]
            rank[near] = NONE
            near = near[~last[near]]
            rank[near] = self.rank(sym[near], sym[near + 1])
        return out

    def count_pieces(self, pieces: list[str]) -> np.ndarray:
        """Tokens of every pre-token, given in the byte alphabet of the vocabulary."""
        lengths = np.fromiter((len(p) for p in pieces), np.int64, len(pieces))
        points = np.frombuffer("".join(pieces).encode("utf-32-le"), np.uint32)
        ends = np.cumsum(lengths)[lengths > 0] - 1
        alphabet = np.zeros(2048, np.int64)
        closing = np.zeros(2048, np.int64)
        for c in set(np.unique(points).tolist()):
            alphabet[c] = self.vocab.get(chr(c), -1)
            closing[c] = self.vocab.get(chr(c) + self.suffix, -1)
        symbols = alphabet[points]
        symbols[ends] = closing[points[ends]]
        return self.merge(symbols, lengths)

    def measure(self, texts: list[str], whole: bool) -> tuple[np.ndarray, np.ndarray]:
        """Counts of texts, one value each (the form `Encoder` takes)."""
        owners, pieces, fixed = [], [], np.zeros(len(texts), np.int64)
        split, clean = self.library.pre_tokenizer.pre_tokenize_str, self.library.normalizer
        for i, text in enumerate(texts):
            parts = [text]
            if self.special is not None and "<|" in text:
                parts = self.special.split(text)
                fixed[i] = len(parts) - 1
            for part in parts:
                if part:
                    found = split(clean.normalize_str(part) if clean is not None else part)
                    pieces.extend(p for p, _ in found)
                    owners.append((i, len(found)))
        if not pieces:
            return np.ones(len(texts), np.int64), fixed.astype(np.int32)
        counts = self.count_pieces(pieces)
        owner = np.repeat(np.array([o for o, _ in owners]), np.array([n for _, n in owners]))
        total = fixed + np.bincount(owner, weights=counts, minlength=len(texts)).astype(np.int64)
        return np.ones(len(texts), np.int64), total.astype(np.int32)


_counters: dict[str, Encoder] = {}


def _counter(path: str) -> Encoder:
    if path not in _counters:
        _counters[path] = Encoder(Merger(path).measure, False)
    return _counters[path]


def count_tokens(docs: DataFrame, vocab_path: str, limit: int = 2048, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id, n_bytes, n_tokens, over_limit of every row."""

    @tidied
    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counter = _counter(vocab_path)
        for batch in batches:
            n_bytes = pc.fill_null(pc.binary_length(batch.column(1)), 0).cast(pa.int64())
            totals = []
            for _, _, pieces, values in counter.slices(batch.column(1)):
                doc = np.repeat(np.arange(len(pieces)), pieces)
                totals.append(np.bincount(doc, weights=values, minlength=len(pieces)).astype(np.int64))
            if totals:
                n = np.concatenate(totals)
                yield pa.RecordBatch.from_arrays([batch.column(0), n_bytes, pa.array(n), pa.array(n > limit)], ["doc_id", "n_bytes", "n_tokens", "over_limit"])

    return docs.select(F.col(id_col).alias("doc_id"), F.col(text_col)).mapInArrow(count, "doc_id long, n_bytes long, n_tokens long, over_limit boolean")


