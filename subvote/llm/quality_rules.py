"""Quality rules by line sequence labelling.

A document is the sequence of its lines that hold a word.  A linear-chain conditional
random field with two labels (boilerplate 0, content 1) is decoded by Viterbi; the share
of word characters in content lines decides whether the document stays.

The field is trained here, on a bounded sample of labelled documents (`train_rows`
documents with the smallest hash of their id).  Labels are of documents, those of lines
are latent: lines start with their document's quality, then rounds of a line model without
transitions move lines that look like the other class over to it, as long as half of a
document's lines keep its own label.  The field's weights and transitions follow the
gradient of the conditional likelihood of the labels reached, so a good document may hold
boilerplate and a bad one content.  Without labels of both classes `PRIOR` is used.

Defined cases: null text has no words; a document without words has no lines and share 0;
ties between labels go to content; repeated rows are judged alike; an empty table gives
no rows; other columns are ignored by `judge` and returned as they are by `kept_rows`.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from subvote.llm._text import U64, Words, mix64, roll, span_hashes, text_slices
from subvote.llm._worker import tidied

FEATURES = ("bias", "symbols", "pipes", "exclaims", "capitals", "digits", "repeats", "seen", "short", "stop", "long_words")
_SYMBOL = np.zeros(256, dtype=bool)
_SYMBOL[list(b"#*$%&|<>")] = True


@dataclass
class Field:
    """Weights of content against boilerplate, and transition scores [from, to]."""

    weights: np.ndarray
    transitions: np.ndarray


#: Used without labels: symbols, pipes, exclamation marks, capitals and repeats speak against content.
PRIOR = Field(np.array([2.0, -6.0, -6.0, -6.0, -5.0, -2.0, -6.0, -1.0, -0.2, 0.5, 0.0]), np.array([[0.5, -0.5], [-0.5, 0.5]]))


@dataclass
class Lines:
    """Lines with words of a slice, document by document."""

    doc: np.ndarray
    features: np.ndarray
    chars: np.ndarray
    base: dict[str, np.ndarray]


def read_lines(buf: np.ndarray, offs: np.ndarray) -> Lines:
    words, n = Words(buf, offs), len(offs) - 1
    total = lambda mask: np.concatenate([[0], np.cumsum(mask, dtype=np.int64)])
    points, symbols = total((buf & 0xC0) != 0x80), total(_SYMBOL[buf])
    word_chars = total(points[words.ends] - points[words.starts])
    per_doc = lambda sums: sums[words.first[1:]] - sums[words.first[:-1]]

    # Words of windows of three that occur again in their document.
    at = words.windows(3)
    window = roll(words.hashes, 3, 0)[at] if len(at) else np.empty(0, U64)
    key = mix64(window ^ mix64(words.doc[at].astype(U64), 5))
    _, back, times = np.unique(key, return_inverse=True, return_counts=True)
    cover = np.zeros(len(words.starts) + 1, np.int64)
    twice = at[times[back] > 1]
    np.add.at(cover, twice, 1)
    np.add.at(cover, twice + 3, -1)
    repeated = total(np.cumsum(cover[:-1]) > 0)

    # Lines: cut at newlines and at document ends.
    cuts = np.flatnonzero(buf == 10)
    starts = np.union1d(cuts + 1, offs[:-1])
    starts = starts[starts < len(buf)] if len(buf) else starts[:0]
    ends = np.empty_like(starts)
    if len(starts):
        ends[:-1], ends[-1] = starts[1:], len(buf)
    ends = ends - (buf[ends - 1] == 10) * (ends > starts) if len(starts) else ends
    lo, hi = np.searchsorted(words.starts, starts), np.searchsorted(words.starts, ends)
    full = hi > lo
    starts, ends, lo, hi = starts[full], ends[full], lo[full], hi[full]
    doc = np.searchsorted(offs, starts, "right") - 1
    line_key = mix64(span_hashes(buf, starts, ends) ^ mix64(doc.astype(U64), 7))
    _, first_at = np.unique(line_key, return_index=True)
    seen = np.ones(len(starts), dtype=bool)
    seen[first_at] = False

    n_line = hi - lo
    line_of = np.repeat(np.arange(len(starts)), n_line)
    inside = np.repeat(lo, n_line) + (np.arange(len(line_of)) - np.repeat(np.cumsum(n_line) - n_line, n_line))
    distinct = np.zeros(len(starts), np.int64)
    if len(inside):
        _, once = np.unique(mix64(words.hashes[inside] ^ mix64(line_of.astype(U64), 9)), return_index=True)
        distinct = np.bincount(line_of[once], minlength=len(starts))
    count = lambda mask: (s := total(mask))[ends] - s[starts]
    upper, lower = count((buf >= 65) & (buf <= 90)), count((buf >= 97) & (buf <= 122))
    chars = word_chars[hi] - word_chars[lo]
    share = lambda a, b: np.minimum(1.0, a / np.maximum(b, 1))
    features = np.stack(
        [
            np.ones(len(starts)), share(symbols[ends] - symbols[starts], n_line), share(count(buf == 124), n_line),
            share(count(buf == 33), n_line), share(upper, upper + lower), share(count((buf >= 48) & (buf <= 57)), chars),
            1.0 - distinct / np.maximum(n_line, 1), seen.astype(float), (n_line < 5).astype(float),
            np.isin(buf[np.maximum(ends - 1, 0)] if len(ends) else buf[:0], list(b".?!")).astype(float), share(chars, 25 * n_line),
        ],
        axis=1,
    )
    base = {
        "n_words": words.counts.astype(np.int64),
        "word_chars": per_doc(word_chars),
        "n_symbols": symbols[offs[1:]] - symbols[offs[:-1]],
        "n_dup_lines": np.bincount(doc, weights=seen, minlength=n).astype(np.int64),
        "n_repeat_words": per_doc(repeated),
    }
    return Lines(doc, features, chars, base)


def _steps(doc: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray, list[np.ndarray]]:
    """First line and number of lines per document; documents with more than t lines, per t."""
    count = np.bincount(doc, minlength=n)
    first = np.cumsum(count) - count
    order = np.argsort(-count, kind="stable")
    alive = np.searchsorted(-count[order], -np.arange(int(count.max(initial=0))), "left")
    return first, count, [order[:k] for k in alive]


def decode(field: Field, lines: Lines, n: int) -> np.ndarray:
    """Best label of every line; all documents of the slice advance one line at a time."""
    score = lines.features @ field.weights
    first, count, steps = _steps(lines.doc, n)
    best = np.zeros((n, 2))
    came = np.zeros((len(score), 2), np.int8)
    for t, docs in enumerate(steps):
        at = first[docs] + t
        if t:
            arrive = best[docs][:, :, None] + field.transitions[None]
            came[at] = (arrive[:, 1] >= arrive[:, 0]).astype(np.int8)
            best[docs] = arrive.max(axis=1)
        best[docs, 1] += score[at]
    label = np.zeros(len(score), np.int8)
    last = (best[:, 1] >= best[:, 0]).astype(np.int8)
    for t in range(len(steps) - 1, -1, -1):
        docs = steps[t]
        at = first[docs] + t
        ends = count[docs] == t + 1
        label[at] = np.where(ends, last[docs], 0)
        going = ~ends
        label[at[going]] = came[at[going] + 1, label[at[going] + 1]]
    return label


def line_labels(lines: Lines, quality: np.ndarray, rounds: int = 4) -> np.ndarray:
    """Latent labels of lines from labels of documents: a line moves to the class it looks like.

    Of every document, the half of its lines that fit its own label best keep it.
    """
    n, own = len(quality), quality[lines.doc].astype(float)
    count = np.bincount(lines.doc, minlength=n)
    first = np.cumsum(count) - count
    y = own
    for _ in range(rounds):
        share = np.array([max(1.0, (y == 0).sum()), max(1.0, (y == 1).sum())])
        weight = (len(y) / (2 * share))[y.astype(int)]
        score = lines.features @ _line_model(lines.features, y, weight)
        # Rank of a line in its document, those that fit the document's label best first.
        order = np.lexsort((np.where(own == 1, -score, score), lines.doc))
        rank = np.empty(len(y), np.int64)
        rank[order] = np.arange(len(y)) - first[lines.doc[order]]
        held = rank < (count[lines.doc] + 1) // 2
        moved = np.where(held, own, (score > 0).astype(float))
        if (moved == y).all():
            break
        y = moved
    return y.astype(np.int8)


def _line_model(x: np.ndarray, y: np.ndarray, weight: np.ndarray, rounds: int = 200, rate: float = 0.5, ridge: float = 1e-4) -> np.ndarray:
    """Logistic regression by gradient steps with momentum."""
    out, speed, size = np.zeros(x.shape[1]), np.zeros(x.shape[1]), max(len(y), 1)
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(x @ out, -30, 30)))
        speed = 0.9 * speed + x.T @ (weight * (y - p)) / size - ridge * out
        out = out + rate * speed
    return out


def train(lines: Lines, labels: np.ndarray, n: int, rounds: int = 300, rate: float = 0.5, ridge: float = 1e-4) -> Field:
    """Maximise the conditional likelihood of the labels of lines in n documents."""
    first, count, steps = _steps(lines.doc, n)
    y = labels.astype(float)
    weights, moves = np.zeros(lines.features.shape[1]), np.zeros((2, 2))
    speed_w, speed_m = np.zeros_like(weights), np.zeros_like(moves)
    # Pairs of labels on neighbouring lines of a document.
    beside = lines.doc[1:] == lines.doc[:-1]
    pairs = np.zeros((2, 2))
    np.add.at(pairs, (labels[:-1][beside].astype(int), labels[1:][beside].astype(int)), 1)
    size = max(len(y), 1)
    for _ in range(rounds):
        score = lines.features @ weights
        alpha, beta = np.zeros((len(y), 2)), np.zeros((len(y), 2))
        for t, docs in enumerate(steps):
            at = first[docs] + t
            if t:
                into = alpha[at - 1][:, :, None] + moves[None]
                alpha[at] = np.logaddexp(into[:, 0], into[:, 1])
            alpha[at, 1] += score[at]
        expected = np.zeros((2, 2))
        last = first + count - 1
        log_z = np.zeros(n)
        some = count > 0
        log_z[some] = np.logaddexp(alpha[last[some], 0], alpha[last[some], 1])
        for t in range(len(steps) - 1, 0, -1):
            at = first[steps[t]] + t
            out = beta[at].copy()
            out[:, 1] += score[at]
            joint = alpha[at - 1][:, :, None] + moves[None] + out[:, None, :]
            expected += np.exp(joint - log_z[steps[t]][:, None, None]).sum(axis=0)
            through = moves[None] + out[:, None, :]
            beta[at - 1] = np.logaddexp(through[:, :, 0], through[:, :, 1])
        p = np.exp(alpha[:, 1] + beta[:, 1] - log_z[lines.doc])
        speed_w = 0.9 * speed_w + (lines.features.T @ (y - p)) / size - ridge * weights
        speed_m = 0.9 * speed_m + (pairs - expected) / size - ridge * moves
        weights, moves = weights + rate * speed_w, moves + rate * speed_m
    return Field(weights, moves)


def fit(docs: DataFrame, labels: DataFrame, train_rows: int = 2000, id_col: str = "doc_id", text_col: str = "text") -> Field:
    """Train on the `train_rows` labelled documents whose ids have the smallest hash."""
    spark = docs.sparkSession
    sample = (
        labels.filter(F.col("quality").isNotNull() & F.col(id_col).isNotNull())
        .select(F.col(id_col).cast("long").alias("id"), F.col("quality").cast("int").alias("quality"))
        .orderBy(F.xxhash64("id"), "id", "quality")
        .limit(train_rows)
        .collect()
    )
    if len({r["quality"] > 0 for r in sample}) < 2:
        return PRIOR
    chosen = spark.createDataFrame(sample, "k_id long, quality int").dropDuplicates(["k_id"])

    @tidied
    def lines_of(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo, hi, buf, offs in text_slices(batch.column(1)):
                lines = read_lines(buf, offs)
                count = np.bincount(lines.doc, minlength=hi - lo)
                rows = [x.tobytes() for x in np.split(lines.features, np.cumsum(count)[:-1])]
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(lo, hi - lo), pa.array(rows, pa.binary())], ["quality", "rows"])

    own = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text"))
    found = own.join(F.broadcast(chosen), F.col("id") == F.col("k_id")).select("quality", "text")  # train_rows rows
    got = found.mapInArrow(lines_of, "quality int, rows binary").collect()
    got = sorted(((r["quality"], bytes(r["rows"])) for r in got))  # the same order in every run
    if len({q > 0 for q, _ in got}) < 2:
        return PRIOR
    blocks = [np.frombuffer(rows).reshape(-1, len(FEATURES)) for _, rows in got]
    doc = np.repeat(np.arange(len(got)), [len(b) for b in blocks])
    features = np.concatenate(blocks)
    lines, quality = Lines(doc, features, np.zeros(len(features)), {}), np.array([int(q > 0) for q, _ in got])
    return train(lines, line_labels(lines, quality), len(got))


COLUMNS = "n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, kept boolean, content_share double"


def verdicts(field: Field, column: pa.Array, min_share: float) -> Iterator[tuple[int, int, list[pa.Array]]]:
    for lo, hi, buf, offs in text_slices(column):
        lines, n = read_lines(buf, offs), hi - lo
        label = decode(field, lines, n)
        b = lines.base
        content = np.bincount(lines.doc, weights=lines.chars * label, minlength=n)
        share = content / np.maximum(np.bincount(lines.doc, weights=lines.chars, minlength=n), 1)
        failed = (b["n_words"] < 50) | (100 * b["n_repeat_words"] > 50 * b["n_words"])
        yield lo, hi, [*map(pa.array, b.values()), pa.array(failed), pa.array(~failed & (share >= min_share)), pa.array(share)]


def judge(docs: DataFrame, field: Field, min_share: float = 0.5, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id and COLUMNS of every row."""
    names = ["doc_id", *[c.split()[0] for c in COLUMNS.split(", ")]]

    @tidied
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo, hi, columns in verdicts(field, batch.column(1), min_share):
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(lo, hi - lo), *columns], names)

    out = docs.select(F.col(id_col).cast("long"), text_col).mapInArrow(run, f"doc_id long, {COLUMNS}")
    return out if id_col == "doc_id" else out.withColumnRenamed("doc_id", id_col)


def kept_rows(docs: DataFrame, field: Field, min_share: float = 0.5, text_col: str = "text") -> DataFrame:
    """The rows of `docs` that stay, with all their columns; no shuffle."""
    at = docs.columns.index(text_col)

    @tidied
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = [columns[-2] for _, _, columns in verdicts(field, batch.column(at), min_share)]
            if keep:
                yield batch.filter(pa.concat_arrays(keep))

    return docs.mapInArrow(run, docs.schema)
