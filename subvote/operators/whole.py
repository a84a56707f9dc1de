"""Optimized search with one order per query over the whole table, in pairs of blocks.

The rows are those of scores, fallback, Hamming order and fold made one after the other
(`scoring`, `candidates`, `refine`), but no row is made of a vote, a score or a candidate: a block of
queries meets all blocks of the base in one task, which holds the base (8 bytes a value and cell)
and four bytes a pair of some of the queries.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import pairwise

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from subvote.operators import activation, cells, refine
from subvote.operators.arrow import sign_words
from subvote.operators.codebooks import Codebooks
from subvote.operators.exact import BASE_ROWS, blocks, spread
from subvote.operators.subspaces import Layout

SCHEMA = "query_id long, rank int, id long, dist2 double, started long, completed long, pruned long, dims long, stopped int, pruned_near array<long>"
#: Pairs of a query and a base vector that one task looks at before it answers.
PAIRS = 16_000_000


def encoded(base: DataFrame, layout: Layout, books: Codebooks) -> DataFrame:
    """Blocks of the base with ids rising: (base_ids, base_vecs, base_cells)."""
    shared = base.sparkSession.sparkContext.broadcast((layout, books))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        layout, books = shared.value
        for batch in batches:
            for raw in zip(*batch.columns, strict=True):
                names, x = np.frombuffer(raw[0].as_buffer(), "<i8"), np.frombuffer(raw[1].as_buffer(), "<f8")
                order = np.argsort(names, kind="stable")
                names, x = names[order], x.reshape(len(names), -1)[order]
                values = (names, x, cells.exact_cells(x, layout, books).astype("<i4"))
                yield pa.RecordBatch.from_arrays([pa.array([v.tobytes()], pa.binary()) for v in values], ["base_ids", "base_vecs", "base_cells"])

    return blocks(base, "base", BASE_ROWS).mapInArrow(run, "base_ids binary, base_vecs binary, base_cells binary")


def tables(queries: DataFrame, layout: Layout, books: Codebooks, counts: np.ndarray, limit: int, rank_cut: int, most: int) -> DataFrame:
    """`activation.weight_table` of up to `most` queries a row: (query_ids, query_weights)."""
    shared = queries.sparkSession.sparkContext.broadcast((layout, books, counts))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for raw in zip(*batch.columns, strict=True):
                ids, q = np.frombuffer(raw[0].as_buffer(), "<i8"), np.frombuffer(raw[1].as_buffer(), "<f8")
                table = activation.weight_table(q.reshape(len(ids), -1), *shared.value, limit, rank_cut)
                yield pa.RecordBatch.from_arrays([pa.array([v.tobytes()], pa.binary()) for v in (ids, table)], ["query_ids", "query_weights"])

    return spread(blocks(queries, "query", most)).mapInArrow(run, "query_ids binary, query_weights binary")


def single(tables: DataFrame) -> DataFrame:
    """(query_id, query_weights), a row per query."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for raw in zip(*batch.columns, strict=True):
                ids = np.frombuffer(raw[0].as_buffer(), "<i8")
                rows = np.frombuffer(raw[1].as_buffer(), "i1").reshape(len(ids), -1)
                yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array([r.tobytes() for r in rows], pa.binary())], ["query_id", "query_weights"])

    return tables.mapInArrow(run, "query_id long, query_weights binary")


class _Held:
    """A block of queries and all of the base it met so far."""

    def __init__(self, ids: np.ndarray, q: np.ndarray):
        self.ids, self.q, self.n = ids, q, 0
        self.names, self.x, self.places = [], [], []

    def add(self, names: np.ndarray, x: np.ndarray, places: np.ndarray) -> None:
        """`places`: n x M, where the weight of every cell of a vector is."""
        for held, part in ((self.names, names), (self.x, x), (self.places, places)):
            held.append(part)
        self.n += len(names)

    def by_id(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(ids, vectors, places) of the whole base, ids rising."""
        names = np.concatenate(self.names)
        order = np.argsort(names, kind="stable")
        return names[order], np.concatenate(self.x)[order], np.concatenate(self.places)[order]


def scores_and_keys(q: np.ndarray, table: np.ndarray, words: np.ndarray, places: np.ndarray, hamming: bool) -> tuple[np.ndarray, np.ndarray]:
    """queries x base: the score and the place in the order; `words` are the sign words of the base."""
    top, dim = 2 * places.shape[1], q.shape[1]
    score = np.empty((len(q), len(places)), np.int16)
    key = np.empty(score.shape, np.int16 if (top + 1) * (dim + 1) < 1 << 15 else np.int64)
    asked = sign_words(q).view(np.uint64)
    for lo in range(0, len(places), BASE_ROWS):
        part = np.zeros((len(q), len(places[lo : lo + BASE_ROWS])), np.int16)
        for column in places[lo : lo + BASE_ROWS].T:
            part += np.take(table, column, axis=1)
        order = (top - part).astype(key.dtype)
        if hamming:
            for base, query in zip(words[lo : lo + BASE_ROWS].T, asked.T, strict=True):
                order += np.bitwise_count(query[:, None] ^ base[None]).astype(key.dtype) * key.dtype.type(top + 1)
        score[:, lo : lo + BASE_ROWS], key[:, lo : lo + BASE_ROWS] = part, order
    return score, key


def candidates_in_order(score: np.ndarray, key: np.ndarray, least: int, k: int) -> np.ndarray:
    """Places of the candidates of a query as they are verified: the best k by score where fewer reach `least`."""
    rows = np.flatnonzero(score >= least)
    if len(rows) < k:
        rows = np.flatnonzero(score)
        rows = np.sort(rows[np.argsort(-score[rows], kind="stable")[:k]])
    return rows[np.argsort(key[rows], kind="stable")]  # places rise with the id; keys of 16 bits get a radix sort


def runs_in_order(score: np.ndarray, key: np.ndarray, least: int, k: int) -> Iterator[np.ndarray]:
    """`candidates_in_order` in runs that grow fourfold, each sorted when it is asked for."""
    rows = np.flatnonzero(score >= least)
    if len(rows) < k:
        yield candidates_in_order(score, key, least, k)
        return
    mine = key[rows]
    low = int(mine.min())
    upto = np.bincount(mine.astype(np.int64) - low).cumsum()
    first, before, want = 0, 0, refine.AHEAD
    while before < len(rows):
        last = int(np.searchsorted(upto, min(before + want, len(rows))))
        some = rows[(mine >= low + first) & (mine <= low + last)]
        yield some[np.argsort(key[some], kind="stable")]
        first, before, want = last + 1, int(upto[last]), 4 * want


def search(base: DataFrame, queries: DataFrame, layout: Layout, books: Codebooks, counts: np.ndarray, limit: int, rank_cut: int, least: int, k: int, step: int, eps: float, patience: int | None, hamming: bool, sampling: bool) -> DataFrame:
    """(query_id, rank, id, dist2) with the counters of the fold on every row; rank 1 also has, as
    pruned_near, the pruned ids among the nearest k of the candidates (ties and rounding included)."""
    n, k2, dim = int(counts[0].sum()), counts.shape[1], layout.dim
    cuts = [*range(step, dim, step), dim]
    most = int(np.clip(PAIRS // max(n, 1), 8, 128))
    # Every row of queries gets the whole base sent, so they are few: three per core.
    rows_each = max(most, -(-queries.count() // (3 * base.sparkSession.sparkContext.defaultParallelism)))
    pairs = spread(blocks(queries, "query", rows_each)).crossJoin(F.broadcast(encoded(base, layout, books)))
    shared = base.sparkSession.sparkContext.broadcast((layout, books, counts))

    def answers(held: _Held) -> Iterator[pa.RecordBatch]:
        if held.n != n:
            raise ValueError(f"a block of queries met {held.n} of {n} vectors")
        names, x, places = held.by_id()
        words = sign_words(x).view(np.uint64)
        for lo in range(0, len(held.ids), most):
            yield answer(held.ids[lo : lo + most], held.q[lo : lo + most], names, x, words, places)

    def answer(ids: np.ndarray, asked: np.ndarray, names: np.ndarray, x: np.ndarray, words: np.ndarray, places: np.ndarray) -> pa.RecordBatch:
        layout, books, counts = shared.value
        scores, keys = scores_and_keys(asked, activation.weight_table(asked, layout, books, counts, limit, rank_cut), words, places, hamming)
        out: list[list] = [[] for _ in SCHEMA.split(", ")]
        if patience is None:
            # All candidates are measured: roughly by products, in full wherever the fold asks for it.
            norms = np.cumsum(np.stack([(x[:, a:b] ** 2).sum(axis=1) for a, b in zip([0, *cuts], cuts, strict=False)]), axis=0)
            longest = float(norms[-1].max())
        for i, query in enumerate(ids.tolist()):
            q = asked[i]
            if patience is not None:
                seen: list[np.ndarray] = []

                def parts() -> Iterator[tuple[np.ndarray, np.ndarray]]:
                    for run in runs_in_order(scores[i], keys[i], least, k):  # noqa: B023
                        seen.append(run)  # noqa: B023
                        for lo in range(0, len(run), refine.AHEAD):
                            some = run[lo : lo + refine.AHEAD]
                            yield names[some], refine.partial_sums(x[some], q, cuts)  # noqa: B023

                best, c, pruned = refine.fold_sums(parts(), cuts, k, eps, patience, sampling)
                rows = np.concatenate([np.empty(0, np.int64), *seen])
                d2 = None
            else:
                rows = candidates_in_order(scores[i], keys[i], least, k)
                if i % 16 == 0:
                    some = asked[i : i + 16]
                    dots = [some[:, a:b] @ x[:, a:b].T for a, b in zip([0, *cuts], cuts, strict=False)]
                    for before, after in pairwise(dots):
                        after += before
                sums = np.stack([(norms[j] - 2 * dots[j][i % 16])[rows] + (q[:t] @ q[:t]) for j, t in enumerate(cuts)], axis=1)
                slack = 1e-14 * dim * (longest + float(q @ q))
                best, c, pruned = refine.fold_all(names[rows], sums, cuts, k, eps, sampling, lambda at: refine.partial_sums(x[rows[at]], q, cuts), slack)  # noqa: B023
                d2 = sums[:, -1]
            near: list[int] = []
            if len(pruned):
                if d2 is None:
                    d2 = ((x[rows[: c.started]] - q) ** 2).sum(axis=1)
                gone = np.zeros(len(d2), bool)
                gone[pruned] = True
                close = np.flatnonzero(d2 <= np.partition(d2, k - 1)[k - 1] + 2e-6)
                near = names[rows[close[gone[close]]]].tolist()
            for rank, (d, name) in enumerate(best, start=1):
                row = (query, rank, name, d, c.started, c.completed, c.pruned, c.dims, c.stopped, near if rank == 1 else [])
                for column, v in zip(out, row, strict=True):
                    column.append(v)
        types = (pa.int64(), pa.int32(), pa.int64(), pa.float64(), *[pa.int64()] * 4, pa.int32(), pa.list_(pa.int64()))
        return pa.RecordBatch.from_arrays([pa.array(v, t) for v, t in zip(out, types, strict=True)], [c.split()[0] for c in SCHEMA.split(", ")])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: _Held | None = None
        for batch in batches:
            for raw in zip(*batch.columns, strict=True):
                ids, q, names, x, codes = (np.frombuffer(v.as_buffer(), t) for v, t in zip(raw, ("<i8", "<f8", "<i8", "<f8", "<i4"), strict=True))
                if held is None or not np.array_equal(held.ids, ids):
                    if held is not None:
                        yield from answers(held)
                    held = _Held(ids.copy(), q.reshape(len(ids), -1).copy())
                held.add(names, x.reshape(len(names), -1), codes.reshape(len(names), -1) + np.arange(layout.m) * k2)
        if held is not None:
            yield from answers(held)

    return pairs.mapInArrow(run, SCHEMA)
