"""Which cells a query activates: ascending cost over the grid of half distances, up to a budget.

Rank 1 is the cheapest cell.  A cell is taken while fewer ids than the budget were pulled
before it, so the last one is taken whole; empty cells use up a rank.  Ties go to the
better left rank, then right rank.
"""

from __future__ import annotations

import heapq
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from subvote.functions.vectors import l2sq, part
from subvote.operators.arrow import matrix
from subvote.operators.codebooks import Codebooks
from subvote.operators.subspaces import Layout


def budget(ratio: float, n: int) -> int:
    """Ids to pull per subspace."""
    return max(1, math.ceil(ratio * n - 1e-9))


def half_distances(queries: DataFrame, layout: Layout, books: DataFrame) -> DataFrame:
    """(query_id, subspace, half, code, d2, half_rank) by a broadcast of the codebooks."""
    halves = F.broadcast(layout.table(queries.sparkSession).join(books, ["subspace", "half"]))
    d2 = F.round(l2sq(part(F.col("vec"), F.col("start"), F.col("len")), F.col("centroid")), 9)
    out = queries.crossJoin(halves).select(F.col("id").alias("query_id"), "subspace", "half", "code", d2.alias("d2"))
    rank = F.row_number().over(Window.partitionBy("query_id", "subspace", "half").orderBy("d2", "code"))
    return out.withColumn("half_rank", rank)


def traverse_relational(half: DataFrame, counts: DataFrame, k: int, limit: int) -> DataFrame:
    """(query_id, subspace, cell, rank, cost, n): the activated cells as a plan."""
    left = half.filter("half = 0").select("query_id", "subspace", F.col("code").alias("lc"), F.col("d2").alias("ld"), F.col("half_rank").alias("lr"))
    right = half.filter("half = 1").select("query_id", "subspace", F.col("code").alias("rc"), F.col("d2").alias("rd"), F.col("half_rank").alias("rr"))
    grid = left.join(right, ["query_id", "subspace"]).withColumn("cell", F.col("lc") * k + F.col("rc")).withColumn("cost", F.col("ld") + F.col("rd"))
    grid = grid.join(F.broadcast(counts), ["subspace", "cell"], "left").withColumn("n", F.coalesce("n", F.lit(0)))
    order = Window.partitionBy("query_id", "subspace").orderBy(F.round("cost", 9), "lr", "rr")
    grid = grid.withColumn("rank", F.row_number().over(order))
    pulled = F.coalesce(F.sum("n").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return grid.withColumn("before", pulled).filter(F.col("before") < limit).select("query_id", "subspace", "cell", "rank", "cost", "n")


def walk(left: np.ndarray, right: np.ndarray) -> Iterator[tuple[int, int, float]]:
    """Cells (left code, right code, cost) in visiting order, lazily by a heap over sorted halves."""
    lo, ro = np.argsort(left, kind="stable"), np.argsort(right, kind="stable")
    ls, rs = left[lo].tolist(), right[ro].tolist()
    heap, seen = [(round(ls[0] + rs[0], 9), 0, 0)], {(0, 0)}
    while heap:
        cost, i, j = heapq.heappop(heap)
        yield int(lo[i]), int(ro[j]), cost
        for a, b in ((i + 1, j), (i, j + 1)):
            if a < len(ls) and b < len(rs) and (a, b) not in seen:
                seen.add((a, b))
                heapq.heappush(heap, (round(ls[a] + rs[b], 9), a, b))


def activate(left: np.ndarray, right: np.ndarray, counts: np.ndarray, limit: int) -> tuple[np.ndarray, int]:
    """(cells in rank order, ids pulled) of one query and subspace; stops at the budget."""
    cells, pulled, k = [], 0, len(right)
    for i, j, _ in walk(left, right):
        if pulled >= limit:
            break
        cells.append(i * k + j)
        pulled += int(counts[i * k + j])
    return np.array(cells, np.int64), pulled


def half_matrix(x: np.ndarray, layout: Layout, books: Codebooks) -> list[np.ndarray]:
    """Per half: queries x K squared distances, rounded so that ties agree with the plan form."""
    return [np.round(((x[:, s : s + w][:, None] - b[None]) ** 2).sum(axis=2), 9) for s, w, b in zip(layout.starts, layout.lengths, books, strict=True)]


def ranked_cells(left: np.ndarray, right: np.ndarray, most: int) -> tuple[np.ndarray, np.ndarray]:
    """(cells in visiting order, how many of them are certain) for a batch of queries.

    The grid is laid out by half ranks, so a stable sort by cost breaks ties as the walk
    does.  Only about `most` cheapest cells are sorted; those as dear as the dearest of
    them may lack a tie and do not count as certain.
    """
    lo, ro = np.argsort(left, axis=1, kind="stable"), np.argsort(right, axis=1, kind="stable")
    n, k = right.shape
    cost = np.round(np.take_along_axis(left, lo, 1)[:, :, None] + np.take_along_axis(right, ro, 1)[:, None, :], 9).reshape(n, -1)
    size = cost.shape[1]
    if most < size:
        some = np.sort(np.argpartition(cost, most - 1, axis=1)[:, :most], axis=1)
        picked = np.take_along_axis(cost, some, 1)
        order = np.argsort(picked, axis=1, kind="stable")
        at, picked = np.take_along_axis(some, order, 1), np.take_along_axis(picked, order, 1)
        certain = (picked < picked[:, -1:]).sum(axis=1)
    else:
        at, certain = np.argsort(cost, axis=1, kind="stable"), np.full(n, size)
    return np.take_along_axis(lo, at // k, 1) * k + np.take_along_axis(ro, at % k, 1), certain


#: Cells of the grids that are laid out at once, about 64 MB of costs.
GRID = 8_000_000


def activate_all(x: np.ndarray, layout: Layout, books: Codebooks, counts: np.ndarray, limit: int, chunk: int | None = None) -> list[list[np.ndarray]]:
    """Activated cells per query and subspace, in rank order; counts is M x K*K over all shards."""
    chunk = chunk or max(1, min(1024, GRID // max(counts.shape[1], 1)))
    return [row for lo in range(0, len(x), chunk) for row in _activate_chunk(x[lo : lo + chunk], layout, books, counts, limit)]


def last_cell(left: np.ndarray, right: np.ndarray, cell: int) -> tuple[float, int, int]:
    """Place of a cell in the visiting order: cost, left rank, right rank."""
    i, j = divmod(int(cell), len(right))
    rank = lambda d, c: int((d < d[c]).sum() + (d[:c] == d[c]).sum())
    return round(float(left[i] + right[j]), 9), rank(left, i), rank(right, j)


def edges(x: np.ndarray, layout: Layout, books: Codebooks, counts: np.ndarray, limit: int, rank_cut: int) -> np.ndarray:
    """queries x M x 6: places of the last activated cell and of the last of the first `rank_cut`.

    A query's activation is all cells up to a place in the visiting order, so two places say
    which cells vote and with what weight, whatever the size of the grid.
    """
    out = np.full((len(x), layout.m, 6), -1.0)
    step = max(1, min(1024, GRID // max(counts.shape[1], 1)))
    for lo in range(0, len(x), step):
        part = x[lo : lo + step]
        half = half_matrix(part, layout, books)
        for q, row in enumerate(_activate_chunk(part, layout, books, counts, limit)):
            for m, cells in enumerate(row):
                left, right = half[2 * m][q], half[2 * m + 1][q]
                out[lo + q, m, :3] = last_cell(left, right, cells[-1])
                if rank_cut:
                    out[lo + q, m, 3:] = last_cell(left, right, cells[min(rank_cut, len(cells)) - 1])
    return out


def up_to(cells: np.ndarray, left: np.ndarray, right: np.ndarray, edge: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Which of some cells lie up to both places of `edge`."""
    k = len(right)
    i, j = cells // k, cells % k
    cost = np.round(left[i] + right[j], 9)
    orders = [np.empty(len(d), np.int64) for d in (left, right)]
    for d, o in zip((left, right), orders, strict=True):
        o[np.argsort(d, kind="stable")] = np.arange(len(d))
    lr, rr = orders[0][i], orders[1][j]
    before = lambda e: (cost < e[0]) | ((cost == e[0]) & ((lr < e[1]) | ((lr == e[1]) & (rr <= e[2]))))
    return before(edge[:3]), before(edge[3:])


def _activate_chunk(x: np.ndarray, layout: Layout, books: Codebooks, counts: np.ndarray, limit: int) -> list[list[np.ndarray]]:
    """Activated cells of every query, a list by subspace."""
    out: list[list[np.ndarray]] = [[np.empty(0, np.int64)] * layout.m for _ in range(len(x))]
    for m, queries, cells, need in _activated(x, layout, books, counts, limit):
        for q, row, end in zip(queries.tolist(), cells, need.tolist(), strict=True):
            out[q][m] = row[:end]
    return out


def weight_table(x: np.ndarray, layout: Layout, books: Codebooks, counts: np.ndarray, limit: int, rank_cut: int) -> np.ndarray:
    """queries x (M K^2): the weight of a vote of every cell, 0 where it is not activated."""
    size = counts.shape[1]
    table = np.zeros((len(x), layout.m, size), np.int8)
    step = max(1, min(1024, GRID // max(size, 1)))
    for lo in range(0, len(x), step):
        for m, queries, cells, need in _activated(x[lo : lo + step], layout, books, counts, limit):
            rank = np.arange(cells.shape[1])
            weight = (rank < need[:, None]).astype(np.int8)
            weight[:, :rank_cut] *= 2
            table[lo + queries[:, None], m, cells] = weight
    return table.reshape(len(x), -1)


def _activated(x: np.ndarray, layout: Layout, books: Codebooks, counts: np.ndarray, limit: int) -> Iterator[tuple[int, np.ndarray, np.ndarray, np.ndarray]]:
    """(subspace, queries, their cells in visiting order, how many of them are activated).

    Vectorised over the queries: a first share of the grid is sorted, and only queries that
    do not reach the budget in it come once more, with a full order.
    """
    half = half_matrix(x, layout, books)
    total = max(1, int(counts[0].sum())) if len(counts) else 1
    for m in range(layout.m):
        left, right = half[2 * m], half[2 * m + 1]
        size = left.shape[1] * right.shape[1]
        most = min(size, 64 + int(4 * size * limit / total))
        cells, certain = ranked_cells(left, right, most)
        pulled = np.cumsum(counts[m][cells], axis=1)
        # A cell is taken while fewer ids than the budget came before it.
        need = (pulled < limit).sum(axis=1) + 1
        late = (need > certain) & (certain < size)
        sure = np.flatnonzero(~late)
        yield m, sure, cells[sure], np.minimum(need[sure], size)
        late = np.flatnonzero(late)
        if len(late):
            cells, _ = ranked_cells(left[late], right[late], size)
            need = (np.cumsum(counts[m][cells], axis=1) < limit).sum(axis=1) + 1
            yield m, late, cells, np.minimum(need, size)


def traverse_heap(queries: DataFrame, layout: Layout, books: Codebooks, counts: np.ndarray, limit: int) -> DataFrame:
    """(query_id, subspace, cell, rank) for a table of queries, lazily per query in Arrow batches."""
    shared = queries.sparkSession.sparkContext.broadcast((layout, books, counts))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        layout, books, counts = shared.value
        for batch in batches:
            if not len(batch):
                continue
            ids, half = batch.column(0).to_numpy(), half_matrix(matrix(batch.column(1)).astype(np.float64), layout, books)
            for q, query in enumerate(ids.tolist()):
                for m in range(layout.m):
                    cells, _ = activate(half[2 * m][q], half[2 * m + 1][q], counts[m], limit)
                    n = len(cells)
                    yield pa.RecordBatch.from_arrays([pa.array([query] * n), pa.array([m] * n, pa.int32()), pa.array(cells.astype(np.int32)), pa.array(np.arange(1, n + 1, dtype=np.int32))], ["query_id", "subspace", "cell", "rank"])

    return queries.select("id", "vec").mapInArrow(run, "query_id long, subspace int, cell int, rank int")
