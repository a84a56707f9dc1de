"""Refinement of candidates: exact distances, Hamming order, dimension sampling, patience."""

from __future__ import annotations

import bisect
from collections.abc import Callable, Iterable
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from subvote.functions.vectors import hamming, l2sq, sign_words
from subvote.operators.arrow import matrix

STEP, EPSILON, PATIENCE = 32, 2.1, 40


def exact(candidates: DataFrame, base: DataFrame, queries: DataFrame, k: int) -> DataFrame:
    """(query_id, rank, id, dist2): every candidate measured, best k kept.

    Only candidates meet vectors: the join is on ids, queries are broadcast by size.
    """
    measured = distances(candidates, base, queries)
    order = Window.partitionBy("query_id").orderBy("dist2", "id")
    return measured.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k).select("query_id", "rank", "id", "dist2")


def distances(candidates: DataFrame, base: DataFrame, queries: DataFrame) -> DataFrame:
    """candidates plus dist2, rounded to 6 places so that ties are ties in every engine."""
    q = queries.select(F.col("id").alias("query_id"), F.col("vec").alias("q"))
    joined = candidates.join(base.select("id", "vec"), "id").join(q, "query_id")
    return joined.withColumn("dist2", F.round(l2sq(F.col("vec"), F.col("q")), 6)).drop("vec", "q")


def order_by_hamming(candidates: DataFrame, base: DataFrame, queries: DataFrame, dim: int) -> DataFrame:
    """candidates plus ham and pos (1 is first): Hamming distance of sign bits, then score, then id."""
    codes = base.select("id", sign_words(F.col("vec"), dim).alias("w"))
    q = queries.select(F.col("id").alias("query_id"), sign_words(F.col("vec"), dim).alias("qw"))
    out = candidates.join(codes, "id").join(q, "query_id").withColumn("ham", hamming(F.col("w"), F.col("qw"))).drop("w", "qw")
    return out.withColumn("pos", F.row_number().over(Window.partitionBy("query_id").orderBy("ham", F.desc("score"), "id")))


def patience_exact(ordered: DataFrame, k: int, patience: int) -> DataFrame:
    """(query_id, pos, id, dist2) of the candidates verified until the top k stayed the same
    `patience` times in a row, for exact distances; window functions only.

    ordered: (query_id, pos, id, dist2).  The k-th smallest distance so far comes from a
    running array; a verification changes the top k if it is below that value.
    """
    w = Window.partitionBy("query_id").orderBy("pos")
    before = F.sort_array(F.collect_list("dist2").over(w.rowsBetween(Window.unboundedPreceding, -1)))
    kth = F.when(F.size(before) >= k, F.element_at(before, k))
    marked = ordered.withColumn("kth", kth).withColumn("changed", F.when(F.col("kth").isNull() | (F.col("dist2") < F.col("kth")), 1).otherwise(0))
    last = F.max(F.when(F.col("changed") == 1, F.col("pos"))).over(w.rowsBetween(Window.unboundedPreceding, -1))
    marked = marked.withColumn("idle", F.col("pos") - 1 - F.coalesce(last, F.lit(0)))
    stopped = F.max(F.when(F.col("idle") >= patience, 1).otherwise(0)).over(w.rowsBetween(Window.unboundedPreceding, 0))
    return marked.withColumn("stopped", stopped).filter("stopped = 0").select("query_id", "pos", "id", "dist2")


@dataclass
class Counters:
    started: int = 0
    completed: int = 0
    pruned: int = 0
    dims: int = 0
    stopped: int = 0


def fold(x: np.ndarray, ids: np.ndarray, q: np.ndarray, k: int, step: int = STEP, eps: float = EPSILON, patience: int | None = None, sampling: bool = True, block: int = 1) -> tuple[list[tuple[float, int]], Counters, list[int]]:
    """Verify candidates in order; returns ((dist2, id) of the best k, counters, pruned ids).

    A candidate is measured `step` dimensions at a time and dropped as soon as its partial
    sum exceeds r_k^2 * t/D * (1 + eps/sqrt(t))^2; at t = D that is the exact test.  The
    fold ends when the best k stayed the same for `patience` candidates.  With block > 1
    the radius is read once per block, which prunes a little less and runs vectorised.
    """
    if block == 1:
        return _fold_singly(x, ids, q, k, step, eps, patience, sampling)
    return _fold_blocks(x, ids, q, k, step, eps, patience, sampling, block)


#: Candidates whose partial sums are worked out at once by the fold of one at a time.
AHEAD = 512


def partial_sums(x: np.ndarray, q: np.ndarray, cuts: list[int]) -> np.ndarray:
    """rows x cuts: squared distance over the first t dimensions for every cut t."""
    part = (x - q) ** 2
    return np.cumsum(np.stack([part[:, a:b].sum(axis=1) for a, b in zip([0, *cuts], cuts, strict=False)], axis=1), axis=1)


def _fold_singly(x: np.ndarray, ids: np.ndarray, q: np.ndarray, k: int, step: int, eps: float, patience: int | None, sampling: bool) -> tuple[list[tuple[float, int]], Counters, list[int]]:
    """The fold with the radius read for every candidate: partial sums come in bulk, the order stays."""
    cuts = [*range(step, x.shape[1], step), x.shape[1]]
    parts = ((ids[lo : lo + AHEAD], partial_sums(x[lo : lo + AHEAD], q, cuts)) for lo in range(0, len(ids), AHEAD))
    best, count, pruned = fold_sums(parts, cuts, k, eps, patience, sampling)
    return best, count, ids[pruned].tolist()


def fold_sums(parts: Iterable[tuple[np.ndarray, np.ndarray]], cuts: list[int], k: int, eps: float, patience: int | None, sampling: bool, exact: Callable[[np.ndarray], np.ndarray] | None = None, slack: float = 0.0) -> tuple[list[tuple[float, int]], Counters, np.ndarray]:
    """The fold of one candidate at a time over runs of (ids, partial sums) in their order; pruned
    candidates come back as places in it.

    Between two candidates that enter the best k the radius stays, so those between them are
    judged at once, in windows that grow while none enters.  With `exact`, the sums given may be
    off by `slack`: wherever that could matter, and for all that enter, they are read from
    `exact` (places in the run -> partial sums).
    """
    dim, times = cuts[-1], [(j, t, float((1 + eps / np.sqrt(t)) ** 2)) for j, t in enumerate(cuts[:-1])] if sampling else []
    best: list[tuple[float, int]] = []
    count, pruned, idle, before = Counters(), [np.empty(0, np.int64)], 0, 0

    def pass_over(gone: list[np.ndarray], first: int, n: int) -> None:
        """Counts n candidates that do not enter; `gone` says per cut which ones exceed its limit."""
        out = np.zeros(n, bool)
        for (_, t, _), g in zip(times, gone, strict=True):
            count.dims += t * int(np.count_nonzero(g[:n] & ~out))
            out |= g[:n]
        lost = np.flatnonzero(out)
        pruned.append(before + first + lost)
        count.started += n
        count.pruned += len(lost)
        count.completed += n - len(lost)
        count.dims += dim * (n - len(lost))

    for ids, sums in parts:
        columns = [np.array(c) for c in sums.T]
        d2, lo, width = np.round(columns[-1], 6), 0, 16
        known = np.zeros(len(ids), bool)

        def read(places: np.ndarray) -> None:
            rows = places[~known[places]]  # noqa: B023
            if len(rows):
                for c, v in zip(columns, exact(rows).T, strict=True):  # noqa: B023
                    c[rows] = v
                d2[rows], known[rows] = np.round(columns[-1][rows], 6), True  # noqa: B023

        while lo < len(ids):
            if len(best) >= k:
                radius, last = best[k - 1]
                hi = min(lo + width, len(ids))
                limits = [(columns[j], radius * t / dim * factor) for j, t, factor in times]
                if exact is not None:
                    close = d2[lo:hi] <= radius + slack + 1e-6
                    for c, limit in limits:
                        close |= np.abs(c[lo:hi] - limit) <= slack
                    if close.any():
                        read(lo + np.flatnonzero(close))
                gone = [~(c[lo:hi] <= limit) for c, limit in limits]
                enters = d2[lo:hi] <= radius
                for g in gone:
                    enters &= ~g
                some = np.flatnonzero(enters)
                some = some[(d2[lo + some] < radius) | (ids[lo + some] < last)]
                at = int(some[0]) if len(some) else hi - lo
                if patience is not None and idle + at >= patience:
                    pass_over(gone, lo, patience - idle)
                    count.stopped = 1
                    return best, count, np.concatenate(pruned)
                pass_over(gone, lo, at)
                idle += at
                lo += at
                if lo == hi:
                    width = min(4 * width, 4096)
                    continue
                width = max(16, width // 4)
            if exact is not None:
                read(np.array([lo]))
            entry = (float(d2[lo]), int(ids[lo]))
            changed = len(best) < k or entry[0] < best[k - 1][0]
            bisect.insort(best, entry)
            del best[k:]
            count.started += 1
            count.completed += 1
            count.dims += dim
            lo += 1
            idle = 0 if changed else idle + 1
            if patience is not None and len(best) >= k and idle >= patience:
                count.stopped = 1
                return best, count, np.concatenate(pruned)
        before += len(ids)
    return best, count, np.concatenate(pruned)


def fold_all(ids: np.ndarray, sums: np.ndarray, cuts: list[int], k: int, eps: float, sampling: bool, exact: Callable[[np.ndarray], np.ndarray] | None = None, slack: float = 0.0) -> tuple[list[tuple[float, int]], Counters, np.ndarray]:
    """`fold_sums` without patience over all candidates, in runs that grow eightfold.

    In a run, only candidates within the radius at its start can enter: they alone are looked at
    one by one, and then all of the run are judged at once, each by the radius of its turn.
    """
    n, dim = len(ids), cuts[-1]
    columns, pruned = [np.array(c) for c in sums.T], [np.empty(0, np.int64)]
    times = [(j, t, float((1 + eps / np.sqrt(t)) ** 2)) for j, t in enumerate(cuts[:-1])] if sampling else []

    def read(places: np.ndarray) -> None:
        if exact is not None and len(places):
            for c, v in zip(columns, exact(places).T, strict=True):
                c[places] = v

    lo = min(k, n)
    read(np.arange(lo))
    best = sorted(zip(np.round(columns[-1][:lo], 6).tolist(), ids[:lo].tolist(), strict=True))
    count = Counters(started=lo, completed=lo, dims=dim * lo)
    while lo < n:
        hi = min(n, 8 * lo)
        radius, last = best[k - 1]
        some = lo + np.flatnonzero(columns[-1][lo:hi] <= radius + slack + 1e-6)
        read(some)
        turns, radii = [lo], [radius]
        for i, name, d, *part in zip(some.tolist(), ids[some].tolist(), np.round(columns[-1][some], 6).tolist(), *(columns[j][some].tolist() for j, _, _ in times), strict=True):
            if (d, name) < (radius, last) and all(c <= radius * t / dim * factor for c, (_, t, factor) in zip(part, times, strict=True)):
                bisect.insort(best, (d, name))
                del best[k:]
                radius, last = best[k - 1]
                turns.append(i + 1)
                radii.append(radius)
        of_turn = np.repeat(radii, np.diff([*turns, hi]))
        out = np.zeros(hi - lo, bool)
        limits = [(j, t, of_turn * t / dim * factor) for j, t, factor in times]
        if exact is not None and limits:
            read(lo + np.flatnonzero(np.logical_or.reduce([np.abs(columns[j][lo:hi] - limit) <= slack for j, _, limit in limits])))
        for j, t, limit in limits:
            gone = ~(columns[j][lo:hi] <= limit) & ~out
            count.dims += t * int(np.count_nonzero(gone))
            out |= gone
        lost = np.flatnonzero(out)
        pruned.append(lo + lost)
        count.started += hi - lo
        count.pruned += len(lost)
        count.completed += hi - lo - len(lost)
        count.dims += dim * (hi - lo - len(lost))
        lo = hi
    return best, count, np.concatenate(pruned)


def _fold_blocks(x: np.ndarray, ids: np.ndarray, q: np.ndarray, k: int, step: int, eps: float, patience: int | None, sampling: bool, block: int) -> tuple[list[tuple[float, int]], Counters, list[int]]:
    dim = x.shape[1]
    cuts = [*range(step, dim, step), dim]
    best: list[tuple[float, int]] = []
    count, pruned, idle = Counters(), [], 0
    for lo in range(0, len(ids), block):
        part, names = x[lo : lo + block], ids[lo : lo + block]
        radius = best[k - 1][0] if len(best) >= k else np.inf
        total, alive, done = np.zeros(len(part)), np.arange(len(part)), 0
        for t in cuts:
            total[alive] += ((part[alive, done:t] - q[done:t]) ** 2).sum(axis=1)
            count.dims += (t - done) * len(alive)
            done = t
            if sampling and t < dim and np.isfinite(radius):
                keep = total[alive] <= radius * t / dim * (1 + eps / np.sqrt(t)) ** 2
                pruned.extend(names[alive[~keep]].tolist())
                alive = alive[keep]
                if not len(alive):
                    break
        # Only candidates that may enter the best k are looked at one by one.
        measured = np.zeros(len(part), dtype=bool)
        measured[alive] = True
        enters = np.flatnonzero(measured & (np.round(total, 6) <= (best[k - 1][0] if len(best) >= k else np.inf)))
        before, stop = 0, len(part)
        for i in [*enters.tolist(), len(part)]:
            if patience is not None and len(best) >= k and idle + i - before >= patience:
                stop = before + max(patience - idle, 0)
                count.stopped = 1
                break
            idle += i - before
            before = i + 1
            if i == len(part):
                break
            entry, changed = (round(float(total[i]), 6), int(names[i])), False
            if len(best) < k or entry < best[k - 1]:
                changed = len(best) < k or entry[0] < best[k - 1][0]
                bisect.insort(best, entry)
                del best[k:]
            idle = 0 if changed else idle + 1
            if patience is not None and len(best) >= k and idle >= patience:
                stop, count.stopped = i + 1, 1
                break
        count.started += stop
        done_ = int(measured[:stop].sum())
        count.completed += done_
        count.pruned += stop - done_
        if count.stopped:
            return best, count, pruned
    return best, count, pruned


def fold_queries(ordered: DataFrame, base: DataFrame, queries: DataFrame, k: int, **options) -> DataFrame:
    """The fold for every query over all its candidates in one order (one task per query).

    ordered: (query_id, id, pos).  Returns (query_id, rank, id, dist2, started, completed,
    pruned, dims, stopped, pruned_ids on rank 1).
    """
    rows = ordered.select("query_id", "id", "pos").join(base.select("id", "vec"), "id")
    rows = rows.join(queries.select(F.col("id").alias("query_id"), F.col("vec").alias("q")), "query_id")

    def run(part: pa.Table) -> pa.Table:
        part = part.sort_by("pos")
        x, q = matrix(part.column("vec")).astype(np.float64), matrix(part.column("q").slice(0, 1)).astype(np.float64)[0]
        best, c, pruned = fold(x, part.column("id").to_numpy(), q, k, **options)
        n = len(best)
        return pa.table(
            {
                "query_id": pa.array([part.column("query_id")[0].as_py()] * n, pa.int64()), "rank": pa.array(range(1, n + 1), pa.int32()),
                "id": pa.array([b[1] for b in best], pa.int64()), "dist2": pa.array([b[0] for b in best], pa.float64()),
                "started": pa.array([c.started] * n, pa.int64()), "completed": pa.array([c.completed] * n, pa.int64()), "pruned": pa.array([c.pruned] * n, pa.int64()),
                "dims": pa.array([c.dims] * n, pa.int64()), "stopped": pa.array([c.stopped] * n, pa.int32()),
                "pruned_ids": pa.array([pruned if r == 0 else [] for r in range(n)], pa.list_(pa.int64())),
            }
        )

    schema = "query_id long, rank int, id long, dist2 double, started long, completed long, pruned long, dims long, stopped int, pruned_ids array<long>"
    return rows.groupBy("query_id").applyInArrow(run, schema)
