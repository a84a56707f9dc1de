"""Many queries against one shard at once: votes, order and fold in arrays, no Python step per query.

Rows are those of `engine.shard_votes` and `refine.fold`, query by query.  Distances come from
products in doubles; wherever their rounding could matter they are measured again in full.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np

from subvote.operators import refine

#: Pairs of a query and a vector that are scored and ordered at once, and those that are folded at once.
PAIRS, FOLDED = 1 << 20, 1 << 20
#: Scores that are added up at once, and queries of a large shard that are scored together, as a row of weights is read whole.
VOTED, SCORED = 1 << 18, 256
#: Candidates that are measured at once.
MEASURED = 1 << 15
#: Candidates in order that a query gets at first where patience may end it early.
AHEAD = 1024
NONE = np.iinfo(np.int64).max


def vote_places(offsets: list[np.ndarray], rows: np.ndarray, k2: int) -> np.ndarray:
    """n x M: where the weight of the cell of every vector is in a table of all cells."""
    m, n = rows.shape
    out = np.empty((n, m), np.int64)
    for j in range(m):
        out[rows[j], j] = np.repeat(offsets[j], np.diff(offsets[m + j])) + j * k2
    return out


def votes(table: np.ndarray, places: np.ndarray) -> np.ndarray:
    """queries x n scores from `table`, cells x queries."""
    n, nq = len(places), table.shape[1]
    table = np.ascontiguousarray(table)  # picked columns come laid out by column
    out = np.empty((nq, n), np.int8 if 2 * places.shape[1] < 128 else np.int16)
    step = max(1, VOTED // max(nq, 1))
    for lo in range(0, n, step):
        score = np.zeros((len(places[lo : lo + step]), nq), out.dtype)
        for column in np.ascontiguousarray(places[lo : lo + step].T):
            score += np.take(table, column, axis=0)
        out[:, lo : lo + step] = score.T
    return out


def in_order(score: np.ndarray, words: np.ndarray, asked: np.ndarray, least: int, top: int, hamming: bool, most: int) -> np.ndarray:
    """queries x `most` places of the candidates: by Hamming distance, then falling score, then
    place; behind the candidates of a query come any."""
    n = score.shape[1]
    kind = np.int32 if (top + 1) * (64 * words.shape[1] + 1) * n + n < 1 << 31 else np.int64
    key = top - score.astype(kind)
    if hamming:
        for base, query in zip(words.view(np.uint64).T, asked.view(np.uint64).T, strict=True):
            key += np.bitwise_count(query[:, None] ^ base[None]).astype(kind) * kind(top + 1)
    key *= kind(n)
    key += np.arange(n, dtype=kind)
    # Behind all candidates, and still a place.
    key[score < least] = np.iinfo(kind).max
    if most < n:
        key = np.partition(key, most - 1, axis=1)[:, :most]
    key.sort(axis=1)
    return key % kind(n)


def fold_many(keys: np.ndarray, parts: list[np.ndarray], count: np.ndarray, n: int, k: int, cuts: list[int], eps: float, patience: int | None, sampling: bool, block: int, exact: Callable[[int, np.ndarray, np.ndarray], np.ndarray], slack: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(k x queries best keys, dims, started, stopped) of `refine.fold` for many queries side by side.

    keys: turns x queries, the squared distance in millionths times n, plus the place of the vector,
    so that keys fall like (distance, id).  parts: the partial sums at every cut but the last,
    `slack` off at most; `exact(cut, turns, queries)` gives them in full.  Of query i the first `count[i]` turns are candidates.
    """
    turns, nq = keys.shape
    dim = cuts[-1]
    times = [(j, t, float((1 + eps / np.sqrt(t)) ** 2)) for j, t in enumerate(cuts[:-1])] if sampling else []
    result, dims, started, stopped = np.full((k, nq), NONE), np.zeros(nq, np.int64), count.copy(), np.zeros(nq, bool)
    live, left, off, first = np.arange(nq), count, slack, 0  # `first`: turn of line 0 of keys and parts
    best = np.full((k, nq), NONE)
    head = keys[:k].copy()
    head[np.arange(len(head))[:, None] >= count] = NONE
    head.sort(axis=0)
    best[: len(head)] = head
    last = np.full(nq, k - 1)  # turn of the last change of the best k
    going = count > 0
    lo = 0
    while lo < turns:
        if lo % 32 == 0 or block > 1:
            going &= left > lo
            some = np.flatnonzero(going)
            if len(some) < 0.7 * len(live):
                result[:, live] = best
                live, left, off, best, last, going = live[some], left[some], off[some], best[:, some], last[some], going[some]
                keys, parts, first = keys[lo - first :][:, some], [p[lo - first :][:, some] for p in parts], lo
                if not len(live):
                    break
        hi = min(lo + block, turns)
        turn = np.arange(lo, hi)[:, None]
        inside = (turn < left) & going
        if lo >= k and times:
            radius = best[k - 1] // n / 1e6
            spent, kept = np.full(inside.shape, dim), inside.copy()
            for j, t, factor in reversed(times):
                part, limit = parts[j][lo - first : hi - first], radius * t / dim * factor
                gone, near = part > limit + off, part > limit - off
                if np.count_nonzero(gone) != np.count_nonzero(near):
                    at, q = np.nonzero(near & ~gone & inside)
                    if len(at):
                        gone[at, q] = exact(j, at + lo, live[q]) > limit[q]
                spent[gone] = t
                kept &= ~gone
            dims[live] += (spent * inside).sum(axis=0)
        else:
            kept = inside
            dims[live] += dim * inside.sum(axis=0)
        for t in range(max(lo, k), hi):
            value = keys[t - first]
            enters = np.flatnonzero((value < best[k - 1]) & kept[t - lo] & going)
            if len(enters):
                mine, v = best[:, enters], value[enters]
                changed = v // n < mine[k - 1] // n
                mine[1:] = np.minimum(mine[1:], np.maximum(mine[:-1], v))
                mine[0] = np.minimum(mine[0], v)
                best[:, enters] = mine
                last[enters[changed]] = t
            if patience is not None:
                ends = np.flatnonzero((t - last >= patience) & going & inside[t - lo])
                if len(ends):
                    started[live[ends]], stopped[live[ends]] = t + 1, True
                    going[ends] = False
        lo = hi
    result[:, live] = best
    return result, dims, started, stopped


class Shard:
    """Vectors of a shard, ids rising, with what all queries need of them."""

    def __init__(self, names: np.ndarray, x: np.ndarray, words: np.ndarray, step: int):
        self.names, self.words, dim = names, words, x.shape[1]
        self.x = x.astype(np.float64)
        self.cuts = [*range(step, dim, step), dim]
        spans = list(zip([0, *self.cuts], self.cuts, strict=False))
        self.slices = [np.ascontiguousarray(self.x[:, a:b].T) for a, b in spans]
        self.norms = np.cumsum(np.stack([(self.x[:, a:b] ** 2).sum(axis=1) for a, b in spans]), axis=0)
        self.longest = float(self.norms[-1].max())
        self.distinct = bool((np.diff(names) > 0).all())

    def fits(self, q: np.ndarray) -> bool:
        """Whether distances to q in millionths and places fit a key, and ids tell places apart."""
        top = 2e6 * (self.longest + float((q * q).sum(axis=1).max(initial=0.0))) + 1
        return self.distinct and top * len(self.names) < 1 << 62

    def sums(self, q: np.ndarray, order: np.ndarray) -> list[np.ndarray]:
        """turns x queries partial sums at every cut, for the places in `order`, queries x turns."""
        n = len(self.names)
        if order.shape[1] * 4 < n:
            some, out = max(1, MEASURED // (order.shape[1] + 1)), []
            for lo in range(0, len(q), some):
                part = self.x[order[lo : lo + some]]
                part -= q[lo : lo + some, None]
                part *= part
                pieces = [part[:, :, a:b].sum(axis=2) for a, b in zip([0, *self.cuts], self.cuts, strict=False)]
                out.append(np.cumsum(np.stack(pieces), axis=0))
            return [np.ascontiguousarray(c.T) for c in np.concatenate(out, axis=1)]
        out, begin = [], 0
        dots, asked = np.zeros((len(q), n)), np.zeros(len(q))
        for x, norms, end in zip(self.slices, self.norms, self.cuts, strict=True):
            part = q[:, begin:end]
            dots += part @ x
            asked += (part * part).sum(axis=1)
            out.append(np.ascontiguousarray(np.take_along_axis(norms - 2 * dots, order, 1).T) + asked)
            begin = end
        return out

    def fold(self, q: np.ndarray, order: np.ndarray, count: np.ndarray, sums: list[np.ndarray], k: int, eps: float, patience: int | None, sampling: bool, block: int) -> tuple[np.ndarray, ...]:
        """(queries x k distances, queries x k places (-1: none), dims, started, stopped)."""
        n = len(self.names)
        slack = 1e-14 * self.x.shape[1] * (self.longest + (q * q).sum(axis=1))
        scaled = sums[-1] * 1e6
        whole = np.rint(scaled)
        turn, of = np.nonzero(np.abs(scaled - whole) > 0.5 - 1e6 * slack - 1e-15 * np.abs(scaled) - 1e-9)
        if len(turn):
            full = refine.partial_sums(self.x[order[of, turn]], q[of], self.cuts)[:, -1]
            whole[turn, of] = np.rint(full * 1e6)
        keys = whole.astype(np.int64) * n + order.T
        exact = lambda j, turn, of: refine.partial_sums(self.x[order[of, turn]], q[of], self.cuts)[:, j]
        best, dims, started, stopped = fold_many(keys, sums[:-1], count, n, k, self.cuts, eps, patience, sampling, block, exact, slack)
        none = best.T == NONE
        return np.where(none, np.inf, best.T // n / 1e6), np.where(none, -1, best.T % n), dims, started, stopped

    def verify(self, q: np.ndarray, asked: np.ndarray, score: Callable[[np.ndarray], np.ndarray], least: int, top: int, k: int, eps: float, patience: int | None, hamming: bool, sampling: bool, block: int) -> Iterator[tuple[np.ndarray, ...]]:
        """(places of queries, distances, places of vectors, candidates, dims, started) of the queries, in batches.

        `score` gives the scores of some queries by their places.  Where patience may end a query early, only
        its first candidates are put in order; queries that need more come again with four times as many.
        """
        n = len(self.names)
        todo, most = np.arange(len(q)), n if patience is None else min(n, max(AHEAD, 4 * k))
        while len(todo):
            again = []
            for lo in range(0, len(todo), max(1, FOLDED // most)):
                batch = todo[lo : lo + max(1, FOLDED // most)]
                held: list[tuple] = []
                for first in range(0, len(batch), max(SCORED, PAIRS // n)):
                    group = batch[first : first + max(SCORED, PAIRS // n)]
                    scores = score(group)
                    for at in range(0, len(group), max(1, PAIRS // n)):
                        some, got = group[at : at + max(1, PAIRS // n)], scores[at : at + max(1, PAIRS // n)]
                        count = np.count_nonzero(got >= least, axis=1)
                        wide = min(n, most, max(k, int(count.max(initial=1))))
                        order = np.zeros((len(some), most), np.int64)
                        order[:, :wide] = in_order(got, self.words, asked[some], least, top, hamming, wide)
                        held.append((order, count, *self.sums(q[some], order[:, :wide])))
                turns = max(h[2].shape[0] for h in held)
                order, count = np.concatenate([h[0] for h in held])[:, :turns], np.concatenate([h[1] for h in held])
                sums = [np.concatenate([np.pad(h[2 + j], ((0, turns - len(h[2 + j])), (0, 0))) for h in held], axis=1) for j in range(len(self.cuts))]
                d2, place, dims, started, stopped = self.fold(q[batch], order, np.minimum(count, turns), sums, k, eps, patience, sampling, block)
                done = stopped | (count <= turns)
                # The last block may have been cut short, and dimensions count by whole blocks.
                done &= (-(-started // block) * block <= turns) | (count <= turns)
                again.append(batch[~done])
                yield batch[done], d2[done], place[done], count[done], dims[done], started[done]
            todo, most = np.concatenate(again), min(n, 4 * most)
