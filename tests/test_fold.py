"""The fold of one candidate at a time gives what blocks of one give, and does not call numpy per candidate."""

import time

import numpy as np
import pytest

from subvote.operators import refine


@pytest.mark.parametrize("patience", [None, 5, 40])
@pytest.mark.parametrize("sampling", [True, False])
@pytest.mark.parametrize("step", [8, 32])
def test_same_as_blocks_of_one(patience, sampling, step):
    rng = np.random.default_rng(step)
    for n in (0, 3, 10, 700, 1500):
        x = np.round(rng.normal(size=(n, 64)), 1)
        x[n // 2 :] = x[: n - n // 2]  # copies: ties in distance
        ids, q = rng.permutation(n), np.round(rng.normal(size=64), 1)
        got = refine.fold(x, ids, q, 10, step, 0.4, patience, sampling, 1)
        assert got == refine._fold_blocks(x, ids, q, 10, step, 0.4, patience, sampling, 1)


@pytest.mark.parametrize("sampling", [True, False])
@pytest.mark.parametrize("step", [8, 32, 64])
@pytest.mark.parametrize("error", [0.0, 1e-4])
def test_whole_runs_same_as_blocks_of_one(sampling, step, error):
    """Runs judged at once give what one candidate at a time gives, also from rough sums."""
    rng = np.random.default_rng(step)
    for n in (0, 3, 10, 81, 700, 1500):
        for k in (1, 10, 100):
            x = np.round(rng.normal(size=(n, 64)), 1)
            x[n // 2 :] = x[: n - n // 2]  # copies: ties in distance
            ids, q = rng.permutation(n), np.round(rng.normal(size=64), 1)
            cuts = [*range(step, 64, step), 64]
            sums = refine.partial_sums(x, q, cuts)
            rough = sums + rng.uniform(-error, error, sums.shape)
            exact = (lambda at: sums[at]) if error else None  # noqa: B023
            best, count, pruned = refine.fold_all(ids, rough, cuts, k, 0.4, sampling, exact, error)
            assert (best, count, ids[pruned].tolist()) == refine._fold_blocks(x, ids, q, k, step, 0.4, None, sampling, 1)


def test_long_runs_are_not_taken_one_by_one():
    rng = np.random.default_rng(1)
    cuts = [32, 64]
    sums = np.cumsum(rng.uniform(20, 60, size=(60000, 2)), axis=1)
    seconds = []
    for f in (lambda: refine.fold_all(np.arange(60000), sums, cuts, 10, 2.1, True), lambda: refine.fold_sums([(np.arange(60000), sums)], cuts, 10, 2.1, None, True)):
        runs = []
        for _ in range(5):
            begin = time.perf_counter()
            f()
            runs.append(time.perf_counter() - begin)
        seconds.append(min(runs))
    print(seconds)
    assert 1.5 * seconds[0] < seconds[1]


def test_fold_is_quick():
    rng = np.random.default_rng(0)
    x, q = rng.normal(size=(20000, 64)), rng.normal(size=64)
    seconds = []
    for f in (lambda: refine.fold(x, np.arange(20000), q, 10), lambda: refine._fold_blocks(x, np.arange(20000), q, 10, 32, 2.1, None, True, 1)):
        begin = time.perf_counter()
        f()
        seconds.append(time.perf_counter() - begin)
    print(seconds)
    assert 4 * seconds[0] < seconds[1]
