"""Nearest base vectors over pairs of blocks: compared with brute force, held while a task meets more of the base."""

import numpy as np
import pytest

from subvote.operators import exact


def table(dim, n, nq, long=1.0):
    rng = np.random.default_rng(dim)
    x = np.round(rng.normal(size=(n, dim)), 2)
    x[n // 2 : n // 2 + n // 8] = x[: n // 8]
    x[3] *= long
    q = np.concatenate([x[: nq // 2], np.round(rng.normal(size=(nq - nq // 2, dim)), 2)])
    return rng.permutation(n), x, q


def found(batches):
    out = {}
    for b in batches:
        for q, i, d in zip(*(c.to_pylist() for c in b.columns), strict=True):
            out.setdefault(q, []).append((d, i))
    return out


def pairs(names, x, q, rows, asked):
    for lo in range(0, len(x), rows):
        for at in range(0, len(q), asked):
            yield at, names[lo : lo + rows], x[lo : lo + rows], np.arange(at, min(at + asked, len(q))), q[at : at + asked]


@pytest.mark.parametrize("room", [0, 20_000, 64 << 20])
@pytest.mark.parametrize("long", [1.0, 1e6, 1e160])
@pytest.mark.parametrize(("dim", "k"), [(1, 3), (5, 1), (64, 10), (200, 130)])
def test_same_as_brute_force(monkeypatch, room, long, dim, k):
    monkeypatch.setattr(exact, "HELD_BYTES", room)
    monkeypatch.setattr(exact, "ROUGH", 5000)
    names, x, q = table(dim, 900, 50, long)
    with np.errstate(over="ignore", invalid="ignore"):
        got = found(exact.nearest_of_pairs(pairs(names, x, q, 128, 20), k))
        for i in range(len(q)):
            d2 = np.round(((x - q[i]) ** 2).sum(axis=1), 6)
            best = np.lexsort((names, d2))[:k]
            assert sorted(got[i])[:k] == [(float(d2[j]), int(names[j])) for j in best]


def test_a_task_sends_k_rows_of_a_query():
    names, x, q = table(16, 2000, 60)
    got = found(exact.nearest_of_pairs(pairs(names, x, q, 100, 25), 7))
    assert [len(v) for v in got.values()] == [7] * 60


def test_bulk_form_uses_all_cores(spark):
    names, x, q = table(8, 60, 6)
    df = spark.createDataFrame([(int(i), v.tolist()) for i, v in zip(names, x, strict=True)], "id long, vec array<double>").coalesce(1)
    plan = exact.knn(df, df.filter("id < 5"), 3)._jdf.queryExecution().optimizedPlan().toString()
    assert "Repartition" in plan


@pytest.mark.parametrize("form", [exact.knn_relational, exact.knn])
@pytest.mark.parametrize("k", [2, 40])
def test_tasks_send_packed_rows(spark, monkeypatch, form, k):
    """Neighbours of a task travel as few rows and meet again: few base rows, copies, distances beyond all numbers."""
    monkeypatch.setattr(exact, "BASE_ROWS", 7)
    names, x, q = table(3, 60, 30)
    x[5], x[6], x[7:20] = 1e200, np.nan, x[20]
    asked = np.arange(len(q))
    base = spark.createDataFrame([(int(i), v.tolist()) for i, v in zip(names, x, strict=True)], "id long, vec array<double>")
    queries = spark.createDataFrame([(int(i), v.tolist()) for i, v in zip(asked, q, strict=True)], "id long, vec array<double>")
    for some in (base, base.filter("id < 9")):
        out = form(some, queries, k)
        assert "RepartitionByExpression [query_ids" in out._jdf.queryExecution().optimizedPlan().toString()
        got = {}
        for r in out.collect():
            got.setdefault(r["query_id"], []).append((r["rank"], r["id"], repr(r["dist2"])))
        rows = {r["id"] for r in some.collect()}
        of = np.array([i in rows for i in names])
        with np.errstate(over="ignore", invalid="ignore"):
            for i in asked:
                d2 = np.round(((x[of] - q[i]) ** 2).sum(axis=1), 6)
                best = np.lexsort((names[of], d2))[:k]
                assert sorted(got[i]) == [(rank, int(names[of][j]), repr(float(d2[j]))) for rank, j in enumerate(best, start=1)]
