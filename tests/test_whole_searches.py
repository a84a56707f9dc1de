"""Registered searches answer from all rows: compared with brute force in numpy."""

import numpy as np

import __spark_entry__ as entry
from subvote.sources import vectors as sources


def rows(df):
    found = sorted((r["id"], r["vec"]) for r in df.select("id", "vec").collect())
    return np.array([i for i, _ in found]), np.array([v for _, v in found], dtype=float)


def test_udtf_knn_searches_all_rows(spark, sf):
    got = {(r["query_id"], r["rank"]): (r["id"], r["dist2"]) for r in entry.queries()["q_udtf_knn"](spark, sf).collect()}
    ids, x = rows(sources.embeddings(spark, sf))
    want = {}
    for q in np.flatnonzero(ids % 100 == 0):
        d2 = np.round(((x - x[q]) ** 2).sum(axis=1), 6)
        for rank, i in enumerate(np.lexsort((ids, d2))[:3], start=1):
            want[int(ids[q]), rank] = (int(ids[i]), float(d2[i]))
    assert got == want


def test_doc_hash_knn_is_whole(spark, sf):
    got = {r["query_id"]: (r["sum_dist2"], r["n"]) for r in entry.queries()["q_doc_hash_knn"](spark, sf).collect()}
    ids, x = rows(sources.documents(spark, sf, 768))
    want = {}
    for q in np.flatnonzero(ids % 100 == 0):
        d2 = np.delete(np.round(((x - x[q]) ** 2).sum(axis=1), 6), q)
        want[int(ids[q])] = (round(float(np.sort(d2)[:3].sum()), 4), 3)
    assert got.keys() == want.keys()
    for q, (total, n) in got.items():
        assert n == 3 and abs(total - want[q][0]) < 2e-4


def test_doc_knn_join_has_768_dimensions(spark, sf):
    got = entry.queries()["q_doc_knn_join"](spark, sf).collect()
    ids, x = rows(sources.documents(spark, sf, 768))
    at = {int(i): j for j, i in enumerate(ids)}
    assert got
    for r in got:
        assert abs(r["dist2"] - ((x[at[r["query_id"]]] - x[at[r["id"]]]) ** 2).sum()) < 1e-4
