"""The method and the exact scan at the size of the smaller published sets.

python bench_scale.py N D Q K: synthetic clustered vectors, both modes over a few budgets,
beside the exact scan in bulk form.  Prints one JSON line per configuration.
"""

from __future__ import annotations

import json
import sys
import time
from dataclasses import replace
from pathlib import Path

sys.path.insert(0, str(Path(__file__).resolve().parent))

from pyspark.sql import functions as F  # noqa: E402

from subvote.operators import exact, metrics  # noqa: E402
from subvote.operators.engine import IndexParams, SearchParams, build_index, counters, footprint, search  # noqa: E402
from subvote.session import local_session  # noqa: E402
from subvote.sources import vectors as sources  # noqa: E402


def main(n: int = 60_000, dim: int = 784, n_queries: int = 1000, k: int = 100) -> None:
    spark = local_session(8, 16, "14g")
    df = sources.synthetic(spark, n + n_queries, dim, spectrum=0.995, latent=24, partitions=32)
    base, queries = df.filter(F.col("id") >= n_queries).persist(), df.filter(F.col("id") < n_queries).persist()
    base.count()
    queries.count()
    begin = time.perf_counter()
    truth = exact.knn(base, queries, k).persist()
    truth.count()
    seconds = time.perf_counter() - begin
    print(json.dumps({"method": "exact", "n": n, "dim": dim, "k": k, "qps": round(n_queries / seconds, 1), "recall": 1.0}), flush=True)
    for policy in ("adaptive", "never"):
        begin = time.perf_counter()
        index = build_index(base, IndexParams(m=8, k=50, iters=6, policy=policy, shard_rows=max(1024, n // 16), train_rows=20_000))
        build = time.perf_counter() - begin
        stored = footprint(index).agg(F.sum("of_raw")).first()[0]
        seen = {"rotated": index.matrix is not None, "cev": round(index.report.cev, 3), "build_s": round(build, 1), "stages": {s: round(v, 1) for s, v in index.seconds.items()}, "stored_of_raw": round(stored, 2)}
        print(json.dumps({"policy": policy, **seen}), flush=True)
        guaranteed = SearchParams("guaranteed", 0.02, 0.3)
        for params in (guaranteed, replace(guaranteed, ratio=0.05), SearchParams("optimized", 0.02, 0.4, patience_factor=4, step=98, block=256), SearchParams("optimized", 0.05, 0.4, patience_factor=4, step=98, block=256)):
            search(index, queries.limit(10), k, params).count()
            begin = time.perf_counter()
            found = search(index, queries, k, params).persist()
            found.count()
            seconds = time.perf_counter() - begin
            work = counters(search(index, queries.limit(100), k, params, details=True)).agg(F.avg("candidates"), F.avg("dims")).first()
            row = {"policy": policy, "mode": params.mode, "ratio": params.ratio, "fraction": params.min_fraction, "qps": round(n_queries / seconds, 1)}
            row |= {"recall": round(metrics.recall(found, truth, k).first()["recall"], 4), "candidates": round(work[0]), "dims": round(work[1])}
            print(json.dumps(row), flush=True)
            found.unpersist()


if __name__ == "__main__":
    main(*map(int, sys.argv[1:]))
