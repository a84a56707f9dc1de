"""Baseline: navigable small-world graphs, one per shard.

A graph does not fit a shuffle engine; every shard gets its own layered graph, every query
visits all shards, and the shard results are merged.  Made for small tables.
"""

from __future__ import annotations

import heapq
import math
import pickle
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from subvote.operators.arrow import matrix
from subvote.operators.exact import apart, collect_queries, merge


class SmallWorld:
    """Layers of neighbour lists; layer 0 holds all points, each higher one about 1/links of them."""

    def __init__(self, x: np.ndarray, links: int = 16, ef_construction: int = 64, seed: int = 7):
        self.x, self.links = x, links
        rng = np.random.default_rng(seed)
        levels = np.minimum((-np.log(rng.random(len(x))) / math.log(max(links, 2))).astype(int), 16)
        self.layers: list[dict[int, list[int]]] = [{} for _ in range(int(levels.max(initial=0)) + 1)]
        self.entry = -1
        self.top = -1
        for i in range(len(x)):
            self._insert(i, int(levels[i]), ef_construction)

    def _far(self, q: np.ndarray, at: list[int]) -> np.ndarray:
        return ((self.x[at] - q) ** 2).sum(axis=1)

    def _walk(self, q: np.ndarray, start: list[int], ef: int, layer: int) -> list[tuple[float, int]]:
        """The ef nearest points found from the start points, nearest first."""
        seen = set(start)
        open_ = [(float(d), i) for d, i in zip(self._far(q, start), start, strict=True)]
        heapq.heapify(open_)
        best = [(-d, i) for d, i in open_]
        heapq.heapify(best)
        while open_:
            d, i = heapq.heappop(open_)
            if len(best) >= ef and d > -best[0][0]:
                break
            near = [j for j in self.layers[layer].get(i, []) if j not in seen]
            if not near:
                continue
            seen.update(near)
            for e, j in zip(self._far(q, near).tolist(), near, strict=True):
                if len(best) < ef or e < -best[0][0]:
                    heapq.heappush(open_, (e, j))
                    heapq.heappush(best, (-e, j))
                    if len(best) > ef:
                        heapq.heappop(best)
        return sorted((-d, i) for d, i in best)

    def _spread(self, found: list[tuple[float, int]], most: int) -> list[int]:
        """Neighbours that are nearer to the point than to each other, filled up by distance."""
        kept: list[int] = []
        for d, i in found:
            if len(kept) >= most:
                break
            if not kept or (self._far(self.x[i], kept) >= d).all():
                kept.append(i)
        for _, i in found:
            if len(kept) >= most:
                break
            if i not in kept:
                kept.append(i)
        return kept

    def _insert(self, i: int, level: int, ef: int) -> None:
        for layer in range(level + 1):
            self.layers[layer].setdefault(i, [])
        if self.entry < 0:
            self.entry, self.top = i, level
            return
        at = [self.entry]
        for layer in range(self.top, level, -1):
            at = [self._walk(self.x[i], at, 1, layer)[0][1]]
        for layer in range(min(level, self.top), -1, -1):
            found = [f for f in self._walk(self.x[i], at, ef, layer) if f[1] != i]
            most = 2 * self.links if layer == 0 else self.links
            mine = self._spread(found, self.links)
            self.layers[layer][i] = mine
            for j in mine:
                back = self.layers[layer][j]
                back.append(i)
                if len(back) > most:
                    order = sorted(zip(self._far(self.x[j], back).tolist(), back, strict=True))
                    self.layers[layer][j] = self._spread(order, most)
            at = [j for _, j in found] or at
        if level > self.top:
            self.entry, self.top = i, level

    def search(self, q: np.ndarray, k: int, ef: int) -> list[tuple[float, int]]:
        at = [self.entry]
        for layer in range(self.top, 0, -1):
            at = [self._walk(q, at, 1, layer)[0][1]]
        return self._walk(q, at, max(ef, k), 0)[:k]


@dataclass
class GraphIndex:
    graphs: DataFrame
    shards: int = 1


def build(base: DataFrame, links: int = 16, ef_construction: int = 64, shards: int = 4, seed: int = 7) -> GraphIndex:
    def pack(part: pa.Table) -> pa.Table:
        ids = part.column("id").to_numpy()
        order = np.argsort(ids, kind="stable")
        world = SmallWorld(matrix(part.column("vec"))[order].astype(np.float64), links, ef_construction, seed)
        return pa.table({"shard": part.column("shard").slice(0, 1), "graph": pa.array([pickle.dumps((ids[order], world))], pa.binary())})

    sharded = base.select("id", "vec").withColumn("shard", F.pmod(F.xxhash64("id"), F.lit(shards)).cast("int"))
    return GraphIndex(apart(sharded, "shard", shards).groupBy("shard").applyInArrow(pack, "shard int, graph binary").persist(), shards)


def search(index: GraphIndex, queries: DataFrame, k: int, ef_search: int = 64) -> DataFrame:
    """(query_id, rank, id, dist2); a graph goes to several tasks, each with every `parts`-th query."""
    ids, q = collect_queries(queries)
    spark = queries.sparkSession
    shared = spark.sparkContext.broadcast((ids, q))
    parts = math.ceil(2 * spark.sparkContext.defaultParallelism / index.shards)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, q = shared.value
        for batch in batches:
            for raw, part in zip(batch.column(0), batch.column(1).to_pylist(), strict=True):
                names, world = pickle.loads(raw.as_buffer().to_pybytes())
                for i in range(part, len(ids), parts):
                    query = int(ids[i])
                    found = world.search(q[i], k, ef_search)
                    yield pa.RecordBatch.from_arrays([pa.array([query] * len(found)), pa.array([int(names[j]) for _, j in found], pa.int64()), pa.array([round(d, 6) for d, _ in found])], ["query_id", "id", "dist2"])

    every = index.graphs.select("graph", F.explode(F.array(*[F.lit(i) for i in range(parts)])).alias("part"))
    return merge(every.repartition(index.shards * parts).mapInArrow(run, "query_id long, id long, dist2 double"), k)
