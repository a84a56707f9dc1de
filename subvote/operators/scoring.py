"""Votes of activated cells: uniform, rank-weighted, and own-cell only."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from subvote.operators.exact import BASE_ROWS, QUERY_ROWS, blocks, spread


def weights(activations: DataFrame, rank_cut: int = 0, high: int = 2, low: int = 1) -> DataFrame:
    """Adds `weight`: `high` for ranks up to the cut, else `low`; a cut of 0 is uniform."""
    return activations.withColumn("weight", F.when(F.col("rank") <= rank_cut, high).otherwise(low))


def votes(activations: DataFrame, assignments: DataFrame) -> DataFrame:
    """(query_id, id, score): weights summed over the subspaces whose activated cell holds the id.

    The activations of a batch (queries x subspaces x cells) are the small side; Spark
    broadcasts them when their size allows and sort-merges them otherwise.
    """
    hit = assignments.join(activations.select("query_id", "subspace", "cell", "weight"), ["subspace", "cell"])
    return hit.groupBy("query_id", "id").agg(F.sum("weight").cast("long").alias("score"))


def uniform(activations: DataFrame, assignments: DataFrame) -> DataFrame:
    """Every collision counts 1: the collision count, between 0 and M."""
    return votes(weights(activations), assignments)


def rank_weighted(activations: DataFrame, assignments: DataFrame, rank_cut: int) -> DataFrame:
    """Collisions in the `rank_cut` cheapest cells count 2."""
    return votes(weights(activations, rank_cut), assignments)


def own_cell(query_cells: DataFrame, assignments: DataFrame) -> DataFrame:
    """The strict reading: a vote only where the id lies in the query's own cell.

    query_cells: (query_id, subspace, cell).
    """
    return votes(weights(query_cells.withColumn("rank", F.lit(1))), assignments)


def share_of_double_votes(activations: DataFrame, rank_cut: int) -> DataFrame:
    """Per query: share of the pulled ids that carry double weight."""
    double = F.sum(F.when(F.col("rank") <= rank_cut, F.col("n")).otherwise(0))
    return activations.groupBy("query_id").agg((double / F.sum("n")).alias("double_share"), F.sum("n").alias("votes"), F.count("*").alias("cells"))


def _weight_blocks(activations: DataFrame, rank_cut: int, m: int, k2: int) -> DataFrame:
    """Rows of up to QUERY_ROWS queries: their ids and, for every cell of every subspace, the weight of its votes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo in range(0, len(batch), QUERY_ROWS):
                part = batch.slice(lo, QUERY_ROWS)
                places = part.column(1).flatten().to_numpy()
                table = np.zeros((len(part), m * k2), np.int8)
                table[np.repeat(np.arange(len(part)), part.column(1).value_lengths().to_numpy()), places // 4] = places % 4
                ids = part.column(0).to_numpy().astype("<i8")
                yield pa.RecordBatch.from_arrays([pa.array([a.tobytes()], pa.binary()) for a in (ids, table)], ["query_ids", "query_weights"])

    place = (F.col("subspace") * k2 + F.col("cell")) * 4 + F.col("weight")
    rows = weights(activations, rank_cut).groupBy("query_id").agg(F.collect_list(place.cast("int")).alias("places"))
    return rows.mapInArrow(run, "query_ids binary, query_weights binary")


def summary(activations: DataFrame, assignments: DataFrame, rank_cut: int, least: int, k: int, m: int, k2: int) -> DataFrame:
    """(query_id, passed, scored, best) of the queries with votes: ids from `least` votes on, ids with any,
    and, where fewer than k passed, the best k as structs (low, id) of minus the score and the id.

    Votes are counted in dense arrays over pairs of blocks, so no row is made of a vote or of a score.
    """
    cells = F.transform(F.sort_array(F.collect_list(F.struct("subspace", "cell"))), lambda x: x["cell"])
    return summary_of(_weight_blocks(activations, rank_cut, m, k2), assignments.groupBy("id").agg(cells.alias("cells")), least, k, m, k2)


def summary_of(tables: DataFrame, codes: DataFrame, least: int, k: int, m: int, k2: int) -> DataFrame:
    """`summary` from blocks (query_ids, query_weights) and (id, cells)."""
    base = blocks(codes.select("id", F.col("cells").cast("array<double>").alias("vec")), "base", BASE_ROWS)
    pairs = spread(base).crossJoin(F.broadcast(tables))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for raw in zip(*batch.columns, strict=True):
                names, cells, ids, table = (np.frombuffer(v.as_buffer(), t) for v, t in zip(raw, ("<i8", "<f8", "<i8", "i1"), strict=True))
                order = np.argsort(names)
                names, cells = names[order], cells.reshape(len(names), m).astype(np.int64)[order]
                table, n = table.reshape(len(ids), m * k2), len(names)
                for lo in range(0, len(ids), 64):
                    score = np.zeros((len(ids[lo : lo + 64]), n), np.int16)
                    for j in range(m):
                        score += np.take(table[lo : lo + 64], j * k2 + cells[:, j], axis=1)
                    passed, scored = (score >= least).sum(axis=1), (score > 0).sum(axis=1)
                    best, sizes = [], np.zeros(len(score), np.int32)
                    for i in np.flatnonzero(passed < k).tolist():
                        at = np.flatnonzero(score[i])
                        at = at[np.argsort(-score[i, at], kind="stable")[:k]]
                        best.append((-score[i, at].astype(np.int64), names[at]))
                        sizes[i] = len(at)
                    low, found = (np.concatenate([b[c] for b in best]) if best else np.empty(0, np.int64) for c in (0, 1))
                    offsets = pa.array(np.concatenate([[0], np.cumsum(sizes)]).astype(np.int32))
                    lists = pa.ListArray.from_arrays(offsets, pa.StructArray.from_arrays([pa.array(low), pa.array(found)], ["low", "id"]))
                    yield pa.RecordBatch.from_arrays([pa.array(ids[lo : lo + 64]), pa.array(passed), pa.array(scored), lists], ["query_id", "passed", "scored", "best"])

    parts = pairs.mapInArrow(run, "query_id long, passed long, scored long, best array<struct<low: long, id: long>>")
    per = parts.groupBy("query_id").agg(F.sum("passed").alias("passed"), F.sum("scored").alias("scored"), F.flatten(F.collect_list("best")).alias("best"))
    best = F.when(F.col("passed") < k, F.slice(F.sort_array("best"), 1, k))
    return per.filter("scored > 0").select("query_id", "passed", "scored", best.alias("best"))


def pair_scores(activations: DataFrame, assignments: DataFrame, pairs: DataFrame, rank_cut: int) -> DataFrame:
    """(query_id, id, score) of given pairs (query_id, id), 0 where no activated cell holds the id."""
    on = weights(activations, rank_cut).select("query_id", "subspace", "cell", "weight")
    held = pairs.select("query_id", "id").join(assignments, "id").join(on, ["query_id", "subspace", "cell"], "left")
    return held.groupBy("query_id", "id").agg(F.sum(F.coalesce("weight", F.lit(0))).cast("long").alias("score"))


def pair_weights(pairs: DataFrame, codes: DataFrame, tables: DataFrame, k2: int) -> DataFrame:
    """(query_id, id, subspace, weight) of given pairs (query_id, id) from (id, cells) and (query_id,
    query_weights): a row per subspace, 0 where the cell of the id is not activated."""
    held = pairs.select("query_id", "id").join(codes, "id").join(tables, "query_id")
    rows = held.select("query_id", "id", "query_weights", F.posexplode("cells").alias("subspace", "cell"))
    return rows.select("query_id", "id", "subspace", F.hex(F.expr(f"substring(query_weights, subspace * {k2} + cell + 1, 1)")).cast("int").alias("weight"))
