"""Mixing sources to target weights by hash-random order and distributed prefix sums.

Every row gets a random key from the md5 of its id, rows are range-sorted by (source,
key), each task keeps a running size per source, a small prefix over the tasks' sums gives
every task its start, and the running size decides which rows fall within the budget.

Defined cases: null text has size 0; a null source is a source of its own, last in
order; rows of one id (or of none) are ordered by the digest of their text, so that they
spread over ranges too; repeated rows each count and each have their own share; an empty
table gives no rows; a source without words has target 0; other columns are ignored by
`mix` and carried along, whatever their names, by `apply_mix`.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StructField, StructType

from subvote.llm._store import materialize, text_tag, whole_row
from subvote.llm._worker import tidied

WORD = "[^\\x20\\x09-\\x0D]+"


def n_words(text: Column) -> Column:
    """Number of words, counted by their first characters without building them."""
    spaced = F.concat(F.lit(" "), F.coalesce(text, F.lit("")))
    return F.regexp_count(spaced, F.lit("[\\x20\\x09-\\x0D][^\\x20\\x09-\\x0D]")).cast("long")


def targets(sizes: DataFrame, weights: Sequence[float], share: float, max_epochs: float) -> DataFrame:
    """(source, source_size) -> target: a share of all sizes by weight, capped per source.

    What a cap cuts off goes to the others by weight, until no target is above its cap.
    The fixed point fills sources in order of cap over weight: with the first j capped,
    the others get weight times (budget left) / (weight left); j is the smallest number
    for which that level is at most the cap over weight of the next source.
    """
    w = F.element_at(F.array(*[F.lit(float(x)) for x in weights]), (F.pmod(F.col("_i") - 1, F.lit(len(weights))) + 1).cast("int"))
    order = Window.orderBy(F.col("source").asc_nulls_last())
    ranked = sizes.withColumn("_i", F.row_number().over(order)).withColumn("_w", w)
    ranked = ranked.withColumn("_cap", F.col("source_size") * F.lit(float(max_epochs)))
    fill = Window.orderBy(F.col("_cap") / F.col("_w"), "_i")
    before, everything = fill.rowsBetween(Window.unboundedPreceding, -1), Window.orderBy(F.lit(1)).rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    ranked = (
        ranked.withColumn("_budget", F.sum("source_size").over(everything) * F.lit(float(share)))
        .withColumn("_level", (F.col("_budget") - F.coalesce(F.sum("_cap").over(before), F.lit(0.0))) / (F.sum("_w").over(everything) - F.coalesce(F.sum("_w").over(before), F.lit(0.0))))
        .withColumn("_open", F.col("_level") <= F.col("_cap") / F.col("_w"))
    )
    level = F.first(F.when(F.col("_open"), F.col("_level")), ignorenulls=True).over(fill.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
    return ranked.withColumn("_final", level).select(
        "source", "source_size", F.least(F.col("_cap"), F.coalesce(F.col("_w") * F.col("_final"), F.col("_cap"))).alias("target")
    )


def mix(
    docs: DataFrame,
    weights: Sequence[float] = (3.0, 1.0, 2.0),
    share: float = 1.5,
    max_epochs: float = 2.0,
    id_col: str = "doc_id",
    source_col: str = "source",
    text_col: str = "text",
) -> DataFrame:
    """One row per input row: id, size, source, source_size, target, taken.

    `taken` counts the words the mix takes of the row over all epochs; the row that
    crosses the budget of its source is taken in part, so budgets are met to the word.
    """
    rows = _sized(docs, id_col, source_col, text_col)
    return _plan(rows, weights, share, max_epochs).select(F.col("_id").alias(id_col), "size", "source", "source_size", "target", "taken")


def _sized(docs: DataFrame, id_col: str, source_col: str, text_col: str, *more: Column) -> DataFrame:
    key = F.md5(F.coalesce(F.col(id_col).cast("string"), F.lit("")).cast("binary"))
    text = F.col(text_col)
    return docs.select(
        F.col(id_col).alias("_id"), F.col(source_col).alias("source"), n_words(text).alias("size"), key.alias("_key"),
        text_tag(text).alias("_tag"), F.col(source_col).isNull().alias("_none"), *more,
    )


def _edges(column: pa.Array) -> list[int]:
    """Rows at which a sorted column takes another value, the first row included."""
    if len(column) < 2:
        return list(range(len(column)))
    left, right = column.slice(0, len(column) - 1), column.slice(1)
    same = pc.or_(pc.fill_null(pc.equal(left, right), False), pc.and_(pc.is_null(left), pc.is_null(right)))
    return [0, *(np.flatnonzero(~same.to_numpy(zero_copy_only=False)) + 1).tolist()]


def _plan(rows: DataFrame, weights: Sequence[float], share: float, max_epochs: float) -> DataFrame:
    """Adds source_size, target, taken to sized rows."""
    # Ranges are cut by (source, key, text); sources and ids with many rows span many tasks.
    order = ("_none", "source", "_key", "_tag")
    ranged = rows.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("_part", F.spark_partition_id())
    schema = StructType([*ranged.schema.fields, StructField("_before", LongType())])
    source, size = ranged.columns.index("source"), ranged.columns.index("size")

    @tidied
    def running(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Adds the size of all rows of the same source that come before in the task."""
        name, total = None, 0
        for batch in batches:
            if not len(batch):
                continue
            found, sizes = batch.column(source), batch.column(size).to_numpy()
            ends = np.cumsum(sizes)
            edges = _edges(found)
            before = ends - sizes
            for lo, hi in zip(edges, [*edges[1:], len(batch)], strict=True):
                here = found[lo].as_py()
                total = total if lo == 0 and here == name else 0
                before[lo:hi] += total - before[lo]
                name, total = here, int(before[hi - 1] + sizes[hi - 1])
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(before)], schema.names)

    dealt = materialize(ranged.mapInArrow(running, schema), "mix-rows")
    sums = dealt.groupBy("source", "_part").agg(F.sum("size").alias("_sum"))
    sums = materialize(sums.coalesce(1), "mix-sums")
    goal = targets(sums.groupBy("source").agg(F.sum("_sum").alias("source_size")), weights, share, max_epochs)
    starts = sums.withColumn(
        "_start",
        F.coalesce(F.sum("_sum").over(Window.partitionBy("source").orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)),
    ).select(F.col("source").alias("_s"), F.col("_part").alias("_p"), "_start")
    goal = goal.withColumnRenamed("source", "_g")
    plan = starts.join(goal, F.col("_s").eqNullSafe(F.col("_g"))).drop("_g")
    out = dealt.join(plan, F.col("source").eqNullSafe(F.col("_s")) & (F.col("_part") == F.col("_p")))
    goal_words = F.floor(F.col("target")).cast("long")
    epochs = F.when(F.col("source_size") > 0, F.floor(goal_words / F.col("source_size"))).otherwise(0).cast("long")
    left = goal_words - epochs * F.col("source_size")
    part = F.greatest(F.lit(0).cast("long"), F.least(F.col("size"), left - (F.col("_start") + F.col("_before"))))
    return out.withColumn("taken", epochs * F.col("size") + part)


def apply_mix(
    docs: DataFrame,
    weights: Sequence[float] = (3.0, 1.0, 2.0),
    share: float = 1.5,
    max_epochs: float = 2.0,
    id_col: str = "doc_id",
    source_col: str = "source",
    text_col: str = "text",
    epoch_col: str | None = None,
) -> DataFrame:
    """The mixture as rows of `docs`: a row repeats once per epoch that takes it.

    Whole rows travel with the plan, so every row is taken as planned even where ids repeat.
    Where a budget ends inside a document, the last copy is the text up to the last word
    taken, as it stands.  `epoch_col` names a column for the number of the copy, from 1.
    """
    plan = _plan(_sized(docs, id_col, source_col, text_col, whole_row()), weights, share, max_epochs)
    whole = F.when(F.col("size") > 0, F.floor(F.col("taken") / F.col("size"))).otherwise(0)
    rest = F.when(F.col("size") > 0, F.col("taken") % F.col("size")).otherwise(0).cast("int")
    copies = (whole + F.when(rest > 0, 1).otherwise(0)).cast("int")
    rows = plan.select("row", whole.alias("_whole"), rest.alias("_rest"), copies.alias("_copies")).filter("_copies > 0")
    rows = rows.withColumn("_copy", F.explode(F.sequence(F.lit(1), F.col("_copies"))))
    text = F.col("row").getField(text_col)
    # Pieces of white space and one word each, in order: a prefix of them is a prefix of the text.
    cut = F.array_join(F.slice(F.split(text, "(?<=[^\\x20\\x09-\\x0D])(?=[\\x20\\x09-\\x0D])"), 1, F.col("_rest")), "")
    taken = F.when(F.col("_copy") > F.col("_whole"), cut).otherwise(text)
    columns = [taken.alias(c) if c == text_col else F.col("row").getField(c).alias(c) for c in docs.columns]
    return rows.select(*columns, *([F.col("_copy").alias(epoch_col)] if epoch_col else []))
