"""Exact deduplication by 128-bit content hash with byte comparison inside groups.

Only the documents of groups with two or more rows have their bytes compared, each
against the row of its group that stays; rows that differ from it (a hash collision) are
grouped once more by the whole normalised text.

Defined cases: null text counts as empty; empty texts equal each other; a null id sorts
before all ids; rows repeated with one id and one text are copies of each other, count
in `group_size` and carry the same `kept` (`kept_rows` returns one of them); an empty
table gives an empty result; other columns are ignored by `groups` and returned as they
are by `kept_rows`.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from subvote.llm._store import materialize, whole_row

SPACE = "[\\x20\\x09-\\x0D]"


def normalized(text: Column) -> Column:
    return F.regexp_replace(F.coalesce(text, F.lit("")), SPACE + "+", "")


def _winner(rows: DataFrame, key: list[str]) -> DataFrame:
    """Per key: the staying row (most code points, then smallest id), size, rows tied with it."""
    tied = rows.groupBy(*key, "_chars", "_id").agg(F.count("*").alias("_n"))
    return tied.groupBy(*key).agg(
        F.min(F.struct((-F.col("_chars")).alias("c"), F.col("_id").alias("id"), F.col("_n").alias("n"))).alias("_best"),
        F.sum("_n").alias("_size"),
    )


def groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", hash_of=F.md5) -> DataFrame:
    """One row per input row: id, keep_id, group_size, kept, text_sha256, n_code_points, n_tied.

    `hash_of` maps the normalised text to the 128-bit hash; tests pass a colliding one.
    """
    text = F.coalesce(F.col(text_col), F.lit(""))
    base = docs.select(
        F.col(id_col).alias("_id"), F.length(text).cast("long").alias("_chars"), normalized(F.col(text_col)).alias("_norm")
    ).withColumn("_h", F.unhex(hash_of(F.encode("_norm", "utf-8"))))
    keys = materialize(
        base.select("_id", "_chars", "_h", F.sha2(F.encode("_norm", "utf-8"), 256).alias("_sha")), "dedup-keys"
    )
    found = _winner(keys, ["_h"])
    several = materialize(found.filter("_size > 1").select("_h", "_best", "_size"), "dedup-groups")

    members = materialize(base.join(several.hint("merge"), "_h").select("_h", "_id", "_chars", "_norm", "_best"), "dedup-members")
    stays = members.filter((F.col("_id").eqNullSafe(F.col("_best.id"))) & (F.col("_chars") == -F.col("_best.c")))
    reference = materialize(stays.groupBy("_h").agg(F.min("_norm").alias("_ref")), "dedup-references")
    differs = materialize(
        members.join(reference.hint("merge"), "_h").filter(F.col("_norm") != F.col("_ref")).select("_h", "_id", "_chars", "_norm"),
        "dedup-collisions",
    )
    if differs.isEmpty():
        out = keys.join(several.select("_h", "_best", "_size"), "_h", "left")
        best = F.coalesce("_best", F.struct((-F.col("_chars")).alias("c"), F.col("_id").alias("id"), F.lit(1).cast("long").alias("n")))
        return _decide(out.withColumn("_best", best).withColumn("_size", F.coalesce("_size", F.lit(1).cast("long"))), id_col)
    # Some texts share a hash: in those groups the whole text is the key.
    clash = differs.select("_h").distinct()
    whole = members.join(clash, "_h", "left_semi").withColumn("_sha", F.sha2(F.encode("_norm", "utf-8"), 256))
    exact = whole.drop("_best").join(_winner(whole, ["_norm"]), "_norm")
    rest = keys.join(clash, "_h", "left_anti")
    rest = rest.join(_winner(rest, ["_h"]), "_h")
    columns = ["_id", "_chars", "_sha", "_best", "_size"]
    return _decide(exact.select(columns).unionByName(rest.select(columns)), id_col)


def _decide(rows: DataFrame, id_col: str) -> DataFrame:
    kept = F.col("_id").eqNullSafe(F.col("_best.id")) & (F.col("_chars") == -F.col("_best.c"))
    return rows.select(
        F.col("_id").alias(id_col), F.col("_best.id").alias("keep_id"), F.col("_size").alias("group_size"),
        kept.alias("kept"), F.col("_sha").alias("text_sha256"), F.col("_chars").alias("n_code_points"), F.col("_best.n").alias("n_tied"),
    )


def kept_rows(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of `docs` that stay, with all their columns.

    Rows are matched by id, text digest and length, so ids that repeat with different texts
    are judged apart; of rows that repeat in all three, one stays.
    """
    keep = groups(docs, id_col, text_col).filter("kept").select(
        F.col(id_col).alias("k_id"), F.col("text_sha256").alias("k_sha"), F.col("n_code_points").alias("k_chars"), F.col("n_tied").alias("k_tied")
    ).dropDuplicates(["k_id", "k_sha"])
    own = docs.select(
        whole_row(), F.col(id_col).alias("id"), F.sha2(F.encode(normalized(F.col(text_col)), "utf-8"), 256).alias("sha"),
        F.length(F.coalesce(F.col(text_col), F.lit(""))).alias("chars"),
    )
    rows = own.join(keep, F.col("id").eqNullSafe(F.col("k_id")) & (F.col("sha") == F.col("k_sha")) & (F.col("chars") == F.col("k_chars")))
    once = rows.filter("k_tied = 1").select("row")
    repeated = rows.filter("k_tied > 1").dropDuplicates(["k_id", "k_sha"]).select("row")
    return once.unionByName(repeated).select("row.*")
