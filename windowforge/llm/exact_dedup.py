"""Exact deduplication on DataFrame functions alone."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import ascii_lower, fresh_name, materialize

#: Ids that are broadcast at most.
BROADCAST_IDS = 500_000


def content_hash(text: Column) -> Column:
    """128 bits of content."""
    return F.unhex(F.md5(text))


def exact_groups(
    docs: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    keep: str = "min",
    normalise: Callable[[Column], Column] = ascii_lower,
    hashed: Callable[[Column], Column] = content_hash,
) -> DataFrame:
    """One row per input row: id, keep_id, group_size, kept, text_sha256.

    Rows group by ``hashed`` of the normalised text *and* by the text itself, so that the grouping compares bytes and
    texts that merely share a hash part. The map side of that aggregation folds copies before anything is shuffled: a
    text held by a third of all rows leaves each task once. Rows then meet their group by hash and SHA-256 on narrow
    rows, in a join whose large partitions AQE splits.

    ``keep`` is "min" (smallest stable id) or "max". Null texts count as empty, empty texts are one group, repeated
    rows count each and share one fate, a row without an id is kept only where its whole group has none, an empty table
    gives an empty result, other columns are ignored.
    """
    if keep not in ("min", "max"):
        raise ValueError("keep is 'min' or 'max'")
    rows = docs.select(F.col(id_col).alias("_id"), normalise(F.col(text_col)).alias("_text"))
    best = {"min": F.min, "max": F.max}[keep]
    groups = (
        rows.groupBy(hashed(F.col("_text")).alias("_h"), "_text")
        .agg(best("_id").alias("keep_id"), F.count(F.lit(1)).alias("group_size"))
        .select("_h", F.unhex(F.sha2("_text", 256)).alias("_sha"), "keep_id", "group_size")
    )
    members = rows.select("_id", hashed(F.col("_text")).alias("_h"), F.unhex(F.sha2("_text", 256)).alias("_sha"))
    return members.join(groups, ["_h", "_sha"]).select(
        F.col("_id").alias(id_col),
        "keep_id",
        "group_size",
        F.col("_id").eqNullSafe(F.col("keep_id")).alias("kept"),
        F.lower(F.hex("_sha")).alias("text_sha256"),
    )


def exact_dedup(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: str = "min", **options) -> DataFrame:
    """The rows of ``docs`` that stay, every column as it was; of repeated rows with one id, one stays.

    A row without an id never displaces another and stays, once, only if its whole group has none. Texts move only where
    ids repeat or are missing; else the ids that go are taken out of the scan.
    """
    groups = materialize(exact_groups(docs, id_col, text_col, keep, **options), "exact-groups")
    unsure = groups.groupBy(id_col).agg(F.count(F.lit(1)).alias("rows")).filter(F.col(id_col).isNull() | (F.col("rows") > 1))
    if not unsure.isEmpty():
        return one_row_each(docs, id_col, text_col, keep, **options)
    return without(docs, groups.filter(~F.col("kept")), id_col)


def without(docs: DataFrame, gone: DataFrame, id_col: str) -> DataFrame:
    """Rows whose id is not among those that go; these are broadcast only up to a bound."""
    ids = gone.select(id_col)
    return docs.join(F.broadcast(ids) if ids.count() <= BROADCAST_IDS else ids, id_col, "left_anti").select(*docs.columns)


def one_row_each(docs: DataFrame, id_col: str, text_col: str, keep: str, normalise=ascii_lower, hashed=content_hash) -> DataFrame:
    """The row that stays of each group, by one aggregation that carries whole rows."""
    n = fresh_name(docs, "n")
    rows = docs.withColumn(n, normalise(F.col(text_col)))
    order = F.struct(F.col(id_col).isNull() if keep == "min" else F.col(id_col).isNotNull(), F.col(id_col))
    pick = {"min": F.min_by, "max": F.max_by}[keep]
    chosen = rows.groupBy(hashed(F.col(n)).alias("h"), F.col(n).alias("n")).agg(pick(F.struct(*docs.columns), order).alias("row"))
    return chosen.select(*[F.col("row").getField(c).alias(c) for c in docs.columns])
