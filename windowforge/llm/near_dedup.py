"""One document of each group of near copies."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialize
from .exact_dedup import without
from .jaccard import jaccard_groups


def near_dedup(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """The rows whose id is the smallest of its group, every column as it was. Documents without words stay, rows without an id too;
    rows that repeat an id stay or go together. Very long texts are compared whole. An empty table stays empty, and columns of any name
    stay as they are."""
    groups = materialize(jaccard_groups(docs, id_col, text_col, **options), "near-groups")
    return without(docs, groups.filter(F.col(id_col) != F.col("component_id")), id_col)
