"""Windows with their tokens: the one place where text moves."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def windows(manifest: DataFrame, segments: DataFrame, window: int, pad: str | None = None) -> DataFrame:
    """(window_id, tokens, n_docs, n_tokens, pad): pieces in their order, cut at the window; with ``pad`` filled up to its length."""
    pieces = manifest.filter("used > 0").join(segments.select("seg_id", "doc_id", "tokens"), "seg_id")
    pieces = pieces.select("window_id", "doc_id", F.struct("pos", F.slice("tokens", F.col("start") + 1, F.col("used")).alias("t")).alias("p"))
    whole = pieces.groupBy("window_id").agg(F.flatten(F.sort_array(F.collect_list("p"))["t"]).alias("tokens"), F.count_distinct("doc_id").alias("n_docs"))
    whole = whole.withColumn("n_tokens", F.size("tokens")).withColumn("pad", F.lit(window) - F.col("n_tokens"))
    if pad is not None:
        whole = whole.withColumn("tokens", F.concat("tokens", F.array_repeat(F.lit(pad), F.col("pad"))))
    return whole.select("window_id", "tokens", "n_docs", "n_tokens", "pad")
