"""What windows are worth: relevance, homogeneity, penalty, and the counts beside them. Each is one aggregation by window."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from windowforge.functions import vec as V
from windowforge.operators.density import vector_sums


def by_document(manifest: DataFrame, segments: DataFrame, vecs: DataFrame) -> DataFrame:
    """(window_id, doc_id, vec): each document of a window once, by its first segment there, so that a document is no pair with itself."""
    rows = manifest.join(segments.select("seg_id", "doc_id", "seg_no"), "seg_id").join(vecs.select("seg_id", "vec"), "seg_id")
    return rows.groupBy("window_id", "doc_id").agg(F.min_by("vec", F.struct("seg_no", "start")).alias("vec"))


def relevance(rows: DataFrame, pairs: str = "ordered") -> DataFrame:
    """(window_id, docs, relevance): cosines summed over the pairs of a window, without forming one. Rows are (window_id, vec)."""
    sums = vector_sums(rows, "window_id")
    whole = V.dot(F.col("vec"), F.col("vec")) - F.col("nonzero")
    return sums.select("window_id", F.col("n").alias("docs"), (whole if pairs == "ordered" else whole / 2).alias("relevance"))


def mean_cosine(rel: DataFrame) -> DataFrame:
    """One row: window_mean over windows of two or more documents, pair_mean over all pairs."""
    many = rel.filter("docs > 1")
    return many.agg(F.avg(F.col("relevance") / (F.col("docs") * (F.col("docs") - 1))).alias("window_mean"), (F.sum("relevance") / F.sum(F.col("docs") * (F.col("docs") - 1))).alias("pair_mean"))


def per_window(manifest: DataFrame, window: int) -> DataFrame:
    """(window_id, members, used, total, over, squares): counts that the measures below are sums of."""
    return manifest.groupBy("window_id").agg(
        F.count(F.lit(1)).alias("members"),
        F.sum("used").cast("long").alias("used"),
        (F.sum("used") + F.sum("cut")).cast("long").alias("total"),
        F.greatest(F.sum("used") + F.sum("cut") - window, F.lit(0)).cast("long").alias("over"),
        F.sum(F.col("used") * (F.col("used") + 1)).cast("long").alias("squares"),
    )


def homogeneity(w: DataFrame, window: int) -> DataFrame:
    """Sum of L over the number of members; empty windows do not count."""
    return w.agg(F.sum(F.lit(float(window)) / F.col("members")).alias("homogeneity"))


def penalty_of(w: DataFrame, window: int, mode: str = "printed") -> DataFrame:
    """"printed": 1 if all fits into one window, else L / number of members - 1, over the whole manifest. "per_window_length": by window, 1 or L / length - 1."""
    if mode == "printed":
        return w.agg(F.when(F.coalesce(F.sum("total"), F.lit(0)) <= window, 1.0).otherwise(F.lit(float(window)) / F.sum("members") - 1).alias("penalty"))
    return w.agg(F.sum(F.when(F.col("total") <= window, 1.0).otherwise(F.lit(float(window)) / F.col("total") - 1)).alias("penalty"))


def violations(w: DataFrame, window: int, eps: int = 0) -> DataFrame:
    """Windows whose segments exceed the capacity by more than ``eps`` tokens before they are cut."""
    return w.filter(F.col("total") > window + eps).select("window_id", "total", (F.col("total") - window).alias("excess"))


def scalarise(df: DataFrame, weights: dict[str, float], name: str = "objective") -> DataFrame:
    """Adds the weighted sum of columns; weights are not negative."""
    if min(weights.values(), default=0) < 0:
        raise ValueError("weights are not negative")
    whole: Column = F.lit(0.0)
    for column, weight in weights.items():
        whole = whole + weight * F.col(column)
    return df.withColumn(name, whole)


def counts(w: DataFrame, window: int) -> DataFrame:
    """One row of the measures that need no vectors."""
    s = F.col("used").cast("double")
    share = F.when(s > 0, 1 - F.col("squares") / (s * (s + 1))).otherwise(0.0)
    return w.agg(
        F.count(F.lit(1)).alias("windows"),
        F.avg("members").alias("members"),
        F.max("members").alias("most_members"),
        F.avg((F.col("members") == 1).cast("double")).alias("single_share"),
        (F.sum("used") / (F.lit(float(window)) * F.count(F.lit(1)))).alias("fill"),
        F.avg(share).alias("cross_attention"),
        F.sum("over").alias("cut_tokens"),
        (F.sum("over") / F.greatest(F.sum("total"), F.lit(1))).alias("cut_share"),
        F.sum((F.col("over") > 0).cast("long")).alias("violating"),
        F.max("over").alias("worst_excess"),
        F.sum(F.lit(float(window)) / F.col("members")).alias("homogeneity"),
        (F.count(F.lit(1)) * float(window) * window).alias("attention_padded"),
        F.sum(s * (s + 1) / 2).alias("attention_causal"),
        F.sum((s * (s + 1) - F.col("squares")) / 2).alias("attention_across"),
    )


def documents_cut(manifest: DataFrame, segments: DataFrame) -> DataFrame:
    """One row: documents that lost tokens, documents in more than one window."""
    per = manifest.join(segments.select("seg_id", "doc_id"), "seg_id").groupBy("doc_id").agg(F.max((F.col("cut") > 0).cast("int")).alias("cut"), F.count_distinct("window_id").alias("w"))
    return per.agg(F.sum("cut").cast("long").alias("documents_cut"), F.sum((F.col("w") > 1).cast("long")).alias("documents_split"))


def report(manifest: DataFrame, segments: DataFrame, vecs: DataFrame, window: int, method: str) -> DataFrame:
    """One row of all measures of a method."""
    w = per_window(manifest, window)
    rel = relevance(by_document(manifest, segments, vecs))
    return (
        counts(w, window)
        .crossJoin(mean_cosine(rel))
        .crossJoin(rel.agg(F.sum("relevance").alias("relevance")))
        .crossJoin(penalty_of(w, window, "per_window_length"))
        .crossJoin(documents_cut(manifest, segments))
        .select(F.lit(method).alias("method"), F.lit(window).alias("window"), "*")
    )
