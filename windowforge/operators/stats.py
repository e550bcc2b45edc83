"""Tables about clusters, paths and domains."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from windowforge.operators import assign as A


def cluster_sizes(membership: DataFrame, by: str = "cluster_id") -> DataFrame:
    return membership.groupBy(by).agg(F.count(F.lit(1)).alias("size"))


def cluster_table(sizes: DataFrame, small: int = 100) -> DataFrame:
    """One row: clusters, largest, smallest, mean, median, below ``small``, single, and the shares of the last two."""
    n = F.count(F.lit(1))
    return sizes.agg(
        n.alias("clusters"),
        F.max("size").alias("largest"),
        F.min("size").alias("smallest"),
        F.avg("size").alias("mean"),
        F.percentile("size", 0.5).alias("median"),
        F.count_if(F.col("size") < small).alias("below"),
        F.count_if(F.col("size") == 1).alias("single"),
        (F.count_if(F.col("size") < small) / n).alias("below_share"),
        (F.count_if(F.col("size") == 1) / n).alias("single_share"),
    )


def cohesion(docs: DataFrame, cents: DataFrame) -> DataFrame:
    """One row: mean cosine to the nearest centre, to the second, their gap, and a silhouette from those two. Compared with every centre, however
    many there are: a measure must not depend on which index their number calls for."""
    near = A.assign(docs, cents, "exact")
    a, b = 1 - F.col("cos"), 1 - F.col("second")
    return near.agg(F.avg("cos").alias("own"), F.avg("second").alias("second"), F.avg(F.col("cos") - F.col("second")).alias("gap"), F.avg(F.when(F.greatest(a, b) > 0, (b - a) / F.greatest(a, b)).otherwise(0.0)).alias("silhouette"))


def isolation(sizes: DataFrame, manifest: DataFrame, membership: DataFrame, by: str = "cluster_id") -> DataFrame:
    """One row: share of clusters or paths of one document, share of documents in them, share of windows that mix several."""
    one = sizes.agg(F.avg((F.col("size") == 1).cast("double")).alias("single_clusters"), (F.sum((F.col("size") == 1).cast("long")) / F.sum("size")).alias("single_documents"))
    mixed = manifest.select("window_id", "seg_id").join(membership.select("seg_id", F.col(by).alias("g")), "seg_id").groupBy("window_id").agg((F.min("g") < F.max("g")).cast("double").alias("mixed"))
    return one.crossJoin(mixed.agg(F.avg("mixed").alias("mixed_windows")))


def domain_stats(rows: DataFrame, domain: str, tokens: str = "n_tokens") -> DataFrame:
    return rows.groupBy(F.col(domain).alias("domain")).agg(F.max(tokens).cast("long").alias("max_len"), F.min(tokens).cast("long").alias("min_len"), F.avg(tokens).alias("avg_len"), F.count(F.lit(1)).alias("documents"), F.sum(tokens).cast("long").alias("tokens"))


def interval(tokens: Column, edges: list[int]) -> Column:
    """Name of the length interval; a length equal to an edge belongs to the interval above."""
    out = F.when(tokens < edges[0], f"<{edges[0]}")
    for low, high in zip(edges, edges[1:]):
        out = out.when(tokens < high, f"{low}-{high}")
    return out.otherwise(f">={edges[-1]}")


def length_mix(rows: DataFrame, domain: str, edges: list[int], tokens: str = "n_tokens") -> DataFrame:
    """(domain, interval, documents, share of the domain's documents, share of its longest interval)."""
    per = rows.groupBy(F.col(domain).alias("domain"), interval(F.col(tokens), edges).alias("interval")).agg(F.count(F.lit(1)).alias("documents"))
    of = Window.partitionBy("domain")
    share = F.col("documents") / F.sum("documents").over(of)
    top = F.sum(F.when(F.col("interval") == f">={edges[-1]}", F.col("documents")).otherwise(0)).over(of) / F.sum("documents").over(of)
    return per.select("domain", "interval", "documents", share.alias("share"), top.alias("longest_share"))


def domain_share(rows: DataFrame, domain: str, tokens: str = "n_tokens") -> DataFrame:
    per = rows.groupBy(F.col(domain).alias("domain")).agg(F.sum(tokens).cast("long").alias("tokens"))
    whole = per.agg(F.sum("tokens").alias("whole"))
    return per.crossJoin(F.broadcast(whole)).select("domain", "tokens", (F.col("tokens") / F.col("whole")).alias("share"))
