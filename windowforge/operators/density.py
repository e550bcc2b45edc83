"""How many clusters to begin with, from the density of subsets. No pair is ever formed: for unit vectors the sum of all
ordered cosines is the squared length of their sum less their number."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from windowforge.functions import columns
from windowforge.functions import vec as V
from windowforge.session import settled, ship

#: Sums of a group between its tasks and its total.
MIDDLE = 256
#: Bytes of sums that a task holds before it passes them on.
SUM_BYTES = 64 << 20
#: Bytes of vectors in a block that meets others of its subset.
PAIR_BYTES = 2 << 20


def split(df: DataFrame, n_subsets: int, seed: int = 7, key: str = "seg_id") -> DataFrame:
    """Adds subset_id: near-equal subsets that cover the corpus, drawn by hash."""
    return df.withColumn("subset_id", subset(F.col(key), n_subsets, seed))


def subset(key: Column, n_subsets: int, seed: int) -> Column:
    return (F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}:"), key.cast("string"))), 1, 7), 16, 10).cast("long") % n_subsets).cast("int")


def vector_sums(df: DataFrame, by: str, vec: str = "vec", unit: bool = True) -> DataFrame:
    """(by, vec, n, nonzero): vector sums by group. Each task sums what it holds first, so a group sends one row per task; these are
    added in two steps, so that no row ever gathers more than a MIDDLE-th of them, or MIDDLE."""
    ship(df.sparkSession)
    kind = df.schema[by].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        place: dict = {}
        sums, n, nonzero = np.zeros((0, 0)), np.zeros(0, dtype=np.int64), np.zeros(0, dtype=np.int64)

        def out() -> pa.RecordBatch:
            k = len(place)
            return columns.batch(g=pa.array(list(place), own), vec=columns.lists(sums[:k]), n=n[:k], nonzero=nonzero[:k])

        for batch in batches:
            own = batch.column(0).type
            for b in range(0, len(batch), 1000):
                part = batch.slice(b, 1000)
                codes = part.column(0).dictionary_encode()
                known = codes.indices.is_valid().to_numpy(zero_copy_only=False)  # rows without a group are in none
                x = columns.matrix(part.column(1)).astype(np.float64)[known]
                if not len(x):
                    continue
                if unit:
                    size = np.sqrt((x * x).sum(axis=1, keepdims=True))
                    x = np.divide(x, size, out=np.zeros_like(x), where=size > 0)
                names = codes.dictionary.to_pylist()
                if len(place) and sum(g not in place for g in names) + len(place) > max(1, SUM_BYTES // (8 * x.shape[1] or 1)):
                    yield out()
                    place = {}
                    sums, n, nonzero = np.zeros((0, 0)), np.zeros(0, dtype=np.int64), np.zeros(0, dtype=np.int64)
                at = np.array([place.setdefault(g, len(place)) for g in names], dtype=np.int64)[codes.indices.drop_null().to_numpy()]
                if len(place) > len(sums):
                    more = max(64, 2 * len(place)) - len(sums)
                    sums = np.concatenate([sums.reshape(len(sums), x.shape[1]), np.zeros((more, x.shape[1]))])
                    n, nonzero = (np.concatenate([c, np.zeros(more, dtype=np.int64)]) for c in (n, nonzero))
                order = np.argsort(at, kind="stable")
                groups, begin = np.unique(at[order], return_index=True)
                sums[groups] += np.add.reduceat(x[order], begin, axis=0) if len(groups) < len(order) else x[order]
                n += np.bincount(at, minlength=len(n))
                nonzero += np.bincount(at[(x != 0).any(axis=1)], minlength=len(n))
        if place:
            yield out()

    part = df.select(F.col(by).alias("g"), F.col(vec).alias("v")).mapInArrow(run, f"g {kind}, vec array<double>, n long, nonzero long")
    add = lambda a, x: F.when(F.size(a) == 0, x).otherwise(F.zip_with(a, x, lambda p, q: p + q))
    total = F.aggregate(F.collect_list("vec"), F.array().cast("array<double>"), add)
    middle = part.withColumn("_m", F.spark_partition_id() % MIDDLE).groupBy("g", "_m").agg(total.alias("vec"), F.sum("n").alias("n"), F.sum("nonzero").alias("nonzero"))
    return middle.groupBy("g").agg(total.alias("vec"), F.sum("n").alias("n"), F.sum("nonzero").alias("nonzero")).withColumnRenamed("g", by)


def rho(pair_sum: Column, m: Column, mode: str) -> Column:
    """From the sum over ordered pairs of m documents: twice the mean as printed, the mean, or 1 less the mean. Fewer than two documents have density 0."""
    mean = F.when(m > 1, pair_sum / (m * (m - 1))).otherwise(0.0)
    if mode == "printed":
        return 2 * mean
    return mean if mode == "mean_cosine" else F.when(m > 1, 1 - mean).otherwise(0.0)


def subset_density(df: DataFrame, mode: str = "mean_cosine", vec: str = "vec") -> DataFrame:
    """(subset_id, m, rho) of rows with subset_id and a vector."""
    sums = vector_sums(df, "subset_id", vec)
    return sums.select("subset_id", F.col("n").alias("m"), rho(V.dot(F.col("vec"), F.col("vec")) - F.col("nonzero"), F.col("n"), mode).alias("rho"))


def subset_density_pairs(df: DataFrame, mode: str = "mean_cosine", vec: str = "vec", key: str = "seg_id") -> DataFrame:
    """The same from all pairs of each subset, as the check of the fast form: blocks of vectors lie in files and meet as products of
    matrices, so that a row moves for each pair of blocks. Vectors that are null, hold null or have another length than their partner
    give pairs without a cosine, which are left out of the sum."""
    ship(df.sparkSession)
    kind, files = df.schema["subset_id"].dataType.simpleString(), max(1, math.ceil(math.sqrt(4 * df.sparkSession.sparkContext.defaultParallelism)))

    def packed(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held: dict = {}

        def out(at: tuple) -> pd.DataFrame:
            x = np.stack(held.pop(at))
            return pd.DataFrame({"subset_id": [at[0]], "width": [at[1]], "x": [x.tobytes()]})

        for batch in batches:
            for subset_id, v in zip(batch["subset_id"].tolist(), batch["v"]):
                at = subset_id, len(v)
                held.setdefault(at, []).append(np.asarray(v, dtype=np.float64))
                if len(held[at]) * max(len(v), 1) * 8 >= PAIR_BYTES:
                    yield out(at)
        for at in list(held):
            yield out(at)

    def met(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for subset_id, width, place, x, other, y in batch.itertuples(index=False):
                a, b = (units(np.frombuffer(z, dtype=np.float64).reshape(-1, width)) if width else np.zeros((0, 0)) for z in (x, y))
                cos = [float((np.triu(c, 1 + k) if place == other else c).sum()) for k in range(0, len(a), 512) for c in (a[k : k + 512] @ b.T,)]
                yield pd.DataFrame({"subset_id": [subset_id], "s": [2 * sum(cos)]})

    whole = df.filter(F.col(vec).isNotNull() & ~F.exists(vec, lambda v: v.isNull())).select("subset_id", F.col(vec).alias("v"), key)
    dealt = whole.repartition(files, key).select("subset_id", "v").mapInPandas(packed, f"subset_id {kind}, width int, x binary")
    held = settled(dealt.withColumn("place", F.monotonically_increasing_id()), "pair-blocks")
    other = held.select(F.col("subset_id").alias("_s"), F.col("width").alias("_w"), F.col("place").alias("other"), F.col("x").alias("y"))
    same = F.col("subset_id").between(F.col("_s"), F.col("_s")) & F.col("width").between(F.col("_w"), F.col("_w"))  # no key: a shuffle by it would leave a subset to one task
    both = held.join(other, same & (F.col("place") <= F.col("other"))).select("subset_id", "width", "place", "x", "other", "y")
    pairs = both.mapInPandas(met, f"subset_id {kind}, s double").groupBy("subset_id").agg(F.sum("s").alias("s"))
    sizes = df.groupBy("subset_id").agg(F.count(F.lit(1)).alias("m"))
    return sizes.join(pairs, "subset_id", "left").select("subset_id", "m", rho(F.coalesce("s", F.lit(0.0)), F.col("m"), mode).alias("rho"))


def units(x: np.ndarray) -> np.ndarray:
    """Rows of length 1; those of length 0 stay, and what isn't a number stays one."""
    size = np.sqrt((x * x).sum(axis=1, keepdims=True))
    return np.divide(x, size, out=np.zeros_like(x), where=size != 0)


def initial_clusters(df: DataFrame, n_subsets: int = 10, mode: str = "mean_cosine", seed: int = 7, vec: str = "vec", key: str = "seg_id") -> DataFrame:
    """One row: documents, mean_rho, raw (size times mean density, rounded down), n_clusters (raw brought into 1 .. documents)."""
    per = subset_density(split(df, n_subsets, seed, key), mode, vec)
    whole = per.agg(F.coalesce(F.sum("m"), F.lit(0)).alias("documents"), F.coalesce(F.avg("rho"), F.lit(0.0)).alias("mean_rho"))
    raw = F.floor(F.round(F.col("documents") * F.col("mean_rho"), 9))
    return whole.withColumn("raw", raw).withColumn("n_clusters", F.greatest(F.lit(1), F.least("raw", "documents")).cast("long"))
