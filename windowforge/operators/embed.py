"""Vectors of segments: hashed text, given vectors, or any model."""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from windowforge.functions import columns
from windowforge.session import settled, ship


def bucket(token: Column, dim: int) -> Column:
    """First seven hexadecimal digits of the MD5, modulo the dimension: the same in every engine."""
    return (F.conv(F.substring(F.md5(token), 1, 7), 16, 10).cast("long") % dim).cast("int")


def sign(token: Column) -> Column:
    return F.when(F.conv(F.substring(F.md5(token), 8, 1), 16, 10).cast("int") % 2 == 0, 1).otherwise(-1)


def hash_sparse(segments: DataFrame, dim: int = 1024, key: str = "seg_id") -> DataFrame:
    """(key, b, tf): bucket counts by expressions alone."""
    return segments.select(key, F.explode("tokens").alias("t")).groupBy(key, bucket(F.lower("t"), dim).alias("b")).agg(F.count(F.lit(1)).alias("tf"))


class _Buckets(dict):
    def __init__(self, dim: int, signed: bool):
        self.dim, self.signed = dim, signed

    def __missing__(self, token: str) -> tuple[int, float]:
        if len(self) > 300_000:
            self.clear()
        digest = hashlib.md5(token.encode()).hexdigest()
        self[token] = found = int(digest[:7], 16) % self.dim, (-1.0 if self.signed and int(digest[7], 16) % 2 else 1.0)
        return found


def _counted(tokens: pa.Array, known: _Buckets) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of a column of token lists: how many buckets each list has, these buckets, their counts. Each token is looked up once a batch."""
    words = tokens.flatten().dictionary_encode()
    found = [known[t.lower()] for t in words.dictionary.to_pylist()]
    at, sign = (np.array([f[k] for f in found], dtype=kind)[words.indices.to_numpy(zero_copy_only=False)] for k, kind in ((0, np.int64), (1, np.float64)))
    at += np.repeat(np.arange(len(tokens)) * known.dim, tokens.value_lengths().to_numpy(zero_copy_only=False))
    touched = np.flatnonzero(np.bincount(at, minlength=len(tokens) * known.dim))  # signed counts may add up to 0
    total = np.bincount(at, weights=sign, minlength=len(tokens) * known.dim)
    row, b = np.divmod(touched, known.dim)
    return np.bincount(row, minlength=len(tokens)), b, total[touched]


def hash_counts(segments: DataFrame, dim: int = 1024, signed: bool = False, key: str = "seg_id") -> DataFrame:
    """(key, b, tf): for each segment the buckets that its tokens touch, and their counts, in one pass over the text."""
    ship(segments.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = _Buckets(dim, signed)
        for batch in batches:
            for k in range(0, len(batch), 1000):
                part = batch.slice(k, 1000)
                sizes, b, tf = _counted(part.column(1), known)
                ends = pa.array(np.concatenate([[0], np.cumsum(sizes)]), pa.int32())
                yield pa.RecordBatch.from_arrays([part.column(0), *(pa.ListArray.from_arrays(ends, pa.array(x, pa.int32())) for x in (b, tf.astype(np.int32)))], names=[key, "b", "tf"])

    return segments.select(key, "tokens").mapInArrow(run, f"{key} string, b array<int>, tf array<int>")


def bucket_frequency(counted: DataFrame, dim: int = 1024) -> DataFrame:
    """(b, df) of ``hash_counts``: how many segments touch each bucket; ``dim`` rows at most. One narrow pass sums per task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(dim, dtype=np.int64)
        for batch in batches:
            total += np.bincount(batch.column(0).flatten().to_numpy(zero_copy_only=False), minlength=dim)
        hit = np.flatnonzero(total)
        yield columns.batch(b=hit, df=total[hit])

    return counted.select("b").mapInArrow(run, "b long, df long").groupBy("b").agg(F.sum("df").alias("df"))


def document_frequency(segments: DataFrame, dim: int = 1024) -> DataFrame:
    """(b, df): how many segments touch each bucket."""
    return bucket_frequency(hash_counts(segments.select(F.lit("").alias("seg_id"), "tokens"), dim), dim)


def hash_embed(segments: DataFrame, dim: int = 1024, idf: bool = True, signed: bool = False, key: str = "seg_id") -> DataFrame:
    """(key, vec array<float>): unit vectors of hashed tokens, weighted by tf and, with ``idf``, by 1 + ln((n+1)/(df+1)) of the bucket.

    The text is read once, where it lies: what is kept of it are the segments' counts by bucket, and what moves are the bucket
    frequencies, ``dim`` numbers. A segment without tokens has the zero vector.
    """
    weight, counted = np.ones(dim), hash_counts(segments, dim, signed, key)
    if idf:
        counted = settled(counted, "counts")
        n = counted.count()
        for r in bucket_frequency(counted, dim).collect():  # dim rows
            weight[r["b"]] = r["df"]
        seen = np.zeros(dim) if n == 0 else np.where(weight > 0, weight, 0)
        weight = 1 + np.log((n + 1) / (seen + 1))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(0, len(batch), 1000):
                part = batch.slice(k, 1000)
                x = np.zeros((len(part), dim))
                row = np.repeat(np.arange(len(part)), part.column(1).value_lengths().to_numpy(zero_copy_only=False))
                x[row, part.column(1).flatten().to_numpy(zero_copy_only=False)] = part.column(2).flatten().to_numpy(zero_copy_only=False)
                x *= weight
                size = np.sqrt((x * x).sum(axis=1, keepdims=True))
                x = np.divide(x, size, out=np.zeros_like(x), where=size > 0)
                yield pa.RecordBatch.from_arrays([part.column(0), columns.lists(x.astype(np.float32))], names=[key, "vec"])

    return counted.mapInArrow(run, f"{key} string, vec array<float>")


def given(segments: DataFrame, vectors: DataFrame, id_col: str = "vec_id", vec_col: str = "embedding", key: str = "seg_id") -> DataFrame:
    """(key, vec) from a table of vectors that is joined on the document's number; segments without a vector are left out."""
    return segments.select(key, "doc_id").join(vectors.select(F.col(id_col).alias("doc_id"), F.col(vec_col).alias("vec")), "doc_id").select(key, "vec")


def with_model(segments: DataFrame, model: Callable[[], Callable[[list[str]], np.ndarray]], dim: int, key: str = "seg_id") -> DataFrame:
    """(key, vec) from any function of texts; ``model`` builds it once in each worker."""
    ship(segments.sparkSession)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        embed = model()
        for batch in batches:
            x = np.asarray(embed([" ".join(t) for t in batch["tokens"]]), dtype=np.float32).reshape(len(batch), dim)
            yield pd.DataFrame({key: batch[key].to_numpy(), "vec": list(x)})

    return segments.select(key, "tokens").mapInPandas(run, f"{key} string, vec array<float>")
