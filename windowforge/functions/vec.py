"""Vector algebra as expressions. Sums run in double; a zero vector has cosine 0 with everything."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def norm(a: Column) -> Column:
    return F.sqrt(dot(a, a))


def cosine(a: Column, b: Column) -> Column:
    size = norm(a) * norm(b)
    return F.when(size > 0, dot(a, b) / size).otherwise(0.0)


def normalize(a: Column) -> Column:
    size = norm(a)
    return F.transform(a, lambda x: F.when(size > 0, x.cast("double") / size).otherwise(0.0))


def scale(a: Column, by: Column) -> Column:
    return F.transform(a, lambda x: x.cast("double") * by)


def sum_native(df: DataFrame, by: list[str], vec: str = "vec") -> DataFrame:
    """(by..., vec, n): vector sums by expressions alone; one row per group and coordinate is shuffled."""
    long = df.select(*by, F.posexplode(vec).alias("at", "x")).groupBy(*by, "at").agg(F.sum(F.col("x").cast("double")).alias("x"), F.count(F.lit(1)).alias("n"))
    return long.groupBy(*by).agg(F.sort_array(F.collect_list(F.struct("at", "x"))).alias("v"), F.max("n").alias("n")).select(*by, F.col("v.x").alias("vec"), "n")
