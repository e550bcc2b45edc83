"""Sums over a global order without a single task that sees all rows."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from windowforge.session import settled

#: Ranges at least; as many as the session shuffles into where that is more, so that they grow with the cluster.
PARTS = 64


def running(df: DataFrame, order: Column, value: str, ties: list[str], parts: int | None = None) -> DataFrame:
    """Adds ``before``: the sum of ``value`` over all rows that come earlier by (order, ties).

    Rows are dealt by ranges of the order, sums run inside each, and the totals of the ranges, a row each, are added up and
    joined back by broadcast (``parts`` rows at most).
    """
    parts = parts or max(PARTS, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    dealt = df.withColumn("_order", order).repartitionByRange(parts, "_order", *ties).withColumn("_part", F.spark_partition_id())
    dealt = settled(dealt, "dealt")
    inside = Window.partitionBy("_part").orderBy("_order", *ties).rowsBetween(Window.unboundedPreceding, -1)
    totals = dealt.groupBy("_part").agg(F.sum(value).alias("_total"))
    lead = totals.select("_part", F.coalesce(F.sum("_total").over(Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("_lead"))  # parts rows
    return dealt.join(F.broadcast(lead), "_part").withColumn("before", (F.coalesce(F.sum(value).over(inside), F.lit(0)) + F.col("_lead")).cast("long")).drop("_part", "_lead", "_order")
