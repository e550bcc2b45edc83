"""Streams: counts by time, late data, repeated events, frozen centres, growing centres, online packing, joins in time.

The first four also take batch frames, which is how they are checked.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from windowforge.operators import assign as A


def _marked(events: DataFrame, ts: str, late: str) -> DataFrame:
    return events.withWatermark(ts, late) if events.isStreaming else events


def tumbling(events: DataFrame, width: str = "1 hour", ts: str = "ts", late: str = "2 hours") -> DataFrame:
    """(start, event_type, events, value): by windows that do not overlap; events later than the watermark are dropped."""
    return _marked(events, ts, late).groupBy(F.window(ts, width).alias("w"), "event_type").agg(F.count(F.lit(1)).alias("events"), F.sum("value").alias("value")).select(F.col("w.start").alias("start"), "event_type", "events", "value")


def sliding(events: DataFrame, width: str = "2 hours", every: str = "1 hour", ts: str = "ts", late: str = "2 hours") -> DataFrame:
    return _marked(events, ts, late).groupBy(F.window(ts, width, every).alias("w"), "event_type").agg(F.count(F.lit(1)).alias("events")).select(F.col("w.start").alias("start"), "event_type", "events")


def sessions(events: DataFrame, gap: str = "30 minutes", ts: str = "ts", late: str = "2 hours") -> DataFrame:
    """(user_id, start, end, events): a session ends when a user is silent for ``gap``."""
    return _marked(events, ts, late).groupBy("user_id", F.session_window(ts, gap).alias("w")).agg(F.count(F.lit(1)).alias("events")).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "events")


def deduplicated(events: DataFrame, key: str = "event_id", ts: str = "ts", late: str = "2 hours") -> DataFrame:
    return events.withWatermark(ts, late).dropDuplicatesWithinWatermark([key]) if events.isStreaming else events.dropDuplicates([key])


def interval_join(left: DataFrame, right: DataFrame, key: str, within: str = "1 hour", late: str = "2 hours") -> DataFrame:
    """Rows of right (key, rts) that follow rows of left (key, lts) by at most ``within``."""
    a, b = _marked(left, "lts", late), _marked(right, "rts", late)
    return a.join(b, (a[key] == b[key]) & (b["rts"] >= a["lts"]) & (b["rts"] <= a["lts"] + F.expr(f"INTERVAL {within}"))).drop(b[key])


def assign_to(cents: DataFrame, sink: str):
    """A foreachBatch function: nearest frozen centre of each document, appended to ``sink``."""

    def run(batch: DataFrame, number: int) -> None:
        A.assign(batch, cents, "auto").withColumn("batch", F.lit(number)).write.mode("append").parquet(sink)

    return run


def update_centroids(path: str):
    """A foreachBatch function: sums and counts by cluster of the batches so far, a folder for each batch, so that a repeated batch overwrites itself.

    Rows are (cluster_id, vec). ``centroids(spark, path)`` gives the means."""
    from windowforge.operators.density import vector_sums

    def run(batch: DataFrame, number: int) -> None:
        vector_sums(batch, "cluster_id", unit=False).select("cluster_id", "vec", "n").write.mode("overwrite").parquet(f"{path}/batch={number}")

    return run


def centroids(spark, path: str) -> DataFrame:
    from windowforge.functions import vec as V
    from windowforge.operators.density import vector_sums

    rows = spark.read.parquet(path)
    sums = vector_sums(rows, "cluster_id", unit=False).select("cluster_id", "vec")
    return sums.join(rows.groupBy("cluster_id").agg(F.sum("n").alias("n")), "cluster_id").select("cluster_id", V.scale(F.col("vec"), 1 / F.col("n")).alias("vec"), "n")


def pack(segments: DataFrame, window: int, flush: str = "10 minutes") -> DataFrame:
    """Online packing: (cluster_id, window_no, seg_id, offset, used, full). State is the open window of each cluster; a segment that does not
    fit closes it, and silence for ``flush`` closes it too.

    Segments come as they arrive, not longest first, and a cluster has one open window: a weaker policy than the batch one.
    Rows are (cluster_id, seg_id, n_tokens).
    """

    def run(key, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        number, at = state.get if state.exists else (0, 0)
        out = []
        if state.hasTimedOut:
            state.update((number + 1, 0))
        else:
            for batch in batches:
                for s, n in batch[["seg_id", "n_tokens"]].itertuples(index=False):
                    if at and at + n > window:
                        number, at = number + 1, 0
                    used = min(int(n), window)
                    out.append((key[0], number, s, at, used, at + used >= window))
                    at += used
            state.update((int(number), int(at)))
            state.setTimeoutDuration(_ms(flush))
        yield pd.DataFrame(out, columns=["cluster_id", "window_no", "seg_id", "offset", "used", "full"])

    return segments.groupBy("cluster_id").applyInPandasWithState(run, "cluster_id string, window_no long, seg_id string, offset long, used long, full boolean", "number long, at long", "append", GroupStateTimeout.ProcessingTimeTimeout)


def _ms(text: str) -> int:
    number, unit = text.split()
    return int(float(number) * {"second": 1, "minute": 60, "hour": 3600}[unit.rstrip("s")] * 1000)


