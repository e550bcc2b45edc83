"""Learning rate by step, and windows dealt to steps of constant tokens."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from windowforge.operators.prefix import running


def learning_rate(step: Column, total: int, warmup: int = 1000, peak: float = 3e-4, final: float = 0.0) -> Column:
    """Linear up to the peak at ``warmup``, then half a cosine down to ``final`` at ``total``."""
    share = F.least(F.greatest((step - warmup) / F.lit(max(total - warmup, 1)), F.lit(0.0)), F.lit(1.0))
    return F.when(step < warmup, step * (peak / warmup)).otherwise(final + (peak - final) * 0.5 * (1 + F.cos(F.pi() * share)))


def batch(windows: DataFrame, window: int, tokens_per_step: int, seed: int = 7, key: str = "window_id") -> DataFrame:
    """Adds ``step``: windows in an order drawn by hash, tokens_per_step // window of them in each step, the last step maybe fewer."""
    each = max(1, tokens_per_step // window)
    placed = running(windows.withColumn("_one", F.lit(1)), F.md5(F.concat(F.lit(f"{seed}:"), F.col(key).cast("string"))), "_one", [key])
    return placed.withColumn("step", F.floor(F.col("before") / each).cast("long")).drop("_one", "before")
