"""Only one domain organised, the rest in random order, all mixed in their shares."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from windowforge.operators.prefix import running


def mix(rows: DataFrame, domain: str, ratios: dict[str | None, float], token_budget: int, tokens: str = "n_tokens", seed: int = 7, key: str = "seg_id") -> DataFrame:
    """Of each domain (None: the rows that name none) the rows, in an order drawn by hash, that begin within its share of the budget."""
    parts = []
    for name, share in ratios.items():
        placed = running(rows.filter(F.col(domain).eqNullSafe(name)), F.md5(F.concat(F.lit(f"{seed}:"), F.col(key).cast("string"))), tokens, [key])
        parts.append(placed.filter(F.col("before") < share * token_budget).drop("before"))
    return reduce(DataFrame.unionByName, parts)


def domain_ratios(rows: DataFrame, domain: str, tokens: str = "n_tokens") -> dict[str | None, float]:
    """Shares of the tokens by domain, None for rows that name none; a row per domain."""
    got = rows.groupBy(domain).agg(F.sum(tokens).alias("t")).collect()
    whole = sum(r["t"] for r in got) or 1
    return {r[domain]: r["t"] / whole for r in sorted(got, key=lambda r: str(r[domain]))}
