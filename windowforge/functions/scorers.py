"""Scores of predictions against references. Texts are compared by lower-cased whitespace tokens."""

from __future__ import annotations

from collections import Counter

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def lcs(a: list[str], b: list[str]) -> int:
    """Length of the longest common subsequence."""
    row = [0] * (len(b) + 1)
    for x in a:
        last = 0
        for j, y in enumerate(b, 1):
            last, row[j] = row[j], last + 1 if x == y else max(row[j], row[j - 1])
    return row[-1]


def rouge_l_of(pred: str | None, ref: str | None) -> float:
    a, b = (pred or "").lower().split(), (ref or "").lower().split()
    if not a or not b:
        return float(a == b)
    n = lcs(a, b)
    return 2 * n / (len(a) + len(b))


def token_f1_of(pred: str | None, ref: str | None) -> float:
    a, b = (pred or "").lower().split(), (ref or "").lower().split()
    if not a or not b:
        return float(a == b)
    n = sum((Counter(a) & Counter(b)).values())
    return 2 * n / (len(a) + len(b))


def _paired(fn, pred: Column, ref: Column) -> Column:
    @F.pandas_udf("double")
    def scored(a: pd.Series, b: pd.Series) -> pd.Series:
        return pd.Series([fn(x, y) for x, y in zip(a, b)], dtype="float64")

    return scored(pred, ref)


def rouge_l(pred: Column, ref: Column) -> Column:
    return _paired(rouge_l_of, pred, ref)


def token_f1(pred: Column, ref: Column) -> Column:
    """Overlap as multisets."""
    return _paired(token_f1_of, pred, ref)


def token_f1_any(pred: Column, refs: Column) -> Column:
    """The best over several references."""

    @F.pandas_udf("double")
    def scored(a: pd.Series, b: pd.Series) -> pd.Series:
        return pd.Series([max((token_f1_of(x, y) for y in (ys if ys is not None else [])), default=0.0) for x, ys in zip(a, b)], dtype="float64")

    return scored(pred, refs)


def normalized(text: Column) -> Column:
    return F.trim(F.regexp_replace(F.lower(F.coalesce(text, F.lit(""))), r"\s+", " "))


def exact_match(pred: Column, ref: Column) -> Column:
    return (normalized(pred) == normalized(ref)).cast("double")


def edit_sim(pred: Column, ref: Column) -> Column:
    """1 less the edit distance over the longer length, in characters; two empty texts are alike."""
    longer = F.greatest(F.length(pred), F.length(ref))
    return F.when(longer > 0, 1 - F.levenshtein(pred, ref) / longer).otherwise(1.0)


def pass_at_k(df: DataFrame, by: list[str], passed: str = "passed", k: int = 1) -> DataFrame:
    """(by..., n, c, pass_at_k): chance that of k runs drawn from n, c of which passed, one passes: 1 less the product over the last c runs of (1 - k / i)."""
    per = df.groupBy(*by).agg(F.count(F.lit(1)).alias("n"), F.sum(F.col(passed).cast("long")).alias("c"))
    factors = F.aggregate(F.sequence(F.col("n") - F.col("c") + 1, F.col("n")), F.lit(1.0), lambda s, i: s * (1 - F.lit(float(k)) / i))
    return per.withColumn("pass_at_k", F.when(F.col("c") == 0, 0.0).when(F.col("n") - F.col("c") < k, 1.0).otherwise(1 - factors))
