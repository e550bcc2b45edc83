"""Tokens, counts and segments of at most L tokens."""

from __future__ import annotations

from functools import lru_cache

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

PATTERNS = {"whitespace": r"\S+", "word": r"[\p{L}\p{N}]+"}


def tokenize(text: Column, how: str = "whitespace") -> Column:
    """Tokens in order; null has none."""
    if how not in PATTERNS:
        raise ValueError(f"how is one of {', '.join(PATTERNS)}; token counts of a vocabulary come from bpe_count")
    return F.regexp_extract_all(F.coalesce(text, F.lit("")), F.lit(PATTERNS[how]), 0)


def count_tokens(text: Column, how: str = "whitespace") -> Column:
    return F.size(tokenize(text, how))


@lru_cache(maxsize=2)
def _vocabulary(path: str):
    from tokenizers import Tokenizer

    return Tokenizer.from_file(path)


def bpe_count(text: Column, path: str) -> Column:
    """Number of tokens by a tokenizers file that every executor has under the same path."""

    @F.pandas_udf("int")
    def counted(texts: pd.Series) -> pd.Series:
        found = _vocabulary(path).encode_batch_fast(texts.fillna("").tolist(), add_special_tokens=False)
        return pd.Series([len(x.ids) for x in found], dtype="int32")

    return counted(text)


def segment(df: DataFrame, window: int, overlong: str = "split", how: str = "whitespace", id_col: str = "doc_id", text_col: str = "text", prefix: Column | None = None) -> DataFrame:
    """seg_id, doc_id, seg_no, start, n_tokens, tokens and the other columns but the text.

    "split" keeps every token, "truncate" the first ``window`` ones. A text without tokens is one segment of none. One
    narrow pass: nothing is shuffled.
    """
    if overlong not in ("split", "truncate"):
        raise ValueError("overlong is 'split' or 'truncate'")
    others = [c for c in df.columns if c not in (text_col, id_col)]
    rows = df.select(F.col(id_col).alias("doc_id"), *others, tokenize(F.col(text_col), how).alias("_tokens"))
    if overlong == "split":
        last = F.greatest(F.ceil(F.size("_tokens") / F.lit(window)) - 1, F.lit(0)).cast("int")
        rows = rows.select("doc_id", *others, "_tokens", F.explode(F.sequence(F.lit(0), last)).alias("seg_no"))
    else:
        rows = rows.withColumn("seg_no", F.lit(0))
    cut = F.slice("_tokens", F.col("seg_no") * window + 1, F.lit(window))
    name = F.concat_ws(":", *([prefix] if prefix is not None else []), F.col("doc_id").cast("string"), F.col("seg_no").cast("string"))
    return rows.select(name.alias("seg_id"), "doc_id", *others, "seg_no", (F.col("seg_no") * window).alias("start"), F.size(cut).alias("n_tokens"), F.size("_tokens").alias("doc_tokens"), cut.alias("tokens"))
