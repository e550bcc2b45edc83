"""Quality classifier: boosted trees over statistics of a document's bytes, words and lines."""

from __future__ import annotations

from collections.abc import Iterator
from operator import eq

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .boosting import Trees, boost
from .common import fresh_name, ship, tidily

#: Labelled rows that a model is fitted on at most, the first by hash; a score never depends on how many there are beyond them.
TRAINING_ROWS = 20_000
#: Classes of bytes whose shares are features.
CLASSES = {
    "upper": b"ABCDEFGHIJKLMNOPQRSTUVWXYZ",
    "lower": b"abcdefghijklmnopqrstuvwxyz",
    "digit": b"0123456789",
    "space": b" \t\r\x0b\x0c",
    "line": b"\n",
    "stop": b".?",
    "comma": b",;:",
    "shout": b"!",
    "bar": b"|",
    "sign": b"#$%&*@^~<>=+\\/_",
    "quote": b"\"'`()[]{}-",
    "control": bytes([*range(0, 9), *range(14, 32), 127]),
}
NAMES = [*CLASSES, "bytes_log", "words_log", "word_length", "distinct_words", "repeats", "longest_word", "lines_log", "words_a_line", "distinct_lines", "closed_lines", "upper_of_letters", "signs_a_word"]
_MASK = np.stack([np.isin(np.arange(256), np.frombuffer(c, dtype=np.uint8)) for c in CLASSES.values()]).astype(np.float64)


def statistics(text: str) -> np.ndarray:
    """One row of features from a whole text; the empty text counts as one empty word."""
    raw = text.encode()
    counts = _MASK @ np.bincount(np.frombuffer(raw, dtype=np.uint8), minlength=256) if raw else np.zeros(len(CLASSES))
    words, lines = raw.split(), [x for x in raw.split(b"\n") if x]
    n, w, k = max(len(raw), 1), max(len(words), 1), max(len(lines), 1)
    by = dict(zip(CLASSES, counts))
    letters = by["upper"] + by["lower"]
    return np.array(
        [
            *(counts / n),
            np.log1p(len(raw)),
            np.log1p(len(words)),
            (n - by["space"] - by["line"]) / w,
            len(set(words)) / w ** 0.9,
            sum(map(eq, words, words[1:])) / w,
            np.log1p(max(map(len, words), default=0)),
            np.log1p(len(lines)),
            np.log1p(w / k),
            len(set(lines)) / k,
            sum(x[-1:] in b".!?" for x in lines) / k,
            by["upper"] / max(letters, 1),
            (by["sign"] + by["shout"] + by["bar"]) / w,
        ]
    )


def held_out(doc_id: Column) -> Column:
    """Rows that training never sees."""
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit(""))) % 3 == 1


def train(docs: DataFrame, labels: DataFrame, target: str = "quality", rows: int = TRAINING_ROWS, **options) -> Trees:
    """Fits on at most ``rows`` labelled documents outside the held-out third, those with the smallest hash. Only their statistics reach the driver."""
    ship(docs.sparkSession)
    chosen = labels.filter(F.col(target).isNotNull() & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id"))).groupBy("doc_id").agg(F.max(target).alias("_y"))
    chosen = chosen.orderBy(F.xxhash64("doc_id"), "doc_id").limit(rows)
    names = ", ".join(f"f{k} double" for k in range(len(NAMES)))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            x = np.stack([statistics(t) for t in batch["_t"]]) if len(batch) else np.zeros((0, len(NAMES)))
            out = pd.DataFrame(x, columns=[f"f{k}" for k in range(len(NAMES))])
            out.insert(0, "_y", batch["_y"].to_numpy())
            out.insert(0, "doc_id", batch["doc_id"].to_numpy())
            yield out

    rows_of = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("_t")).join(F.broadcast(chosen), "doc_id")  # broadcast: at most ``rows`` rows
    seen = rows_of.select("doc_id", F.col("_y").cast("double").alias("_y"), "_t").mapInPandas(tidily(run), f"doc_id long, _y double, {names}").toPandas()
    seen = seen.sort_values(list(seen.columns), kind="stable")
    return boost(seen.iloc[:, 2:].to_numpy(dtype=np.float64).reshape(-1, len(NAMES)), seen["_y"].to_numpy(dtype=np.float64), **options)


def score(docs: DataFrame, model: Trees, keep: str | None = None) -> DataFrame:
    """doc_id, held_out, score, predicted; with ``keep`` all columns of ``docs`` and the score under that name, which none of them may have.

    Null texts count as empty and are scored like any other. Repeated rows score alike; an empty table gives an empty
    result.
    """
    ship(docs.sparkSession)

    @F.pandas_udf("double")
    def scored(texts: pd.Series) -> pd.Series:
        if not len(texts):
            return pd.Series([], dtype="float64")
        return pd.Series(1 / (1 + np.exp(-model.raw(np.stack([statistics(t) for t in texts])))))

    out = scored(F.coalesce(F.col("text"), F.lit("")))
    if keep:
        return docs.withColumn(keep, out)
    return docs.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), out.alias("score")).withColumn("predicted", (F.col("score") >= 0.5).cast("int"))


def classify(docs: DataFrame, labels: DataFrame, **options) -> DataFrame:
    return score(docs, train(docs, labels, **options))


def keep_good(docs: DataFrame, labels: DataFrame, threshold: float = 0.5, **options) -> DataFrame:
    """The rows that the classifier accepts, all columns as they were, whatever their names.

    Null texts count as empty and are judged like any other; repeated rows stay or go together; an empty table gives an empty result.
    """
    name = fresh_name(docs, "score")
    return score(docs, train(docs, labels, **options), keep=name).filter(F.col(name) >= threshold).drop(name)
