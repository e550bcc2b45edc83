"""Example generators, a stand-in reader, and the measures over their scores.

The reader is no model: it looks for the question in what a window of L tokens lets it see, and copies what stands there. It tests
generators, scorers and the limit of length; its scores say nothing about any model.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from windowforge.functions.tokens import tokenize

KV_POSITIONS = {140: [1, 35, 70, 105, 140], 300: [1, 50, 100, 150, 200, 250, 300]}


def kv_examples(spark, pairs: int, positions: list[int], examples: int | DataFrame = 500) -> DataFrame:
    """(example_id, n_pairs, position, pairs, context, key, answer): dictionaries of hashed keys and values, as a map and as the text that a reader
    gets, one key asked for. Made where they are used, for as many numbers or for the column example_id of a frame; a dictionary is made
    and printed once for all positions."""
    ids = examples if isinstance(examples, DataFrame) else spark.range(examples).withColumnRenamed("id", "example_id")
    made = lambda i, what: F.md5(F.concat_ws(":", F.lit(what), F.col("example_id").cast("string"), F.lit(str(pairs)), i.cast("string")))
    entries = F.transform(F.sequence(F.lit(1), F.lit(pairs)), lambda i: F.struct(made(i, "k").alias("k"), made(i, "v").alias("v")))
    printed = F.array_join(F.transform(F.map_entries("pairs"), lambda e: F.concat(e["key"], F.lit(": "), e["value"])), " ")
    base = ids.select("example_id", F.map_from_entries(entries).alias("pairs")).select("*", printed.alias("context")).select("*", F.explode(F.array(*[F.lit(p) for p in positions])).alias("position"))
    return base.select("example_id", F.lit(pairs).alias("n_pairs"), "position", "pairs", "context", made(F.col("position"), "k").alias("key"), made(F.col("position"), "v").alias("answer"))


def kv_read(examples: DataFrame, window: int, tokens_a_pair: int = 80) -> DataFrame:
    """Adds prediction: what the dictionary gives if all of it lies within the window; null (the printed dash) if the prompt is longer."""
    fits = F.col("n_pairs") * tokens_a_pair <= window
    return examples.withColumn("prediction", F.when(fits, F.element_at("pairs", F.col("key"))))


def accuracy(df: DataFrame, by: list[str]) -> DataFrame:
    """(by..., examples, accuracy): null predictions have no accuracy."""
    return df.groupBy(*by).agg(F.count(F.lit(1)).alias("examples"), F.avg((F.col("prediction") == F.col("answer")).cast("double")).alias("accuracy"))


def needle_grid(needles: DataFrame, haystack: DataFrame, lengths: list[int], depths: list[int], window: int) -> DataFrame:
    """(length, depth, score): a needle of words put at a depth of a haystack of ``length`` tokens; the reader scores 1 to 10 by the share of it within the first ``window`` tokens.

    needles: (needle_id, text); haystack: one row (tokens)."""
    grid = needles.select("needle_id", tokenize(F.col("text")).alias("needle")).crossJoin(F.broadcast(haystack))
    grid = grid.select("*", F.explode(F.array(*[F.lit(n) for n in lengths])).alias("length")).select("*", F.explode(F.array(*[F.lit(d) for d in depths])).alias("depth"))
    at = F.floor(F.greatest(F.col("length") - F.size("needle"), F.lit(0)) * F.col("depth") / 100).cast("int")
    text = F.concat(F.slice("tokens", F.lit(1), at), "needle", F.slice("tokens", at + 1, F.greatest(F.col("length") - F.size("needle") - at, F.lit(0))))
    seen = F.slice(text, F.lit(1), F.lit(window))
    share = F.greatest(F.least(F.size(seen) - at, F.size("needle")), F.lit(0)) / F.size("needle")
    return grid.select("length", "depth", "needle_id", F.greatest(F.lit(1), F.round(share * 10)).cast("double").alias("score")).groupBy("length", "depth").agg(F.avg("score").alias("score"))


def first_words(text: Column, n: int) -> Column:
    return F.array_join(F.slice(tokenize(text), 1, n), " ")


def next_words(text: Column, skip: int, n: int) -> Column:
    return F.array_join(F.slice(tokenize(text), skip + 1, n), " ")


def answer_after(text: Column, question: Column, n: int, window: int | None = None) -> Column:
    """The n words that follow the question in the first ``window`` tokens of a text; empty if it is not there."""
    words = tokenize(text)
    joined = F.array_join(F.slice(words, 1, window) if window else words, " ")
    at = F.instr(joined, question)
    return F.when((at > 0) & (question != ""), next_words(F.substr(joined, at + F.length(question)), 0, n)).otherwise("")


def ngram_likelihood(train: DataFrame, test: DataFrame, order: int = 2, smoothing: float = 1.0, key: str = "seg_id") -> DataFrame:
    """(key, n, log_likelihood, perplexity) of tokens by additive smoothing of unigrams or bigrams over the vocabulary of the training rows.

    Counts are tables joined by n-gram; the vocabulary's size and the number of tokens are the only scalars."""
    def grams(df: DataFrame) -> DataFrame:
        words = df.select(F.col(key).alias("id"), F.posexplode("tokens").alias("at", "t"))
        if order == 1:
            return words.select("id", F.lit("").alias("before"), "t")
        before = F.coalesce(F.lag("t").over(Window.partitionBy("id").orderBy("at")), F.lit("<s>"))
        return words.select("id", before.alias("before"), "t")

    seen = grams(train)
    pairs, heads = seen.groupBy("before", "t").agg(F.count(F.lit(1)).alias("c")), seen.groupBy("before").agg(F.count(F.lit(1)).alias("h"))
    size = seen.agg(F.count_distinct("t").alias("v"))
    joined = grams(test).join(pairs, ["before", "t"], "left").join(heads, "before", "left").crossJoin(F.broadcast(size))
    p = (F.coalesce("c", F.lit(0)) + smoothing) / (F.coalesce("h", F.lit(0)) + smoothing * (F.col("v") + 1))
    return joined.groupBy("id").agg(F.count(F.lit(1)).alias("n"), F.sum(F.log(p)).alias("log_likelihood")).withColumn("perplexity", F.exp(-F.col("log_likelihood") / F.col("n"))).withColumnRenamed("id", key)


def improvement(scores: DataFrame, base: str, ours: str = "framework", how: str = "ratio_of_sums", by: str = "category") -> DataFrame:
    """(by, improvement) in percent. Scores are (category, task, window, method, score); cells that either side lacks do not count."""
    cells = scores.filter(F.col("method").isin(base, ours)).groupBy(by, "task", "window").pivot("method", [base, ours]).agg(F.first("score")).filter(F.col(base).isNotNull() & F.col(ours).isNotNull())
    if how == "ratio_of_sums":
        return cells.groupBy(by).agg(((F.sum(ours) / F.sum(base) - 1) * 100).alias("improvement"))
    return cells.groupBy(by).agg(((F.avg(F.col(ours) / F.col(base)) - 1) * 100).alias("improvement"))


def radar(scores: DataFrame) -> DataFrame:
    """(category, window, method, score): averages over the tasks."""
    return scores.groupBy("category", "window", "method").agg(F.avg("score").alias("score"))
