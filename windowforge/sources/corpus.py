"""Corpora from the given tables and from files, and the sinks."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def strip_html(html: Column) -> Column:
    """Text of a page: scripts, styles, comments and tags go, white space is folded."""
    out = F.regexp_replace(F.coalesce(html, F.lit("")), r"(?is)<(script|style)[^>]*>.*?</(script|style)>", " ")
    out = F.regexp_replace(out, r"(?s)<!--.*?-->", " ")
    return F.trim(F.regexp_replace(F.regexp_replace(out, r"<[^>]*>", " "), r"[ \t\r\n]+", " "))


def conversations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(doc_id, text): the turns of each conversation in their order, a line each."""
    rows = table(spark, sf_dir, "conversations")
    turns = F.sort_array(F.collect_list(F.struct("turn", "role", "text")))
    return rows.groupBy("conv_id").agg(turns.alias("t")).select(F.col("conv_id").alias("doc_id"), F.array_join(F.transform("t", lambda x: F.concat_ws(": ", x["role"], x["text"])), "\n").alias("text"))


def corpus(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(domain, doc_id, text): documents, pages without tags, conversations, benchmark passages."""
    parts = {
        "documents": table(spark, sf_dir, "documents").select("doc_id", "text"),
        "pages": table(spark, sf_dir, "pages").select(F.col("page_id").alias("doc_id"), strip_html(F.col("html")).alias("text")),
        "conversations": conversations(spark, sf_dir),
        "benchmark": table(spark, sf_dir, "benchmark").select(F.col("item_id").alias("doc_id"), "text"),
    }
    out = None
    for name, df in parts.items():
        df = df.select(F.lit(name).alias("domain"), F.col("doc_id").cast("long").alias("doc_id"), "text")
        out = df if out is None else out.unionByName(df)
    return out


def read_texts(spark: SparkSession, path: str, kind: str, schema: str = "doc_id long, text string") -> DataFrame:
    """Raw documents from files: parquet, orc, json (a document a line), csv, text (a document a line), books (a document a file)."""
    if kind == "books":
        return spark.read.text(path, wholetext=True).select(F.xxhash64(F.input_file_name()).alias("doc_id"), F.col("value").alias("text"))
    if kind == "text":
        return spark.read.text(path).select(F.xxhash64(F.input_file_name(), "value").alias("doc_id"), F.col("value").alias("text"))
    if kind == "parquet":
        return spark.read.schema(schema).parquet(path)
    reader = spark.read.schema(schema)
    if kind == "csv":
        reader = reader.option("header", True).option("multiLine", True).option("escape", '"')
    return reader.format(kind).load(path)


def write_manifest(manifest: DataFrame, path: str, method: str, window: int) -> None:
    """For trainers that read by manifest: a folder for each length and method."""
    manifest.withColumn("window", F.lit(window)).withColumn("method", F.lit(method)).write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("window", "method").parquet(path)


def write_windows(windows: DataFrame, path: str, tokens_a_file: int = 1 << 26, kind: str = "json") -> None:
    """Windows as JSON lines or Parquet, files cut by rows that hold about as many tokens."""
    each = windows.agg(F.max("n_tokens")).first()[0] or 1
    windows.write.option("maxRecordsPerFile", max(1, tokens_a_file // each)).format(kind).save(path)
