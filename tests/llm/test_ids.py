"""Ids and columns come out as they went in."""

import pytest
from pyspark.sql import functions as F

from windowforge.llm import common
from windowforge.llm.bpe import bpe_round_trip
from windowforge.llm.exact_dedup import exact_dedup, exact_groups, one_row_each
from windowforge.llm.jaccard import jaccard_groups
from windowforge.llm.licenses import license_scan
from windowforge.llm.near_dedup import near_dedup
from windowforge.llm.packing import pack
from windowforge.llm.quality import keep_good
from windowforge.llm.secret_scan import redact, secret_scan
from windowforge.llm.token_counts import token_counts
from windowforge.llm.warc import warc_round_trip

LARGE = 2**60 + 1
ROWS = [(None, "nobody has me"), (LARGE, "some words of a text"), (LARGE + 1, None), (LARGE + 2, "")]


@pytest.mark.parametrize("operator", [jaccard_groups, token_counts, bpe_round_trip, pack, secret_scan, license_scan, exact_groups])
def test_large_ids_beside_null(spark, operator):
    docs = spark.createDataFrame(ROWS, "doc_id long, text string").coalesce(1)
    got = operator(docs)
    assert got.schema["doc_id"].dataType.simpleString() == "bigint"
    assert {r.doc_id for r in got.collect()} == {i for i, _ in ROWS}
    named = operator(docs.withColumn("doc_id", F.col("doc_id").cast("string")))
    assert {r.doc_id for r in named.collect()} == {None if i is None else str(i) for i, _ in ROWS}


def test_large_pages_beside_null(spark):
    pages = spark.createDataFrame([(i, "u", t) for i, t in ROWS], "page_id long, url string, html string").coalesce(1)
    assert {r.page_id for r in warc_round_trip(pages).collect()} == {i for i, _ in ROWS}


@pytest.mark.parametrize("name", ["_score", "score", "SCORE", "_wf_n", "n", "id", "_t", "_text", "class"])
def test_columns_of_any_name_stay(spark, name):
    docs = spark.createDataFrame([(i, t, "mine") for i, t in ROWS], f"doc_id long, text string, `{name}` string")
    labels = spark.createDataFrame([(LARGE, 1, 0)], "doc_id long, quality int, toxic int")
    for out in (keep_good(docs, labels, threshold=0.0), redact(docs), one_row_each(docs, "doc_id", "text", "min"), exact_dedup(docs), near_dedup(docs)):
        assert out.columns == docs.columns and {r[name] for r in out.select(name).collect()} == {"mine"}


def test_texts_in_small_parts(spark, monkeypatch):
    docs = spark.createDataFrame([(i, "word " * (i % 7)) for i in range(60)] + [(60, "long " * 500)], "doc_id long, text string")
    whole = sorted(token_counts(docs).collect())
    monkeypatch.setattr(common, "BYTES_AT_ONCE", 40)
    assert sorted(token_counts(docs).collect()) == whole
