import hashlib
import random

from pyspark.sql import functions as F

from windowforge.llm.exact_dedup import exact_dedup, exact_groups

ROWS = [(1, "Abc", "x"), (2, "aBC", "y"), (3, None, "z"), (4, "", "z"), (5, "É", "q"), (6, "é", "q"), (7, "long " * 50_000, "l"), (8, "LONG " * 50_000, "l")]


def plain(text):
    return "".join(c.lower() if "A" <= c <= "Z" else c for c in text or "")


def expect(rows, keep):
    groups = {}
    for i, t, _ in rows:
        groups.setdefault(plain(t), []).append(i)
    pick = {"min": min, "max": max}[keep]
    return sorted((i, pick(g), len(g), i == pick(g), hashlib.sha256(n.encode()).hexdigest()) for n, g in groups.items() for i in g)


def test_groups(spark):
    rng = random.Random(1)
    rows = ROWS + [(100 + i, rng.choice(["a", "B", "b", "c c"]), "r") for i in range(300)] + [(1, "Abc", "x")]
    frame = spark.createDataFrame(rows, "doc_id long, text string, kept string").repartition(5)
    for keep in ("min", "max"):
        assert sorted(tuple(r) for r in exact_groups(frame, keep=keep).collect()) == expect(rows, keep)


def test_equal_hashes_of_different_texts_do_not_meet(spark):
    rows = [(i, t, "") for i, t in enumerate(["ab", "cd", "ab", "ef", "CD", "abc"])]
    frame = spark.createDataFrame(rows, "doc_id long, text string, c string")
    weak = exact_groups(frame, hashed=lambda c: F.length(c).cast("string").cast("binary"))
    assert sorted(tuple(r) for r in weak.collect()) == expect(rows, "min")


def test_rows_that_stay(spark):
    frame = spark.createDataFrame(ROWS, "doc_id long, text string, keep_id string")
    got = exact_dedup(frame)
    assert got.columns == frame.columns and sorted(r.doc_id for r in got.collect()) == [1, 3, 5, 6, 7]
    assert sorted(r.doc_id for r in exact_dedup(frame, keep="max").collect()) == [2, 4, 5, 6, 8]


def test_missing_and_repeated_ids(spark):
    frame = spark.createDataFrame([(None, "a"), (3, "A"), (3, "A"), (None, "b"), (None, "B")], "doc_id long, text string")
    for keep in ("min", "max"):
        assert sorted((r.doc_id or -1, r.text.lower()) for r in exact_dedup(frame, keep=keep).collect()) == [(-1, "b"), (3, "a")]


def test_empty(spark):
    frame = spark.createDataFrame([], "doc_id long, text string")
    assert exact_groups(frame).count() == 0 and exact_dedup(frame).count() == 0
