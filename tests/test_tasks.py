import datetime as dt
import random
from concurrent.futures import ThreadPoolExecutor

import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from windowforge.functions import scorers as S
from windowforge.functions import sql, vec
from windowforge.functions.tokens import segment
from windowforge.operators import evals as E
from windowforge.operators import mixture, project, stats
from windowforge.plans import queries_evals
from windowforge.plans.scores import score_rows
from windowforge.sources import corpus as C
from windowforge.sources import examples


def test_worked_scores(spark):
    assert S.rouge_l_of("a b c d", "a c d e") == pytest.approx(0.75) and S.token_f1_of("a a b", "a b b") == pytest.approx(2 / 3)
    df = spark.createDataFrame([("kitten", "sitting", "A  b", "a b"), ("", "", None, "")], "a string, b string, c string, d string")
    rows = df.select(S.edit_sim(F.col("a"), F.col("b")), S.exact_match(F.col("c"), F.col("d")), S.rouge_l(F.col("a"), F.col("a")), S.token_f1(F.col("a"), F.col("b"))).collect()
    assert [round(x, 6) for x in rows[0]] == [round(1 - 3 / 7, 6), 1.0, 1.0, 0.0] and list(rows[1]) == [1.0, 1.0, 1.0, 1.0]
    runs = spark.createDataFrame([("t", int(i < 3)) for i in range(10)] + [("u", 0)] * 4, "task string, passed int")
    got = {r.task: r.pass_at_k for r in S.pass_at_k(runs, ["task"]).collect()}
    assert got["t"] == pytest.approx(0.3) and got["u"] == 0
    assert {r.task: r.pass_at_k for r in S.pass_at_k(runs, ["task"], k=5).collect()}["t"] == pytest.approx(1 - (7 * 6 * 5 * 4 * 3) / (10 * 9 * 8 * 7 * 6))
    refs = spark.createDataFrame([("a b", ["x", "a b c"])], "p string, r array<string>")
    assert refs.select(S.token_f1_any(F.col("p"), F.col("r"))).first()[0] == pytest.approx(0.8)


def test_lcs_by_brute_force():
    rng = random.Random(1)
    for _ in range(50):
        a, b = ([rng.choice("abc") for _ in range(rng.randint(0, 7))] for _ in range(2))
        best = 0
        for mask in range(1 << len(a)):
            sub, it = [x for i, x in enumerate(a) if mask >> i & 1], iter(b)
            if all(x in it for x in sub):
                best = max(best, len(sub))
        assert S.lcs(a, b) == best


def test_key_values(spark):
    made = E.kv_examples(spark, 140, [1, 140], 20)
    assert made.filter(F.size("pairs") == 140).count() == 40
    fits = E.accuracy(E.kv_read(made, 16384), ["position"]).collect()
    assert all(r.accuracy == 1 and r.examples == 20 for r in fits)
    assert all(r.accuracy is None for r in E.accuracy(E.kv_read(E.kv_examples(spark, 300, [50], 5), 16384), ["position"]).collect())
    examples.register(spark)
    rows = spark.read.format("windowforge_examples").option("pairs", 5).option("examples", 7).option("position", 3).option("block", 2).load().collect()
    assert len(rows) == 7 and all(f"{r.question}: {r.answer}" in r.context for r in rows)


def test_key_value_examples_come_with_their_dictionaries(spark):
    rows = entry.queries()["kv_examples"](spark, "/root/testdata/sf0.001").collect()
    suppliers = spark.read.parquet("/root/testdata/sf0.001/supplier.parquet").count()
    assert len(rows) == 12 * suppliers
    for r in rows:
        words = r.context.split(" ")
        keys, values = words[::2], words[1::2]
        assert len(set(keys)) == len(values) == r.n_pairs and (keys[r.position - 1], values[r.position - 1]) == (f"{r.key}:", r.answer)


def test_key_value_sql_gives_the_same(spark):
    import duckdb

    con = duckdb.connect()
    con.execute("CREATE VIEW supplier AS SELECT * FROM '/root/testdata/sf0.001/supplier.parquet'")
    want = sorted(con.execute(entry.oracle_sql()["kv_examples"]).fetchall())
    assert sorted(map(tuple, entry.queries()["kv_examples"](spark, "/root/testdata/sf0.001").collect())) == want


def test_haystack_reads_on_behind_empty_documents(spark, tmp_path):
    texts = [(i, None if i % 2 else "") for i in range(2500)] + [(2500 + i, f"a{i} b{i} c{i}") for i in range(40)]
    spark.createDataFrame(texts, "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    tokens = queries_evals._haystack(spark, str(tmp_path), 50).first()["tokens"]
    assert tokens == [f"{c}{i}" for i in range(17) for c in "abc"]


def test_needle_at_the_limit(spark):
    needles = spark.createDataFrame([(1, "n1 n2 n3 n4")], "needle_id long, text string")
    hay = spark.createDataFrame([([f"h{i}" for i in range(100)],)], "tokens array<string>")
    got = {(r.length, r.depth): r.score for r in E.needle_grid(needles, hay, [20, 40], [0, 50, 100], 20).collect()}
    assert got == {(20, 0): 10, (20, 50): 10, (20, 100): 10, (40, 0): 10, (40, 50): 5, (40, 100): 1}


def test_claims_recompute(spark):
    scores = spark.createDataFrame(score_rows(), "category string, task string, window int, method string, score double")
    got = {r.category: r.improvement for r in E.improvement(scores, "random").collect()}
    assert got["retrieval"] == pytest.approx(18.10, abs=0.01) and got["summarization"] == pytest.approx(21.27, abs=0.01) and got["code"] == pytest.approx(3.81, abs=0.01) and got["general"] == pytest.approx(4.94, abs=0.01)
    graph = {r.category: r.improvement for r in E.improvement(scores, "graph").collect()}
    assert graph["retrieval"] == pytest.approx(9.57, abs=0.01) and graph["code"] == pytest.approx(3.46, abs=0.01)
    assert {r.category: r.improvement for r in E.improvement(scores, "random", how="mean_of_ratios").collect()}["retrieval"] == pytest.approx(25.85, abs=0.05)


def test_likelihood_sums_to_one(spark):
    train = spark.createDataFrame([("a", "x y x".split())], "seg_id string, tokens array<string>")
    test = spark.createDataFrame([(t, [t]) for t in ("x", "y", "unseen")], "seg_id string, tokens array<string>")
    p = [float(np.exp(r.log_likelihood)) for r in E.ngram_likelihood(train, test, 1).collect()]
    assert sum(p) == pytest.approx(1.0)


def test_domain_tables(spark):
    rows = spark.createDataFrame([("a", 1), ("a", 5), ("b", 10)], "d string, n_tokens int")
    assert {r.domain: (r.max_len, r.min_len, r.avg_len) for r in stats.domain_stats(rows, "d").collect()} == {"a": (5, 1, 3.0), "b": (10, 10, 10.0)}
    assert {(r.domain, r.interval): (r.share, r.longest_share) for r in stats.length_mix(rows, "d", [5, 10]).collect()} == {("a", "<5"): (0.5, 0.0), ("a", "5-10"): (0.5, 0.0), ("b", ">=10"): (1.0, 1.0)}
    assert mixture.domain_ratios(rows, "d") == {"a": 6 / 16, "b": 10 / 16}
    t = stats.cluster_table(spark.createDataFrame([(1,), (1,), (150,), (8,)], "size long")).first()
    assert (t.clusters, t.largest, t.smallest, t.mean, t.median, t.below, t.single) == (4, 150, 1, 40.0, 4.5, 3, 2)


def test_maps_separate_groups(spark):
    rng = np.random.default_rng(3)
    rows = [(f"{g}{i:02d}", (np.eye(3)[g] * 5 + rng.normal(size=3) * 0.1).astype(np.float32).tolist()) for g in range(3) for i in range(25)]
    docs = spark.createDataFrame(rows, "seg_id string, vec array<float>")
    for fn in (lambda: project.tsne(docs, 75, perplexity=10, iters=250), lambda: project.pca(docs, 75)):
        got = {r.seg_id: np.array([r.x, r.y]) for r in fn().collect()}
        centres = [np.mean([v for k, v in got.items() if k[0] == str(g)], axis=0) for g in range(3)]
        near = [int(np.argmin([np.linalg.norm(v - c) for c in centres])) == int(k[0]) for k, v in got.items()]
        assert np.mean(near) > 0.95


def test_map_of_the_graph_holds_every_segment(spark):
    rows = entry.queries()["tsne_graph"](spark, "/root/testdata/sf0.01").collect()
    english = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").filter("lang = 'en'").select("doc_id", "text")
    want = {r.seg_id for r in segment(english, 1024).select("seg_id").collect()}
    assert len(rows) == len(want) > 300 and {r.seg_id for r in rows} == want
    y = np.array([(r.x, r.y) for r in rows])
    assert np.isfinite(y).all() and len(np.unique(y, axis=0)) > 300


def test_whole_map_separates_groups(spark, monkeypatch):
    rng = np.random.default_rng(3)
    rows = [(f"{g}{i:03d}", (np.eye(3)[g] * 5 + rng.normal(size=3) * 0.5).astype(np.float32).tolist()) for g in range(3) for i in range(150)]
    docs, keep = spark.createDataFrame(rows, "seg_id string, vec array<float>"), project.blocks
    whole = {r.seg_id: (r.x, r.y) for r in project.tsne_whole(docs, perplexity=10, iters=250).collect()}
    got = {k: np.array(v) for k, v in whole.items()}
    centres = [np.mean([v for k, v in got.items() if k[0] == str(g)], axis=0) for g in range(3)]
    near = [int(np.argmin([np.linalg.norm(v - c) for c in centres])) == int(k[0]) for k, v in got.items()]
    assert len(got) == 450 and np.mean(near) > 0.95
    monkeypatch.setattr(project, "blocks", lambda df, key, block, label: keep(df, key, 40, label))  # many blocks give the same
    assert {r.seg_id: (r.x, r.y) for r in project.tsne_whole(docs.repartition(7), perplexity=10, iters=250).collect()} == whole
    few = lambda n: sorted(r.seg_id for r in project.tsne_whole(docs.limit(n), iters=20).collect())
    assert [len(few(n)) for n in (0, 1, 2, 3, 30)] == [0, 1, 2, 3, 30]


def test_forces_of_the_whole_map_by_all_pairs():
    rng, n = np.random.default_rng(4), 500
    x = project.unit(rng.normal(size=(n, 5)))
    near = np.stack([np.delete(np.arange(n), i) for i in range(n)])
    far = ((x[:, None] - x[None]) ** 2).sum(axis=2)
    p, want = project.odds(np.take_along_axis(far, near, 1), 10.0), project.neighbour_odds(x, 10.0)
    both = np.zeros((n, n))
    np.put_along_axis(both, near, p, 1)
    assert np.allclose((both + both.T) / (2 * n), want, atol=1e-11)
    with ThreadPoolExecutor(2) as pool:
        for scale, close in ((1e-4, 1e-9), (1.0, 1e-3), (10.0, 0.012)):
            y = rng.normal(scale=scale, size=(n, 2))
            q = 1 / (1 + ((y[:, None] - y[None]) ** 2).sum(axis=2))
            np.fill_diagonal(q, 0)
            force = lambda w: w.sum(axis=1)[:, None] * y - w @ y
            assert np.allclose(project.pulls(y, near, p, pool), force((both + both.T) / (2 * n) * q), rtol=1e-9, atol=1e-18)
            for (push, total), most in ((project.pushes(y, pool), close), (project.all_pushes(y), 1e-9)):
                assert abs(total / q.sum() - 1) < most and np.linalg.norm(push - force(q * q)) < most * np.linalg.norm(force(q * q))


def test_registered_sql(spark):
    sql.register_all(spark)
    row = spark.sql("SELECT wf_cosine(array(1D, 0D), array(1D, 1D)), wf_cosine(array(0D), array(1D)), wf_pack_score(0.5D, 5, 10, 10), wf_edit_sim('ab', 'ab')").first()
    assert row[0] == pytest.approx(2**-0.5) and row[1] == 0 and row[2] == pytest.approx(0.5 + 0.5 + 10 / 15) and row[3] == 1
    assert [tuple(r) for r in spark.sql("SELECT seg_no, start, tokens FROM wf_segments(array('a', 'b', 'c'), 2)").collect()] == [(0, 0, ["a", "b"]), (1, 2, ["c"])]
    assert [r.word for r in spark.sql("SELECT * FROM wf_needle('a b c d e f', 'N', 50, 5)").collect()] == ["a", "b", "N", "c", "d"]


def test_vector_algebra(spark):
    df = spark.createDataFrame([("g", [3.0, 4.0]), ("g", [0.0, 0.0])], "g string, vec array<float>")
    assert [r[0] for r in df.select(vec.norm(F.col("vec"))).collect()] == [5.0, 0.0]
    assert [list(r[0]) for r in df.select(vec.normalize(F.col("vec"))).collect()] == [[0.6, 0.8], [0.0, 0.0]]
    s = vec.sum_native(df, ["g"]).first()
    assert list(s.vec) == [3.0, 4.0] and s.n == 2


def test_files_in_and_out(spark, tmp_path):
    docs = spark.createDataFrame([(1, 'a "q" b\nc'), (2, "é")], "doc_id long, text string")
    for kind in ("parquet", "orc", "json"):
        docs.write.format(kind).save(f"{tmp_path}/{kind}")
        assert sorted(map(tuple, C.read_texts(spark, f"{tmp_path}/{kind}", kind).collect())) == [(1, 'a "q" b\nc'), (2, "é")]
    docs.write.option("header", True).option("escape", '"').csv(f"{tmp_path}/csv")
    assert sorted(r.text for r in C.read_texts(spark, f"{tmp_path}/csv", "csv").collect()) == ['a "q" b\nc', "é"]
    (tmp_path / "books").mkdir()
    (tmp_path / "books" / "one.txt").write_text("x\ny")
    assert [r.text for r in C.read_texts(spark, f"{tmp_path}/books", "books").collect()] == ["x\ny"]
    assert sorted(r.text for r in C.read_texts(spark, f"{tmp_path}/books", "text").collect()) == ["x", "y"]
    m = spark.createDataFrame([("w", 0, "s")], "window_id string, pos int, seg_id string")
    C.write_manifest(m, f"{tmp_path}/m", "random", 16)
    C.write_manifest(m, f"{tmp_path}/m", "graph", 16)
    assert {r.method for r in spark.read.parquet(f"{tmp_path}/m").collect()} == {"random", "graph"}
    C.write_windows(spark.createDataFrame([("w", ["a"], 1)], "window_id string, tokens array<string>, n_tokens int"), f"{tmp_path}/w")
    assert spark.read.json(f"{tmp_path}/w").first().tokens == ["a"]


def test_hour_sums_round_seconds(spark, tmp_path):
    at = lambda s: dt.datetime(2024, 1, 1, tzinfo=dt.timezone.utc) + dt.timedelta(seconds=s)
    rows = [(1, at(0.4), 7, 1.0), (2, at(3600.6), 7, 2.0), (3, at(3600.5), 8, 4.0), (4, at(0.2), 8, 8.0)]
    spark.createDataFrame(rows, "event_id long, ts timestamp, user_id long, value double").write.parquet(f"{tmp_path}/events.parquet")
    assert dict(entry.queries()["win_range_events"](spark, str(tmp_path)).collect()) == {1: 1.0, 2: 2.0, 3: 12.0, 4: 8.0}


@pytest.mark.parametrize("name", ["kv_examples", "kv_accuracy", "kv_average", "kv_data_source", "kv_table_function", "lr_schedule", "fn_sql_registered", "radar_averages", "improvement_claims", "agg_pivot_scores"])
def test_given_tables_are_read(spark, name):
    rows = entry.queries()[name](spark, "/root/testdata/sf0.001")
    assert rows.inputFiles() and rows.count() > 0
