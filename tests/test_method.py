import math
import os
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from tests import reference as R
from windowforge import session
from windowforge.config import Config
from windowforge.functions.schedule import batch, learning_rate
from windowforge.functions.tokens import segment
from windowforge.operators import assign as A
from windowforge.operators import baselines as B
from windowforge.operators import density as D
from windowforge.operators import blocks, costs, embed, isodata, materialize, mixture, objective, pack, stats
from windowforge.operators.prefix import running
from windowforge.plans import organize as P
from windowforge.plans import queries_method
from windowforge.schema import SEGMENTS, require

FOUR = [("A", 7, [1.0, 0.0]), ("B", 6, [0.0, 1.0]), ("C", 4, [1.0, 0.0]), ("D", 3, [0.0, 1.0])]


def members(spark, rows, cluster="k"):
    return spark.createDataFrame([(cluster, n, i, 0, size, v) for i, (n, size, v) in enumerate(rows)], "cluster_id string, seg_id string, doc_id long, seg_no int, n_tokens int, vec array<float>")


def vectors(spark, rows):
    return spark.createDataFrame(rows, "seg_id string, vec array<float>")


def random_vectors(n, dim, seed, groups=5):
    rng = np.random.default_rng(seed)
    centres = rng.normal(size=(groups, dim))
    x = centres[rng.integers(0, groups, n)] + 0.5 * rng.normal(size=(n, dim))
    return {f"v{i:03d}": np.float32(v / np.linalg.norm(v)).tolist() for i, v in enumerate(x)}


# packing: the worked examples


def placed(rows):
    return {r.seg_id: (int(r.window_id.split("|")[1]), r.used, r.cut, round(r.score, 6)) for r in rows}


def test_worked_packing(spark):
    got = placed(pack.pack(members(spark, FOUR), Config(window=10)).collect())
    assert got == {"A": (0, 7, 0, 2.0), "B": (1, 6, 0, 2.0), "C": (0, 3, 1, 2.209091), "D": (1, 3, 0, 2.4)}
    got = placed(pack.pack(members(spark, FOUR), Config(window=10, alpha=0.0)).collect())
    assert {k: v[0] for k, v in got.items()} == {"A": 0, "B": 1, "C": 1, "D": 0} and all(v[2] == 0 for v in got.values())


def test_worked_objective(spark):
    m = pack.pack(members(spark, FOUR), Config(window=10))
    rel = objective.relevance(m.join(vectors(spark, [(n, v) for n, _, v in FOUR]), "seg_id"))
    assert rel.agg(F.sum("relevance")).first()[0] == pytest.approx(4.0)
    assert objective.relevance(m.join(vectors(spark, [(n, v) for n, _, v in FOUR]), "seg_id"), "unordered").agg(F.sum("relevance")).first()[0] == pytest.approx(2.0)
    w = objective.per_window(m, 10)
    assert objective.homogeneity(w, 10).first()[0] == pytest.approx(10.0)
    assert objective.penalty_of(w, 10, "per_window_length").first()[0] == pytest.approx(1 - 1 / 11)
    assert objective.penalty_of(w, 10, "printed").first()[0] == pytest.approx(1.5)
    assert [(r.total, r.excess) for r in objective.violations(w, 10).collect()] == [(11, 1)] and objective.violations(w, 10, 1).count() == 0
    with pytest.raises(ValueError):
        objective.scalarise(w, {"members": -1.0})


@pytest.mark.parametrize("alpha,beta,lam", [(1, 1, 1), (0, 1, 1), (1, 0, 1), (1, 1, 0), (1, 0, 0), (0, 0, 1)])
def test_packing_follows_the_plain_version(spark, alpha, beta, lam):
    rng = random.Random(alpha * 4 + beta * 2 + lam)
    vec = random_vectors(40, 6, 3)
    docs = [(n, rng.choice([1, 5, 30, 64, 64, 100]), v) for n, v in sorted(vec.items())]
    got = {r.seg_id: r for r in pack.pack(members(spark, docs).repartition(3), Config(window=100, alpha=float(alpha), beta=float(beta), lam=float(lam))).collect()}
    want, room = R.pack(docs, 100, alpha, beta, lam)
    assert {n: int(got[n].window_id.split("|")[1]) for n in got} == {n: w for n, w, _ in want}
    tokens = sum(d[1] for d in docs)
    assert sum(room) == math.ceil(tokens / 100) * 100 - tokens
    assert sum(r.cut for r in got.values()) == sum(-x for x in room if x < 0)
    assert sum(r.used + r.cut for r in got.values()) == tokens and len(got) == len(docs)


def test_packing_options(spark):
    docs = [(f"s{i}", 60, [1.0, 0.0]) for i in range(6)]
    dropped = pack.pack(members(spark, docs), Config(window=100, leftover="drop"), n_windows=1).collect()
    opened = pack.pack(members(spark, docs), Config(window=100), n_windows=1).collect()
    assert len(dropped) == 2 and len(opened) == 6 and len({r.window_id for r in opened}) == 3
    full = [("a", 100, [1.0, 0.0]), ("b", 100, [1.0, 0.0]), ("c", 1, [1.0, 0.0])]
    for eligible in ("nonneg", "positive"):
        got = pack.pack(members(spark, full), Config(window=100, eligible=eligible, beta=0.0, lam=0.0)).collect()
        assert {r.seg_id for r in got} == {"a", "b", "c"}
    parts = pack.pack(members(spark, [(f"s{i}", 10, [1.0, 0.0]) for i in range(50)]), Config(window=100, max_cluster=10)).collect()
    assert len(parts) == 50 and len({r.cluster_id for r in parts}) > 1
    back = pack.pack(members(spark, [("x", 20, [1.0, 0.0])], "p").unionByName(members(spark, [("y", 30, [1.0, 0.0])], "q")), Config(window=100, backfill=True)).collect()
    assert sum(r.used for r in back) == 50


def plain_pack(lengths, vectors, c, n):
    """Every window scored for every segment."""
    bins, out = pack.Bins.empty(n, c.window, vectors.shape[1]), []
    for i, (length, v) in enumerate(zip(lengths.tolist(), vectors)):
        free = bins.remaining >= 0 if c.eligible == "nonneg" else bins.remaining > 0
        if not free.any():
            if c.leftover == "drop":
                break
            one = pack.Bins.empty(1, c.window, vectors.shape[1])
            bins = pack.Bins(c.window, *(np.concatenate([getattr(bins, x), getattr(one, x)]) for x in ("sums", "size", "count", "remaining")))
            free = np.append(free, True)
        f = np.where(free, bins.scores(v, length, c), -np.inf)
        at = int(np.argmax(f))
        out.append((i, at, int(c.window - bins.remaining[at]), int(bins.count[at]), float(f[at])))
        bins.put(at, v, length)
    return out


def test_large_clusters_are_packed_whole(spark):
    n = 20_500
    frame = spark.range(n).select(F.lit("hot").alias("cluster_id"), F.concat(F.lit("s"), "id").alias("seg_id"), F.col("id").alias("doc_id"), F.lit(0).alias("seg_no"), (F.col("id") % 61 + 1).cast("int").alias("n_tokens"), F.array(F.sin("id"), F.cos("id")).alias("vec"))
    got = {r.seg_id: (r.cluster_id, r.window_id, r.pos, r.score) for r in pack.pack(frame, Config(window=1024)).collect()}
    rows = sorted(frame.collect(), key=lambda r: (-r.n_tokens, r.doc_id))
    lengths = np.array([r.n_tokens for r in rows])
    want = plain_pack(lengths, np.array([r.vec for r in rows]), Config(window=1024), math.ceil(lengths.sum() / 1024))
    assert got == {rows[i].seg_id: ("hot", f"hot|{at:06d}", pos, f) for i, at, _, pos, f in want}


def test_packing_queries_take_every_language(spark):
    d = "/root/testdata/sf0.001"
    n = queries_method.segments(spark, d).count()
    for name in ("pack_without_clusters", "weight_sweep"):
        for r in queries_method.QUERIES[name](spark, d).collect():
            assert round(r.windows * r.members, 1) == pytest.approx(n, abs=1), (name, r)


def test_windows_left_out_of_scoring_would_not_win():
    rng = np.random.default_rng(8)
    for c in (Config(window=100), Config(window=100, alpha=0.0), Config(window=100, beta=0.0, lam=0.0), Config(window=100, eligible="positive", empty_cos=0.5), Config(window=100, leftover="drop")):
        for budget in (None, 7):
            lengths, vectors = np.sort(rng.integers(0, 101, 500))[::-1], rng.normal(size=(500, 4)).round(1)
            vectors[::50] = 0
            assert pack.pack_cluster(lengths, vectors, c, budget) == plain_pack(lengths, vectors, c, budget or math.ceil(lengths.sum() / 100))


def test_few_windows_are_scored_exactly(monkeypatch):
    rng = np.random.default_rng(3)
    lengths, vectors, scored = np.sort(rng.integers(10, 101, 3000))[::-1], rng.random((3000, 32)) ** 4, []
    monkeypatch.setattr(pack.Bins, "scores", lambda self, *a, real=pack.Bins.scores: (scored.append(len(self.size)), real(self, *a))[1])
    got = pack.pack_cluster(lengths, vectors, Config(window=100))
    assert sum(scored) < 20 * len(lengths)  # not each window that its room alone might let win
    assert got == plain_pack(lengths, vectors, Config(window=100), math.ceil(lengths.sum() / 100))
    for scale in (1e-20, 1e20):  # beyond 32 bits
        assert [r[:4] for r in pack.pack_cluster(lengths[:600], vectors[:600] * scale, Config(window=100))] == [r[:4] for r in pack.pack_cluster(lengths[:600], vectors[:600], Config(window=100))]


def test_greedy_against_the_optimum():
    rng = random.Random(2)
    vec = random_vectors(6, 4, 8)
    names, lengths = sorted(vec), {n: rng.choice([20, 40, 60]) for n in vec}
    n = max(1, math.ceil(sum(lengths.values()) / 100))
    got, _ = R.pack([(a, lengths[a], vec[a]) for a in names], 100)
    windows = [[a for a, w, _ in got if w == k] for k in range(n)]
    assert sum(R.objective(windows, lengths, vec, 100)) <= R.best_partition(names, lengths, vec, 100, n) + 1e-9


# density


def test_density_modes(spark):
    rows = [("a", [1.0, 0.0]), ("b", [0.0, 1.0]), ("c", [1.0, 0.0])]
    df = vectors(spark, rows).withColumn("subset_id", F.lit(0))
    for mode, want in (("mean_cosine", 1 / 3), ("printed", 2 / 3), ("mean_dissimilarity", 2 / 3)):
        assert D.subset_density(df, mode).first().rho == pytest.approx(want)
        assert D.subset_density_pairs(df, mode).first().rho == pytest.approx(want)
    counts = {mode: D.initial_clusters(vectors(spark, rows), 1, mode).first().n_clusters for mode in ("mean_cosine", "printed", "mean_dissimilarity")}
    assert counts == {"mean_cosine": 1, "printed": 2, "mean_dissimilarity": 2}
    one = D.initial_clusters(vectors(spark, [("a", [1.0, 0.0]), ("b", [-1.0, 0.0])]), 1).first()
    assert one.raw < 0 and one.n_clusters == 1


def test_density_from_pairs_of_blocks(spark, monkeypatch):
    """No row for a pair of vectors: blocks meet. Null vectors and zero ones count as documents, whose cosines are 0."""
    vec = random_vectors(90, 4, 8)
    rows = [(i, [float(x) for x in v], k % 3) for k, (i, v) in enumerate(vec.items())] + [("z", [0.0] * 4, 0), ("n", None, 0), ("m", [1.0, None, 0.0, 0.0], 1), ("one", [1.0] * 4, 9)]
    df, labels, keep = spark.createDataFrame(rows, "seg_id string, vec array<double>, subset_id int"), [], D.settled
    monkeypatch.setattr(D, "settled", lambda df, label: labels.append(held := keep(df, label)) or held)
    monkeypatch.setattr(D, "PAIR_BYTES", 4 * 8 * 4)  # blocks of four
    got = {r.subset_id: (r.m, r.rho) for r in D.subset_density_pairs(df.repartition(3)).collect()}
    for k, m in ((0, 32), (1, 31), (2, 30), (9, 1)):
        x = A.unit(np.array([v for _, v, s in rows if s == k and v and None not in v]))
        assert got[k][0] == m and got[k][1] == pytest.approx(((x @ x.T).sum() - (x != 0).any(axis=1).sum()) / (m * (m - 1)) if m > 1 else 0)
    assert len(labels) == 1 and 20 <= labels[0].count() < 90


def test_zero_vectors_and_single_rows(spark):
    df = vectors(spark, [("a", [0.0, 0.0]), ("b", [1.0, 0.0]), ("c", [1.0, 0.0])]).withColumn("subset_id", F.lit(0))
    assert D.subset_density(df).first().rho == pytest.approx(D.subset_density_pairs(df).first().rho)
    assert D.subset_density(df.limit(1)).first().rho == 0


# clustering


def test_worked_round(spark):
    docs = vectors(spark, [("a", [1.0, 0.0]), ("b", [0.8, 0.6]), ("c", [0.6, 0.8]), ("d", [0.0, 1.0])])
    cents = spark.createDataFrame([("x", [1.0, 0.0], 0), ("y", [0.0, 1.0], 0)], "cluster_id string, vec array<double>, n long")
    near = A.exact(docs, cents).withColumn("cos", F.round("cos", 6))
    got = {r.seg_id: r.spawned for r in isodata.spawn(near, 0.8).collect()}
    assert got == {"a": False, "b": True, "c": True, "d": False}
    assert not any(r.spawned for r in isodata.spawn(near, 0.8, last=True).collect())
    last = isodata.recenter(isodata.spawn(near, 0.8, True), docs, cents).collect()
    assert sum(r["shift"] for r in last) == pytest.approx(0.632456, abs=1e-5)
    assert {r.cluster_id: [round(x, 5) for x in r.vec] for r in last} == {"x": [0.9, 0.3], "y": [0.3, 0.9]}
    means = isodata.recenter(isodata.spawn(near, 0.8), docs, cents)
    edges = isodata.merge_edges(means, 0.8001).collect()
    assert [(e.a, e.b) for e in edges] == [("r/b", "r/c")] and edges[0].cos == pytest.approx(0.96, abs=1e-6)
    after = isodata.unified(means, isodata.merge(means, 0.8001)).collect()
    assert sorted((r.n, [round(x, 5) for x in r.vec]) for r in after) == [(1, [0.0, 1.0]), (1, [1.0, 0.0]), (2, [0.7, 0.7])]


@pytest.mark.parametrize("seed,delta", [(1, 0.5), (2, 0.7), (3, 0.3)])
def test_fit_follows_the_plain_version(spark, seed, delta):
    vec = random_vectors(60, 8, seed)
    docs = vectors(spark, list(vec.items())).repartition(3)
    done = isodata.fit(docs, Config(delta=delta, n_clusters=6, rounds=4, assign="exact", seed=seed))
    groups = {}
    for r in done.membership.collect():
        groups.setdefault(r.cluster_id, set()).add(r.seg_id)
    seeds = [r.cluster_id for r in isodata.seed(docs, 6, seed).collect()]
    want, trace = R.cluster(vec, seeds, delta, 4, 1e-3)
    assert {frozenset(g) for g in groups.values()} == want
    assert [(r["round"], r.spawned, r.merged, r.clusters) for r in done.trace.orderBy("round").collect()] == [t[:4] for t in trace]
    assert sum(len(g) for g in groups.values()) == 60


def test_rounds_resume(spark, tmp_path):
    vec = random_vectors(50, 8, 12)
    docs, c = vectors(spark, list(vec.items())), Config(delta=0.6, n_clusters=5, rounds=3, assign="exact", epsilon=0.0)
    whole = isodata.fit(docs, c)
    sets = lambda done: {frozenset(r.m) for r in done.membership.groupBy("cluster_id").agg(F.collect_set("seg_id").alias("m")).collect()}
    first = isodata.fit(docs, c, state=f"file://{tmp_path}/s")
    again = isodata.fit(docs, c, state=f"file://{tmp_path}/s")
    assert sets(whole) == sets(first) == sets(again) and again.trace.count() == first.trace.count()
    more = isodata.fit(docs, c.with_(rounds=4), state=f"file://{tmp_path}/s")
    assert more.trace.count() >= first.trace.count()


def test_many_seeds(spark, monkeypatch):
    docs = vectors(spark, list(random_vectors(60, 4, 2).items()))
    few = {r.cluster_id for r in isodata.seed(docs, 20, 5).collect()}
    monkeypatch.setattr(isodata, "SEEDS_AT_ONCE", 5)
    assert {r.cluster_id for r in isodata.seed(docs, 20, 5).collect()} == few


def test_merge_modes(spark):
    rows = [("a", [1.0, 0.0], 1), ("b", [0.9, 0.436], 1), ("c", [0.62, 0.785], 1), ("d", [0.0, -1.0], 4)]
    cents = spark.createDataFrame(rows, "cluster_id string, vec array<double>, n long")
    roots = lambda how: {r.cluster_id: r.root for r in isodata.merge(cents, 0.85, how).collect()}
    assert roots("components") == {"a": "a", "b": "a", "c": "a", "d": "d"}
    assert roots("mutual_best") == {"a": "a", "b": "b", "c": "b", "d": "d"} or roots("mutual_best") == {"a": "a", "b": "a", "c": "c", "d": "d"}
    assert len(set(roots("sequential").values())) == 3


def test_other_spawning_and_classic(spark):
    vec = random_vectors(40, 6, 9)
    docs = vectors(spark, list(vec.items()))
    done = isodata.fit(docs, Config(delta=0.6, n_clusters=3, rounds=2, assign="exact", spawn="sequential", shift="mean", finalize=True))
    assert done.membership.count() == 40
    old = isodata.classic(docs, 5, rounds=2)
    assert old.membership.count() == 40 and old.trace.count() == 2


def test_assigners(spark):
    vec = random_vectors(300, 16, 4, groups=40)
    docs = vectors(spark, list(vec.items()))
    cents = isodata.seed(docs, 80, 1)
    truth = A.exact(docs, cents)
    nested = {r.seg_id: r.cluster_id for r in A.exact_sql(docs, cents).collect()}
    assert {r.seg_id: r.cluster_id for r in truth.collect()} == nested
    for how, least in (("hnsw", 0.97), ("cells", 0.8), ("lsh", 0.8)):
        got = A.recall(A.assign(docs, cents, how), truth).first()
        assert got.recall >= least and got.never_above == 1 and got.documents == 300
    assert A.choose(10, 64) == "exact" and A.choose(40_000, 1024) == "cells" and A.choose(10_000, 1024) == "hnsw"
    index = {k: A.Hnsw(A.unit(np.random.default_rng(0).normal(size=(k, 8)))).seal() for k in (200, 2000)}
    asked = A.unit(np.random.default_rng(1).normal(size=(50, 8)))
    cost, hit = {}, {}
    for k, graph in index.items():
        _, places, evals = graph.search(asked)
        cost[k], hit[k] = evals.sum(), (places[:, 0] == (asked @ graph.c.T).argmax(axis=1)).mean()
    assert cost[2000] < 5 * cost[200] and min(hit.values()) > 0.95


def test_assigners_with_small_groups(spark, monkeypatch):
    """Cells and buckets that are dealt over parts give what whole ones give; ties between tables go to the smaller id."""
    vec = random_vectors(200, 8, 6, groups=10)
    docs = vectors(spark, [*vec.items(), ("copy-a", vec["d1"] if "d1" in vec else next(iter(vec.values()))), ("none", [0.0] * 8)])
    cents = isodata.seed(docs, 30, 2)
    whole = {how: sorted(A.assign(docs, cents, how).select("seg_id", "cluster_id").collect()) for how in ("cells", "lsh")}
    monkeypatch.setattr(A, "GROUP_ROWS", 7)
    for how, rows in whole.items():
        assert sorted(A.assign(docs, cents, how).select("seg_id", "cluster_id").collect()) == rows
    edges = {how: sorted(B.knn_graph(docs, 4, how).collect()) for how in ("cells", "lsh")}
    monkeypatch.setattr(A, "GROUP_ROWS", 1000)
    for how, rows in edges.items():
        assert sorted(B.knn_graph(docs, 4, how).collect()) == rows


def test_groups_are_looked_up_without_copies(spark, monkeypatch):
    """Cells and buckets of broadcast centres give what those give that move by key, and write nothing down."""
    vec = random_vectors(120, 8, 6, groups=10)
    docs, labels, keep = vectors(spark, [*vec.items(), ("none", [0.0] * 8)]), [], A.settled
    cents = isodata.seed(docs, 20, 2)
    monkeypatch.setattr(A, "settled", lambda df, label: labels.append(label) or keep(df, label))
    ways = {"cells": {}, "lsh": {"tables": 3, "bits": 5}}
    rows = lambda how: sorted(A.assign(docs, cents, how, **ways[how]).select("seg_id", "cluster_id", "cos", "evals").collect())
    here = {how: rows(how) for how in ways}
    assert not labels and all(len(r) == 121 for r in here.values())
    monkeypatch.setattr(A, "IN_PLACE_BYTES", 0)
    monkeypatch.setattr(A, "GROUP_ROWS", 7)  # dealt over parts
    for how in ways:
        assert rows(how) == here[how]


def test_nearest_of_many_centres_in_blocks(monkeypatch):
    rng = np.random.default_rng(5)
    x, c = A.unit(rng.normal(size=(300, 12))), rng.normal(size=(400, 12)).astype(np.float32)
    c[37], c[5], x[7], x[8] = c[300], 0, 0, A.unit(c[300:301].astype(float))[0]  # equal centres, a zero centre, a zero vector, a hit
    cos = np.round(x @ A.unit(c.astype(np.float64)).T, 12)
    rank = np.argsort(-cos, axis=1, kind="stable")[:, :2]
    want = rank[:, 0], *np.take_along_axis(cos, rank, 1).T
    monkeypatch.setattr(A, "PRODUCT_BYTES", 4 * 400 * 50)  # six blocks
    sizes, inside = [], A.Nearest._two
    monkeypatch.setattr(A.Nearest, "_two", lambda self, part: sizes.append(len(part)) or inside(self, part))
    for got, wanted in zip(A.top_two(x, A.unit(c.astype(np.float64))), want):
        assert np.allclose(got, wanted, atol=1e-12)
    assert max(sizes) == 50 and (A.Nearest(c).two(x)[0] == want[0]).all()
    assert A.choose(20_000, 1024, 55_000) == "exact" and A.choose(20_000, 1024, 10**7) == "hnsw"
    assert [len(v) for v in A.Nearest(c[:1]).two(x[:3])] == [3, 3, 3] and [len(v) for v in A.Nearest(c).two(x[:0])] == [0, 0, 0]


def test_exact_and_cohesion_beyond_a_broadcast(spark, monkeypatch):
    """Centres that are too many for a broadcast give the same rows and measures, bit for bit."""
    vec = random_vectors(200, 8, 6, groups=10)
    docs = vectors(spark, [*vec.items(), ("copy-a", next(iter(vec.values()))), ("copy-b", next(iter(vec.values()))), ("none", [0.0] * 8)])
    cents = isodata.seed(docs, 150, 2)
    rows, keep, files = lambda: sorted(A.assign(docs, cents, "exact").collect()), A.blocks, []
    whole, measures = rows(), stats.cohesion(docs, cents).first()
    monkeypatch.setattr(A, "BROADCAST_BYTES", 64)
    monkeypatch.setattr(A, "blocks", lambda df, key, block, label: files.append(label) or keep(df, key, 9, label))  # many small blocks
    assert len(whole) == 203 and rows() == whole and files
    assert stats.cohesion(docs, cents).first().asDict() == pytest.approx(measures.asDict(), abs=1e-12)
    one = isodata.seed(docs, 1, 2)
    assert {(r.second, r.evals) for r in A.exact(docs, one).collect()} == {(-1.0, 1)} and A.exact(docs.limit(0), one).count() == 0


def test_cohesion_ignores_what_the_number_of_centres_calls_for(spark, monkeypatch):
    docs = vectors(spark, list(random_vectors(120, 8, 3, groups=10).items()))
    cents = isodata.seed(docs, 60, 2)
    measures = stats.cohesion(docs, cents).first()
    monkeypatch.setattr(A, "choose", lambda *size: "cells")
    monkeypatch.setattr(A, "cells_for", lambda k, dim: 20)
    assert stats.cohesion(docs, cents).first() == measures


def test_mutual_mergers_form_no_pairs(spark, monkeypatch):
    """A row per centre is enough, and gives what all links give; equal centres too."""
    vec = random_vectors(120, 6, 8, groups=5)
    rows = [(i, [float(x) for x in v], 1) for i, v in vec.items()]
    cents = spark.createDataFrame([*rows, ("twin", rows[0][1], 1), ("zwin", rows[0][1], 1)], "cluster_id string, vec array<double>, n long")
    for delta in (0.2, 0.9):
        assert isodata.best_edges(cents, delta).count() <= 122
        whole = sorted(isodata.mutual_best(isodata.merge_edges(cents, delta), cents).collect())
        assert sorted(isodata.merge(cents, delta, "mutual_best").collect()) == whole


def test_near_centres_beyond_the_broadcast_are_exact(spark, monkeypatch):
    vec = random_vectors(300, 4, 8)
    cents = spark.createDataFrame([(i, [float(x) for x in v], 1) for i, v in vec.items()], "cluster_id string, vec array<double>, n long")
    rows = lambda forest=False: sorted((r.a, r.b, r.cos) for r in isodata.merge_edges(cents, 0.2, forest=forest).collect())
    roots = lambda: sorted(isodata.components(isodata.merge_edges(cents, 0.97, forest=True), cents).collect())
    every, joined = rows(), roots()
    monkeypatch.setattr(isodata, "MERGE_EXACT", 100)
    monkeypatch.setattr(blocks, "BLOCK_BYTES", 4 * 8 * 40)  # eight blocks
    beyond = rows()
    assert [r[:2] for r in beyond] == [r[:2] for r in every] and np.allclose([r[2] for r in beyond], [r[2] for r in every])
    assert roots() == joined


def test_components_on_either_side_of_the_bound(spark):
    vec = random_vectors(120, 6, 8, groups=15)
    cents = spark.createDataFrame([(i, [float(x) for x in v], 1) for i, v in vec.items()], "cluster_id string, vec array<double>, n long")
    every = isodata.merge_edges(cents, 0.9)
    roots = lambda edges, bound: sorted(isodata.components(edges, cents, driver=bound).collect())
    assert roots(every, 1000) == roots(every, 5) == roots(isodata.merge_edges(cents, 0.9, forest=True), 1000)
    assert isodata.merge_edges(cents, 0.9, forest=True).count() < 120


def test_paths_by_cell_beyond_the_bound(spark, monkeypatch):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    p = P.prepare(docs, Config(dim=64))
    whole = P.graph_paths(p)
    assert whole.filter("not exact").isEmpty()
    monkeypatch.setattr(B, "TRAVERSE_NODES", 50)
    parts = P.graph_paths(p)
    assert parts.filter("exact").isEmpty() and parts.count() == whole.count() == parts.select("seg_id").distinct().count()


def test_intermediates_go(spark):
    def build():
        return session.settled(session.settled(spark.range(10), "a").filter("id > 3"), "b")

    before = set(os.listdir(session.state_dir(spark).removeprefix("file://")))
    assert session.distilled(spark, "c", build).count() == 6
    left = set(os.listdir(session.state_dir(spark).removeprefix("file://"))) - before
    assert [x.split("-")[0] for x in left] == ["c"]
    with pytest.raises(ValueError):
        session.distilled(spark, "d", lambda: [session.settled(spark.range(3), "e"), int("x")])
    assert not {x for x in os.listdir(session.state_dir(spark).removeprefix("file://")) if x.startswith("e-")}


def test_null_domains_stay(spark):
    rows = [(i, " ".join(["w%d" % (i % 7)] * 20), d) for i, d in enumerate(["en", "de", None] * 6)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    found = P.organize_domain(docs, "lang", "en", Config(window=64, dim=32, n_clusters=2, rounds=2))
    assert {r.seg_id for r in found.collect()} == {f"{i}:0" for i in range(18)}
    assert found.filter("window_id is null").isEmpty()
    ratios = mixture.domain_ratios(docs.withColumn("n_tokens", F.lit(20)).withColumn("seg_id", F.col("doc_id").cast("string")), "lang")
    assert set(ratios) == {"en", "de", None}
    mixed = mixture.mix(docs.withColumn("n_tokens", F.lit(20)).withColumn("seg_id", F.col("doc_id").cast("string")), "lang", ratios, 10_000)
    assert mixed.count() == 18


# baselines


def test_worked_chop(spark):
    rows = spark.createDataFrame([("d1", 4), ("d2", 5), ("d3", 6)], "seg_id string, n_tokens int")
    got = sorted((r.window_id[-1], r.seg_id, r.start, r.offset, r.used) for r in B.chop(rows, F.col("seg_id"), 5).collect())
    assert got == [("0", "d1", 0, 0, 4), ("0", "d2", 0, 4, 1), ("1", "d2", 1, 0, 4), ("1", "d3", 0, 4, 1), ("2", "d3", 1, 0, 5)]
    w = objective.counts(objective.per_window(B.chop(rows, F.col("seg_id"), 5).filter("window_id like '%0'"), 5), 5).first()
    assert w.cross_attention == pytest.approx(1 - (4 * 5 + 1 * 2) / (5 * 6))


def test_prefix_sums_over_ranges(spark):
    rng = random.Random(1)
    rows = [(i, rng.randint(0, 9)) for i in range(500)]
    got = {r.i: r.before for r in running(spark.createDataFrame(rows, "i long, n int").repartition(7), F.col("i") % 50, "n", ["i"]).collect()}
    want, total = {}, 0
    for i, n in sorted(rows, key=lambda r: (r[0] % 50, r[0])):
        want[i] = total
        total += n
    assert got == want


def test_graph_and_paths(spark):
    vec = random_vectors(60, 8, 5)
    docs = vectors(spark, list(vec.items()))
    edges = B.knn_graph(docs, 4, "exact", block=20).collect()
    for n in vec:
        near = sorted(((-round(R.cosine(vec[n], vec[m]), 12), m) for m in vec if m != n))[:4]
        assert [e.dst for e in sorted((e for e in edges if e.src == n), key=lambda e: (-e.w, e.dst))] == [m for _, m in near]
    frame = spark.createDataFrame([(e.src, e.dst, e.w) for e in edges], "src string, dst string, w double")
    paths = {}
    for r in B.traverse(frame, docs.select("seg_id")).collect():
        paths.setdefault(r.path_id, []).append((r.pos, r.seg_id))
    assert [[s for _, s in sorted(paths[p])] for p in sorted(paths)] == R.walk(list(vec), [(e.src, e.dst, e.w) for e in edges])
    celled = B.traverse(frame, docs.withColumn("c", F.crc32("seg_id") % 3), "c").collect()
    assert sorted(r.seg_id for r in celled) == sorted(vec) and not any(r.exact for r in celled)


def test_all_pairs_move_results_alone(spark):
    vec = random_vectors(400, 64, 5) | {f"z{i:03d}": [1.0] + [0.0] * 63 for i in range(60)}  # a group of copies beside noise
    docs = vectors(spark, list(vec.items()))
    docs.count()
    before = costs.counters(spark)["shuffle_written"]
    edges = B.knn_graph(docs, 4, "exact", block=10).collect()
    assert costs.counters(spark)["shuffle_written"] - before < 460 * 64 * 8 * 10  # 46 blocks: each vector copied to all of them is nine times that
    for n in vec:
        near = sorted(((-round(R.cosine(vec[n], vec[m]), 12), m) for m in vec if m != n))[:4]
        assert [e.dst for e in sorted((e for e in edges if e.src == n), key=lambda e: (-e.w, e.dst))] == [m for _, m in near]


def test_walks_hold_numbers(spark):
    frame = spark.createDataFrame([(f"n{i}", f"n{i + k}", 1.0 / k) for i in range(60) for k in (1, 2, 3)], "src string, dst string, w double")
    nodes = spark.createDataFrame([(f"n{i}",) for i in range(70)], "seg_id string")
    got = B.traverse(frame, nodes)
    assert got.count() == 70
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert "FlatMapCoGroupsInPandas" not in plan  # which would hold all edges with their names in one task


def test_every_baseline_places_every_token(spark):
    rng = random.Random(6)
    vec = random_vectors(50, 6, 6)
    rows = [(n, i, 0, rng.choice([0, 1, 40, 100]), v) for i, (n, v) in enumerate(vec.items())]
    segs = spark.createDataFrame([(n, i, k, s) for n, i, k, s, _ in rows], "seg_id string, doc_id long, seg_no int, n_tokens int")
    docs, tokens = vectors(spark, [(n, v) for n, _, _, _, v in rows]), sum(r[3] for r in rows)
    edges = B.knn_graph(docs, 5)
    mem = segs.join(docs, "seg_id").withColumn("cluster_id", F.lit("k"))
    ways = {
        "random": B.random_windows(segs, 100),
        "single": B.single_windows(segs, 100),
        "graph": B.graph_windows(segs, B.traverse(edges, segs.select("seg_id")), 100),
        "retrieval": B.retrieval_windows(segs, edges, 100, 5),
        "first": B.window_first(mem, Config(window=100)),
        **{rule: B.fit_decreasing(segs, 100, rule) for rule in ("best", "worst")},
    }
    for name, m in ways.items():
        assert m.agg(F.sum("used") + F.sum("cut")).first()[0] == tokens, name
        assert m.groupBy("window_id").agg(F.sum("used").alias("u")).filter("u > 100").count() == 0, name


# text


def test_segments(spark):
    df = spark.createDataFrame([(1, "a b c d e"), (2, ""), (3, None), (4, "x y")], "doc_id long, text string")
    got = {r.seg_id: r.tokens for r in segment(df, 2).collect()}
    assert got == {"1:0": ["a", "b"], "1:1": ["c", "d"], "1:2": ["e"], "2:0": [], "3:0": [], "4:0": ["x", "y"]}
    assert {r.seg_id: r.n_tokens for r in segment(df, 2, "truncate").collect()} == {"1:0": 2, "2:0": 0, "3:0": 0, "4:0": 2}
    with pytest.raises(ValueError):
        segment(df, 2, "other")
    with pytest.raises(ValueError):
        require(df, SEGMENTS)


def test_hashed_vectors(spark):
    df = segment(spark.createDataFrame([(1, "a b a"), (2, ""), (3, "A B a"), (4, "zz")], "doc_id long, text string"), 10)
    v = {r.seg_id: np.array(r.vec) for r in embed.hash_embed(df, 64).collect()}
    assert np.allclose(v["1:0"], v["3:0"]) and not v["2:0"].any() and np.linalg.norm(v["4:0"]) == pytest.approx(1, abs=1e-6)
    model = embed.with_model(df, lambda: lambda texts: np.array([[len(t), 1.0] for t in texts]), 2)
    assert {r.seg_id: list(r.vec) for r in model.collect()}["4:0"] == [2.0, 1.0]


def test_windows_hold_their_tokens(spark):
    segs = segment(spark.createDataFrame([(i, " ".join(f"{i}_{k}" for k in range(7 * i % 40))) for i in range(1, 30)], "doc_id long, text string"), 16)
    m = B.random_windows(segs, 16)
    whole = materialize.windows(m, segs, 16, pad="_").collect()
    assert all(len(r.tokens) == 16 for r in whole) and sum(r.n_tokens for r in whole) == sum(7 * i % 40 for i in range(1, 30))
    assert len({t for r in whole for t in r.tokens if t != "_"}) == sum(r.n_tokens for r in whole)


def test_same_manifest_for_any_partitioning(spark):
    vec = random_vectors(80, 8, 7)
    rows = [(n, 10 + i % 50, v) for i, (n, v) in enumerate(sorted(vec.items()))]
    sets = [sorted((r.window_id, r.pos, r.seg_id) for r in pack.pack(members(spark, rows).repartition(k), Config(window=100)).collect()) for k in (1, 4, 16)]
    assert sets[0] == sets[1] == sets[2]


def test_whole_plan_and_domain(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    c = Config(window=512, dim=64, rounds=2, n_clusters=8, delta=0.5)
    done = P.organize(docs, c)
    assert done.manifest.select("seg_id").distinct().count() == done.prepared.segments.count() == done.manifest.count()
    assert stats.cluster_table(stats.cluster_sizes(done.clustering.membership)).first().clusters >= 1
    one = P.organize_domain(docs, "lang", "fr", c)
    assert {r.method for r in one.select("method").distinct().collect()} == {"framework", "random"}


def test_steps_and_rate(spark):
    steps = batch(spark.range(100).select(F.col("id").cast("string").alias("window_id")), 1024, 8 * 1024)
    sizes = sorted(r["count"] for r in steps.groupBy("step").count().collect())
    assert sizes == [4] + [8] * 12
    lr = {r.s: r.v for r in spark.createDataFrame([(0,), (500,), (1000,), (4087,)], "s long").select("s", learning_rate(F.col("s"), 4087).alias("v")).collect()}
    assert lr[500] == pytest.approx(1.5e-4) and lr[1000] == pytest.approx(3e-4) and lr[0] == 0 and lr[4087] == pytest.approx(0, abs=1e-12)


def test_config_is_checked():
    for bad in ({"merge": "x"}, {"alpha": -1.0}, {"rounds": 0}):
        with pytest.raises(ValueError):
            Config(**bad)


def test_connected_rows_are_not_compared_again(spark, monkeypatch):
    """Blocks connect what all links connect, with fewer links than rows; cosines at the threshold, equal, zero and infinite vectors too."""
    rng = np.random.default_rng(4)
    x = np.concatenate([rng.normal(size=(300, 16)), np.eye(16)[:1] * 0.6 + np.eye(16)[1:2] * 0.8, np.eye(16)[:2], np.zeros((2, 16)), np.full((1, 16), np.inf)])
    x = np.concatenate([x, x[:20]])
    with np.errstate(invalid="ignore"):
        u = blocks.unit(x)
        for delta in (0.6, 0.4, 0.8):
            near = np.round(u @ u.T, 12) > delta
            want = isodata.connected([(str(i), str(j)) for i, j in zip(*np.nonzero(near)) if i != j], [str(i) for i in range(len(x))])
            joined, links = blocks.Joined(delta), []
            cuts = [*range(0, len(x), 100), len(x)]
            for p, a in enumerate(cuts[:-1]):
                for b, end in zip(cuts[p:], cuts[p + 1 :]):
                    i, j, cos = joined.see(a, u[a : cuts[p + 1]], u[a : cuts[p + 1]].astype(np.float32), b, u[b:end])
                    assert (cos > delta).all() and near[a + i, b + j].all()
                    links += [(str(a + s), str(b + t)) for s, t in zip(i, j)]
            assert len(links) < len(x) and isodata.connected(links, list(want)) == want
    rows = spark.createDataFrame([(f"c{i:03d}", v.tolist(), 1) for i, v in enumerate(x[:300])], "cluster_id string, vec array<double>, n long")
    whole = sorted(isodata.merge(rows, 0.6).collect())
    monkeypatch.setattr(isodata, "FOREST_NUMBERS", 0)
    monkeypatch.setattr(blocks, "BLOCK_BYTES", 16 * 8 * 40)
    assert sorted(isodata.merge(rows, 0.6).collect()) == whole


def test_text_is_read_once_for_vectors(spark):
    df = spark.createDataFrame([("a", ["x", "Y", "y"]), ("b", []), ("c", ["x"] * 3)], "seg_id string, tokens array<string>")
    for signed in (False, True):
        found = embed.hash_embed(df, 32, signed=signed)
        assert "tokens" not in found._jdf.queryExecution().optimizedPlan().toString()
        v = {r.seg_id: np.array(r.vec) for r in found.collect()}
        assert not v["b"].any() and np.isclose(np.linalg.norm(v["a"]), 1) and np.isclose(abs(v["c"]).max(), 1)
    assert {r.b: r.df for r in embed.document_frequency(df, 32).collect()} == {r.b: r["count"] for r in embed.hash_sparse(df, 32).groupBy("b").count().collect()}


def test_sums_beyond_what_a_task_holds(spark, monkeypatch):
    df = spark.createDataFrame([(f"g{i % 7}" if i % 11 else None, [float(i), 1.0, 0.0]) for i in range(200)], "g string, vec array<float>").coalesce(2)
    want = {f"g{k}": [float(sum(i for i in range(200) if i % 11 and i % 7 == k)), float(sum(1 for i in range(200) if i % 11 and i % 7 == k)), 0.0] for k in range(7)}
    whole = D.vector_sums(df, "g", unit=False).collect()
    monkeypatch.setattr(D, "SUM_BYTES", 24)
    for rows in (whole, D.vector_sums(df, "g", unit=False).collect()):
        assert {r.g: list(r.vec) for r in rows} == want and {r.g: r.n for r in rows} == {g: v[1] for g, v in want.items()}
    with pytest.raises(Exception, match="another length"):
        D.vector_sums(spark.createDataFrame([("a", [1.0]), ("a", [1.0, 2.0])], "g string, vec array<float>").coalesce(1), "g").collect()


def test_large_products_are_shared(monkeypatch):
    rng = np.random.default_rng(6)
    lengths, vectors = np.sort(rng.integers(1, 101, 700))[::-1], rng.random((700, 8))
    alone = pack.pack_cluster(lengths, vectors, Config(window=100))
    monkeypatch.setattr(pack, "SHARED_PRODUCT", 1)
    assert pack.pack_cluster(lengths, vectors, Config(window=100)) == alone == plain_pack(lengths, vectors, Config(window=100), math.ceil(lengths.sum() / 100))


def test_vectors_are_written_once(spark, monkeypatch):
    made = []
    for module in (P, isodata):
        monkeypatch.setattr(module, "settled", lambda df, label: (made.append(label), session.settled(df, label))[1])
    docs = spark.createDataFrame([(i, f"a{i % 3} b{i % 5} c") for i in range(20)], "doc_id long, text string")
    done = P.organize(docs, Config(window=8, dim=16, n_clusters=2, rounds=1))
    assert made.count("vectors") == 1 and done.manifest.count() == 20
