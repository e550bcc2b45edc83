import numpy as np

from windowforge.llm import nndescent
from windowforge.llm.nndescent import nearest


def exact(rows, k, every):
    rows = {i: np.asarray(np.float32(v), dtype=np.float64) for i, v in rows if v and None not in v and np.isfinite(v).all() and any(v)}
    out = {}
    for q in rows:
        if q % every == 0:
            scored = sorted((-float((rows[q] * v).sum()), i) for i, v in rows.items() if i != q)
            out[q] = [(i, -s) for s, i in scored[:k]]
    return out


def compare(spark, rows, k=5, every=4):
    frame = spark.createDataFrame([(i, [float(x) if x is not None else None for x in v] if v is not None else None) for i, v in rows], "vec_id long, embedding array<float>")
    got = {}
    for r in nearest(frame, k, every).collect():
        got.setdefault(r.query_id, {})[r["rank"]] = (r.vec_id, r.score)
    want, hit, all_ = exact(rows, k, every), 0, 0
    assert set(got) == {q for q in want if want[q]}
    for q, answers in want.items():
        mine = [got[q][i] for i in sorted(got[q])] if answers else []
        assert len(mine) == len(answers) and all(a[1] > b[1] or a[1] == b[1] and a[0] < b[0] for a, b in zip(mine, mine[1:]))
        hit += len({i for i, _ in mine} & {i for i, _ in answers})
        all_ += len(answers)
    return hit / max(all_, 1)


def test_recall_ties_and_bad_vectors(spark, monkeypatch):
    rng = np.random.default_rng(1)
    rows = [(i, rng.normal(size=16).tolist()) for i in range(1200)]
    rows += [(2000 + i, rows[4][1]) for i in range(150)]  # a vector that many rows share
    rows += [(3000, None), (3004, [0.0] * 16), (3008, [float("nan")] * 16), (3012, [float("inf")] + [0.0] * 15), (3016, [None] + [1.0] * 15), (3020, [])]
    assert compare(spark, rows) >= 0.95
    monkeypatch.setattr(nndescent, "LEAF", 64)
    monkeypatch.setattr(nndescent, "BLOCK", 300)
    monkeypatch.setattr(nndescent, "QUERIES", 50)
    assert compare(spark, rows) >= 0.95


def test_few_rows(spark):
    assert compare(spark, []) == 0
    assert compare(spark, [(0, [1.0, 2.0])]) == 0
    assert compare(spark, [(0, [1.0, 2.0]), (4, [1.0, 2.0]), (5, [-1.0, 0.5])]) == 1


def test_clusters_and_lengths(spark, monkeypatch):
    rng = np.random.default_rng(6)
    centres = rng.normal(size=(100, 24))
    rows = [(i, (centres[i % 100] + 0.3 * rng.normal(size=24)).tolist()) for i in range(4000)]  # more than 33 a cluster: the graph is in pieces
    assert compare(spark, rows, 10, 37) >= 0.95
    long = rows + [(8001, (1e7 * rng.normal(size=24)).tolist())]  # one long vector leaves the others their numbers
    assert compare(spark, long, 10, 37) >= 0.95
    monkeypatch.setattr(nndescent, "LEAF", 128)
    monkeypatch.setattr(nndescent, "BLOCK", 1024)
    assert compare(spark, long, 10, 37) >= 0.95


def test_one_hot_vector_and_large_ids(spark):
    big = 20 * (2**58 + 1)
    rng = np.random.default_rng(3)
    rows = [(i, rng.normal(size=8).tolist()) for i in range(60)] + [(big + i, [1.0] * 8) for i in range(300)]
    assert compare(spark, rows, 20, 20) == 1


def test_few_nodes_are_scored(spark, monkeypatch):
    """The graph does the work: small leaves and blocks, recall against brute force, and the share of nodes that a query scores."""
    monkeypatch.setattr(nndescent, "LEAF", 256)
    monkeypatch.setattr(nndescent, "BLOCK", 2048)
    rng = np.random.default_rng(9)
    base = rng.normal(size=(12, 24))  # twelve directions in 24 dimensions
    x = (rng.normal(size=(8000, 12)) @ base).astype(np.float32)
    frame = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<float>")
    answers, lists, count = nndescent._nearest(frame, 10, 100, "vec_id", "embedding", 48, {"k": 32, "through": 12, "rounds": 4})
    got = {}
    for r in answers.collect():
        got.setdefault(r.query_id, set()).add(r.vec_id)
    want = {q: set(sorted((i for i in range(8000) if i != q), key=lambda i, q=q, s=x.astype(float) @ x[q].astype(float): (-s[i], i))[:10]) for q in range(0, 8000, 100)}
    assert count == 8000 and np.mean([len(want[q] & got[q]) / 10 for q in want]) >= 0.95
    assert lists.agg(nndescent.F.avg("seen")).first()[0] < 0.15 * count
