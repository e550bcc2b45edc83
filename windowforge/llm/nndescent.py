"""Nearest neighbours by inner product: NN-descent builds one graph over all vectors in rounds of joins, queries walk it greedily.

Equal vectors are one node that keeps the smallest ids among its rows, as many as one answer can hold.

*Start.* Random hyperplanes deal the nodes over leaves; neighbours within a leaf, and a few within a random bucket, are the
first edges, so that nothing is without an edge.

*Rounds.* Each node shows a sample of its edges, new ones and old ones apart, to both their ends. Edges that share a middle node
are brought together by its block, with the vectors of their other ends, each once for a block: two ends of one middle node,
one of them new, become a candidate edge of both. What beats a node's worst edge is offered to it, and each node keeps its best.
Rounds end when few edges still change.

*Search.* A query starts from its own node's edges. In each step the best nodes of its list that are not opened yet are joined
with their edges, forward and reverse, and these with their vectors; the list keeps the best, until all in it are open.

Graph and walk use directions of 16 bits a number with the length kept apart. What a query met last is scored again on the
original numbers in double precision.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Observation, Window
from pyspark.sql import functions as F

from .common import distilled, materialize, ship

#: Nodes of a leaf that are compared with each other at first, of a random bucket, and of a block that one task treats in a round; blocks at least.
LEAF, BUCKET, BLOCK, BLOCKS = 512, 256, 8_192, 8
#: Edges that a node keeps, edges of each kind and direction that it shows in a round, reverse edges that a query also walks.
NEIGHBOURS, THROUGH, REVERSE = 64, 24, 16
#: Candidates that a block offers to a node at most, and a random bucket; the best ones.
OFFERS, LOOSE = 16, 4
#: Rounds at most, and the share of edges that changed below which they end.
ROUNDS, STILL = 7, 0.05
#: A query's list, what it opens in a step at most, steps at most, and queries of a task.
BEAM, EXPAND, STEPS, QUERIES = 64, 32, 16, 512
OFFER = "node long, other binary, score binary"
GRAPH = "node long, vector binary, other binary, score binary, fresh binary, new array<long>, old array<long>, changed long"


def usable(vectors: DataFrame, id_col: str, vector_col: str) -> DataFrame:
    """(id, v): rows with an id and a vector that is neither null nor zero, holds finite numbers alone and has the most common length."""
    rows = vectors.select(F.col(id_col).alias("id"), F.col(vector_col).alias("v")).filter("id is not null and v is not null and size(v) > 0")
    rows = rows.filter(F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists("v", lambda x: x != 0))
    common = rows.groupBy(F.size("v").alias("k")).count().orderBy(F.desc("count"), "k").first()
    return rows.filter(F.size("v") == (common["k"] if common else 0))


def nodes_of(rows: DataFrame, keep: int) -> DataFrame:
    """One row per distinct vector: node (its smallest id), the vector v in doubles, members (its ``keep`` smallest ids).

    The smallest ids are taken in two steps, so that a vector which a third of all rows share never meets in one task.
    """
    smallest = lambda c: F.slice(F.array_sort(F.array_distinct(c)), 1, keep)
    part = rows.groupBy("v", F.pmod(F.xxhash64("id"), F.lit(64)).alias("salt")).agg(F.collect_set("id").alias("ids"))
    whole = part.select("v", smallest(F.col("ids")).alias("ids")).groupBy("v").agg(smallest(F.flatten(F.collect_list("ids"))).alias("members"))
    return whole.select(F.col("members")[0].alias("node"), F.col("v").cast("array<double>").alias("v"), "members")


def packed(v: np.ndarray) -> bytes:
    """A vector that is not zero: its length in double precision, then its direction in 16 bits a number."""
    v = np.asarray(v, dtype=np.float64)
    largest = np.abs(v).max()
    norm = np.sqrt(((v / largest) ** 2).sum())
    return np.float64(min(float(largest) * float(norm), np.finfo(np.float64).max)).astype("<f8").tobytes() + (v / largest / norm).astype("<f2").tobytes()


def unpacked(vectors: pd.Series) -> tuple[np.ndarray, np.ndarray]:
    """Lengths and directions."""
    raw = np.frombuffer(b"".join(vectors), dtype=np.uint8).reshape(len(vectors), -1)
    return raw[:, :8].copy().view("<f8")[:, 0], raw[:, 8:].copy().view("<f2").astype(np.float32)


def block_of(node: Column, blocks: int) -> Column:
    return F.pmod(F.xxhash64(node, F.lit(3)), F.lit(blocks).cast("long"))


def best_each(of: np.ndarray, other: np.ndarray, score: np.ndarray, most: int) -> np.ndarray:
    """Places of the ``most`` best rows of each ``of``, repeated pairs once, in the order of ``of`` and best first; ties to smaller ``other``."""
    at = np.lexsort((other, of))
    first = np.ones(len(at), dtype=bool)
    first[1:] = (of[at][1:] != of[at][:-1]) | (other[at][1:] != other[at][:-1])
    at = at[first]
    at = at[np.lexsort((other[at], -score[at], of[at]))]
    group = of[at]
    return at[np.arange(len(at)) - np.searchsorted(group, group) < most]


def offers(node: np.ndarray, of: np.ndarray, other: np.ndarray, score: np.ndarray) -> pd.DataFrame:
    """A row per node that is offered something; ``of`` are places in ``node``, in order."""
    places, begin = np.unique(of, return_index=True)
    cut = lambda a: [x.tobytes() for x in np.split(a, begin[1:])] if len(places) else []
    return pd.DataFrame({"node": node[places], "other": cut(node[other].astype("<i8")), "score": cut(score.astype("<f8"))})


def inside(group: pd.DataFrame, k: int) -> pd.DataFrame:
    """Each node of a group is offered its k nearest others there."""
    group = group.sort_values("node", kind="stable")
    node = group["node"].to_numpy(dtype=np.int64)
    length, x = unpacked(group["vector"])
    most, found = min(k, len(node) - 1), []
    for b in range(0, len(node) if most > 0 else 0, 512):
        score = (x[b : b + 512] @ x.T).astype(np.float64) * length
        score[np.arange(len(score)), np.arange(b, b + len(score))] = -np.inf
        at = np.argpartition(-score, most - 1, axis=1)[:, :most]
        found.append((np.repeat(np.arange(b, b + len(score)), most), at.ravel(), np.take_along_axis(score, at, 1).ravel()))
    if not found:
        return pd.DataFrame({"node": [], "other": [], "score": []}).astype({"node": "int64", "other": object, "score": object})
    of, other, score = (np.concatenate(z) for z in zip(*found))
    return offers(node, of, other, score)


def met(edges: pd.DataFrame, ends: pd.DataFrame, most: int) -> pd.DataFrame:
    """Candidate edges of a block. edges (mid, x, fresh): what the middle nodes were shown; ends (x, vector, floor): their vectors, and the
    score that a candidate must beat."""
    ends = ends.sort_values("x", kind="stable")
    node, floor = ends["x"].to_numpy(dtype=np.int64), ends["floor"].to_numpy(dtype=np.float64)
    length, x = unpacked(ends["vector"])
    mid, end, fresh = edges["mid"].to_numpy(dtype=np.int64), np.searchsorted(node, edges["x"].to_numpy(dtype=np.int64)), edges["fresh"].to_numpy(dtype=bool)
    at = np.lexsort((~fresh, end, mid))
    mid, end, fresh = mid[at], end[at], fresh[at]
    once = np.ones(len(mid), dtype=bool)
    once[1:] = (mid[1:] != mid[:-1]) | (end[1:] != end[:-1])
    mid, end, fresh = mid[once], end[once], fresh[once]
    mids, begin, size = np.unique(mid, return_index=True, return_counts=True)
    place = np.arange(len(mid)) - np.repeat(begin, size)
    table, new = np.full((len(mids), size.max()), len(node), dtype=np.int64), np.zeros((len(mids), size.max()), dtype=bool)
    row = np.repeat(np.arange(len(mids)), size)
    table[row, place], new[row, place] = end, fresh
    wide = np.vstack([x, np.zeros((1, x.shape[1]), dtype=np.float32)])
    scale = max(float(length.max()), 1e-300)  # 32 bits compare, 64 bits are passed on
    lengths, floors = np.append(length / scale, 0.0).astype(np.float32), np.append(floor / scale, np.inf).astype(np.float32)
    even = bool((lengths[:-1] == 1).all())
    held: list[tuple[np.ndarray, ...]] = []
    rows = 0
    for b in range(0, len(mids), 128):
        ids, flag = table[b : b + 128], new[b : b + 128]
        y = wide[ids]
        score = np.matmul(y, y.transpose(0, 2, 1))
        if not even:
            score *= lengths[ids][:, None, :]
        g, i, j = np.nonzero(score > floors[ids][:, :, None])
        real = (flag[g, i] | flag[g, j]) & (i != j) & (ids[g, j] < len(node))
        g, i, j = g[real], i[real], j[real]
        held.append((ids[g, i], ids[g, j], score[g, i, j].astype(np.float64) * scale))
        rows += len(g)
        if rows > 3_000_000 or b + 128 >= len(mids):
            of, other, score = (np.concatenate(z) for z in zip(*held))
            at = best_each(of, other, score, most)
            held, rows = [(of[at], other[at], score[at])], 0
    return offers(node, *held[0])


def kept(block: pd.DataFrame, offered: pd.DataFrame, k: int, through: int, draw: list[int]) -> pd.DataFrame:
    """The nodes of a block with their best edges so far, and samples of new and of old ones to show in the next round."""
    block = block.sort_values("node", kind="stable")
    node = block["node"].to_numpy(dtype=np.int64)

    def flat(frame: pd.DataFrame) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        if not len(frame):
            return np.zeros(0, dtype=np.int64), np.zeros(0, dtype=np.int64), np.zeros(0)
        of = np.repeat(np.searchsorted(node, frame["node"].to_numpy(dtype=np.int64)), [len(v) // 8 for v in frame["other"]])
        return of, np.frombuffer(b"".join(frame["other"]), dtype="<i8"), np.frombuffer(b"".join(frame["score"]), dtype="<f8")

    (of, other, score), (of2, other2, score2) = flat(block), flat(offered)
    state = np.frombuffer(b"".join(block["fresh"]), dtype=np.uint8)  # 0: shown before, 1: not yet
    of, other, score = np.concatenate([of, of2]), np.concatenate([other, other2]), np.concatenate([score, score2])
    state = np.concatenate([state, np.full(len(of2), 2, dtype=np.uint8)])
    at = best_each(of, other, score, k)  # stable: an edge that was there comes before its like
    of, other, score, state = of[at], other[at], score[at], state[at]
    changed = np.bincount(of[state == 2], minlength=len(node))
    rng = np.random.default_rng([*draw, int(node[0]) & 0xFFFFFFFF])
    chance, shown = rng.random(len(of)), []
    fresh = state > 0
    for kind in (fresh, ~fresh):
        some = np.flatnonzero(kind)
        some = some[np.lexsort((chance[some], of[some]))]
        shown.append(some[np.arange(len(some)) - np.searchsorted(of[some], of[some]) < through])
    fresh = fresh.copy()
    fresh[shown[0]] = False
    ends = np.arange(len(node) + 1)
    cut = lambda a, o: np.split(a, np.searchsorted(o, ends[1:-1])) if len(node) > 1 else [a]
    lists = [cut(other[s], of[s]) for s in shown]
    return pd.DataFrame(
        {
            "node": node, "vector": block["vector"].tolist(), "other": [v.tobytes() for v in cut(other.astype("<i8"), of)], "score": [v.tobytes() for v in cut(score.astype("<f8"), of)],
            "fresh": [v.tobytes() for v in cut(fresh.astype(np.uint8), of)], "new": lists[0], "old": lists[1], "changed": changed,
        }
    )


def leaves(points: DataFrame, count: int, size: int, seed: int) -> DataFrame:
    """Adds leaf and part: sides of random hyperplanes, as many as bring a leaf to about ``size`` nodes; larger leaves are dealt over parts."""
    bits = max(0, int(np.ceil(np.log2(max(count, 1) / size))))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        planes = None
        for batch in batches:
            if len(batch):
                _, x = unpacked(batch["vector"])
                planes = np.random.default_rng(seed).normal(size=(x.shape[1], bits)) if planes is None else planes
                yield batch.assign(leaf=(x @ planes > 0) @ (1 << np.arange(bits, dtype=np.int64)) if bits else 0)

    placed = points.mapInPandas(run, "node long, vector binary, leaf long")
    many = placed.groupBy("leaf").agg(F.ceil(F.count(F.lit(1)) / (2 * size)).cast("long").alias("parts")).filter("parts > 1")  # one row a leaf that is too large
    return placed.join(F.broadcast(many), "leaf", "left").withColumn("part", F.pmod(F.xxhash64("node"), F.coalesce("parts", F.lit(1).cast("long")))).drop("parts")


def build_graph(points: DataFrame, count: int, rounds: int = ROUNDS, k: int = NEIGHBOURS, through: int = THROUGH, seed: int = 5, leaf: int | None = None, block: int | None = None) -> DataFrame:
    """From (node, vector) a graph (node, vector, other, score): packed ids of each node's best others and their scores. Each round is written down."""
    blocks, give = max(BLOCKS, -(-count // (block or BLOCK))), OFFERS
    spread = leaves(points, count, leaf or LEAF, seed).groupBy("leaf", "part").applyInPandas(lambda g: inside(g, k), OFFER)
    buckets = F.pmod(F.xxhash64("node", F.lit(seed)), F.lit(max(1, -(-count // BUCKET))).cast("long"))
    offered = spread.unionByName(points.groupBy(buckets.alias("bucket")).applyInPandas(lambda g: inside(g, LOOSE), OFFER))
    none = F.unhex(F.lit(""))
    graph = points.select("node", "vector", none.alias("other"), none.alias("score"), none.alias("fresh"))

    def merging(turn: int):
        return lambda block, offered: kept(block, offered.rename(columns={"to": "node", "o": "other", "s": "score"}), k, through, [seed, turn])

    for turn in range(rounds + 1):
        told = Observation()
        # names of their own: a cogroup takes columns that both sides inherit for one
        gifts = offered.select(F.col("node").alias("to"), F.col("other").alias("o"), F.col("score").alias("s"))
        both = graph.select("node", "vector", "other", "score", "fresh").groupBy(block_of(F.col("node"), blocks)).cogroup(gifts.groupBy(block_of(F.col("to"), blocks)))
        merged = both.applyInPandas(merging(turn), GRAPH)
        graph = materialize(merged.observe(told, F.sum("changed").alias("changed")), f"graph-{turn}")
        if turn == rounds or (turn and (told.get["changed"] or 0) < STILL * k * count):
            break
        shown = graph.select(F.col("node").alias("mid"), F.explode(F.concat(F.transform("new", lambda v: F.struct(v.alias("x"), F.lit(True).alias("fresh"))), F.transform("old", lambda v: F.struct(v.alias("x"), F.lit(False).alias("fresh"))))).alias("e")).select("mid", "e.x", "e.fresh")
        order = Window.partitionBy("mid", "fresh").orderBy(F.xxhash64("mid", "x", F.lit(turn)))
        back = shown.select(F.col("x").alias("mid"), F.col("mid").alias("x"), "fresh").withColumn("k", F.row_number().over(order)).filter(F.col("k") <= through).drop("k")
        edges = materialize(shown.unionByName(back).select(block_of(F.col("mid"), blocks).alias("b"), "mid", "x", "fresh"), f"edges-{turn}")
        floor = F.when(F.octet_length("score") >= 8 * k, F.substring("score", 8 * k - 7, 8))
        ends = edges.select(F.col("b").alias("block"), F.col("x").alias("end")).distinct().join(graph.select(F.col("node").alias("end"), "vector", floor.alias("worst")), "end")

        def meet(edges: pd.DataFrame, ends: pd.DataFrame) -> pd.DataFrame:
            floors = [np.frombuffer(s, dtype="<f8")[-1] if s is not None else -np.inf for s in ends["worst"]]
            return met(edges, ends.rename(columns={"end": "x"}).assign(floor=floors), give)

        offered = edges.groupBy("b").cogroup(ends.groupBy("block")).applyInPandas(meet, OFFER)
    return graph.select("node", "vector", "other", "score")


def step(lists: pd.DataFrame, links: pd.DataFrame, ends: pd.DataFrame, beam: int, expand: int) -> pd.DataFrame:
    """One step of a task's queries: what they opened last is read, the lists keep the best, and the next ones are opened."""
    if not len(lists):
        return lists
    lists = lists.sort_values("query", kind="stable")
    node = np.zeros(0, dtype=np.int64)
    if len(ends):
        ends = ends.sort_values("end", kind="stable")
        node = ends["end"].to_numpy(dtype=np.int64)
        length, x = unpacked(ends["vector"])
    around = dict(zip(links["at"], links["around"])) if len(links) else {}
    _, q = unpacked(lists["vector"])
    rows = []
    for i, (query, other, score, done, opened, seen) in enumerate(zip(lists["query"], lists["other"], lists["score"], lists["done"], lists["opened"], lists["seen"])):
        ids, scores, closed = np.frombuffer(other, dtype="<i8"), np.frombuffer(score, dtype="<f8"), np.frombuffer(done, dtype=np.uint8)
        found = [around[v] for v in opened if v in around]
        if found:
            fresh = np.setdiff1d(np.concatenate(found), np.append(ids, query))
            at = np.searchsorted(node, fresh)
            ids, scores = np.concatenate([ids, fresh]), np.concatenate([scores, (x[at] @ q[i]).astype(np.float64) * length[at]])
            closed = np.concatenate([closed, np.zeros(len(fresh), dtype=np.uint8)])
            seen += len(fresh)
        best = np.lexsort((ids, -scores))[:beam]
        ids, scores, closed = ids[best], scores[best], closed[best].copy()
        nexts = np.flatnonzero(closed == 0)[:expand]
        closed[nexts] = 1
        rows.append((query, ids.astype("<i8").tobytes(), scores.astype("<f8").tobytes(), closed.tobytes(), ids[nexts], seen))
    out = pd.DataFrame(rows, columns=["query", "other", "score", "done", "opened", "seen"])
    out.insert(1, "vector", lists["vector"].tolist())
    out.insert(0, "b", lists["b"].to_numpy())
    return out


def spelled(packed_rows: DataFrame) -> DataFrame:
    """(node, x, place) from (node, other): a row for each packed id, places from 0."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            sizes = [len(o) // 8 for o in batch["other"]]
            ids = np.frombuffer(b"".join(batch["other"]), dtype="<i8")
            yield pd.DataFrame({"node": np.repeat(batch["node"].to_numpy(), sizes), "x": ids, "place": np.concatenate([np.arange(n) for n in sizes] or [np.zeros(0, dtype=np.int64)])})

    return packed_rows.mapInPandas(run, "node long, x long, place long")


LISTS = "b long, query long, vector binary, other binary, score binary, done binary, opened array<long>, seen long"


def search(graph: DataFrame, asking: DataFrame, beam: int = BEAM, expand: int = EXPAND, reverse: int = REVERSE, steps: int = STEPS) -> DataFrame:
    """For nodes that ask, (query, near, seen): the ids in their lists when all of these are open, and how many nodes they scored; a node
    that came back after it had fallen out of the list counts again."""
    forward = materialize(spelled(graph.select("node", "other")), "links")
    nearest_first = Window.partitionBy("x").orderBy("place", "node")
    back = forward.withColumn("k", F.row_number().over(nearest_first)).filter(F.col("k") <= reverse).select(F.col("x").alias("at"), F.col("node").alias("x"))
    links = materialize(forward.select(F.col("node").alias("at"), "x").unionByName(back).groupBy("at").agg(F.collect_set("x").alias("around")), "around")
    points = graph.select(F.col("node").alias("end"), "vector")
    blocks = max(1, -(-asking.count() // QUERIES))
    none, zero = F.unhex(F.lit("")), F.lit(0).cast("long")
    begin = graph.join(asking, "node", "left_semi").select(block_of(F.col("node"), blocks).alias("b"), F.col("node").alias("query"), "vector", "other", "score", none.alias("done"), F.array().cast("array<long>").alias("opened"), zero.alias("seen"))

    def first(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            sizes = [len(o) // 8 for o in batch["other"]]
            yield step(batch.assign(done=[bytes(n) for n in sizes], seen=sizes), pd.DataFrame(), pd.DataFrame(), beam, expand)

    lists, finished = materialize(begin.mapInPandas(first, LISTS), "lists"), None
    for turn in range(steps):
        busy = lists.filter(F.size("opened") > 0)
        done = lists.filter(F.size("opened") == 0).select("query", "other", "seen")
        finished = done if finished is None else finished.unionByName(done)
        if busy.isEmpty():
            return finished.select("query", "other", "seen")
        wanted = busy.select("b", F.explode("opened").alias("at")).distinct()
        near = materialize(wanted.join(links, "at").select(F.col("b").alias("block"), "at", "around"), f"near-{turn}")
        ends = near.select(F.col("block"), F.explode("around").alias("end")).distinct().join(points, "end")
        given = near.select("block", F.col("at").alias("one"), "around", F.lit(None).cast("binary").alias("where")).unionByName(
            ends.select("block", F.col("end").alias("one"), F.lit(None).cast("array<long>").alias("around"), F.col("vector").alias("where"))
        )

        def go(mine: pd.DataFrame, given: pd.DataFrame) -> pd.DataFrame:
            if not len(given):
                return step(mine, given, given, beam, expand)
            ends = given["where"].notna()
            return step(mine, given[~ends].rename(columns={"one": "at"}), given[ends].rename(columns={"one": "end", "where": "vector"}), beam, expand)

        lists = materialize(busy.groupBy("b").cogroup(given.groupBy("block")).applyInPandas(go, LISTS), f"lists-{turn}")
    return finished.unionByName(lists.select("query", "other", "seen"))



def nearest(vectors: DataFrame, k: int = 20, every: int = 20, id_col: str = "vec_id", vector_col: str = "embedding", beam: int = BEAM, **options) -> DataFrame:
    """query_id, rank, vec_id, score: answers for the rows whose id is divisible by ``every``; ties go to smaller ids.

    Rows without an id, and vectors that are null, empty, zero, of another length than most, or hold null or non-finite
    numbers take no part. Rows that repeat id and vector are one. An empty table gives an empty result; further columns are
    ignored.
    """
    spark = vectors.sparkSession
    ship(spark)
    return distilled(spark, "nearest", lambda: _nearest(vectors, k, every, id_col, vector_col, max(beam, 2 * k + 16), options)[0])


def _nearest(vectors: DataFrame, k: int, every: int, id_col: str, vector_col: str, beam: int, options: dict) -> tuple[DataFrame, DataFrame, int]:
    """The answers, the lists that they come from, and the number of nodes."""
    rows = usable(vectors, id_col, vector_col)

    @F.pandas_udf("binary")
    def short(vectors: pd.Series) -> pd.Series:
        return pd.Series([packed(v) for v in vectors], dtype=object)

    nodes = materialize(nodes_of(rows, k + 1), "nodes")
    count = nodes.count()
    points = materialize(nodes.select("node", short("v").alias("vector")), "points")
    queries = rows.filter(F.col("id") % every == 0).dropDuplicates(["id"]).select(F.col("id").alias("query_id"), F.col("v").cast("array<double>").alias("v"))
    queries = materialize(queries.join(nodes.select("v", F.col("node").alias("own")), "v").select("query_id", "own"), "queries")
    asking = queries.select(F.col("own").alias("node")).distinct()
    lists = materialize(search(build_graph(points, count, **options), asking, beam), "found")
    near = spelled(lists.select(F.col("query").alias("node"), "other")).select(F.col("node").alias("own"), F.col("x").alias("node")).unionByName(asking.select(F.col("node").alias("own"), "node"))
    dot = F.aggregate(F.zip_with("q", "v", lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)
    scored = near.join(nodes, "node").join(nodes.select(F.col("node").alias("own"), F.col("v").alias("q")), "own").select("own", dot.alias("score"), F.explode("members").alias("vec_id"))
    first = Window.partitionBy("own").orderBy(F.desc("score"), "vec_id")
    best = scored.withColumn("r", F.row_number().over(first)).filter(F.col("r") <= k + 1).groupBy("own").agg(F.sort_array(F.collect_list(F.struct("r", "vec_id", "score"))).alias("best"))
    others = F.slice(F.filter("best", lambda b: b["vec_id"] != F.col("query_id")), 1, k)
    answers = queries.join(best, "own").select("query_id", F.posexplode(others).alias("at", "b"))
    return answers.select("query_id", (F.col("at") + 1).cast("int").alias("rank"), "b.vec_id", "b.score"), lists, count
