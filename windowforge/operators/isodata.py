"""Clustering in rounds: nearest centre above a threshold, documents that are near to none open clusters, means, merging.

State is three tables a round, written to the state folder, so that a round can be repeated from the one before; the driver sees
counts, and the links of centres up to a bound. Far documents are collected first and opened together after the assignment (``spawn="batch"``), which does not
depend on their order.
"""

from __future__ import annotations

import time
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, Observation, Window
from pyspark.sql import functions as F

from windowforge.config import Config
from windowforge.functions import vec as V
from windowforge.operators import assign as A
from windowforge.operators.blocks import above, connecting, nearest
from windowforge.operators.density import initial_clusters, vector_sums
from windowforge.operators.prefix import running
from windowforge.schema import VECTORS, require
from windowforge.session import settled

#: Centres that are broadcast to find near pairs, and merged on the driver; beyond, both sides lie in files.
MERGE_EXACT = 20_000
#: Numbers in the centres up to which the links of a forest are sought by broadcast.
FOREST_NUMBERS = 1 << 21
#: Centres whose ids, and 64 times MERGE_EXACT links, the driver holds to connect them.
CONNECT_HERE = 1 << 18
#: Seeds that are taken by one ordered limit.
SEEDS_AT_ONCE = 100_000


@dataclass
class Clustering:
    membership: DataFrame  # seg_id, cluster_id, cos
    centroids: DataFrame  # cluster_id, vec, n
    trace: DataFrame  # round, spawned, emptied, merged, clusters, shift, evals, seconds


def seed(docs: DataFrame, k: int, seed: int = 7) -> DataFrame:
    """k documents in the order of a hash, as centres; the same for any partitioning."""
    order = F.md5(F.concat(F.lit(f"{seed}:"), "seg_id"))
    if k <= SEEDS_AT_ONCE:
        first = docs.select("seg_id", order.alias("_order")).orderBy("_order", "seg_id").limit(k).select("seg_id")  # vectors are fetched for the chosen alone
        picked = docs.join(first, "seg_id", "left_semi")
    else:  # too many for one place: ranks come from sums over ranges of the order
        picked = running(docs.withColumn("_one", F.lit(1)), order, "_one", ["seg_id"]).filter(F.col("before") < k)
    return picked.select(F.col("seg_id").alias("cluster_id"), F.col("vec").cast("array<double>").alias("vec"), F.lit(0).cast("long").alias("n"))


def spawn(assigned: DataFrame, delta: float, last: bool = False, label: str = "r") -> DataFrame:
    """(seg_id, cluster_id, cos, spawned): documents whose best cosine is not above ``delta`` get a cluster of their own, but in the last round none does."""
    far = F.lit(False) if last else ~(F.col("cos") > delta)
    return assigned.withColumn("spawned", far).withColumn("cluster_id", F.when(F.col("spawned"), F.concat(F.lit(f"{label}/"), "seg_id")).otherwise(F.col("cluster_id"))).withColumn("cos", F.when(F.col("spawned"), 1.0).otherwise(F.col("cos")))


def spawn_sequential(docs: pd.DataFrame, ids: list[str], centres: np.ndarray, delta: float, label: str) -> pd.DataFrame:
    """One document after the other, each centre counting from when it opens: a reference for small inputs."""
    names, c, out = list(ids), [*centres], []
    for s, v in zip(docs["seg_id"], A.unit(A.matrix(docs["vec"]))):
        cos = np.round(np.stack(c) @ v, 12) if c else np.zeros(0)
        at = int(np.argmax(cos)) if len(c) else -1
        if at >= 0 and cos[at] > delta:
            out.append((s, names[at], float(cos[at]), False))
        else:
            names.append(f"{label}/{s}")
            c.append(v)
            out.append((s, names[-1], 1.0, True))
    return pd.DataFrame(out, columns=["seg_id", "cluster_id", "cos", "spawned"])


def recenter(members: DataFrame, docs: DataFrame, cents: DataFrame) -> DataFrame:
    """(cluster_id, vec, n, shift): means of the members' vectors and how far each centre has moved. Clusters without members are dropped;
    a cluster that has just opened has not moved."""
    sums = vector_sums(members.join(docs.select("seg_id", "vec"), "seg_id"), "cluster_id", unit=False)
    means = sums.select("cluster_id", V.scale(F.col("vec"), 1 / F.col("n")).alias("vec"), "n")
    old = cents.select("cluster_id", F.col("vec").alias("old"))
    gap = F.sqrt(F.aggregate(F.zip_with("vec", "old", lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x))
    return means.join(old, "cluster_id", "left").select("cluster_id", "vec", "n", F.coalesce(gap, F.lit(0.0)).alias("shift"))


def _pairs(own: np.ndarray, x: np.ndarray, names: np.ndarray, c: np.ndarray, delta: float, forest: bool, label: np.ndarray) -> Iterator[pd.DataFrame]:
    """(a, b, cos) with a < b where rows of x and c are nearer than ``delta``, block by block. With ``forest`` only links between what the
    earlier ones have not connected yet: ``label`` holds the connected parts of the names, which are in order."""
    most = max(16, min(1024, A.PRODUCT_BYTES // (8 * max(len(c), 1))))
    for k in range(0, len(x), most):
        cos = np.round(x[k : k + most] @ c.T, 12)
        at = np.searchsorted(names, own[k : k + most])
        i, j = np.nonzero(cos > delta)
        if forest:
            keep = []
            rows, begin = np.unique(i, return_index=True)
            for row, near in zip(rows, np.split(j, begin[1:])):
                parts, first = np.unique(label[near], return_index=True)
                new = parts != label[at[row]]
                if new.any():
                    keep += [(row, near[f]) for f in first[new]]
                    label[np.isin(label, parts)] = label[at[row]]
            i, j = (np.array(z, dtype=np.int64) for z in zip(*keep)) if keep else (np.zeros(0, dtype=np.int64), np.zeros(0, dtype=np.int64))
            low, high = np.minimum(at[i], j), np.maximum(at[i], j)
        else:
            upward = at[i] < j
            i, j = i[upward], j[upward]
            low, high = at[i], j
        yield pd.DataFrame({"a": names[low], "b": names[high], "cos": cos[i, j]})


def merge_edges(cents: DataFrame, delta: float, cells: int | None = None, forest: bool = False) -> DataFrame:
    """(a, b, cos) with a < b of centres whose cosine is above ``delta``. Exact: by broadcast blocks up to MERGE_EXACT centres, beyond by blocks
    that lie in files. With ``cells`` within so many coarse cells instead, each centre copied to its nearest ones. With ``forest`` only as many as connect what all of them connect: a dense
    group then gives a row per centre and task, not one per pair."""
    size = cents.agg(F.count(F.lit(1)), F.max(F.size("vec"))).first()
    if cells is None and forest and size[0] * (size[1] or 0) > FOREST_NUMBERS:
        return connecting(cents, "cluster_id", delta, 2048)
    if size[0] <= MERGE_EXACT and cells is None:
        ids, c = A.collected(cents)
        held = cents.sparkSession.sparkContext.broadcast((np.array(ids, dtype=object), c))

        def run(batches):
            names, c = held.value
            label = np.arange(len(names))
            for batch in batches:
                if len(batch):
                    yield from _pairs(batch["cluster_id"].to_numpy(), A.unit(A.matrix(batch["vec"])), names, c, delta, forest, label)

        return cents.select("cluster_id", "vec").repartition(max(1, min(64, size[0] // 500))).mapInPandas(run, "a string, b string, cos double")
    if cells is None:
        return (connecting if forest else above)(cents, "cluster_id", delta, 2048)
    coarse = A.coarse_centres(cents, cells)
    placed = A.with_cells(cents, "cluster_id", coarse, min(4, len(coarse)))

    def inside(group: pd.DataFrame) -> pd.DataFrame:
        group = group.sort_values("cluster_id")
        x, names = A.unit(A.matrix(group["vec"])), group["cluster_id"].to_numpy()
        return pd.concat(_pairs(names, x, names, x, delta, forest, np.arange(len(names))))

    return placed.groupBy("cell").applyInPandas(inside, "a string, b string, cos double").groupBy("a", "b").agg(F.max("cos").alias("cos"))


def connected(pairs: Iterable[tuple[str, str]], nodes: list[str]) -> dict[str, str]:
    """By node the smallest node that the pairs connect it with."""
    root = {n: n for n in nodes}

    def find(n: str) -> str:
        while root[n] != n:
            root[n] = root[root[n]]
            n = root[n]
        return n

    for a, b in pairs:
        x, y = sorted((find(a), find(b)))
        root[y] = x
    return {n: find(n) for n in nodes}


def components(edges: DataFrame, nodes: DataFrame, most: int = 50, driver: int = CONNECT_HERE) -> DataFrame:
    """(cluster_id, root): smallest id that edges reach. Up to ``driver`` centres on the driver, if the edges are few as well; beyond, by
    handing minima along edges and halving paths, where every step is written down."""
    few = nodes.count() <= driver and edges.count() <= 64 * min(driver, MERGE_EXACT)
    if few:
        pairs, ids = edges.select("a", "b").toArrow(), nodes.select("cluster_id").toArrow().column(0).to_pylist()
        found = connected(zip(pairs.column("a").to_pylist(), pairs.column("b").to_pylist()), ids)
        return nodes.sparkSession.createDataFrame(pa.table({"cluster_id": pa.array(found.keys(), pa.string()), "root": pa.array(found.values(), pa.string())}))
    both = settled(edges.select("a", "b").unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct(), "merge-edges")
    label = settled(nodes.select(F.col("cluster_id").alias("a"), F.col("cluster_id").alias("root")), "merge-label")
    for _ in range(most):
        heard = both.join(label.select(F.col("a").alias("b"), "root"), "b").groupBy("a").agg(F.min("root").alias("m"))
        new = label.join(heard, "a", "left").select("a", F.least("root", F.coalesce("m", "root")).alias("root"), F.col("root").alias("was"))
        jump = new.select(F.col("a").alias("root"), F.col("root").alias("far"))
        new = settled(new.join(jump, "root").select("a", F.least("root", "far").alias("root"), "was"), "merge-label")
        label = new.select("a", "root")
        if new.filter("root <> was").isEmpty():
            return label.select(F.col("a").alias("cluster_id"), "root")
    raise RuntimeError("merging has not settled")


def best_edges(cents: DataFrame, delta: float) -> DataFrame:
    """(a, b, cos) with a < b: of the links above ``delta`` each centre's nearest alone, ties to the smaller id, exactly. Two centres that choose
    each other do so among these too; a dense group gives a row per centre, not one per pair."""
    found = nearest(cents.select(F.col("cluster_id").alias("seg_id"), "vec"), 1, 2048).filter(F.col("w") > delta)
    return found.groupBy(F.least("src", "dst").alias("a"), F.greatest("src", "dst").alias("b")).agg(F.max("w").alias("cos"))


def mutual_best(edges: DataFrame, nodes: DataFrame) -> DataFrame:
    """(cluster_id, root): two centres unify where each is the other's nearest; no chains."""
    both = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b"), "cos"))
    order = Window.partitionBy("a").orderBy(F.desc("cos"), "b")
    first = both.withColumn("k", F.row_number().over(order)).filter("k = 1").select("a", "b")
    pairs = first.alias("x").join(first.alias("y"), (F.col("x.a") == F.col("y.b")) & (F.col("x.b") == F.col("y.a"))).select(F.col("x.a").alias("cluster_id"), F.least("x.a", "x.b").alias("root"))
    return nodes.select("cluster_id").join(pairs, "cluster_id", "left").select("cluster_id", F.coalesce("root", "cluster_id").alias("root"))


def merged_sequentially(ids: list[str], vecs: np.ndarray, counts: list[int], delta: float) -> dict[str, str]:
    """Most similar pair first, its mean taken anew before the next; a reference for few centres."""
    groups = {i: (v * n, n, [i]) for i, v, n in zip(ids, vecs, counts)}
    while True:
        names = sorted(groups)
        x = A.unit(np.stack([groups[i][0] / max(groups[i][1], 1) for i in names])) if names else np.zeros((0, 1))
        cos = np.triu(np.round(x @ x.T, 12), 1)
        cos[np.tril_indices(len(names))] = -2
        if not len(names) or cos.max() <= delta:
            return {i: name for name, (_, _, own) in groups.items() for i in own}
        i, j = np.unravel_index(np.argmax(cos), cos.shape)
        a, b = names[i], names[j]
        groups[a] = (groups[a][0] + groups[b][0], groups[a][1] + groups[b][1], groups[a][2] + groups[b][2])
        del groups[b]


def merge(cents: DataFrame, delta: float, how: str = "components") -> DataFrame:
    """(cluster_id, root) for all centres."""
    if how == "sequential":
        ids, _ = A.collected(cents)
        rows = cents.select("cluster_id", "vec", "n").orderBy("cluster_id").toPandas()
        found = merged_sequentially(ids, A.matrix(rows["vec"]), rows["n"].tolist(), delta)
        return cents.sparkSession.createDataFrame(list(found.items()), "cluster_id string, root string")
    if how == "mutual_best":
        return mutual_best(settled(best_edges(cents, delta), "best"), cents)
    return components(settled(merge_edges(cents, delta, forest=True), "merge-edges"), cents)


def unified(cents: DataFrame, mapping: DataFrame) -> DataFrame:
    """Centres after merging: means weighted by their members."""
    weighted = cents.join(mapping, "cluster_id").select("root", V.scale(F.col("vec"), F.col("n").cast("double")).alias("vec"), "n")
    sums = vector_sums(weighted, "root", unit=False).select("root", "vec")
    counts = weighted.groupBy("root").agg(F.sum("n").alias("n"))
    return sums.join(counts, "root").select(F.col("root").alias("cluster_id"), V.scale(F.col("vec"), 1 / F.greatest(F.col("n"), F.lit(1))).alias("vec"), "n")


def one_round(docs: DataFrame, cents: DataFrame, before: int, config: Config, last: bool, label: str) -> tuple[DataFrame, DataFrame, dict]:
    """Assignment, opening, means, merging; (membership, centres, figures). ``before``: how many centres come in."""
    if config.spawn == "sequential":
        ids, c = A.collected(cents)
        rows = docs.select("seg_id", "vec").orderBy("seg_id").toPandas()
        found = spawn_sequential(rows, ids, c, -2.0 if last else config.delta, label)
        members = docs.sparkSession.createDataFrame(found).withColumn("evals", F.lit(len(ids)).cast("long"))
    else:
        members = spawn(A.assign(docs, cents, config.assign), config.delta, last, label)
    opened, moved = Observation(), Observation()  # the figures come with the writes, not from further passes
    members = settled(members.select("seg_id", "cluster_id", "cos", "spawned", "evals").observe(opened, F.sum(F.col("spawned").cast("long")).alias("spawned"), F.sum("evals").alias("evals")), f"{label}-members")
    means = settled(recenter(members, docs, cents).observe(moved, (F.sum("shift") if config.shift == "sum" else F.avg("shift")).alias("shift"), F.count(F.lit(1)).alias("k")), f"{label}-means")
    mapping = merge(means, config.delta, config.merge)
    if config.merge == "mutual_best" or moved.get["k"] > MERGE_EXACT:
        mapping = settled(mapping, f"{label}-merge")
    left = Observation()
    after = settled(unified(means, mapping).observe(left, F.count(F.lit(1)).alias("k")), f"{label}-centres")
    spawned, k, now = opened.get["spawned"] or 0, moved.get["k"], left.get["k"]
    figures = {"spawned": spawned, "emptied": before + spawned - k, "merged": k - now, "clusters": now, "shift": float(moved.get["shift"] or 0.0), "evals": opened.get["evals"] or 0}
    return members.join(mapping, "cluster_id").select("seg_id", F.col("root").alias("cluster_id"), "cos"), after, figures


ROUND = "round int, spawned long, emptied long, merged long, clusters long, shift double, evals long, seconds double"


def fit(docs: DataFrame, config: Config = Config(), state: str | None = None, kept: bool = False) -> Clustering:
    """Rounds until the centres rest or ``rounds`` are done; memberships and the list of far documents begin anew in each.

    ``kept``: the vectors lie in files already and need no copy. With ``state``, a folder, every round's tables are kept there and a later call goes on after the last round that is complete.
    """
    spark = docs.sparkSession
    docs = require(docs, VECTORS, "vectors")
    docs = docs if kept else settled(docs, "vectors")
    rows, cents, membership = resumed(spark, state) if state else ([], None, None)
    if cents is None:
        k = config.n_clusters or initial_clusters(docs, config.n_subsets, config.density, config.seed).first()["n_clusters"]
        cents = settled(seed(docs, k, config.seed), "centres-0")
    for t in range(len(rows) + 1, config.rounds + 1):
        if rows and rows[-1][5] < config.epsilon:
            break
        began = time.monotonic()
        membership, cents, figures = one_round(docs, cents, rows[-1][4] if rows else cents.count(), config, t == config.rounds, f"r{t}")
        rows.append((t, *figures.values(), round(time.monotonic() - began, 3)))
        if state:
            membership.write.mode("overwrite").parquet(f"{state}/round={t}/membership")
            cents.write.mode("overwrite").parquet(f"{state}/round={t}/centroids")
            spark.createDataFrame(rows, ROUND).coalesce(1).write.mode("overwrite").parquet(f"{state}/trace/{t}")  # last: it marks the round as complete
    if config.finalize and rows:
        membership = A.assign(docs, cents, config.assign).select("seg_id", "cluster_id", "cos")
    if membership is not None:
        membership = settled(membership, "membership")
    return Clustering(membership, cents, spark.createDataFrame(rows, ROUND))


def resumed(spark, state: str) -> tuple[list[tuple], DataFrame | None, DataFrame | None]:
    """Figures, centres and membership of the last complete round of a state folder; nothing if there is none."""
    try:
        found = spark.read.option("recursiveFileLookup", "true").parquet(f"{state}/trace").distinct().orderBy("round").collect()
    except AnalysisException:
        return [], None, None
    last = f"{state}/round={found[-1]['round']}"
    return [tuple(r) for r in found], spark.read.parquet(f"{last}/centroids"), spark.read.parquet(f"{last}/membership")


def classic(docs: DataFrame, k: int, rounds: int = 5, min_size: int = 2, max_std: float = 0.05, min_dist: float = 0.3, seed_: int = 7) -> Clustering:
    """The known algorithm as a comparison: nearest centre always, small clusters discarded, wide ones split along their widest
    coordinate, centres nearer than ``min_dist`` (Euclid) merged by mutual choice."""
    spark = docs.sparkSession
    docs = settled(docs.select("seg_id", "vec"), "vectors")
    cents, rows, members = settled(seed(docs, k, seed_), "classic-0"), [], None
    for t in range(1, rounds + 1):
        began, before = time.monotonic(), cents.count()
        members = settled(A.assign(docs, cents, "exact").select("seg_id", "cluster_id", "cos", "evals"), f"classic-{t}")
        sizes = members.groupBy("cluster_id").count()
        big = sizes.filter(F.col("count") >= min_size).select("cluster_id")
        if big.isEmpty():
            big = sizes.select("cluster_id")
        held = members.join(docs, "seg_id").join(big, "cluster_id", "left_semi").select("cluster_id", F.posexplode("vec").alias("at", "x"))
        per = held.groupBy("cluster_id", "at").agg(F.avg(F.col("x").cast("double")).alias("mean"), F.stddev_pop(F.col("x").cast("double")).alias("std"), F.count(F.lit(1)).alias("n"))
        whole = per.groupBy("cluster_id").agg(F.sort_array(F.collect_list(F.struct("at", "mean"))).alias("v"), F.max(F.struct("std", "at")).alias("w"), F.max("n").alias("n"))
        whole = whole.select("cluster_id", F.col("v.mean").alias("vec"), F.col("w.std").alias("std"), F.col("w.at").alias("at"), "n")
        wide = (F.col("std") > max_std) & (F.col("n") >= 2 * min_size)
        shifted = lambda s: F.transform("vec", lambda x, i: F.when(i == F.col("at"), x + s * F.col("std")).otherwise(x))
        split = whole.filter(wide).select(F.explode(F.array(F.struct(F.concat("cluster_id", F.lit("+")).alias("cluster_id"), shifted(1).alias("vec")), F.struct(F.concat("cluster_id", F.lit("-")).alias("cluster_id"), shifted(-1).alias("vec")))).alias("s"), "n").select("s.cluster_id", "s.vec", (F.col("n") / 2).cast("long").alias("n"))
        grown = settled(whole.filter(~wide).select("cluster_id", "vec", "n").unionByName(split), f"classic-grown-{t}")
        # for unit vectors a Euclidean distance is a cosine
        mapping = settled(mutual_best(settled(best_edges(grown, 1 - min_dist**2 / 2), f"classic-best-{t}"), grown), f"classic-merge-{t}")
        cents = settled(unified(grown, mapping), f"classic-cents-{t}")
        now = cents.count()
        rows.append((t, int(split.count() // 2), before - big.count(), grown.count() - now, now, 0.0, members.agg(F.sum("evals")).first()[0] or 0, round(time.monotonic() - began, 3)))
    members = settled(A.assign(docs, cents, "exact").select("seg_id", "cluster_id", "cos"), "classic-final")
    return Clustering(members, cents, spark.createDataFrame(rows, ROUND))
