"""Packing the segments of a cluster into windows: longest first, each into the window with the best score.

The score adds relevance (cosine with the window's centre), the free share of the window, and a penalty for what would be cut.
The pass over a cluster is sequential, clusters are independent. A cluster's rows stream through one task in their order, which
holds its open windows alone; so clusters of any size are packed whole. Text does not move.
"""

from __future__ import annotations

import math
import os
from collections.abc import Iterator
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from windowforge.config import Config
from windowforge.session import ship

MANIFEST = "cluster_id string, window_id string, pos int, seg_id string, start int, offset int, n_tokens int, used int, cut int, score double"


def penalty(length: Column, remaining: Column, window: int) -> Column:
    """1 where the segment fits, else falling towards 0 with what sticks out."""
    return F.when(length <= remaining, 1.0).otherwise(F.lit(float(window)) / (window + length - remaining))


def score(cos: Column, remaining: Column, length: Column, window: int, alpha: float = 1.0, beta: float = 1.0, lam: float = 1.0) -> Column:
    return alpha * cos + beta * (remaining / F.lit(float(window))) + lam * penalty(length, remaining, window)


def window_budget(members: DataFrame, window: int) -> DataFrame:
    """(cluster_id, tokens, n_windows): as many windows as the tokens need."""
    return members.groupBy("cluster_id").agg(F.sum("n_tokens").cast("long").alias("tokens")).withColumn("n_windows", F.greatest(F.lit(1), F.ceil(F.col("tokens") / window)).cast("long"))


def order(members: DataFrame) -> DataFrame:
    """Adds place: 1 for the longest segment of its cluster; ties by document and segment number."""
    by = Window.partitionBy("cluster_id").orderBy(F.desc("n_tokens"), "doc_id", "seg_no")
    return members.withColumn("place", F.row_number().over(by))


@dataclass
class Bins:
    """The windows of one cluster while they fill."""

    window: int
    sums: np.ndarray
    size: np.ndarray
    count: np.ndarray
    remaining: np.ndarray

    @classmethod
    def empty(cls, n: int, window: int, dim: int) -> Bins:
        return cls(window, np.zeros((n, dim)), np.zeros(n), np.zeros(n, dtype=np.int64), np.full(n, window, dtype=np.int64))

    def scores(self, v: np.ndarray, length: int, c: Config) -> np.ndarray:
        norm = float(np.sqrt(v @ v))
        bottom = self.size * norm
        dots = np.einsum("nd,d->n", self.sums, v)  # row by row: a row's sum does not depend on which others are scored with it
        cos = np.divide(dots, bottom, out=np.zeros(len(bottom)), where=bottom > 0)
        cos[self.count == 0] = c.empty_cos
        over = np.maximum(length - self.remaining, 0)
        return np.round(c.alpha * cos + c.beta * self.remaining / self.window + c.lam * self.window / (self.window + over), 12)

    def put(self, at: int, v: np.ndarray, length: int) -> None:
        self.sums[at] += v
        self.size[at] = np.sqrt(self.sums[at] @ self.sums[at])
        self.count[at] += 1
        self.remaining[at] -= length


#: Segments whose products with the open windows are taken together.
AHEAD = 256


#: Threads that share a large product: a hot cluster is one task, which the others wait for.
THREADS = 4
#: Multiplications from which a product is shared.
SHARED_PRODUCT = 1 << 28


def multiplied(v: np.ndarray, sums: np.ndarray, out: np.ndarray) -> None:
    """Products of v with sums, into the first columns of ``out``."""
    threads = min(THREADS, os.cpu_count() or 1) if v.size * len(sums) >= SHARED_PRODUCT else 1
    cuts = [len(sums) * t // threads for t in range(threads + 1)]

    def part(t: int) -> None:
        out[:, cuts[t] : cuts[t + 1]] = v @ sums[cuts[t] : cuts[t + 1]].T

    if threads == 1:
        return part(0)
    with ThreadPoolExecutor(threads) as pool:
        list(pool.map(part, range(threads)))


class Filling:
    """A cluster's windows while its segments come, longest first.

    Empty windows score alike and the first of them is taken, so the used ones are those before it. Closed windows are forgotten.
    The next segments' products with all open windows come from one product of matrices, in 32 bits, and follow each placement by
    the segments' products with each other. Their error has a bound: only windows that might still be the best are scored in 64.
    """

    def __init__(self, n: int, dim: int, c: Config):
        self.n, self.c, self.used = n, c, 0
        self.bins, self.at, self.open = Bins.empty(64, c.window, dim), np.zeros(64, dtype=np.int64), 0  # the first self.open places hold open windows, in order
        self.mass = np.zeros(64)  # sums of the members' norms, which bound the error
        self.sums32, self.base, self.inverse, self.length = np.zeros((64, dim), dtype=np.float32), np.zeros(64), np.zeros(64), None

    def _room(self) -> None:
        """Room for one more window: closed ones go, or the arrays double."""
        b = self.bins
        keep = np.flatnonzero(self.eligible(b.remaining[: self.open]))
        size = max(64, 2 * len(keep))
        new, at, mass = Bins.empty(size, b.window, b.sums.shape[1]), np.zeros(size, dtype=np.int64), np.zeros(size)
        sums32, base, inverse, slack = np.zeros(new.sums.shape, dtype=np.float32), np.zeros(size), np.zeros(size), np.zeros(size)
        pairs = ((new.sums, b.sums), (new.size, b.size), (new.count, b.count), (new.remaining, b.remaining), (at, self.at), (mass, self.mass))
        for mine, old in (*pairs, (sums32, self.sums32), (base, self.base), (inverse, self.inverse), (slack, self.slack)):
            mine[: len(keep)] = old[keep]
        rough = np.zeros((len(self.rough), size), dtype=self.rough.dtype)
        rough[:, : len(keep)] = self.rough[:, keep]
        self.bins, self.at, self.mass, self.rough, self.open = new, at, mass, rough, len(keep)
        self.sums32, self.base, self.inverse, self.slack = sums32, base, inverse, slack

    def ahead(self, vectors: np.ndarray) -> None:
        """The vectors of the segments that ``place`` takes next, AHEAD of them at most."""
        self.v, self.norm = vectors, np.sqrt(np.einsum("nd,nd->n", vectors, vectors))
        real = self.norm[self.norm > 0]
        kind = np.float32 if not len(real) or 1e-12 < real.min() <= real.max() < 1e12 else np.float64
        v = vectors.astype(kind) if self.c.alpha else np.zeros((len(vectors), 0), dtype=kind)
        self.rough, self.error = np.zeros((len(v) if self.c.alpha else 0, len(self.at)), dtype=kind), (vectors.shape[1] + 2 * len(v) + 16) * 2 * float(np.finfo(kind).eps)
        self.slack = self.c.alpha * self.error * self.mass * self.inverse
        if np.count_nonzero(self.eligible(self.bins.remaining[: self.open])) < 0.75 * self.open:
            self._room()
        if self.c.alpha:
            self.gram = v @ v.T
            multiplied(v, (self.sums32 if kind == np.float32 else self.bins.sums)[: self.open], self.rough)

    def eligible(self, remaining: np.ndarray) -> np.ndarray:
        return remaining >= 0 if self.c.eligible == "nonneg" else remaining > 0

    def without_cosine(self, remaining: np.ndarray, length: int) -> np.ndarray:
        """The part of the score that no vector has to do with; none for closed windows. It stays while the length does."""
        c = self.c
        f = c.beta * remaining / c.window + c.lam * c.window / (c.window + np.maximum(length - remaining, 0))
        f[~self.eligible(remaining)] = -np.inf
        return f

    def best(self, i: int, length: int, fresh: float) -> tuple[int, float]:
        """The open window of the highest score for segment i, if it reaches ``fresh``; -1 if none does."""
        c, k = self.c, self.open
        if length != self.length:
            self.length, self.base[:k] = length, self.without_cosine(self.bins.remaining[:k], length)
        f = self.base[:k]
        if c.alpha:
            if self.rough.dtype == np.float32:
                f = f + self.rough[i, :k] * (self.inverse[:k] * (c.alpha / self.norm[i] if self.norm[i] else 0.0))
            else:  # products of norms may vanish
                bottom = self.bins.size[:k] * self.norm[i]
                f = f + c.alpha * np.divide(self.rough[i, :k], bottom, out=np.zeros(k), where=bottom > 0)
            slack = self.slack[:k]
            rows = np.flatnonzero(f + slack >= max((f - slack).max(initial=-np.inf), fresh) - 1e-9)
            rows = rows[np.isfinite(f[rows])]
            if not len(rows):
                return -1, fresh
            f = self.scores(rows, self.v[i], length)
        else:
            rows, f = np.arange(k), np.round(f, 12)
        at = int(np.argmax(f)) if k else -1
        return (int(rows[at]), float(f[at])) if at >= 0 and np.isfinite(f[at]) and f[at] >= fresh else (-1, fresh)

    def place(self, i: int, length: int) -> tuple[int, int, int, float] | None:
        """For segment i of those ahead: (window, tokens before it, place in the window, score); none where no window is open and leftovers are dropped."""
        c = self.c
        fresh = self.fresh_score(length) if self.used < self.n else -np.inf
        slot, best = self.best(i, length, fresh)
        if slot < 0:
            if self.used >= self.n:
                if c.leftover == "drop":
                    return None
                self.n += 1
                best = self.fresh_score(length)
            if self.open == len(self.at):
                self._room()
            slot, self.at[self.open] = self.open, self.used
            self.open, self.used = self.open + 1, self.used + 1
        placed = (int(self.at[slot]), int(c.window - self.bins.remaining[slot]), int(self.bins.count[slot]), float(best))
        b = self.bins
        b.put(slot, self.v[i], length)
        self.mass[slot] += self.norm[i]
        self.sums32[slot], self.inverse[slot] = b.sums[slot], 1 / b.size[slot] if b.size[slot] > 0 else 0.0
        self.slack[slot] = c.alpha * self.error * self.mass[slot] * self.inverse[slot]
        if self.length is not None:
            self.base[slot] = self.without_cosine(b.remaining[slot : slot + 1], self.length)[0]
        if c.alpha:
            self.rough[:, slot] += self.gram[:, i]
        return placed

    def fresh_score(self, length: int) -> float:
        c = self.c
        return float(np.round(c.alpha * c.empty_cos + c.beta + c.lam * c.window / (c.window + max(length - c.window, 0)), 12))

    def scores(self, rows: np.ndarray, v: np.ndarray, length: int) -> np.ndarray:
        b = self.bins
        return Bins(b.window, b.sums[rows], b.size[rows], b.count[rows], b.remaining[rows]).scores(v, length, self.c)


def pack_cluster(lengths: np.ndarray, vectors: np.ndarray, c: Config, n_windows: int | None = None) -> list[tuple[int, int, int, int, float]]:
    """(row, window, tokens before it in the window, place in the window, score) for rows that come longest first.

    A window takes segments while its remaining capacity is not negative (or, by option, positive), so it may overflow once; what
    sticks out is cut later. With as many windows as the tokens need, some window is always open.
    """
    filling = Filling(n_windows if n_windows is not None else max(1, math.ceil(int(lengths.sum()) / c.window)), vectors.shape[1], c)
    out = []
    for row, length in enumerate(lengths.tolist()):
        if row % AHEAD == 0:
            filling.ahead(vectors[row : row + AHEAD].astype(np.float64))
        if (placed := filling.place(row % AHEAD, length)) is None:
            break
        out.append((row, *placed))
    return out


def capped(members: DataFrame, most: int) -> DataFrame:
    """Clusters of more than ``most`` rows are dealt over parts by hash, each a cluster of its own in the manifest: on request only, as it changes results."""
    sizes = members.groupBy("cluster_id").agg(F.count(F.lit(1)).alias("_size"))
    parts = F.ceil(F.col("_size") / most)
    part = F.when(F.col("_size") > most, F.concat("cluster_id", F.lit("#"), F.pmod(F.xxhash64("seg_id"), parts).cast("string"))).otherwise(F.col("cluster_id"))
    return members.join(sizes, "cluster_id").withColumn("cluster_id", part).drop("_size")


def pack(members: DataFrame, config: Config = Config(), n_windows: int | None = None) -> DataFrame:
    """members (cluster_id, seg_id, doc_id, seg_no, n_tokens, vec) -> manifest, a row per placed segment."""
    ship(members.sparkSession)
    columns = [x.split()[0] for x in MANIFEST.split(", ")]

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        cluster, filling, dropped, first = None, None, False, 0
        for batch in batches:
            rows = []
            names, vecs = batch["cluster_id"].tolist(), batch["vec"].tolist()
            ahead = 0  # rows of this batch whose products are taken
            for row, (name, seg, length, budget) in enumerate(zip(names, batch["seg_id"], batch["n_tokens"].tolist(), batch["n_windows"].tolist())):
                if filling is None or name != cluster:
                    cluster, filling, dropped = name, Filling(budget, len(vecs[row]), config), False
                    ahead = row
                if row == ahead and not dropped:
                    first, ahead = row, min(row + AHEAD, len(names))
                    ahead = next((k for k in range(first, ahead) if names[k] != name), ahead)
                    filling.ahead(np.array(vecs[first:ahead], dtype=np.float64))
                placed = None if dropped else filling.place(row - first, length)
                if placed is None:
                    dropped = True
                    continue
                at, before, pos, f = placed
                used = min(length, max(0, config.window - before))
                rows.append((name, f"{name}|{at:06d}", pos, seg, 0, min(before, config.window), length, used, length - used, f))
            yield pd.DataFrame(rows, columns=columns)

    needed = members.select("cluster_id", "seg_id", "doc_id", "seg_no", "n_tokens", "vec")
    if config.max_cluster is not None:
        needed = capped(needed, config.max_cluster)
    if n_windows is not None:
        budgeted = needed.withColumn("n_windows", F.lit(n_windows).cast("long"))
    else:
        budget = window_budget(needed, config.window).select(F.col("cluster_id").alias("_c"), "n_windows")
        budgeted = needed.join(budget, F.col("cluster_id").eqNullSafe(F.col("_c"))).drop("_c")
    inside = ["cluster_id", F.desc("n_tokens"), F.asc_nulls_last("doc_id"), "seg_no"]
    manifest = budgeted.repartition("cluster_id").sortWithinPartitions(*inside).select("cluster_id", "seg_id", "n_tokens", "n_windows", "vec").mapInPandas(run, MANIFEST)
    return backfill(manifest, config.window) if config.backfill else manifest


def backfill(manifest: DataFrame, window: int, below: float = 0.5, groups: int = 64) -> DataFrame:
    """Windows that are filled less than ``below`` move together, first fit by falling fill, within groups drawn by hash. Others stay."""
    fill = manifest.groupBy("window_id").agg(F.sum("used").alias("fill")).withColumn("low", F.col("fill") < below * window)

    def run(group: pd.DataFrame) -> pd.DataFrame:
        out, room = [], []
        for w, n in group.sort_values(["fill", "window_id"], ascending=[False, True])[["window_id", "fill"]].itertuples(index=False):
            at = next((i for i, (_, free, _) in enumerate(room) if free >= n), None)
            if at is None:
                room.append([w, window, 0])
                at = len(room) - 1
            out.append((w, room[at][0], window - room[at][1], room[at][2]))
            room[at][1] -= n
            room[at][2] += 1
        return pd.DataFrame(out, columns=["window_id", "to", "shift", "turn"])

    low = fill.filter("low").withColumn("g", F.pmod(F.xxhash64("window_id"), F.lit(groups)))
    moved = low.groupBy("g").applyInPandas(run, "window_id string, to string, shift int, turn int")
    joined = manifest.join(moved, "window_id", "left")
    at = Window.partitionBy("_w").orderBy("_turn", "pos")
    placed = joined.withColumn("_w", F.coalesce("to", "window_id")).withColumn("_turn", F.coalesce("turn", F.lit(0)))
    return placed.withColumn("pos", (F.row_number().over(at) - 1).cast("int")).withColumn("offset", (F.col("offset") + F.coalesce("shift", F.lit(0))).cast("int")).withColumn("window_id", F.col("_w")).select(*manifest.columns)
