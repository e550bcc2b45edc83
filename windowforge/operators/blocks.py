"""All rows against all rows without a shuffle of copies: vectors lie in blocks in the state folder, and the blocks meet as a Cartesian
product, which reads the right side's files anew for each part of the left. What a task keeps are the results alone."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from windowforge.session import settled

#: Bytes of vectors in a block at most.
BLOCK_BYTES = 4 << 20


def unit(x: np.ndarray) -> np.ndarray:
    size = np.sqrt((x * x).sum(axis=1, keepdims=True))
    return np.divide(x, size, out=np.zeros_like(x), where=size > 0)


def blocks(rows: DataFrame, key: str, block: int, label: str = "blocks") -> DataFrame:
    """(at, names, x, wide): blocks of vectors in the order of their keys. ``at`` is the place of the first one: places rise with the keys
    over all blocks. ``x`` are floats of 32 bits if the vectors are, else of 64 (``wide``)."""
    size = rows.agg(F.count(F.lit(1)), F.max(F.size("vec"))).first()
    wide = rows.schema["vec"].dataType.elementType.simpleString() != "float"
    kind = np.float64 if wide else np.float32
    most = max(1, min(block, BLOCK_BYTES // (max(size[1] or 1, 1) * np.dtype(kind).itemsize)))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        part, done, names, held = 0, 0, [], []

        def out(n: int) -> pd.DataFrame:
            nonlocal done, names, held
            row = pd.DataFrame({"at": [(part << 32) + done], "names": [names[:n]], "x": [np.stack(held[:n]).astype(kind).tobytes()], "wide": wide})
            done, names, held = done + n, names[n:], held[n:]
            return row

        for batch in batches:
            part = int(batch["part"].iloc[0]) if len(batch) else part
            names += batch[key].tolist()
            held += list(batch["vec"])
            while len(names) >= most:
                yield out(most)
        if names:
            yield out(len(names))

    tasks = math.ceil(math.sqrt(4 * rows.sparkSession.sparkContext.defaultParallelism))  # files on each side, so that pairs of them keep all cores busy
    files = max(1, -(-size[0] // (8 * most)), min(tasks, -(-size[0] // 256)))
    dealt = rows.select(key, "vec").repartitionByRange(files, key).sortWithinPartitions(key).withColumn("part", F.spark_partition_id())
    return settled(dealt.mapInPandas(run, "at long, names array<string>, x binary, wide boolean"), label)


def paired(held: DataFrame, upward: bool = False) -> DataFrame:
    """Each block as (at, names, x, wide) with each as (at2, names2, x2); ``upward``: only with those from itself on."""
    other = held.select(F.col("at").alias("at2"), F.col("names").alias("names2"), F.col("x").alias("x2"))
    return held.join(other, F.col("at") <= F.col("at2")) if upward else held.crossJoin(other)


def opened(names, x: bytes, wide: bool) -> tuple[np.ndarray, np.ndarray]:
    """Names and unit vectors of a block."""
    names = np.asarray(names, dtype=object)
    return names, unit(np.frombuffer(x, dtype=np.float64 if wide else np.float32).reshape(len(names), -1).astype(np.float64))


class Best:
    """The k nearest of each row of a block, while others come by; of equally near ones those at smaller places stay.

    Products in 32 bits, whose error has a bound, rule out most; the cosines of the rest are computed in 64.
    """

    def __init__(self, names: np.ndarray, x: np.ndarray, k: int):
        self.names, self.x, self.k, self.x32 = names, x, k, x.astype(np.float32)
        self.margin = (x.shape[1] + 16) * 2.0**-23
        self.cos = np.full((len(x), k), -np.inf)
        self.place = np.zeros((len(x), k), dtype=np.int64)
        self.near = np.full((len(x), k), None, dtype=object)

    def see(self, at: int, names: np.ndarray, x: np.ndarray) -> None:
        k, rough = self.k, self.x32 @ x.astype(np.float32).T
        if len(names) and self.names[0] <= names[-1] and names[0] <= self.names[-1]:
            same = np.minimum(np.searchsorted(names, self.names), len(names) - 1)
            own = np.flatnonzero(names[same] == self.names)
            rough[own, same[own]] = -np.inf
        floor = self.cos[:, -1] - self.margin
        if not np.isfinite(floor).all() and len(names) > k:  # the block's own k-th best is a floor as well
            floor = np.maximum(floor, np.partition(rough, len(names) - k, axis=1)[:, len(names) - k] - 2 * self.margin)
        i, j = np.nonzero(rough >= np.where(np.isfinite(floor), floor, -3.0).astype(np.float32)[:, None])
        if not len(i):
            return
        if len(i) > 64 * len(self.x):  # many as near as each other
            cos = (self.x @ x.T)[i, j]
        else:
            cos = np.concatenate([np.einsum("nd,nd->n", self.x[i[b : b + 16384]], x[j[b : b + 16384]]) for b in range(0, len(i), 16384)])
        cos = np.round(cos, 12)
        keep = cos >= self.cos[i, -1]
        i, j, cos = i[keep], j[keep], cos[keep]
        if not len(i):
            return
        rows = np.unique(i)
        row = np.concatenate([np.repeat(rows, k), i])
        cos, place = np.concatenate([self.cos[rows].ravel(), cos]), np.concatenate([self.place[rows].ravel(), at + j])
        near = np.concatenate([self.near[rows].ravel(), names[j]])
        order = np.lexsort((place, -cos, row))
        row = row[order]
        rank = np.arange(len(row)) - np.searchsorted(row, row)
        order, row, rank = order[rank < k], row[rank < k], rank[rank < k]
        self.cos[row, rank], self.place[row, rank], self.near[row, rank] = cos[order], place[order], near[order]

    def frame(self, at: int) -> pd.DataFrame:
        real = np.isfinite(self.cos)
        return pd.DataFrame({"at": [at], "src": [np.repeat(self.names, real.sum(axis=1))], "dst": [self.near[real]], "w": [self.cos[real]], "place": [self.place[real]]})


def nearest(rows: DataFrame, k: int, block: int) -> DataFrame:
    """(src, dst, w): for each of ``rows`` (seg_id, vec) the k others of largest cosine, ties to smaller ids, exactly. What moves between
    tasks is a row of results for each block and part of the other side."""
    held = blocks(rows, "seg_id", block)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        at, best = None, None
        for batch in batches:
            for mine, names, x, wide, other, names2, x2 in batch.itertuples(index=False):
                if best is None or mine != at:
                    if best is not None:
                        yield best.frame(at)
                    at, best = mine, Best(*opened(names, x, wide), k)
                best.see(other, *opened(names2, x2, wide))
        if best is not None:
            yield best.frame(at)

    def merged(group: pd.DataFrame) -> pd.DataFrame:
        src, dst, w, place = (np.concatenate([np.asarray(v, dtype=t) for v in group[c]]) for c, t in (("src", object), ("dst", object), ("w", float), ("place", np.int64)))
        own, row = np.unique(src.astype(str), return_inverse=True)
        order = np.lexsort((place, -w, row))
        row = row[order]
        order = order[np.arange(len(row)) - np.searchsorted(row, row) < k]
        return pd.DataFrame({"src": src[order], "dst": dst[order], "w": w[order]})

    found = paired(held).mapInPandas(run, "at long, src array<string>, dst array<string>, w array<double>, place array<long>")
    return found.groupBy("at").applyInPandas(merged, "src string, dst string, w double")


def above(rows: DataFrame, key: str, delta: float, block: int) -> DataFrame:
    """(a, b, cos) with a < b of rows (key, vec) whose cosine is above ``delta``, exactly."""
    held = blocks(rows, key, block)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for at, names, x, wide, other, names2, x2 in batch.itertuples(index=False):
                (mine, x), (theirs, y) = opened(names, x, wide), opened(names2, x2, wide)
                cos = np.round(x @ y.T, 12)
                i, j = np.nonzero(np.triu(cos > delta, 1) if at == other else cos > delta)
                yield pd.DataFrame({"a": mine[i], "b": theirs[j], "cos": cos[i, j]})

    return paired(held, upward=True).mapInPandas(run, "a string, b string, cos double")


#: Rows of a block that meet another block at once; what they connect needs no further products.
STRIP = 64


class Joined:
    """Which rows of the blocks seen so far are connected, and the links that have connected them.

    Rows that are connected already are not compared. Products in 32 bits, whose error has a bound, decide most; the cosines
    of pairs within that bound of ``delta`` are computed in 64.
    """

    def __init__(self, delta: float):
        self.delta, self.parent, self.begin = delta, np.zeros(0, dtype=np.int64), {}

    def numbers(self, at: int, n: int) -> np.ndarray:
        if at not in self.begin:
            self.begin[at] = len(self.parent)
            self.parent = np.concatenate([self.parent, np.arange(len(self.parent), len(self.parent) + n)])
        return np.arange(self.begin[at], self.begin[at] + n)

    def roots(self, i: np.ndarray) -> np.ndarray:
        root = self.parent[i]
        while (root != (up := self.parent[root])).any():
            root = up
        self.parent[i] = root
        return root

    def root(self, i: int) -> int:
        while (up := int(self.parent[i])) != i:
            i = up
        return i

    def see(self, at: int, x: np.ndarray, x32: np.ndarray, other: int, y: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Compares unit vectors of two blocks; (i, j, cos) of links between rows that nothing has connected before."""
        mine, theirs, y32 = self.numbers(at, len(x)), self.numbers(other, len(y)), y.astype(np.float32)
        margin, found = (x.shape[1] + 16) * 2.0**-23, []
        for b in range(0, len(x), STRIP):
            ra, rb = self.roots(mine[b : b + STRIP]), self.roots(theirs)
            values, times = np.unique(rb, return_counts=True)
            inside = values[times.argmax()]  # the part that most of the other block belongs to
            for rows, to in ((ra == inside, rb != inside), (ra != inside, np.ones(len(y), dtype=bool))):
                rows, to = b + np.flatnonzero(rows), np.flatnonzero(to)
                if not len(rows) or not len(to):
                    continue
                rough = x32[rows] @ (y32 if len(to) == len(y) else y32[to]).T
                i, j = np.nonzero(rough > self.delta - margin)
                sure = rough[i, j] > self.delta + margin
                i, j = rows[i], to[j]
                found += self._link(mine, theirs, i[sure], j[sure])
                i, j = i[~sure], j[~sure]
                apart = self.roots(mine[i]) != self.roots(theirs[j])
                i, j = i[apart], j[apart]
                near = self._cosines(x, y, i, j) > self.delta
                found += self._link(mine, theirs, i[near], j[near])
        i, j = np.array(found, dtype=np.int64).reshape(-1, 2).T
        return i, j, self._cosines(x, y, i, j)

    def _cosines(self, x: np.ndarray, y: np.ndarray, i: np.ndarray, j: np.ndarray) -> np.ndarray:
        parts = [np.einsum("nd,nd->n", x[i[b : b + 4096]], y[j[b : b + 4096]]) for b in range(0, len(i), 4096)]
        return np.round(np.concatenate(parts), 12) if parts else np.zeros(0)

    def _link(self, mine: np.ndarray, theirs: np.ndarray, i: np.ndarray, j: np.ndarray) -> list[tuple[int, int]]:
        out = []
        while len(i):
            ra, rb = self.roots(mine[i]), self.roots(theirs[j])
            apart = ra != rb
            i, j = i[apart], j[apart]
            for f in np.unique(rb[apart], return_index=True)[1].tolist():  # a link for each part on the other side, then anew
                u, v = self.root(int(mine[i[f]])), self.root(int(theirs[j[f]]))
                if u != v:
                    self.parent[max(u, v)] = min(u, v)
                    out.append((int(i[f]), int(j[f])))
        return out


def connecting(rows: DataFrame, key: str, delta: float, block: int) -> DataFrame:
    """(a, b, cos) with a < b: of the links of ``above`` as many as connect what all of them connect, exactly. A task gives no more of them
    than it sees rows."""
    held = blocks(rows, key, block)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        joined, last, mine, mine32 = Joined(delta), None, None, None
        for batch in batches:
            for at, names, x, wide, other, names2, x2 in batch.itertuples(index=False):
                if at != last:
                    mine = opened(names, x, wide)
                    last, mine32 = at, mine[1].astype(np.float32)
                theirs = mine if other == at else opened(names2, x2, wide)
                i, j, cos = joined.see(at, mine[1], mine32, other, theirs[1])
                a, b = mine[0][i], theirs[0][j]
                yield pd.DataFrame({"a": np.where(a < b, a, b), "b": np.where(a < b, b, a), "cos": cos})

    return paired(held, upward=True).mapInPandas(run, "a string, b string, cos double")
