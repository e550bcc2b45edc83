"""Nearest centres by cosine: exact, through a layered graph, through coarse cells, through random projections.

All take documents (seg_id, vec) and centres (cluster_id, vec) and give (seg_id, cluster_id, cos); ties go to the smaller id.
Cosines are compared after rounding to 12 digits, so the order of a sum never decides.
"""

from __future__ import annotations

import heapq
import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from windowforge.functions import columns
from windowforge.operators.blocks import blocks
from windowforge.session import settled, ship

#: Bytes of centres that a broadcast may hold; more of them are searched by cells.
BROADCAST_BYTES = 256 << 20
#: Bytes of centres up to which cells and buckets are looked up where the documents lie; more of them move by key.
IN_PLACE_BYTES = 64 << 20
#: Bytes that one block of products with the centres takes at most.
PRODUCT_BYTES = 32 << 20
#: Multiplications of documents with centres up to which the exact way is chosen before a graph, which is built on the driver.
EXACT_PRODUCTS = 1 << 42
#: Documents that one group of a cell or bucket holds on average at most; hotter ones are dealt over parts.
GROUP_ROWS = 20_000
OUT = "seg_id string, cluster_id string, cos double, second double, evals long"


def unit(x: np.ndarray) -> np.ndarray:
    size = np.sqrt((x * x).sum(axis=1, keepdims=True))
    return np.divide(x, size, out=np.zeros_like(x), where=size > 0)


def matrix(vectors) -> np.ndarray:
    return np.stack([np.asarray(v, dtype=np.float64) for v in vectors]) if len(vectors) else np.zeros((0, 0))


def gathered(cents: DataFrame) -> tuple[list[str], np.ndarray]:
    """Centres on the driver as they are, by id; their size is checked first. In 32 bits where these hold every number, as they do for
    centres that are documents."""
    rows = cents.agg(F.count(F.lit(1)), F.max(F.size("vec"))).first()
    if rows[0] * (rows[1] or 0) * 8 > BROADCAST_BYTES:
        raise ValueError("too many centres to broadcast; assign by cells")
    got = cents.select("cluster_id", F.col("vec").cast("array<double>").alias("vec")).toArrow()
    ids = got.column("cluster_id").to_pylist()
    order = sorted(range(len(ids)), key=ids.__getitem__)
    c = np.concatenate([columns.matrix(part) for part in got.column("vec").chunks if len(part)]) if ids else np.zeros((0, 0))
    del got
    c = c[order]
    narrow = c.astype(np.float32)
    return [ids[i] for i in order], narrow if np.array_equal(narrow, c) else c


def collected(cents: DataFrame) -> tuple[list[str], np.ndarray]:
    """Centres on the driver as unit vectors, by id; their size is checked first."""
    ids, c = gathered(cents)
    return ids, unit(c.astype(np.float64))


class Nearest:
    """The nearest and the second nearest of many centres, for blocks of unit vectors.

    Products in 32 bits, whose error has a bound, rule out most; the cosines of the rest are computed in 64. A block takes as many
    rows as PRODUCT_BYTES hold, however many centres there are.
    """

    def __init__(self, c: np.ndarray):
        self.c, self.norm, self.c32 = c, np.ones(len(c)), np.empty(c.shape, dtype=np.float32)
        for b in range(0, len(c), 4096):
            part = c[b : b + 4096].astype(np.float64)
            self.c32[b : b + 4096] = unit(part)
            self.norm[b : b + 4096] = np.sqrt((part * part).sum(axis=1))
        self.norm[self.norm == 0] = 1
        self.margin = (c.shape[1] + 16) * 2.0**-23 if c.ndim == 2 else 0

    def cosines(self, x: np.ndarray, i: np.ndarray, j: np.ndarray) -> np.ndarray:
        out = np.empty(len(i))
        for b in range(0, len(i), 4096):
            at = j[b : b + 4096]
            out[b : b + 4096] = np.einsum("nd,nd->n", x[i[b : b + 4096]], self.c[at] / self.norm[at, None])
        return np.round(out, 12)

    def two(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Per row the place of the nearest centre (the first of equally near ones), its cosine, the second cosine."""
        most = max(16, PRODUCT_BYTES // (4 * max(len(self.c), 1)))
        parts = [self._two(x[b : b + most]) for b in range(0, len(x), most)] or [self._two(x)]
        return tuple(np.concatenate(p) for p in zip(*parts))

    def _two(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        n, all_ = len(self.c), np.arange(len(x))
        if n < 2 or not len(x):
            return np.zeros(len(x), dtype=np.int64), self.cosines(x, all_, np.zeros(len(x), dtype=np.int64)), np.full(len(x), -1.0)
        rough = x.astype(np.float32) @ self.c32.T
        first = rough.argmax(axis=1)
        if np.isnan(rough[all_, first]).any():  # vectors with infinite numbers are near to none
            rough[np.isnan(rough)] = -np.inf
            first = rough.argmax(axis=1)
        top = rough[all_, first]
        rough[all_, first] = -np.inf
        floor = rough.max(axis=1)
        rough[all_, first] = top
        i, j = np.divmod(np.flatnonzero(rough >= (floor - 2 * self.margin)[:, None]), n)
        cos = self.cosines(x, i, j)
        order = np.lexsort((j, -cos, i))
        begin = np.searchsorted(i[order], all_)  # two candidates a row at least
        return j[order[begin]], cos[order[begin]], cos[order[begin + 1]]


def top_two(x: np.ndarray, c: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Per row the place of the nearest centre, its cosine, the second cosine."""
    if len(x) * len(c) * 8 > PRODUCT_BYTES:
        return Nearest(c).two(x)
    cos = np.round(x @ c.T, 12)
    at = np.argmax(cos, axis=1)
    best = cos[np.arange(len(x)), at]
    if c.shape[0] > 1:
        cos[np.arange(len(x)), at] = -2.0
        return at, best, cos.max(axis=1)
    return at, best, np.full(len(x), -1.0)


def exact(docs: DataFrame, cents: DataFrame) -> DataFrame:
    """Every centre, by blocks of matrix products; centres are broadcast up to BROADCAST_BYTES and lie in files beyond, with the same result."""
    ship(docs.sparkSession)
    size = cents.agg(F.count(F.lit(1)), F.max(F.size("vec"))).first()
    if size[0] * (size[1] or 0) * 8 > BROADCAST_BYTES:
        return exact_in_files(docs, cents, size[0])
    ids, c = gathered(cents)
    held = docs.sparkSession.sparkContext.broadcast((np.array(ids, dtype=object), c))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names, c = held.value
        near, named = Nearest(c), pa.array(names, pa.string())
        for batch in batches:
            for k in range(0, len(batch), 2000):
                part = batch.slice(k, 2000)
                at, best, second = near.two(unit(columns.matrix(part.column(1)).astype(np.float64)))
                yield columns.batch(seg_id=part.column(0).cast(pa.string()), cluster_id=named.take(pa.array(at)), cos=best, second=second, evals=np.full(len(part), len(names), dtype=np.int64))

    return docs.select("seg_id", "vec").mapInArrow(run, OUT)


class Two:
    """The nearest and the second nearest of a block of documents, while blocks of centres come by in any order. Of equally near centres
    the one at the smaller place stays."""

    def __init__(self, names: np.ndarray, x: np.ndarray):
        self.names, self.x, self.place = names, unit(x.astype(np.float64)), None

    def see(self, place: np.ndarray, names: np.ndarray, cos: np.ndarray, second: np.ndarray) -> None:
        if self.place is None:
            self.place, self.near, self.cos, self.second = place, names, cos, second
            return
        better = (cos > self.cos) | (cos == self.cos) & (place < self.place)
        self.second = np.maximum(np.maximum(self.second, second), np.minimum(self.cos, cos))
        self.place, self.near, self.cos = np.where(better, place, self.place), np.where(better, names, self.near), np.where(better, cos, self.cos)


def exact_in_files(docs: DataFrame, cents: DataFrame, k: int) -> DataFrame:
    """``exact`` for ``k`` centres that are too many for a broadcast: documents and centres lie in blocks in files and meet as a Cartesian
    product. What moves between tasks is a row of results for each block of documents and part of the centres."""
    held = blocks(docs, "seg_id", 2048, "assign-documents")
    theirs = blocks(cents, "cluster_id", 2048, "assign-centres").select(F.col("at").alias("at2"), F.col("names").alias("names2"), F.col("x").alias("x2"), F.col("wide").alias("wide2"))
    found = "at long, seg_id array<string>, place array<long>, cluster_id array<string>, cos array<double>, second array<double>"

    def opened(names, x: bytes, wide: bool) -> tuple[np.ndarray, np.ndarray]:
        return np.asarray(names, dtype=object), np.frombuffer(x, dtype=np.float64 if wide else np.float32).reshape(len(names), -1)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        at, two = None, None
        out = lambda: pd.DataFrame({"at": [at], "seg_id": [two.names], "place": [two.place], "cluster_id": [two.near], "cos": [two.cos], "second": [two.second]})
        for batch in batches:
            for mine, names, x, wide, other, names2, x2, wide2 in batch.itertuples(index=False):
                if two is None or mine != at:
                    if two is not None:
                        yield out()
                    at, two = mine, Two(*opened(names, x, wide))
                theirs, c = opened(names2, x2, wide2)
                near, cos, second = Nearest(c).two(two.x)
                two.see(other + near, theirs[near], cos, second)
        if two is not None:
            yield out()

    def merged(group: pd.DataFrame) -> pd.DataFrame:
        two = Two(group["seg_id"].iloc[0], np.zeros((0, 0)))
        for row in group.itertuples(index=False):
            two.see(*(np.asarray(v, dtype=t) for v, t in ((row.place, np.int64), (row.cluster_id, object), (row.cos, float), (row.second, float))))
        return pd.DataFrame({"seg_id": two.names, "cluster_id": two.near, "cos": two.cos, "second": two.second, "evals": k})

    return held.crossJoin(theirs).mapInPandas(run, found).groupBy("at").applyInPandas(merged, OUT)


def exact_sql(docs: DataFrame, cents: DataFrame) -> DataFrame:
    """The same by expressions: a nested-loop join, for small inputs and as the check of the block form."""
    from windowforge.functions import vec as V

    c = cents.select("cluster_id", F.col("vec").alias("cv"))
    scored = docs.select("seg_id", "vec").crossJoin(F.broadcast(c)).select("seg_id", "cluster_id", F.round(V.cosine(F.col("vec"), F.col("cv")), 12).alias("cos"))
    order = Window.partitionBy("seg_id").orderBy(F.desc("cos"), "cluster_id")
    return scored.withColumn("k", F.row_number().over(order)).filter("k = 1").drop("k")


class Hnsw:
    """A layered graph over centres: each has a random height, each layer links near ones, a search descends greedily and fans out on the ground."""

    def __init__(self, c: np.ndarray, m: int = 16, ef: int = 64, seed: int = 7):
        self.c, self.m, self.ef, self.evals = c, m, ef, 0
        rng = np.random.default_rng(seed)
        height = np.minimum((-np.log(rng.random(len(c)) + 1e-12) / np.log(max(m, 2))).astype(int), 12)
        self.layers: list[dict[int, list[int]]] = [{} for _ in range(int(height.max(initial=0)) + 1)]
        self.entry, self.top = -1, -1
        for i in range(len(c)):
            self._add(i, int(height[i]))

    def _near(self, v: np.ndarray, start: list[int], layer: int, ef: int) -> list[tuple[float, int]]:
        links, seen = self.layers[layer], set(start)
        self.evals += len(start)
        first = [(float(s), i) for s, i in zip(self.c[start] @ v, start)]
        todo, held = [(-s, i) for s, i in first], list(first)
        heapq.heapify(todo)
        heapq.heapify(held)
        while todo:
            s, i = heapq.heappop(todo)
            if len(held) >= ef and -s < held[0][0]:
                break
            fresh = [j for j in links.get(i, ()) if j not in seen]
            if fresh:
                seen.update(fresh)
                self.evals += len(fresh)
                for t, j in zip((self.c[fresh] @ v).tolist(), fresh):
                    if len(held) < ef or t > held[0][0]:
                        heapq.heappush(todo, (-t, j))
                        heapq.heappush(held, (t, j))
                        if len(held) > ef:
                            heapq.heappop(held)
        return sorted(held, key=lambda x: (-x[0], x[1]))

    def _add(self, i: int, height: int) -> None:
        start = [self.entry] if self.entry >= 0 else []
        for layer in range(self.top, height, -1):
            start = [self._near(self.c[i], start, layer, 1)[0][1]]
        for layer in range(min(height, self.top), -1, -1):
            found = self._near(self.c[i], start, layer, self.ef)
            links, most = self.layers[layer], self.m * (2 if layer == 0 else 1)
            links[i] = [j for _, j in found[: self.m]]
            for j in links[i]:
                back = links.setdefault(j, [])
                back.append(i)
                if len(back) > most:
                    order = np.argsort(-(self.c[back] @ self.c[j]), kind="stable")[:most]
                    links[j] = [back[k] for k in order]
            start = [j for _, j in found]
        for layer in range(max(self.top + 1, 0), height + 1):
            self.layers[layer][i] = []
        if height > self.top:
            self.entry, self.top = i, height

    def seal(self) -> Hnsw:
        """Links as arrays, a row per centre, filled up with the number of centres."""
        self.links = []
        for layer in self.layers:
            width = max((len(x) for x in layer.values()), default=0)
            table = np.full((len(self.c) + 1, max(width, 1)), len(self.c), dtype=np.int64)
            for i, near in layer.items():
                table[i, : len(near)] = near
            self.links.append(table)
        self.layers = []
        return self

    def search(self, x: np.ndarray, expand: int = 4) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """For a block of vectors at once: cosines and places of the best centres, best first, and the comparisons made for each.

        Upper layers are descended greedily, all vectors a step at a time; on the ground the best ``expand`` centres of each vector's
        list that are not opened yet are opened together, until its ``ef`` best are all open. 32 bits lead the way; the last eight are
        compared anew in 64.
        """
        n, all_, exact = len(self.c), np.arange(len(x)), x
        x, wide = x.astype(np.float32), np.vstack([self.c, np.zeros((1, self.c.shape[1]))]).astype(np.float32)

        def near(ids: np.ndarray, who: np.ndarray) -> np.ndarray:
            cos = np.einsum("qcd,qd->qc", wide[ids], x[who])
            cos[ids == n] = -np.inf
            return cos

        here = np.full(len(x), self.entry, dtype=np.int64)
        cos, evals = x @ wide[self.entry], np.ones(len(x), dtype=np.int64)
        for table in self.links[:0:-1]:
            moving = all_
            while len(moving):
                ids = table[here[moving]]
                found = near(ids, moving)
                evals[moving] += (ids < n).sum(axis=1)
                best = found.argmax(axis=1)
                top = found[np.arange(len(moving)), best]
                up = top > cos[moving]
                here[moving[up]], cos[moving[up]] = ids[up, best[up]], top[up]
                moving = moving[up]
        ids, scores = here[:, None], cos[:, None]
        opened, seen = np.zeros((len(x), 1), dtype=bool), np.zeros((len(x), n + 1), dtype=bool)
        seen[all_, here] = True
        while True:
            order = np.argsort(-scores, axis=1, kind="stable")[:, : self.ef]
            ids, scores, opened = (np.take_along_axis(a, order, 1) for a in (ids, scores, opened))
            rank = np.where(opened | (ids == n), ids.shape[1], np.arange(ids.shape[1]))
            pick = np.argsort(rank, axis=1, kind="stable")[:, :expand]
            fresh = np.take_along_axis(rank, pick, 1) < ids.shape[1]
            if not fresh.any():
                ids = ids[:, :8]
                scores = np.einsum("qcd,qd->qc", self.c[np.minimum(ids, n - 1)], exact)
                scores[ids == n] = -np.inf
                order = np.argsort(-scores, axis=1, kind="stable")
                return np.take_along_axis(scores, order, 1), np.take_along_axis(ids, order, 1), evals
            np.put_along_axis(opened, pick, True, 1)
            around = self.links[0][np.where(fresh, np.take_along_axis(ids, pick, 1), n)].reshape(len(x), -1)
            around = np.sort(np.where(np.take_along_axis(seen, around, 1), n, around), axis=1)
            around[:, 1:][around[:, 1:] == around[:, :-1]] = n
            seen[all_[:, None], around] = True
            evals += (around < n).sum(axis=1)
            ids, scores = np.concatenate([ids, around], 1), np.concatenate([scores, near(around, all_)], 1)
            opened = np.concatenate([opened, around == n], 1)


def hnsw(docs: DataFrame, cents: DataFrame, m: int = 16, ef: int = 64, seed: int = 7) -> DataFrame:
    """Through a layered graph that is built once on the driver and broadcast; comparisons a document grow with the logarithm of the centres."""
    ship(docs.sparkSession)
    ids, c = collected(cents)
    held = docs.sparkSession.sparkContext.broadcast((np.array(ids, dtype=object), Hnsw(c, m, ef, seed).seal()))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        names, index = held.value
        for batch in batches:
            for k in range(0, len(batch), 128):
                part = batch.iloc[k : k + 128]
                scores, places, evals = index.search(unit(matrix(part["vec"])))
                scores = np.where(np.isfinite(scores), np.round(scores, 12), -2.0)
                first = np.where(scores == scores[:, :1], places, len(names)).min(axis=1)  # of equally near centres the one of smallest id
                second = scores[:, 1] if scores.shape[1] > 1 else np.full(len(part), -1.0)
                yield pd.DataFrame({"seg_id": part["seg_id"].to_numpy(), "cluster_id": names[first], "cos": scores[:, 0], "second": np.where(second > -2, second, -1.0), "evals": evals})

    return docs.select("seg_id", "vec").mapInPandas(run, OUT)


def coarse_centres(cents: DataFrame, n_cells: int, seed: int = 7) -> np.ndarray:
    """Coarse cells: centres drawn by hash, as many as cells; a bounded number on the driver."""
    got = cents.orderBy(F.md5(F.concat(F.lit(f"{seed}:"), "cluster_id"))).limit(n_cells).select("vec").toPandas()
    return unit(matrix(got["vec"]))


def cells_for(k: int, dim: int) -> int:
    """Coarse cells for k vectors: as many as a cell then holds vectors, 16 at least, and no more than a broadcast may hold."""
    return int(max(1, min(max(16, math.ceil(math.sqrt(k))), BROADCAST_BYTES // (8 * max(dim, 1)))))


def with_cells(df: DataFrame, key: str, cells: np.ndarray, n_probe: int) -> DataFrame:
    """(key, vec, cell): each row once for each of its ``n_probe`` nearest cells."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            cos = unit(matrix(batch["vec"])) @ cells.T if len(batch) else np.zeros((0, len(cells)))
            near = np.argsort(-np.round(cos, 12), axis=1, kind="stable")[:, :n_probe]
            yield pd.DataFrame({key: np.repeat(batch[key].to_numpy(), near.shape[1]), "vec": [v for v in batch["vec"] for _ in range(near.shape[1])], "cell": near.ravel().astype("int64")})

    return df.select(key, F.col("vec").cast("array<double>").alias("vec")).mapInPandas(run, f"{key} string, vec array<double>, cell long")


def hyperplanes(k: int, dim: int, tables: int, bits: int | None, seed: int) -> np.ndarray:
    """Random hyperplanes (tables, bits, dim); bits grow with the number of vectors, so that a bucket holds some hundreds of them."""
    bits = bits or max(4, min(24, math.ceil(math.log2(max(k, 1) / 256 + 1))))
    return np.random.default_rng(seed).normal(size=(tables, bits, dim))


def bucketed(df: DataFrame, key: str, planes: np.ndarray) -> DataFrame:
    """(key, vec, t, code): each row once for each table, with its side of the table's hyperplanes."""
    tables, bits = planes.shape[:2]

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            x = matrix(batch["vec"])
            for t in range(tables):
                code = ((x @ planes[t].T > 0) @ (1 << np.arange(bits))) if len(x) else np.zeros(0, dtype=int)
                yield pd.DataFrame({key: batch[key].to_numpy(), "vec": batch["vec"], "t": t, "code": code.astype("int64")})

    return df.select(key, F.col("vec").cast("array<double>").alias("vec")).mapInPandas(run, f"{key} string, vec array<double>, t long, code long")


def dealt(left: DataFrame, right: DataFrame, key: str, by: list[str], rows: int | None = None) -> tuple[DataFrame, DataFrame]:
    """Both sides with a column part: groups of more than ``rows`` rows on the left are dealt over parts by hash, to each of which the
    right side is copied. The left side is written down to be counted; there is one number for each group that has several parts."""
    left = settled(left, "dealt")
    parts = left.groupBy(*by).agg(F.ceil(F.count(F.lit(1)) / (rows or GROUP_ROWS)).cast("long").alias("_parts")).filter("_parts > 1")
    spread = lambda df: df.join(F.broadcast(parts), by, "left").withColumn("_parts", F.coalesce("_parts", F.lit(1).cast("long")))
    return (
        spread(left).withColumn("part", F.pmod(F.xxhash64(key), F.col("_parts"))).drop("_parts"),
        spread(right).withColumn("part", F.explode(F.sequence(F.lit(0).cast("long"), F.col("_parts") - 1))).drop("_parts"),
    )


def _within(left: DataFrame, right: DataFrame, keys: list[str], extra: int) -> DataFrame:
    """The nearest centre of the own group; ``extra`` comparisons were needed to find the group."""

    def run(docs: pd.DataFrame, cents: pd.DataFrame) -> pd.DataFrame:
        if not len(docs) or not len(cents):
            return pd.DataFrame({"seg_id": [], "cluster_id": [], "cos": [], "second": [], "evals": []}).astype({"seg_id": object, "cluster_id": object, "cos": float, "second": float, "evals": "int64"})
        cents = cents.sort_values("cluster_id")
        c, names, out = unit(matrix(cents["vec"])), cents["cluster_id"].to_numpy(), []
        for b in range(0, len(docs), 2000):
            part = docs.iloc[b : b + 2000]
            at, best, second = top_two(unit(matrix(part["vec"])), c)
            out.append(pd.DataFrame({"seg_id": part["seg_id"].to_numpy(), "cluster_id": names[at], "cos": best, "second": second, "evals": len(cents) + extra}))
        return pd.concat(out)

    return left.groupBy(*keys).cogroup(right.groupBy(*keys)).applyInPandas(run, OUT)


def in_place(docs: DataFrame, cents: DataFrame, keys, probe: int, extra: int, rest: bool) -> DataFrame:
    """The nearest centre of the documents' groups where the documents lie: centres and their groups are broadcast, so that no vector is
    copied or moved. ``keys`` gives a row of group numbers for each vector, a table each: centres take the first ``probe`` of a table's,
    documents the first. With ``rest`` documents that meet no centre are compared with all."""
    ids, c = gathered(cents)
    groups: dict[tuple[int, int], list[int]] = {}
    for b in range(0, len(c), 2000):
        for t, near in enumerate(keys(c[b : b + 2000].astype(np.float64))):
            for i, row in enumerate(near[:, :probe].tolist(), b):
                for g in row:
                    groups.setdefault((t, g), []).append(i)
    held = docs.sparkSession.sparkContext.broadcast((np.array(ids, dtype=object), c, {g: np.array(i) for g, i in groups.items()}))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        names, c, groups = held.value
        every = Nearest(c) if rest else None
        for batch in batches:
            for k in range(0, len(batch), 2000):
                part = batch.iloc[k : k + 2000]
                x = matrix(part["vec"])
                u, at, cos = unit(x), np.full(len(x), len(names)), np.full(len(x), -np.inf)
                second, evals = np.full(len(x), -1.0), np.zeros(len(x), dtype=np.int64)
                for t, near in enumerate(keys(x)):
                    order = np.argsort(near[:, 0], kind="stable")
                    own, begin = np.unique(near[order, 0], return_index=True)
                    for g, rows in zip(own.tolist(), np.split(order, begin[1:])):
                        if (some := groups.get((t, g))) is None:
                            continue
                        place, best, next_ = top_two(u[rows], unit(c[some].astype(np.float64)))
                        better = (best > cos[rows]) | (best == cos[rows]) & (some[place] < at[rows])
                        at[rows], cos[rows] = np.where(better, some[place], at[rows]), np.where(better, best, cos[rows])
                        second[rows], evals[rows] = np.maximum(second[rows], next_), evals[rows] + len(some) + extra
                left = np.flatnonzero(at == len(names))
                if rest and len(left):
                    at[left], cos[left], second[left] = every.two(u[left])
                    evals[left] = len(names)
                yield pd.DataFrame({"seg_id": part["seg_id"].to_numpy(), "cluster_id": names[at], "cos": cos, "second": second, "evals": evals})

    return docs.select("seg_id", "vec").mapInPandas(run, OUT)


def cells(docs: DataFrame, cents: DataFrame, n_cells: int | None = None, n_probe: int = 4, seed: int = 7) -> DataFrame:
    """Documents go to their one cell and stay there, centres are copied to their ``n_probe`` nearest cells and to every part of a hot
    one. Both sides move by key: nothing is broadcast but the coarse cells, about the root of the centres' number, and the parts of
    hot cells.

    Every coarse centre is a centre and its own cell's nearest, so no cell is without one.
    """
    ship(docs.sparkSession)
    size = cents.agg(F.count(F.lit(1)), F.max(F.size("vec"))).first()
    coarse = coarse_centres(cents, n_cells or cells_for(size[0], size[1] or 1), seed)
    if 0 < size[0] * (size[1] or 0) * 8 <= IN_PLACE_BYTES:
        return in_place(docs, cents, lambda x: [np.argsort(-np.round(unit(x) @ coarse.T, 12), axis=1, kind="stable")], min(n_probe, len(coarse)), len(coarse), False)
    d, c = dealt(with_cells(docs, "seg_id", coarse, 1), with_cells(cents, "cluster_id", coarse, min(n_probe, len(coarse))), "seg_id", ["cell"])
    return _within(d, c, ["cell", "part"], len(coarse))


def lsh(docs: DataFrame, cents: DataFrame, tables: int = 16, bits: int | None = None, seed: int = 7) -> DataFrame:
    """Candidates share a bucket of random hyperplanes in some table; documents that meet no centre take the exact way, or cells
    where the centres are too many for it. Ties between tables go to the smaller id."""
    ship(docs.sparkSession)
    size = cents.agg(F.count(F.lit(1)), F.max(F.size("vec"))).first()
    planes = hyperplanes(size[0], size[1] or 1, tables, bits, seed)
    if 0 < size[0] * (size[1] or 0) * 8 <= IN_PLACE_BYTES:
        weight = 1 << np.arange(planes.shape[1])
        return in_place(docs, cents, lambda x: [((x @ p.T > 0) @ weight)[:, None] for p in planes], 1, 0, True)
    d, c = dealt(bucketed(docs, "seg_id", planes), bucketed(cents, "cluster_id", planes), "seg_id", ["t", "code"])
    met = _within(d, c, ["t", "code", "part"], 0)
    best = met.groupBy("seg_id").agg(F.min(F.struct((-F.col("cos")).alias("far"), "cluster_id")).alias("b"), F.max("second").alias("second"), F.sum("evals").alias("evals"))
    found = best.select("seg_id", F.col("b.cluster_id").alias("cluster_id"), (-F.col("b.far")).alias("cos"), "second", "evals")
    rest = exact if size[0] * (size[1] or 0) * 8 <= BROADCAST_BYTES else cells
    return found.unionByName(rest(docs.join(found.select("seg_id"), "seg_id", "left_anti"), cents))


def choose(k: int, dim: int, docs: int | None = None) -> str:
    """Exact while the products are cheap, the graph while it fits into a broadcast, cells beyond. A graph costs milliseconds a centre on
    the driver; if the number of documents is given, their products with all centres are weighed against that."""
    if k * dim <= 1 << 21 or docs is not None and k * dim * 8 <= BROADCAST_BYTES and k * dim * docs <= EXACT_PRODUCTS:
        return "exact"
    return "hnsw" if k * dim * 8 <= BROADCAST_BYTES and k <= 50_000 else "cells"


def assign(docs: DataFrame, cents: DataFrame, how: str = "auto", **options) -> DataFrame:
    if how == "auto":
        row = cents.agg(F.count(F.lit(1)), F.max(F.size("vec"))).first()
        how = choose(row[0], row[1] or 1, docs.count() if row[0] * (row[1] or 1) > 1 << 21 else None)
    return {"exact": exact, "hnsw": hnsw, "cells": cells, "lsh": lsh}[how](docs, cents, **options)


def recall(approximate: DataFrame, truth: DataFrame) -> DataFrame:
    """One row: documents, recall (the same centre, or one as near), never_above (no cosine above the exact one)."""
    both = approximate.select("seg_id", F.col("cos").alias("a")).join(truth.select("seg_id", F.col("cos").alias("t")), "seg_id", "right")
    return both.agg(F.count(F.lit(1)).alias("documents"), F.avg((F.coalesce("a", F.lit(-2.0)) >= F.col("t") - 1e-9).cast("double")).alias("recall"), F.min((F.coalesce("a", F.lit(-2.0)) <= F.col("t") + 1e-9).cast("int")).alias("never_above"))
