"""What the method is compared with: random order, one document a window, paths through a graph of neighbours, retrieval, and packing by
length alone. All give manifests of one shape: window_id, pos, seg_id, start, offset, n_tokens, used, cut."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from windowforge.config import Config
from windowforge.operators import assign as A
from windowforge.operators.blocks import nearest
from windowforge.operators.pack import Bins
from windowforge.operators.prefix import running
from windowforge.session import settled, ship

PIECES = "window_id string, pos int, seg_id string, start int, offset int, n_tokens int, used int, cut int"
#: Nodes that one traversal may hold.
TRAVERSE_NODES = 2_000_000


def chop(segments: DataFrame, order: Column, window: int, name: str = "w", within: str | None = None) -> DataFrame:
    """Segments laid end to end in an order and cut every ``window`` tokens; a segment over a border becomes pieces. Nothing is lost.

    ``within``: a column of few values whose rows are laid and cut apart from each other; null is a value of its own.
    """
    rows = segments.filter("n_tokens > 0").select("seg_id", "n_tokens", *([within] if within else []), order.alias("_key"))
    if within:
        placed = running(rows, F.struct(within, "_key"), "n_tokens", ["seg_id"])
        first = placed.groupBy(F.col(within).alias("_within")).agg(F.min("before").alias("first"))
        placed = placed.join(F.broadcast(first), F.col(within).eqNullSafe(F.col("_within"))).withColumn("before", F.col("before") - F.col("first"))
        prefix = F.coalesce(F.concat(F.lit(f"{name}|"), F.col(within).cast("string"), F.lit("|")), F.lit(f"{name}-none|"))
    else:
        placed, prefix = running(rows, F.col("_key"), "n_tokens", ["seg_id"]), F.lit(f"{name}|")
    first, last = F.floor(F.col("before") / window), F.floor((F.col("before") + F.col("n_tokens") - 1) / window)
    pieces = placed.withColumn("w", F.explode(F.sequence(first, last)))
    start = F.greatest(F.col("w") * window - F.col("before"), F.lit(0))
    end = F.least((F.col("w") + 1) * window - F.col("before"), F.col("n_tokens").cast("long"))
    pieces = pieces.select(F.concat(prefix, F.lpad(F.col("w").cast("string"), 12, "0")).alias("window_id"), "seg_id", start.cast("int").alias("start"), F.greatest(F.col("before") - F.col("w") * window, F.lit(0)).cast("int").alias("offset"), F.col("n_tokens").cast("int").alias("n_tokens"), (end - start).cast("int").alias("used"))
    pos = F.row_number().over(Window.partitionBy("window_id").orderBy("offset")) - 1
    return pieces.select("window_id", pos.cast("int").alias("pos"), "seg_id", "start", "offset", "n_tokens", "used", F.lit(0).alias("cut"))


def random_windows(segments: DataFrame, window: int, seed: int = 7, within: str | None = None) -> DataFrame:
    """All segments in an order drawn by hash."""
    return chop(segments, F.md5(F.concat(F.lit(f"{seed}:"), F.col("seg_id"))), window, "random", within)


def single_windows(segments: DataFrame, window: int) -> DataFrame:
    """One segment a window, the rest padding."""
    used = F.least("n_tokens", F.lit(window)).cast("int")
    return segments.select(F.concat(F.lit("single|"), "seg_id").alias("window_id"), F.lit(0).alias("pos"), "seg_id", F.lit(0).alias("start"), F.lit(0).alias("offset"), F.col("n_tokens").cast("int").alias("n_tokens"), used.alias("used"), (F.col("n_tokens") - used).cast("int").alias("cut"))


def best_k(edges: DataFrame, k: int) -> DataFrame:
    order_ = Window.partitionBy("src").orderBy(F.desc("w"), "dst")
    return edges.dropDuplicates(["src", "dst"]).withColumn("k", F.row_number().over(order_)).filter(F.col("k") <= k).drop("k")


def _near(left: pd.DataFrame, right: pd.DataFrame, k: int) -> pd.DataFrame:
    if not len(left) or not len(right):
        return pd.DataFrame({"src": [], "dst": [], "w": []}).astype({"src": object, "dst": object, "w": float})
    right = right.sort_values("seg_id")
    names, c, out = right["seg_id"].to_numpy(), A.unit(A.matrix(right["vec"])), []
    for b in range(0, len(left), 1024):
        part = left.iloc[b : b + 1024]
        own = part["seg_id"].to_numpy()
        cos = np.round(A.unit(A.matrix(part["vec"])) @ c.T, 12)
        cos[own[:, None] == names[None, :]] = -np.inf
        at = np.argsort(-cos, axis=1, kind="stable")[:, :k]
        w = np.take_along_axis(cos, at, 1)
        real = np.isfinite(w)
        out.append(pd.DataFrame({"src": np.repeat(own, real.sum(axis=1)), "dst": names[at[real]], "w": w[real]}))
    return pd.concat(out)


def knn_graph(docs: DataFrame, k: int = 20, how: str = "exact", block: int = 4096, n_cells: int | None = None, n_probe: int = 4, tables: int = 16, bits: int | None = None, seed: int = 7) -> DataFrame:
    """Edges (src, dst, w) to the k nearest documents by cosine, ties to smaller ids.

    "exact" compares all blocks with all blocks, which are read from files, and keeps k a row and task before anything is merged; "cells" looks into a
    document's nearest coarse cell, to which others are copied from their ``n_probe`` nearest; "lsh" into shared buckets. Cells
    and bits grow with the documents, and the asking side of a hot cell or bucket is dealt over parts (``assign.dealt``).
    """
    ship(docs.sparkSession)
    rows = docs.select("seg_id", F.col("vec").cast("array<double>").alias("vec"))
    if how == "exact":
        return nearest(docs.select("seg_id", "vec"), k, block)
    if how == "cells":
        width = rows.agg(F.count(F.lit(1)), F.max(F.size("vec"))).first()
        coarse = A.coarse_centres(rows.select(F.col("seg_id").alias("cluster_id"), "vec"), n_cells or A.cells_for(width[0], width[1] or 1), seed)
        left, right = A.dealt(A.with_cells(rows, "seg_id", coarse, 1), A.with_cells(rows, "seg_id", coarse, min(n_probe, len(coarse))), "seg_id", ["cell"])
        keys = ["cell", "part"]
    elif how == "lsh":
        width = rows.agg(F.count(F.lit(1)), F.max(F.size("vec"))).first()
        planes = A.hyperplanes(width[0], width[1] or 1, tables, bits, seed)
        left, right = A.dealt(A.bucketed(rows, "seg_id", planes), A.bucketed(rows, "seg_id", planes), "seg_id", ["t", "code"])
        keys = ["t", "code", "part"]
    else:
        raise ValueError("how is 'exact', 'cells' or 'lsh'")
    met = left.groupBy(*keys).cogroup(right.groupBy(*keys)).applyInPandas(lambda a, b: _near(a, b, k), "src string, dst string, w double")
    return best_k(met, k)


def adjacency(edges: DataFrame, nodes: DataFrame, both_ways: bool) -> DataFrame:
    """Nodes (seg_id, cell, ...) with ``number``, which rises with the ids, and ``near``: the numbers of their neighbours in the same cell, nearest
    first, ties to smaller ids. Lists of numbers take a tenth of what edges with their names take."""
    numbered = settled(running(nodes.withColumn("_one", F.lit(1)), F.col("seg_id"), "_one", []).withColumnRenamed("before", "number").drop("_one"), "numbered")
    src, dst = (numbered.select(F.col("seg_id").alias(end), F.col("number").alias(to), F.col("cell").alias(f"{to}_cell")) for end, to in (("src", "i"), ("dst", "j")))
    linked = edges.join(src, "src").join(dst, "dst").filter("i_cell = j_cell and i <> j").select("i", "j", "w")
    if both_ways:
        linked = linked.select(F.explode(F.array(F.struct("i", "j", "w"), F.struct(F.col("j").alias("i"), F.col("i").alias("j"), "w"))).alias("e")).select("e.*")
    near = linked.groupBy("i").agg(F.sort_array(F.collect_list(F.struct((-F.col("w")).alias("far"), "j"))).alias("near"))
    return numbered.join(near.select(F.col("i").alias("number"), F.array_distinct("near.j").alias("near")), "number", "left").withColumn("near", F.coalesce("near", F.array().cast("array<long>")))


def by_cell(batches: Iterator[pd.DataFrame], columns: list[str]) -> Iterator[tuple[int, dict[str, np.ndarray], np.ndarray, np.ndarray]]:
    """From rows in the order of cells and numbers, cell by cell: the columns, where each node's neighbours begin, and their places in the cell."""

    def whole(cell: int, parts: list[pd.DataFrame]) -> tuple:
        numbers = np.concatenate([p["number"].to_numpy(dtype=np.int64) for p in parts])
        begin = np.concatenate([[0], np.cumsum(np.concatenate([p["size"].to_numpy(dtype=np.int64) for p in parts]))])
        flat = np.concatenate([p["flat"].iloc[0] for p in parts])
        return cell, {c: np.concatenate([p[c].to_numpy() for p in parts]) for c in columns}, begin, np.searchsorted(numbers, flat).astype(np.int32)

    held, own = [], None
    for batch in batches:
        for cell, rows in batch.groupby("cell", sort=False):
            if own is not None and cell != own:
                yield whole(own, held)
                held = []
            own = cell
            flat = np.concatenate([np.zeros(0, dtype=np.int64), *rows["near"]]).astype(np.int64)
            part = rows[["number", *columns]].assign(size=rows["near"].map(len).to_numpy())
            part["flat"] = [flat] + [None] * (len(part) - 1)
            held.append(part)
    if own is not None:
        yield whole(own, held)


def walk_paths(begin: np.ndarray, near: np.ndarray) -> Iterator[list[int]]:
    """Paths that visit each node once: on to the nearest unvisited neighbour, a new path where none is left. Starts: fewest neighbours first, then by place."""
    seen, begin = bytearray(len(begin) - 1), begin.tolist()
    for start in np.argsort(np.diff(begin), kind="stable").tolist():
        path, here = [], None if seen[start] else start
        while here is not None:
            seen[here] = 1
            path.append(here)
            here = next((n for n in near[begin[here] : begin[here + 1]].tolist() if not seen[n]), None)
        if path:
            yield path


def traverse(edges: DataFrame, nodes: DataFrame, cell: str | None = None) -> DataFrame:
    """(path_id, pos, seg_id, exact). Without cells one task walks the whole graph, up to a checked number of nodes; with a column of
    cells each is walked by itself, edges between cells are left out, and ``exact`` is false. The task that walks holds numbers, no names of edges."""
    ship(nodes.sparkSession)
    if cell is None and nodes.count() > TRAVERSE_NODES:
        raise ValueError("too many nodes for one walk; give a column of cells")
    of = nodes.select("seg_id", (F.col(cell).cast("long") if cell else F.lit(0).cast("long")).alias("cell"))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for key, columns, begin, near in by_cell(batches, ["seg_id"]):
            ids, pos, order = [], [], []
            for p, path in enumerate(walk_paths(begin, near)):
                ids += [(int(key) << 40) + p] * len(path)
                pos += range(len(path))
                order += path
            for k in range(0, len(order), 100_000):
                yield pd.DataFrame({"path_id": ids[k : k + 100_000], "pos": pos[k : k + 100_000], "seg_id": columns["seg_id"][order[k : k + 100_000]], "exact": cell is None})

    rows = adjacency(edges, of, True).select("cell", "number", "seg_id", "near")
    return rows.repartition("cell").sortWithinPartitions("cell", "number").mapInPandas(run, "path_id long, pos long, seg_id string, exact boolean")


def graph_windows(segments: DataFrame, paths: DataFrame, window: int) -> DataFrame:
    """Paths laid end to end in the order of the visit, cut every ``window`` tokens."""
    return chop(segments.join(paths.select("seg_id", "path_id", F.col("pos").alias("step")), "seg_id"), F.struct("path_id", "step"), window, "graph")


def retrieval_windows(segments: DataFrame, edges: DataFrame, window: int, fanout: int = 20, cells: int = 1) -> DataFrame:
    """From the first unused segment, pull its nearest unused neighbours until the window is full; then the next one."""
    ship(segments.sparkSession)
    cell = F.pmod(F.xxhash64("seg_id"), F.lit(cells).cast("long"))
    rows = segments.select("seg_id", F.col("n_tokens").cast("int").alias("n_tokens"), cell.alias("cell"))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for key, columns, begin, near in by_cell(batches, ["seg_id", "n_tokens"]):
            names, size, begin, out, w = columns["seg_id"], columns["n_tokens"].tolist(), begin.tolist(), [], 0
            used = bytearray(n <= 0 for n in size)  # segments without tokens go nowhere
            for s in range(len(size)):
                if used[s]:
                    continue
                at = 0
                for pos, n in enumerate([s, *[d for d in near[begin[s] : begin[s + 1]].tolist()[:fanout] if not used[d]]]):
                    if at >= window:
                        break
                    take = min(size[n], window - at)
                    out.append((f"retrieval|{key}|{w:09d}", pos, names[n], 0, at, size[n], take, size[n] - take))
                    used[n] = 1
                    at += take
                w += 1
                if len(out) >= 50_000:
                    yield pd.DataFrame(out, columns=[x.split()[0] for x in PIECES.split(", ")])
                    out = []
            yield pd.DataFrame(out, columns=[x.split()[0] for x in PIECES.split(", ")])

    laid = adjacency(edges, rows, False).select("cell", "number", "seg_id", "n_tokens", "near")
    return laid.repartition("cell").sortWithinPartitions("cell", "number").mapInPandas(run, PIECES)


def window_first(members: DataFrame, config: Config = Config()) -> DataFrame:
    """One window after the other: all remaining segments are scored for it, the best goes in, until it is full. Quadratic and sequential: for small inputs."""
    ship(members.sparkSession)

    def run(group: pd.DataFrame) -> pd.DataFrame:
        group = group.sort_values(["n_tokens", "doc_id", "seg_no"], ascending=[False, True, True], kind="stable").reset_index(drop=True)
        x, n = A.matrix(group["vec"]), group["n_tokens"].to_numpy(dtype=np.int64)
        left, out, w = list(range(len(group))), [], 0
        while left:
            bins, pos = Bins.empty(1, config.window, x.shape[1]), 0
            while left and (bins.remaining[0] > 0 or pos == 0):
                f = [float(bins.scores(x[i], int(n[i]), config)[0]) for i in left]
                i = left.pop(int(np.argmax(f)))
                before = int(config.window - bins.remaining[0])
                used = int(min(n[i], max(0, config.window - before)))
                out.append((f"first|{w:09d}", pos, group["seg_id"].iloc[i], 0, before, int(n[i]), used, int(n[i]) - used))
                bins.put(0, x[i], int(n[i]))
                pos += 1
            w += 1
        return pd.DataFrame(out, columns=[c.split()[0] for c in PIECES.split(", ")])

    return members.withColumn("all", F.lit(0)).groupBy("all").applyInPandas(run, PIECES)


def fit_decreasing(segments: DataFrame, window: int, rule: str = "best", groups: int = 1) -> DataFrame:
    """Bins by length alone, longest first: into the first, the fullest (best) or the emptiest (worst) window with room, else a new one."""
    if rule not in ("first", "best", "worst"):
        raise ValueError("rule is 'first', 'best' or 'worst'")
    ship(segments.sparkSession)

    def run(group: pd.DataFrame) -> pd.DataFrame:
        group = group.sort_values(["n_tokens", "seg_id"], ascending=[False, True], kind="stable")
        free, count, out = np.zeros(0, dtype=np.int64), [], []
        for s, n, g in group[["seg_id", "n_tokens", "g"]].itertuples(index=False):
            used = min(int(n), window)
            fits = np.flatnonzero(free >= used)
            if len(fits):
                at = int(fits[0] if rule == "first" else fits[np.argmin(free[fits])] if rule == "best" else fits[np.argmax(free[fits])])
            else:
                free, at = np.append(free, window), len(free)
                count.append(0)
            out.append((f"{rule}|{g}|{at:09d}", count[at], s, 0, int(window - free[at]), int(n), used, int(n) - used))
            free[at] -= used
            count[at] += 1
        return pd.DataFrame(out, columns=[c.split()[0] for c in PIECES.split(", ")])

    return segments.withColumn("g", F.pmod(F.xxhash64("seg_id"), F.lit(groups))).select("g", "seg_id", "n_tokens").groupBy("g").applyInPandas(run, PIECES)
