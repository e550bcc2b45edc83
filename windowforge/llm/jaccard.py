"""Exact Jaccard join of documents' shingle sets in their metric space, and the groups that its links make.

1 - Jaccard is a metric. Equal sets are one class from the start. The classes are joined in these moves.

*Lone sets.* A link shares so much that it leaves out fewer than ``p = n - ceil(0.75 n) + 1`` shingles of a set of n. Counted
over all texts, the shingles of one third of the hash range show which of them stand in one class alone; a class with p of
these has no link to anything and is done.

*Pivots and regions.* Some documents are drawn as pivots. Every document within a link of pivots belongs to the Voronoi cell
of its nearest one, which makes the cell one component from the start. Distances are computed to those pivots only that can be
as near: sets that share so much share one of their first shingles, rare ones first.

*Windows.* By the triangle inequality, what is linked to a document of a cell lies within the cell's reach (its largest distance
to the pivot) and a link's distance of the pivot. Such documents of other cells, and of none, are copied into the region, unless
they are connected to it already, and are compared with those of the cell whose distance to the pivot differs by no more
than a link's: with a few of them first, and with many times as many in each later step, as long as they are not connected to the
cell. So each link with an end in a cell is found, or its ends are known to be connected. Of links between what lies in cells, only that
the cells are connected is kept.

*Recursion.* Documents that no pivot is linked to are left. They join again among themselves, with eight times as many pivots: large
groups go in the first rounds, to few pivots each, small ones later. When few are left for the number of pivots, each is its own.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import by_text, materialize, ship, tidily
from .shingles import shingles

#: Share of the hash range whose shingles are counted over all texts. Any share gives exact results.
COUNTED = 1 / 3
#: Pivots of the first round, drawn from all documents; eight times as many in each later one, of those that no pivot has joined.
PIVOTS = 64
#: Documents of a cell that its region's boundary meets first, and how many times as many in each later step, until all are met.
LEAF, STEP = 16, 32
#: Sets that hold a shingle which counts as hot; more, if that many shingles would be hot.
HOT, HOT_KEYS = 1_000, 100_000
#: Pairs, and shingles of the pivots in them, that are broadcast at most; beyond, they are joined.
BROADCAST_PAIRS, BROADCAST_SHINGLES = 200_000, 1_000_000
#: Documents whose ids are broadcast at most to pick their texts; beyond, the ids are joined.
BROADCAST_IDS = 500_000


def links_leave(n: int, percent: int) -> int:
    """Of that many shingles of a set, any link's other end has one."""
    return n - -(-percent * n // 100) + 1


def leave(n, percent: int):
    """The same as a column."""
    return (n - F.ceil(F.lit(percent) * n / 100) + 1).cast("long")


def digest_of(s: np.ndarray) -> bytes | None:
    return xxhash.xxh3_128_digest(s.tobytes()) if len(s) else None


def classes_of_rows(docs: DataFrame, id_col: str, text_col: str, size: int) -> DataFrame:
    """Per row: id, n, class of equal sets (null for the empty set)."""

    return by_text(docs, id_col, text_col, "n long, class binary", lambda: lambda texts: [(len(s), digest_of(s)) for s in (shingles(t, size) for t in texts)]).withColumnRenamed(id_col, "id")


def lone_counts(docs: DataFrame, text_col: str, size: int) -> DataFrame:
    """(mark, lone): by the class's mark, how many shingles of the counted range stand in that class alone."""
    limit = np.uint64(int(COUNTED * 2**64) - 1) if COUNTED < 1 else np.uint64(2**64 - 1)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        seen: set[bytes] = set()
        for batch in batches:
            keys, marks = [], []
            for text in batch["_t"]:
                s = shingles(text, size)
                digest = digest_of(s)
                if digest is not None and digest not in seen:  # copies within a task are folded here
                    seen.add(digest)
                    part = s[: np.searchsorted(s, limit, side="right")]
                    keys.append(part)
                    marks.append(np.full(len(part), int.from_bytes(digest[:8], "big", signed=True), dtype=np.int64))
            if keys:
                keys, marks = np.concatenate(keys).astype(np.int64), np.concatenate(marks)
                for k in range(0, len(keys), 1 << 17):
                    yield pd.DataFrame({"key": keys[k : k + (1 << 17)], "mark": marks[k : k + (1 << 17)]})

    rows = docs.select(F.col(text_col).alias("_t")).mapInPandas(tidily(run), "key long, mark long")
    alone = rows.groupBy("key").agg(F.min("mark").alias("mark"), F.max("mark").alias("other")).filter("mark = other")
    return alone.groupBy("mark").agg(F.count(F.lit(1)).alias("lone"))


def sets_of(docs: DataFrame, ids: DataFrame, id_col: str, text_col: str, size: int) -> DataFrame:
    """Whole shingle sets of some documents: (id, set)."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for k in range(0, len(batch), 500):
                part = batch.iloc[k : k + 500]
                yield pd.DataFrame({"id": part["id"].to_numpy(), "set": [shingles(t, size).astype(np.int64) for t in part["_t"]]})

    wanted = F.broadcast(ids) if ids.count() <= BROADCAST_IDS else ids
    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("_t")).join(wanted, "id", "left_semi")
    return rows.mapInPandas(tidily(run), f"id {docs.schema[id_col].dataType.simpleString()}, set array<long>")


def compare(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Distances of pairs (id, p) from their whole sets: id, p, d, linked. Few pairs go to where the sets lie, and few pivots' sets too;
    many are joined, and then only the sets of the pairs move."""
    pairs = materialize(pairs, "pairs")
    few = pairs.count() <= BROADCAST_PAIRS
    wanted = pairs.select("p").distinct()
    pivots = sets.join(F.broadcast(wanted) if few else wanted, F.col("id") == F.col("p"), "left_semi").select(F.col("id").alias("p"), F.col("set").alias("sp"))
    light = few and (pivots.agg(F.sum(F.size("sp"))).first()[0] or 0) <= BROADCAST_SHINGLES
    both = sets.join(F.broadcast(pairs) if few else pairs, "id").join(F.broadcast(pivots) if light else pivots, "p")
    shared = both.select("id", "p", F.size("set").cast("long").alias("n"), F.size("sp").cast("long").alias("pn"), F.size(F.array_intersect("set", "sp")).cast("long").alias("i"))
    union = F.col("n") + F.col("pn") - F.col("i")
    return shared.select("id", "p", (1 - F.col("i") / union).alias("d"), (100 * F.col("i") >= percent * union).alias("linked"))


def components(edges: DataFrame, most: int = 60) -> DataFrame:
    """(node, root): the smallest node that edges (a, b) reach. Neighbours hang themselves on their smallest neighbour, first the larger
    ones, then the smaller ones, until every tree is a star; each round is written down."""
    stars = materialize(edges.select(F.greatest("a", "b").alias("v"), F.least("a", "b").alias("r")).filter("v <> r").distinct(), "stars")
    mark = None
    for _ in range(most):
        both = stars.unionByName(stars.select(F.col("r").alias("v"), F.col("v").alias("r")))
        low = both.groupBy("v").agg(F.min("r").alias("m")).select("v", F.least("v", "m").alias("m"))
        large = both.filter("r > v").join(low, "v").select(F.col("r").alias("v"), F.col("m").alias("r")).filter("v <> r").distinct()
        low = large.groupBy("v").agg(F.min("r").alias("m"))
        small = large.join(low, "v").select(F.explode(F.array(F.struct(F.col("v").alias("v"), F.col("m").alias("r")), F.struct(F.col("r").alias("v"), F.col("m").alias("r")))).alias("e")).select("e.*").filter("v <> r").distinct()
        stars = materialize(small, "stars")
        now = stars.agg(F.count(F.lit(1)), F.sum(F.xxhash64("v", "r").cast("decimal(38,0)"))).first()
        if now == mark:
            break
        mark = now
    else:
        raise RuntimeError("the stars have not settled")
    return stars.select(F.col("v").alias("node"), F.col("r").alias("root"))


def ranked(sets: DataFrame, percent: int) -> DataFrame:
    """(id, n, m, left, key, place): of each set the shingles that a set within the widest window of it cannot all miss, rare ones first.

    m counts the shingles that stand in several sets; the others come first in the order and lead to no other set. ``left`` says how
    many places a link must look at. Shingles that very many sets hold get their frequency from a broadcast, others by a join.
    """
    every = sets.select("id", F.size("set").cast("long").alias("n"), F.explode("set").alias("key"))
    often = materialize(every.groupBy("key").agg(F.count(F.lit(1)).alias("df")).filter("df > 1"), "frequencies")
    hot = F.col("df") > max(HOT, (often.agg(F.sum("df")).first()[0] or 0) // HOT_KEYS)
    known = every.join(F.broadcast(often.filter(hot)), "key").unionByName(every.join(F.broadcast(often.filter(hot).select("key")), "key", "left_anti").join(often.filter(~hot), "key"))
    of_id = Window.partitionBy("id")
    known = known.withColumn("m", F.count(F.lit(1)).over(of_id)).withColumn("left", leave(F.col("n"), percent) - (F.col("n") - F.col("m"))).filter("left > 0")
    known = known.withColumn("place", F.row_number().over(of_id.orderBy("df", "key")))
    return known.filter(F.col("place") <= leave(F.col("n"), max(2 * percent - 100, 0)) - (F.col("n") - F.col("m"))).select("id", "n", "m", "left", "key", "place")


def can(share, one: str = "", two: str = "p"):
    """Whether two sets can share so much through a shingle that both have, by their sizes n, their shingles m that are not their own,
    and the shingle's place among these. They share ``need`` shingles, so that a common one is among the first n - need + 1 of each
    set; and what is common lies, up to this shingle, within the shorter start, beyond it within the shorter rest."""
    col = lambda side, name: F.col(side + name)
    need = F.ceil(share * (col(one, "n") + col(two, "n")) / (1 + share) - 1e-9)
    rest = F.least(col(one, "m") - col(one, "place"), col(two, "m") - col(two, "place"))
    return (rest + 1 >= need) & (F.least(one + "place", two + "place") + rest >= need)


def side(rows: DataFrame, prefix: str) -> DataFrame:
    """The ranked shingles with a prefix before every name but the key's; the id is named by the prefix alone."""
    return rows.select("key", F.col("id").alias(prefix), *[F.col(c).alias(prefix + c) for c in ("n", "m", "left", "place")])


def links(docs: DataFrame, chosen: DataFrame, id_col: str, text_col: str, percent: int, size: int) -> DataFrame:
    """Enough of the links between the chosen documents' sets to connect all that links connect: (a, b)."""
    share_of_link = F.lit(percent / 100)
    within = 1 - percent / 100
    sets = materialize(sets_of(docs, chosen, id_col, text_col, size), "sets")
    rows = materialize(ranked(sets, percent), "ranked")
    edges: list[DataFrame] = []  # what is connected, as stars, and the links that have come since
    found = lambda: reduce(DataFrame.unionByName, edges)

    def connected() -> DataFrame:
        roots = components(found())
        edges[:] = [roots.select(F.col("node").alias("a"), F.col("root").alias("b"))]
        return roots

    def rooted(df: DataFrame, roots: DataFrame, *names: str) -> DataFrame:
        for name in names:
            df = df.join(roots.select(F.col("node").alias(name), F.col("root").alias(name + "root")), name, "left")
            df = df.withColumn(name + "root", F.coalesce(name + "root", name))
        return df

    def measured(pairs: DataFrame, label: str, cells: DataFrame | None = None) -> DataFrame:
        got = materialize(compare(pairs, sets, percent), label)
        link(got, cells)
        return got

    def link(got: DataFrame, cells: DataFrame | None = None) -> None:
        """Keeps the links; what lies in a cell stands there for the cell's pivot, with which it is connected."""
        some = got.filter("linked").select(F.col("id").alias("a"), F.col("p").alias("b"))
        for end in ("a", "b") if cells is not None else ():
            some = some.join(cells.select(F.col("id").alias(end), F.col("p").alias("_cell")), end, "left").withColumn(end, F.coalesce("_cell", end)).drop("_cell")
        edges.append(some if cells is None else materialize(some.select("a", "b").filter("a <> b").distinct(), "links"))

    turn, pivots = 0, PIVOTS
    while True:
        waiting = rows.agg(F.count_distinct("id")).first()[0]
        last = 4 * pivots >= waiting
        drawn = F.lit(True) if last else F.pmod(F.xxhash64("id", F.lit(turn)), F.lit(waiting)) < pivots
        # distances to the pivots that can be linked, over the rarest shingles
        centre = side(rows.filter(drawn), "p")
        met = rows.filter("place <= left").join(centre.filter("pplace <= pleft"), "key").filter("id < p" if last else "id <> p").filter(can(share_of_link))
        to_pivot = materialize(compare(met.select("id", "p").distinct(), sets, percent), f"distances-{turn}")
        if last:
            link(to_pivot)
            return found()
        # regions: each document within a link of pivots lies in the cell of its nearest
        own = rows.filter(drawn).select("id", F.col("id").alias("p"), F.lit(0.0).alias("d")).distinct()
        near = own.unionByName(to_pivot.filter("linked").select("id", "p", "d")) if 2 * within < 1 else own
        cells = near.groupBy("id").agg(F.min(F.struct("d", "p")).alias("to")).select("id", "to.p", "to.d")
        cells = materialize(cells, f"cells-{turn}")
        edges.append(cells.filter("d > 0").select(F.col("id").alias("a"), F.col("p").alias("b")))
        link(to_pivot, cells)
        reach = cells.groupBy("p").agg(F.max("d").alias("reach")).filter("reach > 0")
        # windows: a document linked to one of a cell is within the cell's reach and a link of its pivot
        roots = connected()
        reach = materialize(rooted(reach, roots, "p"), f"reach-{turn}")
        apart = rooted(rows, roots, "id").join(centre.join(reach, "p"), "key").filter("idroot <> proot")
        share = F.lit(1 - within - 1e-9) - F.col("reach")
        early = lambda x: F.col(x + "place") <= F.col(x + "m") - F.ceil(share * F.col(x + "n")) + 1
        apart = apart.filter(early("") & early("p") & can(share)).select("id", "p").distinct().join(to_pivot.select("id", "p"), ["id", "p"], "left_anti")
        windows = to_pivot.filter("not linked").unionByName(measured(apart, f"windows-{turn}")).join(reach.select("p", "reach"), "p")
        windows = windows.filter(F.col("d") <= F.col("reach") + within + 1e-9).select("id", "p", "d")
        # leaves: boundary documents meet some of the cell's own, and more of them in each step as long as they are not connected to the cell
        short = rows.filter("place <= left")
        own = cells.filter("d > 0").withColumnRenamed("d", "pd")
        sizes = own.groupBy("p").agg(F.count(F.lit(1)).alias("size"))
        own = own.join(sizes, "p").select(F.col("id").alias("_p"), F.col("p").alias("cell"), "pd", "size", (F.pmod(F.xxhash64("id"), F.lit(1 << 30)) / (1 << 30)).alias("turn"))
        own = materialize(own.withColumnRenamed("_p", "p"), f"own-{turn}")
        met, most, largest = 0, LEAF, own.agg(F.max("size")).first()[0] or 0
        boundary = materialize(windows, f"boundary-{turn}")
        while met < largest and not boundary.isEmpty():
            boundary = rooted(boundary.select("id", "p", "d"), connected(), "id", "p").filter("idroot <> proot")
            boundary = materialize(boundary, f"boundary-{turn}").withColumnRenamed("p", "cell")
            now = own.filter((F.col("turn") >= met / F.col("size")) & (F.col("turn") < most / F.col("size")))
            # shingles once for each document, however many cells it is a boundary of
            some = short.join(boundary.select("id", "idroot").distinct(), "id")
            inside = side(short, "p").join(now.join(boundary.select("cell", "proot").distinct(), "cell").select("p", "cell", "pd", "proot"), "p")
            meet = some.join(inside, "key").filter("id <> p").filter("idroot <> proot").filter(can(share_of_link)).select("id", "p", "cell", "pd").distinct()
            meet = meet.join(boundary.select("id", "cell", "d"), ["id", "cell"]).filter(F.abs(F.col("d") - F.col("pd")) <= within + 1e-9)
            measured(meet.select("id", "p"), f"leaves-{turn}", cells)
            boundary = boundary.withColumnRenamed("cell", "p")
            met, most = most, STEP * most
        # what no pivot is linked to joins again among itself
        rows = materialize(rows.join(cells.select("id"), "id", "left_anti"), "ranked")
        turn, pivots = turn + 1, 8 * pivots


def jaccard_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", percent: int = 75, size: int = 5) -> DataFrame:
    """Per row: id, n_shingles, component_id (smallest id that links reach; its own where none does).

    Two documents link when 100 * shared >= ``percent`` * joint shingles. Documents without words, null or empty, have no
    shingles and no links. Repeated rows count as one document. Rows without an id are grouped with none and get a null
    component unless an equal set has an id. A very long text is one set, which is held whole and compared like any other. An
    empty table gives an empty result; further columns are ignored.
    """
    ship(docs.sparkSession)
    docs = docs.select(id_col, text_col)
    rows = materialize(classes_of_rows(docs, id_col, text_col, size), "classes")
    classes = rows.filter("class is not null").groupBy("class").agg(F.min("id").alias("least"), F.first("n").alias("n"))
    mark = F.conv(F.hex(F.substring("class", 1, 8)), 16, -10).cast("long")
    lone = lone_counts(docs, text_col, size)
    chosen = classes.withColumn("mark", mark).join(lone, "mark", "left").filter(F.col("least").isNotNull() & (F.coalesce("lone", F.lit(0)) < leave(F.col("n"), percent)))
    edges = links(docs, materialize(chosen.select(F.col("least").alias("id")).distinct(), "not-lone"), id_col, text_col, percent, size)
    belongs = rows.join(classes.select("class", "least"), "class", "left").select("id", "n", F.coalesce("least", "id").alias("least"))
    roots = components(edges)
    return belongs.join(roots.select(F.col("node").alias("least"), "root"), "least", "left").select(F.col("id").alias(id_col), F.col("n").alias("n_shingles"), F.coalesce("root", "least").alias("component_id"))
