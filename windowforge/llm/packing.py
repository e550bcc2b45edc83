"""Packing documents into sequences: length combinations that fill a window, their counts by non-negative least squares."""

from __future__ import annotations

import itertools
import json
import math
import zlib
from collections.abc import Callable
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pandas as pd
import regex
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .bpe import PIECES as SPLIT
from .bpe import visible_bytes, vocabulary
from .common import by_text, materialize, ship

ROWS_IN_BUCKET = 5_000
BUCKET_SHIFT = 40
MAX_BUCKETS = 1 << 22
PIECES = "start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"


@lru_cache(maxsize=1)
def rank_encoder(path: str):
    """tiktoken over the vocabulary of a byte-level tokenizers file, which gives the same ids in less time, and the special strings."""
    import tiktoken

    with open(path, encoding="utf-8") as f:
        spec = json.load(f)
    byte = visible_bytes()
    ranks = {bytes(byte[c] for c in s): i for s, i in spec["model"]["vocab"].items()}
    kind, made = spec.get("pre_tokenizer") or {}, [ranks[bytes(byte[c] for c in "".join(m if isinstance(m, list) else m.split(" ")))] for m in spec["model"]["merges"]]
    if kind.get("type") != "ByteLevel" or kind.get("add_prefix_space") or spec.get("normalizer") or spec["model"]["type"] != "BPE" or any(a >= b for a, b in zip(made, made[1:])):
        raise ValueError("not a plain byte-level BPE file whose merges make their tokens in the order of ids")
    special = {t["content"]: t["id"] for t in spec.get("added_tokens", [])}
    return tiktoken.Encoding("own", pat_str=SPLIT, mergeable_ranks={k: i for k, i in ranks.items() if i not in special.values()}, special_tokens={}), special


def ids_of(path: str, text: str) -> np.ndarray:
    """Ids as the tokenizers library gives them; special strings inside the text become their ids."""
    fast, special = rank_encoder(path)
    if not any(s in text for s in special):
        return np.asarray(fast.encode_ordinary(text), dtype="<u4")
    cut = regex.split("(" + "|".join(regex.escape(s) for s in sorted(special, key=len, reverse=True)) + ")", text)
    return np.concatenate([np.asarray([special[p]] if k % 2 else fast.encode_ordinary(p), dtype="<u4") for k, p in enumerate(cut)])


def combinations(lengths: np.ndarray, window: int, depth: int = 3) -> np.ndarray:
    """Rows of 2 to ``depth`` lengths, ascending and ended by zeros, that add up to the window; at most window ** 2 / 12 rows for depth 3."""
    have = np.zeros(window + 1, dtype=bool)
    have[lengths] = True
    found = []
    small = lengths[lengths <= window // 2]
    pairs = small[have[window - small]]
    found.append(np.stack([pairs, window - pairs, np.zeros_like(pairs)], axis=1))
    if depth >= 3:
        for a in lengths[lengths <= window // 3]:
            b = lengths[(lengths >= a) & (lengths <= (window - a) // 2)]
            b = b[have[window - a - b]]
            found.append(np.stack([np.full_like(b, a), b, window - a - b], axis=1))
    return np.concatenate(found).astype(np.int64)


def least_squares(combos: np.ndarray, histogram: np.ndarray, rounds: int = 600) -> np.ndarray:
    """Counts x >= 0 that minimise |A x - histogram|, A counting the lengths in each combination, by accelerated projected gradient."""
    if not len(combos):
        return np.zeros(0)
    size = len(histogram)
    real = histogram.astype(np.float64).copy()
    real[0] = 0
    scale = max(real.max(), 1.0)
    target = real / scale

    def forward(x: np.ndarray) -> np.ndarray:
        y = sum(np.bincount(combos[:, k], weights=x, minlength=size) for k in range(combos.shape[1]))
        y[0] = 0
        return y

    back = lambda r: sum(np.where(combos[:, k] > 0, r[combos[:, k]], 0) for k in range(combos.shape[1]))
    step = 1.0 / max(back(forward(np.ones(len(combos)))).max(), 1.0)  # row sums bound the largest eigenvalue
    x = z = np.zeros(len(combos))
    momentum = 1.0
    for _ in range(rounds):
        new = np.maximum(0.0, z - step * back(forward(z) - target))
        following = (1 + math.sqrt(1 + 4 * momentum * momentum)) / 2
        z = new + (momentum - 1) / following * (new - x)
        if np.abs(new - x).max() < 1e-9:
            x = new
            break
        x, momentum = new, following
    return x * scale


@dataclass
class Plan:
    """Where the k-th remainder of each length goes. Its size depends on the window alone, not on the documents."""

    window: int
    first: np.ndarray  # per length: first of its slots
    until: np.ndarray  # per slot: rank after its last
    sequence: np.ndarray  # per slot: sequence of its first rank
    offset: np.ndarray  # per slot: place in the sequence
    used: np.ndarray  # per length: ranks that have slots
    stream: np.ndarray  # per length: place of its first other rank in the stream that is chopped
    combined: int  # sequences made of combinations

    def place(self, length: int, rank: int) -> list[tuple[int, int, int, int]]:
        """(start in the remainder, length, sequence, offset) of its pieces."""
        if rank < self.used[length]:
            low, high = self.first[length], self.first[length + 1]
            k = low + int(np.searchsorted(self.until[low:high], rank, side="right"))
            before = self.until[k - 1] if k > low else 0
            return [(0, length, int(self.sequence[k] + rank - before), int(self.offset[k]))]
        at = int(self.stream[length] + (rank - self.used[length]) * length)
        head = min(length, self.window - at % self.window)
        out = [(0, head, self.combined + at // self.window, at % self.window)]
        if head < length:
            out.append((head, length - head, self.combined + (at + head) // self.window, 0))
        return out


def solve(histogram: np.ndarray, window: int, depth: int = 3) -> Plan:
    """histogram[r]: remainders of r tokens. Rounds the least-squares counts down to what is there, then fills up greedily, most wanted
    combinations first; what still remains is laid end to end, longest first, and chopped at the window."""
    left = histogram.astype(np.int64).copy()
    left[0] = 0
    lengths = np.flatnonzero(left)
    combos = combinations(lengths, window, depth)
    wanted = least_squares(combos, left)
    order = np.argsort(-wanted, kind="stable")
    taken = np.zeros(len(combos), dtype=np.int64)
    for limit in (np.floor(wanted + 1e-9).astype(np.int64), None):
        for c in order:
            if limit is not None and not limit[c]:
                break
            members = [int(x) for x in combos[c] if x]
            most = min(left[x] // members.count(x) for x in members)
            n = int(most if limit is None else min(most, limit[c]))
            if n:
                taken[c] += n
                for x in members:
                    left[x] -= n
    slots: list[list[tuple[int, int, int]]] = [[] for _ in range(window + 1)]
    base = 0
    for c in np.flatnonzero(taken):
        at = 0
        for x in combos[c][combos[c] > 0][::-1]:
            slots[x].append((int(taken[c]), base, at))
            at += int(x)
        base += int(taken[c])
    first = np.cumsum([0, *(len(s) for s in slots)])
    until = np.concatenate([np.cumsum([n for n, _, _ in s]) for s in slots if s]) if base else np.zeros(0, dtype=np.int64)
    flat = [x for s in slots for x in s]
    used = np.array([sum(n for n, _, _ in s) for s in slots], dtype=np.int64)
    rest = left[::-1] * np.arange(len(left))[::-1]
    stream = np.zeros(window + 1, dtype=np.int64)
    stream[: len(left)] = (np.cumsum(rest) - rest)[::-1]
    return Plan(window, first, until, np.array([b for _, b, _ in flat], dtype=np.int64), np.array([o for _, _, o in flat], dtype=np.int64), used, stream, base)


def tokenised(docs: DataFrame, id_col: str, text_col: str, window: int, name: str, end_id: int, buckets: int) -> DataFrame:
    """Per row: its tokens, checksums of the full windows, and the ids after them, dealt evenly over the buckets whatever its id."""

    def cut_up() -> Callable[[list[str]], list[tuple]]:
        path, turn = vocabulary(name), itertools.count()

        def tell(texts: list[str]) -> list[tuple]:
            rows = []
            for text in texts:
                ids = np.append(ids_of(path, text), np.uint32(end_id)).astype("<u4")
                cut = len(ids) // window * window
                full = [zlib.crc32(ids[s : s + window].tobytes()) for s in range(0, cut, window)]
                rows.append(((zlib.crc32(ids.tobytes()) + next(turn)) % buckets, len(ids), len(ids) - cut, full, zlib.compress(ids[cut:].astype("<u2").tobytes(), 1) if end_id < 65536 and ids.max() < 65536 else b"4" + ids[cut:].tobytes()))
            return rows

        return tell

    rows = by_text(docs, id_col, text_col, "bucket long, doc_tokens long, rest int, full array<long>, tail binary", cut_up)
    return rows.select(F.col(id_col).cast("string").alias("_i"), "bucket", "doc_tokens", "rest", "full", "tail")  # as text an id passes through workers unchanged, beside nulls too


def unpacked(tail: bytes) -> np.ndarray:
    """The ids of a tail: 16 bits each under zlib, or 32 bits behind a mark that no zlib stream begins with."""
    if tail[:1] == b"4":
        return np.frombuffer(tail, dtype="<u4", offset=1)
    return np.frombuffer(zlib.decompress(tail), dtype="<u2").astype("<u4")


def pack(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", window: int = 1024, name: str = "byte_bpe_50k.json", end_id: int = 0, depth: int = 3) -> DataFrame:
    """One row per piece: id, start, length, ids_crc32, doc_tokens, sequence_id, offset.

    Full windows of a document stand alone. Remainders are placed by their length and their rank among equal lengths:
    combinations of two or three lengths that fill a window exactly take as many as the least-squares solution says, the
    rest are chopped from one stream, so that all sequences but the last are full. Ranks come from counts by bucket, so no
    task sees more than a bucket, even if all rows have one id or one length.

    Null texts count as empty and hold the end id alone. Very long texts are encoded whole; of their full windows only checksums
    move. Repeated rows are packed once each, rows without an id under none. An empty table gives an empty result. Further
    columns are ignored.
    """
    spark = docs.sparkSession
    ship(spark)
    buckets = min(MAX_BUCKETS, max(8, -(-docs.count() // ROWS_IN_BUCKET)))
    rows = materialize(tokenised(docs, id_col, text_col, window, name, end_id, buckets), "pack-tokens")
    counts = rows.filter("rest > 0").groupBy("bucket", "rest").agg(F.count(F.lit(1)).alias("n"))
    histogram = np.zeros(window + 1, dtype=np.int64)
    for r in counts.groupBy("rest").agg(F.sum("n").alias("n")).collect():  # a row per length below the window
        histogram[r["rest"]] = r["n"]
    plan = solve(histogram, window, depth)
    before = F.coalesce(F.sum("n").over(Window.partitionBy("rest").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    ranks = counts.select(F.col("bucket").alias("of"), F.col("rest").alias("size"), before.alias("before"))  # names of their own: a cogroup takes columns that both sides inherit for one

    def place(docs_of: pd.DataFrame, ranks_of: pd.DataFrame) -> pd.DataFrame:
        rank = dict(zip(ranks_of["size"], ranks_of["before"])) if len(ranks_of) else {}
        out, running = [], 0
        for doc, bucket, tokens, rest, full, tail in docs_of.sort_values(["_i", "doc_tokens"], kind="stable")[["_i", "bucket", "doc_tokens", "rest", "full", "tail"]].itertuples(index=False):
            for k, crc in enumerate(full):
                out.append((doc, k * window, window, crc, tokens, ((bucket + 1) << BUCKET_SHIFT) + running, 0))
                running += 1
            if rest:
                k = rank[rest]
                rank[rest] = k + 1
                ids = unpacked(tail)
                for at, length, sequence, offset in plan.place(rest, k):
                    out.append((doc, len(full) * window + at, length, zlib.crc32(ids[at : at + length].tobytes()), tokens, sequence, offset))
        return pd.DataFrame(out, columns=[id_col, "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"])

    placed = rows.groupBy("bucket").cogroup(ranks.groupBy("of")).applyInPandas(place, f"`{id_col}` string, {PIECES}")
    return placed.withColumn(id_col, F.col(id_col).cast(docs.schema[id_col].dataType))
