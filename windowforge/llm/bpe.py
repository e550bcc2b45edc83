"""Byte-level BPE without running merges: longest matches, a table of compatible pairs, backtracking.

A token sequence is the merge result of its bytes exactly when each neighbouring pair is what merging that pair's bytes
alone gives, since a merge across a border looks only at the two tokens beside it. So the encoder walks through a piece
with the longest token at each place (found by one Aho-Corasick pass), goes on while neighbours are compatible, and
steps back to a shorter token where they are not. A place that leads nowhere is marked, so no place is tried twice from
the same token and time stays linear.
"""

from __future__ import annotations

import hashlib
import json
from collections.abc import Callable
from functools import lru_cache

import ahocorasick
import numpy as np
import regex
from pyspark.sql import DataFrame

from .common import by_text

#: Entries kept of pieces met before; longer pieces are encoded anew each time.
CACHED_PIECES, CACHED_LENGTH = 300_000, 48
#: Fixed value: how byte-level BPE cuts texts before merging.
PIECES = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""


def visible_bytes() -> dict[str, int]:
    """Characters by which byte-level vocabularies write bytes: printable ones stand for themselves, the rest follow from 256 on."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(rest)}


class ByteBpe:
    """Encoder and decoder of one tokenizers file of the byte-level kind."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        kind, model = spec.get("pre_tokenizer") or {}, spec["model"]
        if kind.get("type") != "ByteLevel" or kind.get("add_prefix_space") or spec.get("normalizer") or model["type"] != "BPE":
            raise ValueError("not a plain byte-level BPE file")
        byte = visible_bytes()
        raw = lambda s: bytes(byte[c] for c in s)
        self.ids = {raw(s): i for s, i in model["vocab"].items()}
        self.special = {t["content"]: t["id"] for t in spec.get("added_tokens", [])}
        self.rank = {}
        for n, m in enumerate(model["merges"]):
            a, b = m if isinstance(m, list) else m.split(" ")
            a, b = raw(a), raw(b)
            self.rank[self.ids[a], self.ids[b]] = (n, self.ids[a + b])
        size = max([*self.ids.values(), *self.special.values()]) + 1
        parts = [b""] * size
        for s, i in [*self.ids.items(), *((s.encode(), i) for s, i in self.special.items())]:
            parts[i] = s
        self.parts = parts
        self.blob = np.frombuffer(b"".join(parts), dtype=np.uint8)
        self.start = np.concatenate([[0], np.cumsum([len(p) for p in parts])]).astype(np.int64)
        self.automaton = ahocorasick.Automaton()
        for s, i in self.ids.items():
            self.automaton.add_word(s.decode("latin-1"), (i, len(s)))
        self.automaton.make_automaton()
        self.pattern = regex.compile(PIECES)
        self.splitter = regex.compile("(" + "|".join(regex.escape(s) for s in sorted(self.special, key=len, reverse=True)) + ")") if self.special else None
        self.pairs: dict[tuple[int, int], bool] = {}
        self.known = _Pieces(self)

    def merged(self, piece: bytes) -> list[int]:
        """Ids by running the merges; used for pairs only."""
        ids = [self.ids[piece[i : i + 1]] for i in range(len(piece))]
        while len(ids) > 1:
            found = min(((self.rank[p], i) for i, p in enumerate(zip(ids, ids[1:])) if p in self.rank), default=None)
            if found is None:
                break
            (_, new), at = found
            ids[at : at + 2] = [new]
        return ids

    def compatible(self, a: int, b: int) -> bool:
        known = self.pairs.get((a, b))
        if known is None:
            if len(self.pairs) > 2_000_000:
                self.pairs.clear()
            known = self.pairs[a, b] = self.merged(self.parts[a] + self.parts[b]) == [a, b]
        return known

    def piece(self, piece: bytes) -> list[int]:
        """Ids of one piece that merges never leave."""
        whole = self.ids.get(piece)
        if whole is not None and len(piece) == 1:
            return [whole]
        n = len(piece)
        at: list[list[int]] = [[] for _ in range(n)]
        for end, (i, length) in self.automaton.iter(piece.decode("latin-1")):
            at[end - length + 1].append(i)  # shorter tokens of a start end earlier, so lists grow by length
        dead, out, places, tries = bytearray(n + 1), [], [0], [len(at[0])]
        while True:
            here = places[-1]
            if here == n:
                return out
            options, moved = at[here], False
            while tries[-1]:
                tries[-1] -= 1
                token = options[tries[-1]]
                after = here + len(self.parts[token])
                if not dead[after] and (not out or self.compatible(out[-1], token)):
                    out.append(token)
                    places.append(after)
                    tries.append(len(at[after]) if after < n else 0)
                    moved = True
                    break
            if not moved:
                if not out:
                    raise ValueError("a byte has no token")
                dead[here] = 1
                places.pop()
                tries.pop()
                out.pop()

    def packed(self, text: str) -> bytes:
        """Ids of a whole text as little-endian unsigned 32-bit integers; special strings inside it become their ids."""
        if self.splitter is None or not any(s in text for s in self.special):
            return b"".join(map(self.known.__getitem__, self.pattern.findall(text)))
        out = []
        for k, part in enumerate(self.splitter.split(text)):
            out.append(self.special[part].to_bytes(4, "little") if k % 2 else b"".join(map(self.known.__getitem__, self.pattern.findall(part))))
        return b"".join(out)

    def encode(self, text: str) -> list[int]:
        return np.frombuffer(self.packed(text), dtype="<u4").tolist()

    def decode_bytes(self, packed: bytes) -> bytes:
        """Bytes of the tokens, gathered through the table of offsets."""
        ids = np.frombuffer(packed, dtype="<u4").astype(np.int64)
        first = self.start[ids]
        lengths = self.start[ids + 1] - first
        ends = np.cumsum(lengths)
        total = int(ends[-1]) if len(ends) else 0
        return self.blob[np.repeat(first - (ends - lengths), lengths) + np.arange(total)].tobytes()

    def decode(self, packed: bytes) -> str:
        return self.decode_bytes(packed).decode("utf-8", "replace")


class _Pieces(dict):
    """Pieces met before, with their packed ids."""

    def __init__(self, owner: ByteBpe):
        self.owner = owner

    def __missing__(self, piece: str) -> bytes:
        packed = np.array(self.owner.piece(piece.encode()), dtype="<u4").tobytes()
        if len(piece) <= CACHED_LENGTH:
            if len(self) >= CACHED_PIECES:
                self.clear()
            self[piece] = packed
        return packed


@lru_cache(maxsize=2)
def encoder(path: str) -> ByteBpe:
    return ByteBpe(path)


def vocabulary(name: str) -> str:
    """Place of a vocabulary file of the public tokenizers on this machine."""
    import public_tokenizers

    return public_tokenizers.path(name)


def bpe_round_trip(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", name: str = "byte_bpe_50k.json", keep_ids: bool = False) -> DataFrame:
    """Per row: id, n_tokens, ids_sha256, decoded_sha256; with ``keep_ids`` also ids (packed binary) and decoded (string).

    Null texts count as empty and give no tokens. Texts are encoded whole, however long. Repeated rows give repeated
    results, rows without an id one without it, an empty table an empty one, other columns are ignored.
    """
    schema = "n_tokens long, ids_sha256 string, decoded_sha256 string" + (", ids binary, decoded string" if keep_ids else "")

    def both_ways() -> Callable[[list[str]], list[tuple]]:
        bpe = encoder(vocabulary(name))

        def tell(texts: list[str]) -> list[tuple]:
            rows = []
            for text in texts:
                ids = bpe.packed(text)
                back = bpe.decode_bytes(ids)
                if text.encode() != back:
                    back = back.decode("utf-8", "replace").encode()
                row = (len(ids) // 4, hashlib.sha256(ids).hexdigest(), hashlib.sha256(back).hexdigest())
                rows.append(row + ((ids, back.decode("utf-8", "replace")) if keep_ids else ()))
            return rows

        return tell

    return by_text(docs, id_col, text_col, schema, both_ways)
