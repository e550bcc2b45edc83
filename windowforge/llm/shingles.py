"""Word shingles of whole texts as sorted 64-bit numbers."""

from __future__ import annotations

import numpy as np
import xxhash

WORDS_A_SHINGLE = 5
#: Bytes of a word that are hashed eight at a time, all words of a text together; longer words one by one.
LONG_WORD = 256
_MULTIPLY, _SHIFT = np.uint64(0x9E3779B97F4A7C15), np.uint64(29)
_FINAL = ((np.uint64(33), np.uint64(0xFF51AFD7ED558CCD)), (np.uint64(33), np.uint64(0xC4CEB9FE1A85EC53)))
#: By a number of bytes up to eight, what keeps so many at the start of a block.
_KEEP = np.array([(1 << 8 * k) - 1 for k in range(9)], dtype=np.uint64)


def word_hashes(data: bytes) -> np.ndarray:
    """A number for each word; words end at space, tab, line feed, vertical tab, form feed and carriage return only."""
    held = data + bytes(8)
    b = np.frombuffer(held, dtype=np.uint8)[: len(data)]
    inside = np.zeros(len(data) + 2, dtype=bool)
    inside[1:-1] = (b != 32) & (b - np.uint8(9) > 4)
    edges = np.flatnonzero(inside[1:] != inside[:-1])
    starts = edges[::2]
    sizes = edges[1::2] - starts
    blocks = np.ndarray(len(data) + 1, dtype="<u8", buffer=held, strides=(1,))  # eight bytes from any place on
    h = (blocks[starts] & _KEEP[np.minimum(sizes, 8)]) + sizes.astype(np.uint64) * _MULTIPLY
    at, done = np.flatnonzero((sizes > 8) & (sizes <= LONG_WORD)), 8
    while len(at):
        x = h[at]
        h[at] = (x ^ (x >> _SHIFT)) * _MULTIPLY + (blocks[starts[at] + done] & _KEEP[np.minimum(sizes[at] - done, 8)])
        done += 8
        at = at[sizes[at] > done]
    for k in np.flatnonzero(sizes > LONG_WORD):
        h[k] = xxhash.xxh3_64_intdigest(data[starts[k] : starts[k] + sizes[k]])
    for shift, factor in _FINAL:
        h ^= h >> shift
        h *= factor
    return h ^ (h >> np.uint64(33))


def shingles(text: str | None, size: int = WORDS_A_SHINGLE) -> np.ndarray:
    """Distinct shingles, ascending. A-Z are lower-cased; a text of fewer words is one shingle, one without words has none."""
    w = word_hashes((text or "").encode().lower())
    if not len(w):
        return w
    short = len(w) < size
    h = w[:1] + np.uint64(len(w)) if short else w[: len(w) - size + 1].copy()
    for k in range(1, len(w) if short else size):
        h = (h ^ (h >> _SHIFT)) * _MULTIPLY + (w[k : k + 1] if short else w[k : len(w) - size + 1 + k])
    h = np.sort(h ^ (h >> _SHIFT))
    first = np.ones(len(h), dtype=bool)
    np.not_equal(h[1:], h[:-1], out=first[1:])
    return h if first.all() else h[first]
