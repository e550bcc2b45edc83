"""Trees on histograms, grown with numpy and flattened into arrays: boosted for scores, bagged for votes."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np


@dataclass
class Trees:
    """Complete trees of one depth. Node k of a tree has the children 2k+1 and 2k+2; a row goes right where its value is above the threshold."""

    feature: np.ndarray  # trees x inner nodes
    threshold: np.ndarray
    value: np.ndarray  # trees x leaves
    base: float
    depth: int

    def raw(self, x: np.ndarray) -> np.ndarray:
        """Sum of the leaves that each row reaches, all trees at once."""
        x = np.ascontiguousarray(x, dtype=np.float64)
        node = np.zeros((len(x), len(self.feature)), dtype=np.int64)
        tree, row = np.arange(len(self.feature))[None, :], np.arange(len(x))[:, None]
        for _ in range(self.depth):
            node = 2 * node + 1 + (x[row, self.feature[tree, node]] > self.threshold[tree, node])
        return self.base + self.value[tree, node - (2**self.depth - 1)].sum(axis=1)


def edges_of(x: np.ndarray, bins: int) -> list[np.ndarray]:
    """Cut points of each feature at its quantiles; values up to a cut go left of it."""
    out = []
    for k in range(x.shape[1]):
        values = np.unique(x[:, k])
        out.append((values[1:] + values[:-1]) / 2 if len(values) <= bins else np.unique(np.quantile(x[:, k], np.linspace(0, 1, bins + 1)[1:-1])))
    return out


def binned(x: np.ndarray, edges: list[np.ndarray]) -> np.ndarray:
    return np.stack([np.searchsorted(e, x[:, k], side="left") for k, e in enumerate(edges)], axis=1)


def grow(codes: np.ndarray, edges: list[np.ndarray], gradient: np.ndarray, weight: np.ndarray, depth: int, ridge: float, least: float, features_at, bins: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """One tree by levels: sums of gradient and weight by (node, feature, bin) give every node's best cut. Returns features, thresholds, leaf sums / weights."""
    rows, width = codes.shape
    feature, threshold = np.zeros(2**depth - 1, dtype=np.int64), np.full(2**depth - 1, np.inf)
    node = np.zeros(rows, dtype=np.int64)
    cells = codes + np.arange(width)[None, :] * bins
    for level in range(depth):
        first, count = 2**level - 1, 2**level
        flat = ((node - first)[:, None] * (width * bins) + cells).ravel()
        g = np.bincount(flat, weights=np.repeat(gradient, width), minlength=count * width * bins).reshape(count, width, bins)
        h = np.bincount(flat, weights=np.repeat(weight, width), minlength=count * width * bins).reshape(count, width, bins)
        gl, hl = g.cumsum(axis=2), h.cumsum(axis=2)
        gt, ht = gl[:, :, -1:], hl[:, :, -1:]
        gain = gl**2 / (hl + ridge) + (gt - gl) ** 2 / (ht - hl + ridge) - gt**2 / (ht + ridge)
        gain[(hl < least) | (ht - hl < least)] = -1
        for k, e in enumerate(edges):
            gain[:, k, len(e) :] = -1
        for n in range(count):
            allowed = features_at(width)
            best = np.argmax(gain[n, allowed])
            k, b = allowed[best // bins], best % bins
            if gain[n, k, b] > 1e-9:
                feature[first + n], threshold[first + n] = k, edges[k][b]
        cut = np.array([np.searchsorted(edges[feature[i]], threshold[i]) if np.isfinite(threshold[i]) else bins for i in range(first, first + count)])
        at = node - first
        node = 2 * node + 1 + (codes[np.arange(rows), feature[node]] > cut[at])
    leaf = node - (2**depth - 1)
    g, h = (np.bincount(leaf, weights=w, minlength=2**depth) for w in (gradient, weight))
    return feature, threshold, np.where(h > 0, g / (h + ridge), 0.0)


def boost(x: np.ndarray, y: np.ndarray, trees: int = 80, depth: int = 4, rate: float = 0.15, bins: int = 64, ridge: float = 1.0, least: float = 5.0) -> Trees:
    """Logistic boosting; with one class alone the trees are empty and every score is that class's smoothed share."""
    share = (y.sum() + 1.0) / (len(y) + 2.0)
    base = float(np.log(share / (1 - share)))
    if len(np.unique(y)) < 2:
        return Trees(np.zeros((0, 2**depth - 1), dtype=np.int64), np.zeros((0, 2**depth - 1)), np.zeros((0, 2**depth)), base, depth)
    edges = edges_of(x, bins)
    codes, raw, grown = binned(x, edges), np.full(len(y), base), []
    for _ in range(trees):
        p = 1 / (1 + np.exp(-raw))
        f, t, v = grow(codes, edges, y - p, p * (1 - p), depth, ridge, least / 4, lambda width: np.arange(width), bins)
        grown.append((f, t, rate * v))
        raw = raw + Trees(f[None], t[None], rate * v[None], 0.0, depth).raw(x)
    return Trees(*(np.stack(a) for a in zip(*grown)), base, depth)


def forest(x: np.ndarray, y: np.ndarray, trees: int = 60, depth: int = 7, bins: int = 32, seed: int = 7) -> Trees:
    """Random forest: each tree on rows drawn with repetition, each cut among a random root-of-the-width of the features; raw() is the mean share of class 1."""
    rng, edges, grown = np.random.default_rng(seed), edges_of(x, bins), []
    codes, few = binned(x, edges), max(1, round(x.shape[1] ** 0.5))
    for _ in range(trees):
        weight = np.bincount(rng.integers(0, len(y), len(y)), minlength=len(y)).astype(np.float64)
        grown.append(grow(codes, edges, y * weight, weight, depth, 1e-9, 2.0, lambda width: rng.choice(width, few, replace=False), bins))
    f, t, v = (np.stack(a) for a in zip(*grown))
    return Trees(f, t, v / trees, 0.0, depth)
