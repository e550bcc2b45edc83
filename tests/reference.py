"""Plain versions of the sequential methods, written from their descriptions, for small inputs."""

from __future__ import annotations

import itertools
import math


def dot(a, b):
    return sum(x * y for x, y in zip(a, b))


def cosine(a, b):
    na, nb = math.sqrt(dot(a, a)), math.sqrt(dot(b, b))
    return dot(a, b) / (na * nb) if na and nb else 0.0


def mean(vectors):
    return [sum(x) / len(vectors) for x in zip(*vectors)]


def cluster(vectors: dict[str, list[float]], seeds: list[str], delta: float, rounds: int, epsilon: float):
    """Rounds of assignment, opening, means and merging by components. Returns (membership as sets, figures by round)."""
    centres, trace = {s: vectors[s] for s in seeds}, []
    groups = {}
    for t in range(1, rounds + 1):
        groups, opened = {}, []
        for name in sorted(vectors):
            best, where = max(((round(cosine(vectors[name], centres[c]), 12), c) for c in centres), key=lambda x: (x[0], [-ord(ch) for ch in x[1]]))
            top = min(c for c in centres if round(cosine(vectors[name], centres[c]), 12) == best)
            if best > delta or t == rounds:
                groups.setdefault(top, []).append(name)
            else:
                opened.append(name)
            del where
        before = dict(centres)
        for name in opened:
            groups[f"r{t}/{name}"] = [name]
        means = {c: mean([vectors[m] for m in g]) for c, g in groups.items()}
        shift = sum(math.dist(means[c], before[c]) for c in means if c in before)
        root = {c: c for c in means}

        def find(c):
            while root[c] != c:
                c = root[c]
            return c

        for a, b in itertools.combinations(sorted(means), 2):
            if round(cosine(means[a], means[b]), 12) > delta:
                x, y = sorted((find(a), find(b)))
                root[y] = x
        merged = {}
        for c in groups:
            merged.setdefault(find(c), []).extend(groups[c])
        trace.append((t, len(opened), len(means) - len(merged), len(merged), round(shift, 9)))
        groups = merged
        centres = {c: mean([vectors[m] for m in g]) for c, g in groups.items()}
        if shift < epsilon:
            break
    return {frozenset(g) for g in groups.values()}, trace


def pack(docs: list[tuple[str, int, list[float]]], window: int, alpha=1.0, beta=1.0, lam=1.0, empty_cos=0.0):
    """docs (name, length, vector) in any order of names; returns [(name, window, score)]."""
    n = max(1, math.ceil(sum(d[1] for d in docs) / window))
    room, held, out = [window] * n, [[] for _ in range(n)], []
    for name, length, v in sorted(docs, key=lambda d: (-d[1], d[0])):
        best = None
        for w in range(n):
            if room[w] < 0:
                continue
            f1 = cosine(v, mean(held[w])) if held[w] else empty_cos
            p = 1.0 if length <= room[w] else window / (window + length - room[w])
            f = round(alpha * f1 + beta * room[w] / window + lam * p, 12)
            if best is None or f > best[0]:
                best = (f, w)
        room[best[1]] -= length
        held[best[1]].append(v)
        out.append((name, best[1], best[0]))
    return out, room


def walk(nodes, edges):
    """edges (a, b, w): paths by nearest unvisited neighbour, starts by degree then name."""
    near = {}
    for a, b, w in edges:
        near.setdefault(a, {})[b] = w
        near.setdefault(b, {})[a] = w
    seen, paths = set(), []
    for s in sorted(nodes, key=lambda n: (len(near.get(n, {})), n)):
        if s in seen:
            continue
        path = [s]
        seen.add(s)
        while True:
            free = [(-w, b) for b, w in near.get(path[-1], {}).items() if b not in seen]
            if not free:
                break
            path.append(min(free)[1])
            seen.add(path[-1])
        paths.append(path)
    return paths


def objective(windows, lengths, vectors, window):
    """Ordered-pair relevance, homogeneity, per-window length penalty of a list of lists of names."""
    f1 = sum(cosine(vectors[a], vectors[b]) for w in windows for a in w for b in w if a != b)
    f2 = sum(window / len(w) for w in windows if w)
    p = sum(1.0 if sum(lengths[a] for a in w) <= window else window / sum(lengths[a] for a in w) - 1 for w in windows if w)
    return f1, f2, p


def best_partition(names, lengths, vectors, window, n):
    """Highest total over all assignments of a few segments to n windows."""
    best = None
    for choice in itertools.product(range(n), repeat=len(names)):
        windows = [[a for a, c in zip(names, choice) if c == w] for w in range(n)]
        total = sum(objective(windows, lengths, vectors, window))
        best = total if best is None else max(best, total)
    return best
