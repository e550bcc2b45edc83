"""Every option of the method in one frozen record. Bold readings of the ambiguities are the defaults."""

from __future__ import annotations

from dataclasses import dataclass, replace


@dataclass(frozen=True)
class Config:
    # segments
    window: int = 1024
    tokens: str = "whitespace"  # whitespace, word, bpe
    overlong: str = "split"  # split, truncate
    # vectors
    dim: int = 1024
    idf: bool = True
    signed: bool = False
    # initial number of clusters
    n_subsets: int = 10
    density: str = "mean_cosine"  # printed, mean_cosine, mean_dissimilarity
    n_clusters: int | None = None
    # clustering
    delta: float = 0.4
    epsilon: float = 1e-3
    rounds: int = 5
    assign: str = "auto"  # auto, exact, hnsw, cells, lsh
    spawn: str = "batch"  # batch, sequential
    merge: str = "components"  # components, mutual_best, sequential
    shift: str = "sum"  # sum, mean
    finalize: bool = False
    # packing
    alpha: float = 1.0
    beta: float = 1.0
    lam: float = 1.0
    eligible: str = "nonneg"  # nonneg, positive
    empty_cos: float = 0.0
    leftover: str = "open_new"  # open_new, drop
    backfill: bool = False
    max_cluster: int | None = None  # larger clusters are dealt over parts of this size, which changes results; none: packed whole
    # everything random
    seed: int = 7

    def with_(self, **changes) -> Config:
        return replace(self, **changes)

    def __post_init__(self) -> None:
        allowed = {
            "tokens": ("whitespace", "word", "bpe"),
            "overlong": ("split", "truncate"),
            "density": ("printed", "mean_cosine", "mean_dissimilarity"),
            "assign": ("auto", "exact", "hnsw", "cells", "lsh"),
            "spawn": ("batch", "sequential"),
            "merge": ("components", "mutual_best", "sequential"),
            "shift": ("sum", "mean"),
            "eligible": ("nonneg", "positive"),
            "leftover": ("open_new", "drop"),
        }
        for name, options in allowed.items():
            if getattr(self, name) not in options:
                raise ValueError(f"{name} is one of {options}, not {getattr(self, name)!r}")
        if self.window < 1 or self.rounds < 1 or min(self.alpha, self.beta, self.lam) < 0:
            raise ValueError("window and rounds are at least 1, weights at least 0")
