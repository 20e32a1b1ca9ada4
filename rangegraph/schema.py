"""Schemas and parameter objects of the two-vector engine."""

from __future__ import annotations

import warnings
from dataclasses import dataclass, field, replace

OBJECTS = "id long, e array<float>, s array<float>"
QUERIES = "qid long, band int, alpha double, e array<float>, s array<float>"
PAIRS = "p long, x long, de double, ds double"
FRONTIER = PAIRS + ", layer int"
HITS = "qid long, band int, rank int, id long, dist double"
NODES = "shard int, id long, seed boolean, level int, e array<float>, s array<float>, dst array<long>, lo array<array<smallint>>, hi array<array<smallint>>, n_dist long"
SCALE = 10_000


@dataclass(frozen=True)
class BuildParams:
    """How an index is built. th: least share of [0, 1] for which an edge must be of use."""

    M: int = 40
    ef_c: int = 200
    th: float = 0.1
    candidates: str = "frontier"  # or 'greedy': best-first at alpha0
    pruning: str = "range"  # or 'none', or 'rng': the rule at alpha0 only
    seeds: str = "rim"  # or 'centroid', 'random', 'first'
    witness: str = "any"  # or 'active': a witness counts only where its own edge is active
    cap: str = "layer"  # or 'hard': stop inside a layer
    ties: str = "peel"  # or 'definition': twins share a layer
    reverse: str = "reprune"  # or 'append' up to twice M
    alpha0: float = 0.5
    levels: bool = False
    level0_factor: int = 1
    max_seeds: int | None = None
    seed: int = 42

    def __post_init__(self):
        for name, allowed in (("candidates", ("frontier", "greedy")), ("pruning", ("range", "none", "rng")), ("seeds", ("rim", "centroid", "random", "first")), ("witness", ("any", "active")), ("cap", ("layer", "hard")), ("ties", ("peel", "definition")), ("reverse", ("reprune", "append"))):
            if getattr(self, name) not in allowed:
                raise ValueError(f"{name} must be one of {allowed}")
        if self.M < 1 or self.ef_c < 1 or not 0 <= self.th <= 1 or not 0 <= self.alpha0 <= 1:
            raise ValueError("M and ef_c are at least 1, th and alpha0 in [0, 1]")

    def but(self, **changes) -> "BuildParams":
        return replace(self, **changes)


@dataclass(frozen=True)
class SearchParams:
    k: int = 10
    ef_search: int = 10
    gate: bool = True
    early_stop: bool = True
    probes: int | str = "all"  # shards per query, or 'bound': rounds in the order of the lower bound
    whole: bool = False  # all that a search of ef_search holds, instead of k: lists for a merge
    copies: int | None = None  # tasks that share a shard's queries; None: as many as there are cores for

    def __post_init__(self):
        if self.k < 1:
            raise ValueError("k is at least 1")
        if self.ef_search < self.k:
            warnings.warn("ef_search is raised to k", stacklevel=2)
            object.__setattr__(self, "ef_search", self.k)


@dataclass(frozen=True)
class ShardParams:
    """How objects are dealt. n: shards wanted; there are more where a shard would get over max_rows (n = None: as few as that allows)."""

    n: int | None = None
    by: str = "hash"  # or 'cluster'
    max_rows: int = 1_000_000

    def __post_init__(self):
        if self.by not in ("hash", "cluster") or self.max_rows < 1 or (self.n is not None and self.n < 1):
            raise ValueError("by is 'hash' or 'cluster', n and max_rows are at least 1")


@dataclass
class Norm:
    """The two normalisers, largest pairwise distances (or bounds of them)."""

    e: float
    s: float
    extra: dict = field(default_factory=dict)

    def remap(self, alpha: float, other: "Norm") -> float:
        """The weight with these normalisers that orders like `alpha` with the other's."""
        a, b = alpha * self.e / other.e, (1 - alpha) * self.s / other.s
        return a / (a + b) if a + b else alpha
