"""Parameters of the method, with the published values as defaults but for these, which PUBLISHED has as printed.

The entity threshold is 0 with the best 12 of a chunk kept, not 0.5 (on chunks of 256 words the printed score almost never reaches that); terms
in more than a fifth of the chunks or in a single one are no entities; a frozen growth threshold is the mean over the tree's edges between
entities, not the sum over all its edges.
"""

from __future__ import annotations

from dataclasses import dataclass, field


@dataclass(frozen=True)
class ChunkSpec:
    length: int = 256
    overlap: int = 32
    unit: str = "word"  # word, char, sentence


@dataclass(frozen=True)
class EntitySpec:
    max_n: int = 3
    tau: float = 0.0
    mode: str = "literal"  # literal, chunk_max, chunk_rank
    min_df: int = 2
    cap: int | None = 12
    max_df: float = 0.2


@dataclass(frozen=True)
class MapSpec:
    k_facts: int = 5
    floor: float = 0.25


@dataclass(frozen=True)
class InfluenceSpec:
    damping: float = 0.5
    tol: float = 1e-7
    balance: float = 0.05
    flow: str = "push"  # push, pull
    off_edge: str = "none"  # none, uniform
    seed_norm: str = "sum"  # sum, none


@dataclass(frozen=True)
class TreeSpec:
    method: str = "voronoi"  # voronoi, closure, chain, none
    pseudo: float = 10.0


@dataclass(frozen=True)
class GrowSpec:
    threshold: str = "frozen"  # frozen, sum, mean, pooled
    pick: str = "edge"  # edge, node, node_all
    recompute: str = "after"  # after, before
    max_steps: int | None = None
    counted: str = "entities"  # tree edges that set a frozen threshold: entities (without a passage), all
    base: str = "mean"  # how a frozen threshold is taken from the tree: mean, sum, pooled


@dataclass(frozen=True)
class FuseSpec:
    k: int = 5
    weight: float = 0.5
    bm25_scale: str = "raw"  # raw, query_max, minmax
    k1: float = 1.2
    b: float = 0.75


@dataclass(frozen=True)
class Config:
    chunk: ChunkSpec = field(default_factory=ChunkSpec)
    entity: EntitySpec = field(default_factory=EntitySpec)
    map: MapSpec = field(default_factory=MapSpec)
    influence: InfluenceSpec = field(default_factory=InfluenceSpec)
    tree: TreeSpec = field(default_factory=TreeSpec)
    grow: GrowSpec = field(default_factory=GrowSpec)
    fuse: FuseSpec = field(default_factory=FuseSpec)
    phi: float = 0.8
    dim: int = 64
    head_words: int = 32  # words of a passage in the text of its facts


PUBLISHED = Config(entity=EntitySpec(tau=0.5, min_df=1, cap=None, max_df=1.0), influence=InfluenceSpec(off_edge="uniform", seed_norm="none"), grow=GrowSpec(base="sum", counted="all"))
