"""Parameters of a run."""

from __future__ import annotations

from dataclasses import dataclass, replace

FAMILIES = ("xx64", "mm32", "portable")


@dataclass(frozen=True)
class DedupConfig:
    """All parameters, checked when made; b * r is the length of a signature."""

    shingle: str = "word"
    n: int = 8
    stem: str = "none"
    short_doc: str = "whole"
    family: str = "xx64"
    seed: int = 42
    b: int = 50
    r: int = 2
    compress_bands: bool = True
    threshold: float = 0.75
    layout: str = "memory"
    slices: int = 10
    edge_threshold: float = 0.75
    tree_threshold: float = 0.40
    order: str = "band_value_doc"
    refresh: str = "before_bucket"
    mode: str = "sequential"

    def __post_init__(self) -> None:
        for value, allowed in ((self.shingle, ("word", "char")), (self.stem, ("none", "light", "porter")), (self.short_doc, ("whole", "drop", "pad")), (self.family, FAMILIES), (self.layout, ("memory", "cells", "packed")), (self.refresh, ("before_bucket", "each_pair")), (self.mode, ("sequential", "rounds"))):
            if value not in allowed:
                raise ValueError(f"{value!r} is none of {allowed}")
        if self.n < 1 or self.b < 1 or self.r < 1 or self.slices < 1:
            raise ValueError("n, b, r and slices start at 1")
        if not 0 <= self.threshold <= 1 or not 0 <= self.tree_threshold <= self.edge_threshold <= 1:
            raise ValueError("thresholds lie in 0..1, the tree's not above the edge's")

    @property
    def m(self) -> int:
        return self.b * self.r

    def but(self, **changes) -> DedupConfig:
        return replace(self, **changes)


def bands_for(m: int, r: int) -> int:
    """Number of bands of r rows in a signature of m values."""
    if m % r:
        raise ValueError(f"{m} values don't make bands of {r} rows")
    return m // r
