"""Disjoint sets: the plain structure, and one whose roots keep a lower bound on similarity."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np


class DisjointSets:
    """Union by rank and path compression."""

    def __init__(self) -> None:
        self.parent: dict[int, int] = {}
        self.rank: dict[int, int] = {}

    def find(self, x: int) -> int:
        self.parent.setdefault(x, x)
        root = x
        while self.parent[root] != root:
            root = self.parent[root]
        while self.parent[x] != root:
            self.parent[x], x = root, self.parent[x]
        return root

    def join(self, x: int, y: int) -> int:
        """Joins two roots, the lower rank under the higher; gives the root that stays."""
        rx, ry = self.rank.get(x, 0), self.rank.get(y, 0)
        top, under = (x, y) if rx >= ry else (y, x)
        self.parent[under] = top
        self.rank[top] = rx + 1 if rx == ry else max(rx, ry)
        return top

    def union(self, x: int, y: int) -> bool:
        x, y = self.find(x), self.find(y)
        if x == y:
            return False
        self.join(x, y)
        return True


class BoundedForest(DisjointSets):
    """Refuses a union whose tree might hold a pair below the tree threshold.

    A root's bound is the least similarity to it that any member can have, by the triangle inequality
    along tree edges; a single document has 1. Members of two trees are at least
    bound + bound + similarity of the roots - 2 alike.
    """

    def __init__(self, tree_threshold: float, similarity: Callable[[int, int], float]):
        super().__init__()
        self.tree_threshold, self.similarity = tree_threshold, similarity
        self.bound: dict[int, float] = {}

    def union(self, x: int, y: int) -> bool:
        x, y = self.find(x), self.find(y)
        if x == y:
            return False
        sim = self.similarity(x, y)
        bx, by = self.bound.get(x, 1.0), self.bound.get(y, 1.0)
        if bx + by + sim - 2 < self.tree_threshold - 1e-12:
            return False
        top = self.join(x, y)
        own, other = (bx, by) if top == x else (by, bx)
        self.bound[top] = min(own, other - (1 - sim))
        return True


def fold_buckets(buckets: list[list[int]], similarity: Callable[[int, int], float], edge: float, tree: float, refresh: str = "before_bucket", keep: bool = True) -> tuple[BoundedForest, list[tuple[int, int, float]]]:
    """Clusters by buckets in order: the members' roots are compared in pairs, and pairs above edge are joined.

    Gives the forest and, with keep, the pairs that were compared, each with its similarity. A similarity with many(x, ys) is asked for all later roots of a bucket at once.
    """
    forest, seen = BoundedForest(tree, similarity), []
    many = getattr(similarity, "many", None) if refresh != "each_pair" else None
    for bucket in buckets:
        roots = sorted({forest.find(d) for d in bucket})
        if many is not None:
            places = np.array(roots)
            for i, x in enumerate(roots[:-1]):
                alike = many(x, places[i + 1 :])
                if keep:
                    seen += zip([x] * len(alike), roots[i + 1 :], alike.tolist(), strict=True)
                for k in (alike > edge).nonzero()[0].tolist():
                    forest.union(x, roots[i + 1 + k])
            continue
        for i, x in enumerate(roots):
            for y in roots[i + 1 :]:
                if refresh == "each_pair" and forest.find(x) == forest.find(y):
                    continue
                s = similarity(x, y)
                if keep:
                    seen.append((x, y, s))
                if s > edge:
                    forest.union(x, y)
    return forest, seen
