"""Communities by greedy modularity: the method that bounded clusters are compared with."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from neardup.operators.graph import components
from neardup.session import materialize


def local_moves(weights: dict[int, dict[int, float]], loops: dict[int, float], total: float) -> dict[int, int]:
    """Moves nodes in order of id to the neighbouring community with the largest gain, until none moves."""
    home = {v: v for v in weights}
    degree = {v: sum(n.values()) + 2 * loops.get(v, 0.0) for v, n in weights.items()}
    mass = dict(degree)
    moved = True
    while moved:
        moved = False
        for v in sorted(weights):
            near: dict[int, float] = {}
            for u, w in weights[v].items():
                near[home[u]] = near.get(home[u], 0.0) + w
            own = home[v]
            mass[own] -= degree[v]
            gain = lambda c: near.get(c, 0.0) - mass[c] * degree[v] / total  # noqa: B023, E731
            best = max(sorted(set(near) | {own}), key=lambda c: (round(gain(c), 12), c == own, -c))
            mass[best] += degree[v]
            if best != own:
                home[v], moved = best, True
    return home


def louvain_of(edges: list[tuple[int, int, float]], total: float) -> dict[int, int]:
    """Community of each node: local moves, then communities become nodes, until nothing changes; names are lowest members."""
    weights: dict[int, dict[int, float]] = {}
    for a, b, w in edges:
        weights.setdefault(a, {})[b] = weights.setdefault(a, {}).get(b, 0.0) + w
        weights.setdefault(b, {})[a] = weights.setdefault(b, {}).get(a, 0.0) + w
    member, loops = {v: v for v in weights}, {}
    while weights:
        home = local_moves(weights, loops, total)
        low: dict[int, int] = {}
        for v, c in home.items():
            low[c] = min(low.get(c, v), v)
        home = {v: low[c] for v, c in home.items()}
        if len(set(home.values())) == len(weights):
            break
        merged: dict[int, dict[int, float]] = {c: {} for c in set(home.values())}
        inside: dict[int, float] = {}
        for v, n in weights.items():
            inside[home[v]] = inside.get(home[v], 0.0) + loops.get(v, 0.0)
            for u, w in n.items():
                if home[u] == home[v]:
                    inside[home[v]] = inside.get(home[v], 0.0) + w / 2
                else:
                    merged[home[v]][home[u]] = merged[home[v]].get(home[u], 0.0) + w
        member = {v: home[c] for v, c in member.items()}
        weights, loops = merged, inside
    return member


def louvain(edges: DataFrame) -> DataFrame:
    """(doc_id, cluster_id) of the nodes of weighted edges (a, b, jaccard).

    Components of the graph meet only in the total weight, which each task is given; each is worked on by itself.
    """
    total = 2 * (edges.agg(F.sum("jaccard").alias("w")).first().w or 0.0)
    comps = components(edges)
    rows = edges.join(comps, edges.a == comps.id).select("component", "a", "b", "jaccard")

    def one(p: pd.DataFrame) -> pd.DataFrame:
        p = p.sort_values(["a", "b"])
        found = louvain_of(list(p[["a", "b", "jaccard"]].itertuples(index=False, name=None)), total)
        return pd.DataFrame(sorted(found.items()), columns=["doc_id", "cluster_id"])

    return materialize(rows.groupBy("component").applyInPandas(one, "doc_id bigint, cluster_id bigint"), "communities")
