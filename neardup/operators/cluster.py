"""Clusters with a guaranteed least similarity, in sequence within components or in parallel rounds."""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from neardup.functions.sets import jaccard
from neardup.operators.forest import BoundedForest, fold_buckets
from neardup.operators.graph import components
from neardup.operators.verify import Counted, scored
from neardup.session import materialize, release

MOST_MEMBERS = 20_000


def _similarity(sets: dict[int, np.ndarray]):
    """Exact Jaccard of sets of gram hashes, each pair computed once."""
    known: dict[tuple[int, int], float] = {}

    def sim(x: int, y: int) -> float:
        key = (x, y) if x < y else (y, x)
        if key not in known:
            a, b = sets[x], sets[y]
            shared = len(np.intersect1d(a, b, assume_unique=True))
            total = len(a) + len(b) - shared
            known[key] = shared / total if total else 0.0
        return known[key]

    return sim


#: Bytes of counts of shared grams that a task keeps for a component.
COUNTS_HELD = 256_000_000


class Likeness:
    """Exact Jaccard of sets by their places: what one shares with all others is counted at once, when it is first asked for.

    The counts that were used last are kept; others are counted again.
    """

    def __init__(self, sets: list[np.ndarray]):
        self.sets, self.counted = sets, Counted(sets)
        self.kind = np.uint16 if max(map(len, sets), default=0) < 1 << 16 else np.int64
        self.most = max(1, COUNTS_HELD // max(1, len(sets) * np.dtype(self.kind).itemsize))
        self.rows: dict[int, np.ndarray] = {}

    def many(self, x: int, ys: np.ndarray) -> np.ndarray:
        row = self.rows.pop(x, None)
        if row is None:
            row = self.counted.shared(self.sets[x]).astype(self.kind)
            if len(self.rows) >= self.most:
                del self.rows[next(iter(self.rows))]
        self.rows[x] = row
        shared = row[ys].astype(np.int64)
        return shared / np.maximum(1, self.counted.sizes[ys] + len(self.sets[x]) - shared)

    def __call__(self, x: int, y: int) -> float:
        return float(self.many(min(x, y), np.array([max(x, y)]))[0])


def bounded_clusters(bands: DataFrame, grams: DataFrame, edge: float = 0.75, tree: float = 0.40, refresh: str = "before_bucket", edges_only: bool = True, most_members: int = MOST_MEMBERS, scores: DataFrame | None = None) -> DataFrame:
    """Rows (kind, a, b, value): 'member' doc, root, root's bound; 'compared' pair and its similarity.

    Each component is folded by itself in the order band, value, document. With edges_only True the components are those of
    candidate pairs above the edge threshold. A sequential run over all documents also compares roots that share no bucket;
    where such a pair is the only link of two components, and above the threshold, that run joins them and this one doesn't: with
    bands that find nearly all pairs above the threshold the two agree. With edges_only False the components are those of
    shared buckets, and unions and compared pairs are exactly those of the sequential run.

    A component of more than most_members documents is too large for one task: it is clustered by rounds(), which keeps the
    same guarantee in another order; its compared pairs are its edges.
    """
    return bounded_sweep(bands, grams, [edge], tree, refresh, edges_only, most_members, scores).drop("edge")


def bounded_sweep(bands: DataFrame, grams: DataFrame, edges: Sequence[float], tree: float = 0.40, refresh: str = "before_bucket", edges_only: bool = False, most_members: int = MOST_MEMBERS, scores: DataFrame | None = None, compared: bool = True) -> DataFrame:
    """Rows (edge, kind, a, b, value): what bounded_clusters() gives for each edge threshold, over one search of the components.

    Components of shared buckets are the same for all thresholds, and each set is fetched and each similarity computed once for all; with
    edges_only they are those above the lowest threshold; scores (a, b, jaccard) of all candidate pairs are used for that where they are known. Without compared the compared pairs are not kept: only 'member' rows come out.
    """
    edges = sorted(edges)
    buckets = bands.groupBy("band_id", "value").agg(F.count("*").alias("size")).where("size > 1").select("band_id", "value")
    rows = materialize(bands.join(buckets, ["band_id", "value"]), "buckets")
    left, right = rows.select("band_id", "value", F.col("doc_id").alias("a")), rows.select("band_id", "value", F.col("doc_id").alias("b"))
    if edges_only:
        pairs = left.join(right, ["band_id", "value"]).where("a < b").select("a", "b").distinct()
        links = (scored(pairs, grams) if scores is None else scores).where(F.col("jaccard") > edges[0])
    else:
        links = rows.join(rows.groupBy("band_id", "value").agg(F.min("doc_id").alias("a")), ["band_id", "value"]).select("a", F.col("doc_id").alias("b"))
    comps = components(links)
    large = materialize(comps.groupBy("component").agg(F.count("*").alias("n")).where(F.col("n") > most_members).select("component"), "large")
    beyond = None
    if not large.isEmpty():
        beyond = materialize(comps.join(large, "component", "left_semi"), "large-members")
        comps = materialize(comps.join(large, "component", "left_anti"), "small-members")
    members = rows.join(comps, rows.doc_id == comps.id).select("component", "band_id", F.col("value").cast("string").alias("value"), "doc_id")
    sets = grams.join(comps, grams.doc_id == comps.id).select(F.col("component").alias("part"), "doc_id", "grams")

    def fold(one: pd.DataFrame, two: pd.DataFrame) -> pd.DataFrame:
        two = two.sort_values("doc_id")
        ids = two.doc_id.to_numpy()
        sim = Likeness([np.unique(g) for g in two.grams])
        one = one.sort_values(["band_id", "value", "doc_id"])
        # Documents go by their places in order of doc_id, which keeps all orders.
        lists = [np.searchsorted(ids, g.doc_id.to_numpy()).tolist() for _, g in one.groupby(["band_id", "value"], sort=False)]
        lists, out, names = [x for x in lists if len(x) > 1], [], ids.tolist()
        for edge in edges:
            forest, seen = fold_buckets(lists, sim, edge, tree, refresh, compared)
            out += [(edge, "member", d, names[forest.find(k)], forest.bound.get(forest.find(k), 1.0)) for k, d in enumerate(names)]
            out += [(edge, "compared", names[x], names[y], s) for x, y, s in seen]
        return pd.DataFrame(out, columns=["edge", "kind", "a", "b", "value"])

    done = members.groupBy("component").cogroup(sets.groupBy("part")).applyInPandas(fold, "edge double, kind string, a bigint, b bigint, value double")
    if beyond is not None:
        for edge in edges:
            late = _by_rounds(rows, grams, beyond, edge, tree)
            done = done.unionByName((late if compared else late.where("kind = 'member'")).withColumn("edge", F.lit(edge)))
    return materialize(done, "bounded")


def _by_rounds(rows: DataFrame, grams: DataFrame, members: DataFrame, edge: float, tree: float) -> DataFrame:
    """What bounded_clusters() gives, for the members of components that no task can hold."""
    own = rows.join(members.select(F.col("id").alias("doc_id")), "doc_id", "left_semi")
    x, y = own.select("band_id", "value", F.col("doc_id").alias("a")), own.select("band_id", "value", F.col("doc_id").alias("b"))
    edges = materialize(scored(x.join(y, ["band_id", "value"]).where("a < b").select("a", "b").distinct(), grams).where(F.col("jaccard") > edge), "edges")
    found = rounds(edges, grams, edge, tree)
    rest = members.select(F.col("id").alias("doc_id")).join(found, "doc_id", "left_anti").select("doc_id", F.col("doc_id").alias("root"), F.lit(1.0).alias("bound"))
    named = found.select("doc_id", "root", "bound").unionByName(rest).select(F.lit("member").alias("kind"), F.col("doc_id").alias("a"), F.col("root").alias("b"), F.col("bound").alias("value"))
    return named.unionByName(edges.select(F.lit("compared").alias("kind"), "a", "b", F.col("jaccard").alias("value")))


def assignments(folded: DataFrame, docs: DataFrame) -> DataFrame:
    """(doc_id, cluster_id, bound): documents in no bucket are their own cluster; cluster_id is the lowest member."""
    found = folded.where("kind = 'member'").select(F.col("a").alias("doc_id"), F.col("b").alias("root"), F.col("value").alias("bound"))
    names = found.groupBy("root").agg(F.min("doc_id").alias("cluster_id"))
    named = found.join(names, "root").select("doc_id", "cluster_id", "root", "bound")
    rest = docs.select("doc_id").join(named, "doc_id", "left_anti").select("doc_id", F.col("doc_id").alias("cluster_id"), F.col("doc_id").alias("root"), F.lit(1.0).alias("bound"))
    return named.unionByName(rest)


def fold_edges(edges: DataFrame, grams: DataFrame, edge: float, tree: float, order: str = "similarity_desc", seed: int = 42) -> DataFrame:
    """(doc_id, root, bound) of documents with an edge: edges (a, b, jaccard) one by one, strongest first or in a seeded order.

    Strongest first is the spanning-tree variant: a maximum similarity tree grown under the bound.
    """
    links = edges.where(F.col("jaccard") > edge)
    comps = components(links)
    rank = {"similarity_desc": -F.col("jaccard"), "pair": F.lit(0.0), "shuffle": F.xxhash64(F.lit(seed), "a", "b").cast("double")}[order]
    one = links.join(comps, links.a == comps.id).select("component", "a", "b", rank.alias("rank"))
    two = grams.join(comps, grams.doc_id == comps.id).select(F.col("component").alias("part"), "doc_id", "grams")

    def fold(x: pd.DataFrame, y: pd.DataFrame) -> pd.DataFrame:
        forest = BoundedForest(tree, _similarity({d: np.unique(g) for d, g in zip(y.doc_id, y.grams, strict=True)}))
        for a, b in x.sort_values(["rank", "a", "b"])[["a", "b"]].itertuples(index=False):
            forest.union(int(a), int(b))
        return pd.DataFrame([(int(d), forest.find(int(d)), forest.bound.get(forest.find(int(d)), 1.0)) for d in y.doc_id], columns=["doc_id", "root", "bound"])

    return materialize(one.groupBy("component").cogroup(two.groupBy("part")).applyInPandas(fold, "doc_id bigint, root bigint, bound double"), "folded")


def rounds(edges: DataFrame, grams: DataFrame, edge: float = 0.75, tree: float = 0.40, most: int = 12, seed: int = 42) -> DataFrame:
    """(doc_id, root, bound) by parallel unions under the same guarantee; no component meets in one task.

    In each round roots are hubs or spokes by a hash of the round; a spoke offers itself to its most similar hub
    among those that are above the edge threshold and that it can join under the bound. Where the hash parts no such pair, the hubs are the roots that are lower
    than all that they can join, so every round makes a union. Rounds end when no two roots of an edge can be joined.
    Offers are taken in falling order of the bound that they bring to the hub, as long as the two
    lowest bounds there still allow the tree threshold; once one fails all later ones do, so a window decides.
    """
    links = edges.where(F.col("jaccard") > edge).select("a", "b")
    nodes = links.select(F.col("a").alias("doc_id")).unionByName(links.select(F.col("b").alias("doc_id"))).distinct()
    state = materialize(nodes.select("doc_id", F.col("doc_id").alias("root"), F.lit(1.0).alias("bound")), "rounds")
    for k in range(most * 4):
        hub = lambda c: F.pmod(F.xxhash64(F.lit(seed + k), c), F.lit(2)) == 0  # noqa: B023, E731
        ra, rb = state.select(F.col("doc_id").alias("a"), F.col("root").alias("x")), state.select(F.col("doc_id").alias("b"), F.col("root").alias("y"))
        roots = links.join(ra, "a").join(rb, "b").where("x <> y").select(F.least("x", "y").alias("x"), F.greatest("x", "y").alias("y")).distinct()
        gx, gy = grams.select(F.col("doc_id").alias("x"), F.col("grams").alias("gx")), grams.select(F.col("doc_id").alias("y"), F.col("grams").alias("gy"))
        sims = roots.join(gx, "x").join(gy, "y").select("x", "y", jaccard(F.col("gx"), F.col("gy")).alias("s"))
        bounds = state.select("root", "bound").distinct()
        known = sims.join(bounds.select(F.col("root").alias("x"), F.col("bound").alias("bx")), "x").join(bounds.select(F.col("root").alias("y"), F.col("bound").alias("by")), "y")
        # Whether two trees can be joined doesn't depend on which of the roots is the hub.
        open_ = materialize(known.where((F.col("s") > edge) & (F.col("bx") + F.col("by") + F.col("s") - 2 >= tree - 1e-12)), "joinable")
        if open_.isEmpty():
            release(open_)
            return state
        both = open_.select("x", "y", "s", F.col("bx").alias("own"), F.col("by").alias("theirs"))
        both = both.unionByName(open_.select(F.col("y").alias("x"), F.col("x").alias("y"), "s", F.col("by").alias("own"), F.col("bx").alias("theirs")))
        offers = both.where(hub(F.col("x")) & ~hub(F.col("y")))
        if offers.isEmpty():
            offers = both.join(open_.select(F.col("y").alias("x")).distinct(), "x", "left_anti")
        best = offers.groupBy("y").agg(F.max_by(F.struct("x", "s", "own", "theirs"), F.struct("s", -F.col("x"))).alias("o")).select("y", "o.*")
        offer = best.withColumn("g", F.col("theirs") - (1 - F.col("s")))
        order = Window.partitionBy("x").orderBy(F.desc("g"), "y")
        fits = F.col("g") + F.least("own", F.coalesce(F.lag("g").over(order), F.lit(1.0))) - 1 >= tree - 1e-12
        taken = materialize(offer.withColumn("fits", fits).where("fits").select("x", "y", "own", "g"), "taken")
        moved = taken.select(F.col("y").alias("root"), F.col("x").alias("to"))
        lower = taken.groupBy("x").agg(F.least(F.min("own"), F.min("g")).alias("low")).withColumnRenamed("x", "root")
        old, state = state, state.join(moved, "root", "left").select("doc_id", F.coalesce("to", "root").alias("root"), "bound")
        roots_now = bounds.join(moved, "root", "left_anti").join(lower, "root", "left").select("root", F.coalesce("low", "bound").alias("bound"))
        before, state = old, materialize(state.drop("bound").join(roots_now, "root").select("doc_id", "root", "bound"), "rounds")
        release(before, taken, open_)
    raise RuntimeError(f"roots can still be joined after {most * 4} rounds")


def second_round(clusters: DataFrame, edges: DataFrame, edge: float, policy: str = "average", least: float | None = None) -> DataFrame:
    """(doc_id, cluster_id) after merging clusters: by the average of the cross edges ('average'), or if all cross pairs are edges above least ('bounded').

    Only 'bounded' keeps a guarantee: every pair across merged clusters is at least as alike as least.
    """
    ca, cb = clusters.select(F.col("doc_id").alias("a"), F.col("cluster_id").alias("x")), clusters.select(F.col("doc_id").alias("b"), F.col("cluster_id").alias("y"))
    cross = edges.join(ca, "a").join(cb, "b").where("x <> y").select(F.least("x", "y").alias("x"), F.greatest("x", "y").alias("y"), "jaccard")
    sizes = clusters.groupBy("cluster_id").agg(F.count("*").alias("n"))
    links = cross.groupBy("x", "y").agg(F.avg("jaccard").alias("mean"), F.min("jaccard").alias("low"), F.count("*").alias("pairs"))
    if policy == "average":
        merge = links.where(F.col("mean") > edge).select(F.col("x").alias("a"), F.col("y").alias("b"))
    else:
        nx, ny = sizes.select(F.col("cluster_id").alias("x"), F.col("n").alias("nx")), sizes.select(F.col("cluster_id").alias("y"), F.col("n").alias("ny"))
        full = links.join(nx, "x").join(ny, "y").where((F.col("pairs") == F.col("nx") * F.col("ny")) & (F.col("low") >= (edge if least is None else least)))
        # Each cluster merges with one other at most: the lowest of those that offer, where the choice is mutual.
        pick = full.groupBy("x").agg(F.min("y").alias("y"))
        merge = pick.groupBy("y").agg(F.min("x").alias("x")).select(F.col("x").alias("a"), F.col("y").alias("b"))
        merge = merge.join(merge.select(F.col("b").alias("a")), "a", "left_anti")
    names = components(merge).select(F.col("id").alias("cluster_id"), F.col("component").alias("to"))
    return clusters.select("doc_id", "cluster_id").join(names, "cluster_id", "left").select("doc_id", F.coalesce("to", "cluster_id").alias("cluster_id"))


def cross_edges(edges: DataFrame, clusters: DataFrame) -> DataFrame:
    """(a, b, jaccard, x, y): the edges between clusters x and y."""
    ca, cb = clusters.select(F.col("doc_id").alias("a"), F.col("cluster_id").alias("x")), clusters.select(F.col("doc_id").alias("b"), F.col("cluster_id").alias("y"))
    return edges.join(ca, "a").join(cb, "b").where("x <> y").select("a", "b", "jaccard", "x", "y")
