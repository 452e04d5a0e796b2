"""Queries for the methods, baselines, measures and experiments, over whole tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from neardup.config import DedupConfig
from neardup.functions import hashing, sets, text
from neardup.io import table
from neardup.io import spread_documents as documents
from neardup.operators import banding, baseline, candidates, clean, cluster, community, costmodel, exact, metrics, signature, store, synth, tuning, verify
from neardup.plans import pipeline, rules
from neardup.session import materialize, release_shuffles, scratch_path

CFG = DedupConfig()
PORTABLE = DedupConfig(family="portable", b=20, r=2)
#: Clusters with the portable family, so that SQL can follow them from the texts on.
CLUSTERS = CFG.but(family="portable")
SWEEP = (0.60, 0.65, 0.70, 0.75, 0.80, 0.85, 0.90, 0.95)


def _grams(spark: SparkSession, d: str, cfg: DedupConfig = CFG, hashed: bool = False) -> DataFrame:
    return text.grams_of(documents(spark, d), cfg, hashed=hashed)


def _sets(spark: SparkSession, d: str, cfg: DedupConfig = CFG) -> DataFrame:
    return text.gram_sets(documents(spark, d), cfg)


def _exploded(spark: SparkSession, d: str, cfg: DedupConfig = CFG) -> DataFrame:
    return text.exploded(_grams(spark, d, cfg))


# --- words, shingles, sets ---------------------------------------------------------------------------


def tokens_count(spark, d):
    return documents(spark, d).select("doc_id", F.size(text.words("text")).cast("bigint").alias("n_words"))


def word_ngrams(spark, d):
    return _grams(spark, d).select("doc_id", F.size("grams").cast("bigint").alias("n_grams"), F.md5(F.array_join(F.array_sort("grams"), "\n")).alias("grams_md5"))


def char_shingles(spark, d):
    rows = documents(spark, d).select("doc_id", text.char_shingles("text", 4).alias("g"))
    return rows.select("doc_id", F.size("g").cast("bigint").alias("n_shingles"), F.md5(F.array_join(F.array_sort("g"), "\n")).alias("shingles_md5"))


def gram_multiplicity(spark, d):
    return text.gram_multiplicity(documents(spark, d))


def short_documents(spark, d):
    """Documents of fewer than 8 words, and how many grams each rule for them gives."""
    ws = documents(spark, d).select("doc_id", text.words("text").alias("ws")).where(F.size("ws") < 8)
    return ws.select("doc_id", F.size("ws").cast("bigint").alias("n_words"), *[F.size(text.word_ngrams(F.col("ws"), 8, p)).cast("bigint").alias(f"grams_{p}") for p in ("whole", "drop", "pad")])


def stem_light_ngrams(spark, d):
    g = _grams(spark, d, CFG.but(stem="light", n=3))
    return g.select("doc_id", F.size("grams").cast("bigint").alias("n_grams"), F.md5(F.array_join(F.array_sort("grams"), "\n")).alias("grams_md5"))


def stem_porter(spark, d):
    g = _grams(spark, d, CFG.but(stem="porter"))
    return g.select("doc_id", F.size("grams").cast("bigint").alias("n_grams"))


def ngram_length(spark, d):
    """Pairs above 0.75 for each length of grams, all exact: long ones miss, short ones match too much."""
    out = None
    for n in (1, 2, 3, 5, 8, 12):
        one = verify.similar_pairs(_sets(spark, d, CFG.but(n=n)), 0.75).agg(F.count("*").alias("pairs")).select(F.lit(n).alias("n"), "pairs")
        out = one if out is None else out.unionByName(one)
    return out


def gram_dictionary(spark, d):
    x = hashing.gram_dictionary(_exploded(spark, d))
    return x.agg(F.count("*").alias("grams"), F.min("gram_id").alias("low"), F.max("gram_id").alias("high"), F.countDistinct("gram_id").alias("ids"))


def hash_collisions(spark, d):
    """Distinct grams, and how many numbers they have in 64, 60, 32 and 20 bits: what too small a range loses."""
    grams = _exploded(spark, d).select("gram", hashing.md5_number("gram").alias("x"))
    counts = [F.countDistinct(F.xxhash64("gram")).alias("ids64"), F.countDistinct("x").alias("ids60"), *(F.countDistinct(F.col("x") % F.lit(1 << k)).alias(f"ids{k}") for k in (32, 20))]
    return grams.agg(F.countDistinct("gram").alias("grams"), *counts)


# --- exact baselines ----------------------------------------------------------------------------------


def exact_pairs_all(spark, d):
    """The all-pairs baseline over the whole table; its work is quadratic."""
    return verify.all_pairs(_sets(spark, d), 0.2)


def exact_pairs_shared(spark, d):
    return verify.similar_pairs(_sets(spark, d), 0.2)


def exact_pairs_prefix(spark, d):
    """The same pairs, of documents alone whose shared grams are enough of their sets."""
    return verify.similar_pairs(_sets(spark, d), 0.2)


def jaccard_distance(spark, d):
    return verify.shared_gram_pairs(_sets(spark, d)).select("a", "b", (1 - F.col("jaccard")).alias("distance"))


def exact_clusters_text(spark, d):
    return exact.exact_clusters(table(spark, d, "documents"), "text")


def exact_clusters_grams(spark, d):
    return exact.exact_clusters(table(spark, d, "documents"), "grams")


# --- signatures, bands, candidates ---------------------------------------------------------------------


def signature_portable(spark, d):
    sig = signature.signatures(documents(spark, d), PORTABLE)
    return signature.slots(sig).select("doc_id", F.col("slot").cast("bigint").alias("slot"), "h")


def _estimates(spark, d, m: int = 100):
    cfg = PORTABLE.but(b=m, r=1)
    sig = materialize(signature.signatures(documents(spark, d), cfg), "signatures")
    pairs = verify.similar_pairs(_sets(spark, d), 0.2)
    x, y = sig.select(F.col("doc_id").alias("a"), F.col("sig").alias("x")), sig.select(F.col("doc_id").alias("b"), F.col("sig").alias("y"))
    return pairs.join(x, "a").join(y, "b").select("a", "b", "jaccard", signature.estimate(F.col("x"), F.col("y")).alias("estimate"))


def signature_estimate(spark, d):
    return _estimates(spark, d, 40)


def estimate_error(spark, d):
    return metrics.estimate_error(_estimates(spark, d, 40))


def minhash_permutation(spark, d):
    return signature.minhash_permutation(documents(spark, d), 3)


def bands_portable(spark, d):
    return banding.bands(documents(spark, d), PORTABLE).select("doc_id", F.col("band_id").cast("bigint").alias("band_id"), "value")


def bands_uncompressed(spark, d):
    """Candidate pairs by whole runs of slots: compression to 64 bits loses none."""
    return candidates.banded(materialize(banding.bands(documents(spark, d), PORTABLE.but(compress_bands=False)), "bands"))


def _bands(spark, d, cfg=PORTABLE):
    return materialize(banding.bands(documents(spark, d), cfg), "bands")


def candidates_banded(spark, d):
    return candidates.banded(_bands(spark, d))


def candidates_by_band(spark, d):
    return candidates.by_band(_bands(spark, d), list(range(PORTABLE.b)))


def _slots(spark, d):
    return materialize(signature.slots(signature.signatures(documents(spark, d), PORTABLE.but(b=20, r=1))), "slots")


def candidates_inverted(spark, d):
    return candidates.inverted_lists(_slots(spark, d))


def candidates_sorted(spark, d):
    return candidates.sorted_runs(_slots(spark, d))


def cells_layout(spark, d):
    path = scratch_path(spark, "cells")
    store.write_cells(banding.bands(documents(spark, d), PORTABLE), path)
    return store.read_cells(spark, path).select(F.col("band_id").cast("bigint").alias("band_id"), "doc_id", "value")


def packed_layout(spark, d):
    path = scratch_path(spark, "packed")
    store.write_packed(_bands(spark, d), store.slice_ids(documents(spark, d), 10), path)
    return store.read_packed(spark, path).select(F.col("band_id").cast("bigint").alias("band_id"), "doc_id", "value")


def store_read_one_band(spark, d):
    """Candidates of one band, of whose folder alone is read."""
    path = scratch_path(spark, "cells")
    store.write_cells(banding.bands(documents(spark, d), PORTABLE), path)
    return candidates.banded(store.read_cells(spark, path, 3))


def store_operations(spark, d):
    """Rows written in either layout, against the counts of the cost model."""
    bands = _bands(spark, d)
    slices = store.slice_ids(documents(spark, d), 10, ranked=True)
    packed, _ = store.pack(bands, slices)
    n = bands.select("doc_id").distinct().count()
    return bands.agg(F.count("*").alias("cells")).crossJoin(packed.agg(F.count("*").alias("packed"))).withColumn("model_cells", F.lit(n * PORTABLE.b).cast("bigint")).withColumn("model_packed", F.lit(10 * PORTABLE.b).cast("bigint"))


def near_duplicates_075(spark, d):
    return pipeline.near_duplicates(documents(spark, d), CFG)


def near_duplicates_cells(spark, d):
    return pipeline.near_duplicates(documents(spark, d), CFG.but(layout="cells"))


def near_duplicates_packed(spark, d):
    return pipeline.near_duplicates(documents(spark, d), CFG.but(layout="packed"))


def near_duplicates_mm32(spark, d):
    return pipeline.near_duplicates(documents(spark, d), CFG.but(family="mm32"))


def near_duplicates_rewritten(spark, d):
    """The same pairs after all rewrites: copies collapsed, sizes tested in the join, hashes compared."""
    return rules.execute(rules.optimise(rules.DedupPlan(CFG)), documents(spark, d))


def sql_pairs(spark, d):
    pipeline.near_duplicates(documents(spark, d), CFG).createOrReplaceTempView("near_pairs")
    documents(spark, d).createOrReplaceTempView("near_docs")
    return spark.sql("SELECT p.a, p.b, x.lang AS lang_a, y.lang AS lang_b FROM near_pairs p JOIN near_docs x ON x.doc_id = p.a JOIN near_docs y ON y.doc_id = p.b WHERE p.jaccard > 0.75")


# --- the curve, the grid -------------------------------------------------------------------------------

GRID = [(10, 1), (10, 2), (20, 2), (50, 2), (100, 1), (20, 3), (25, 4), (20, 5)]
TRUTH = [0.2, 0.3, 0.4]


def lsh_curve(spark, d):
    """The curve at the similarities, in 20ths, of the two halves of documents, and how many documents have each."""
    h = documents(spark, d).select(text.halves("text").alias("h")).where(F.size("h.x") > 0)
    seen = h.select((F.floor(sets.jaccard(F.col("h.x"), F.col("h.y")) * 20 + 0.5) / 20).alias("s")).groupBy("s").agg(F.count("*").alias("documents"))
    rows = seen.crossJoin(F.broadcast(spark.createDataFrame(GRID, "b int, r int")))  # eight settings
    agree = F.pow("s", F.col("r"))
    return rows.select("s", "b", "r", "documents", F.round(agree, 9).alias("band_agrees"), F.round(1 - agree, 9).alias("band_differs"), F.round(F.pow(1 - agree, F.col("b")), 9).alias("all_differ"), F.round(sets.candidate_probability(F.col("s"), F.col("b"), F.col("r")), 9).alias("candidate"))


def _scored(spark, d):
    return verify.shared_gram_pairs(_sets(spark, d)).select("a", "b", "jaccard")


def _similarities(spark, d):
    """How many of the scored pairs have each similarity."""
    return verify.shared_gram_pairs(_sets(spark, d), counted=True).select("jaccard", "n")


def _similar(spark, d, least):
    return verify.similar_pairs(_sets(spark, d), least).select("a", "b", "jaccard")


def expected_candidates(spark, d):
    return tuning.expected(_similarities(spark, d), GRID, TRUTH)


def choose_bands(spark, d):
    """By the curve: at most 0.05 expected misses."""
    return tuning.choose_bands(tuning.expected(_similarities(spark, d), GRID, TRUTH), 0.05)


def accuracy_grid(spark, d):
    """False candidates and misses, measured, for growing numbers of bands of two rows."""
    truth = materialize(_similar(spark, d, 0.2), "truth")
    return tuning.measured(_bands(spark, d), [5, 10, 15, 20], 2, truth, TRUTH)


def recall_grid(spark, d):
    truth = _similar(spark, d, 0.4)
    return metrics.recall(candidates.banded(_bands(spark, d)), truth).select("true_pairs", "found_pairs", F.round("recall", 6).alias("recall"))


def false_candidates(spark, d):
    return metrics.false_candidates(candidates.banded(_bands(spark, d)), _similar(spark, d, 0.4))


def false_negatives(spark, d):
    return metrics.false_negatives(candidates.banded(_bands(spark, d)), _similar(spark, d, 0.2)).select("a", "b", "jaccard")


def candidate_ratio(spark, d):
    return metrics.candidate_ratio(candidates.banded(_bands(spark, d)), documents(spark, d).count())


def trend_violations(spark, d):
    """Candidates that fewer bands find and more bands miss, and settings whose expected counts move the wrong way: none."""
    bands = _bands(spark, d)
    lost = tuning.nested(bands, 10, 20).select(F.lit(1).alias("x"))
    e = tuning.expected(_similarities(spark, d), [(b, r) for b in (10, 20, 50) for r in (1, 2, 3)], [0.2])
    more_b = e.alias("p").join(e.alias("q"), (F.col("p.r") == F.col("q.r")) & (F.col("p.b") < F.col("q.b")) & (F.col("p.candidates") > F.col("q.candidates"))).select(F.lit(1).alias("x"))
    more_r = e.alias("p").join(e.alias("q"), (F.col("p.b") == F.col("q.b")) & (F.col("p.r") < F.col("q.r")) & (F.col("p.candidates") < F.col("q.candidates"))).select(F.lit(1).alias("x"))
    return lost.unionByName(more_b).unionByName(more_r).agg(F.count("*").alias("violations"))


def synthetic_accuracy(spark, d):
    """The accuracy experiment: copies with a tenth of the words changed, all found with 50 bands of two rows."""
    made = materialize(synth.inject(documents(spark, d), 50, 0.10, 0.10), "injected")
    truth = materialize(verify.similar_pairs(text.gram_sets(made, CFG), 0.2).select("a", "b", "jaccard"), "truth")
    bands = materialize(banding.bands(made, CFG), "bands")
    return tuning.measured(bands, [10, 20, 30, 40, 50], 2, truth, TRUTH)


def _accuracy(spark, d, cfg, bs):
    """Bands of one to five rows against true pairs, with ten copies that have a tenth of the words changed; what one step shuffled is deleted before the next one."""
    made = synth.inject(documents(spark, d), 10, 0.10, 0.10)
    truth = materialize(verify.similar_pairs(text.gram_sets(made, CFG), 0.2).select("a", "b", "jaccard"), "truth")
    release_shuffles(spark)
    sig, out = materialize(signature.signatures(made, cfg), "signatures"), None
    for r in (1, 2, 3, 4, 5):
        one = materialize(tuning.measured(banding.band_values(sig, r, cfg.family, True, cfg.b), bs, r, truth, TRUTH), "measured")
        out = one if out is None else out.unionByName(one)
        release_shuffles(spark)
    return out


def accuracy_rows_of_bands(spark, d):
    """The accuracy experiment's grid: one to five rows of a band and up to twenty bands, with ten copies that have a tenth of the words changed."""
    return _accuracy(spark, d, PORTABLE.but(b=20, r=5), [5, 10, 15, 20])


def accuracy_many_bands(spark, d):
    """The same for 20 to 100 bands, as far as the curves of the experiment go."""
    return _accuracy(spark, d, CFG.but(b=100, r=5), [20, 50, 100])


def choose_bands_measured(spark, d):
    """The setting with the fewest values that misses no pair above each threshold, by the measured grid."""
    return tuning.choose_bands(materialize(accuracy_rows_of_bands(spark, d), "grid"), 0)


def synth_injected(spark, d):
    return synth.inject(documents(spark, d), 100, 0.0, 0.2).where("rate > 0 OR doc_id <> origin_id").select("doc_id", "origin_id", F.round("rate", 9).alias("rate"), F.md5("text").alias("text_md5"))


# --- bounds and clusters -------------------------------------------------------------------------------


def triangle_violations(spark, d):
    """Triples whose ends are less alike than the two similarities between them allow: none."""
    e = materialize(_similar(spark, d, 0.2), "edges")
    both = e.select("a", "b", "jaccard").unionByName(e.select(F.col("b").alias("a"), F.col("a").alias("b"), "jaccard"))
    chain = both.alias("p").join(both.alias("q"), F.col("p.b") == F.col("q.a")).where("p.a < q.b").select(F.col("p.a").alias("a"), F.col("q.b").alias("b"), sets.chain3(F.col("p.jaccard"), F.col("q.jaccard")).alias("low"))
    real = chain.join(e, ["a", "b"], "left").select("low", F.coalesce("jaccard", F.lit(0.2)).alias("jaccard"))
    return real.where("jaccard < low - 1e-9").agg(F.count("*").alias("violations"))


def path_bound(spark, d):
    """Bounds along chains of three edges of similar documents."""
    e = materialize(_similar(spark, d, 0.5), "edges")
    p = e.alias("p").join(e.alias("q"), F.col("p.b") == F.col("q.a")).join(e.alias("r"), F.col("q.b") == F.col("r.a"))
    return p.select(F.col("p.a").alias("a"), F.col("p.b").alias("b"), F.col("q.b").alias("c"), F.col("r.b").alias("d"), F.round(sets.path_bound(F.array("p.jaccard", "q.jaccard", "r.jaccard")), 9).alias("bound"))


def components_075(spark, d):
    from neardup.operators.graph import components

    pairs = pipeline.near_duplicates(documents(spark, d), CFG)
    return components(pairs).select(F.col("id").alias("doc_id"), "component")


def bounded_clusters_075(spark, d):
    return pipeline.clusters(documents(spark, d), CLUSTERS).select("doc_id", "cluster_id", "bound")


def bounded_clusters_rounds(spark, d):
    return pipeline.clusters(documents(spark, d), CFG.but(mode="rounds")).select("doc_id", "cluster_id", "bound")


def _clustered(spark, d, mode="sequential"):
    docs = documents(spark, d)
    return materialize(pipeline.clusters(docs, CFG.but(mode=mode)), "clusters"), materialize(text.grams_of(docs, CFG, hashed=True), "grams")


def cluster_bound_violations(spark, d):
    return metrics.bound_violations(*_clustered(spark, d), CFG.tree_threshold)


def cluster_rounds_violations(spark, d):
    return metrics.bound_violations(*_clustered(spark, d, "rounds"), CFG.tree_threshold)


def _experiment(spark, d, pool=45):
    """The clustering experiment's documents: 500 copies, up to a fifth of the words changed, of a pool of 45 or of all documents."""
    made = synth.inject(documents(spark, d), 500, 0.0, 0.2, pool=pool)
    grams = materialize(text.gram_sets(made, CFG), "grams")
    bands = materialize(banding.bands(made, CFG), "bands")
    edges = materialize(verify.scored_near(candidates.banded(bands), grams), "edges")
    return made, grams, bands, edges


def _sweep_rows(spark, d, measure, pool=45, compared=False):
    made, grams, bands, edges = _experiment(spark, d, pool)
    out, swept = None, cluster.bounded_sweep(bands, grams, SWEEP, 0.40, compared=compared)
    for edge in SWEEP:
        folded = swept.where(F.col("edge") == edge).drop("edge")
        one = measure(made, grams, edges, folded, edge).withColumn("edge", F.lit(edge))
        out = one if out is None else out.unionByName(one)
    return out


def pairs_excluded_sweep(spark, d):
    return _sweep_rows(spark, d, lambda made, grams, edges, folded, edge: metrics.pairs_excluded(edges.count(), folded.where("kind = 'compared'")), compared=True)


def pairs_excluded_all_sources(spark, d):
    """The same with copies of documents drawn from the whole table."""
    return _sweep_rows(spark, d, lambda made, grams, edges, folded, edge: metrics.pairs_excluded(edges.count(), folded.where("kind = 'compared'")), None, compared=True)


def pair_categories_all_sources(spark, d):
    return _sweep_rows(spark, d, lambda made, grams, edges, folded, edge: metrics.pair_categories(edges, cluster.assignments(folded, made), edge, 0.40), None)


def forest_speedup(spark, d):
    """Time and comparisons of checking every candidate pair, against those of folding the same buckets into a bounded forest."""
    return baseline.forest_speedup(spark, *_experiment(spark, d)[1:])


def pair_categories_sweep(spark, d):
    return _sweep_rows(spark, d, lambda made, grams, edges, folded, edge: metrics.pair_categories(edges, cluster.assignments(folded, made), edge, 0.40))


def modularity_sweep(spark, d):
    return _sweep_rows(spark, d, lambda made, grams, edges, folded, edge: metrics.modularity(edges, cluster.assignments(folded, made)))


def cluster_stats_sweep(spark, d):
    return _sweep_rows(spark, d, lambda made, grams, edges, folded, edge: metrics.cluster_stats(cluster.assignments(folded, made)))


def louvain_compare(spark, d):
    """Bounded clusters against communities on one graph: categories over candidates and over all pairs in clusters, modularity, clusters."""
    made, grams, bands, edges = _experiment(spark, d)
    out = None
    for name, clusters in (("bounded", cluster.assignments(cluster.bounded_clusters(bands, grams, 0.75, 0.40, scores=edges), made)), ("communities", community.louvain(edges))):
        clusters = materialize(clusters.select("doc_id", "cluster_id"), "clusters")
        inside = metrics.inside_categories(clusters, grams, 0.75, 0.40).select(*[F.col(c).alias(f"all_{c}") for c in ("same_high", "same_mid", "same_low")])
        one = metrics.pair_categories(edges, clusters, 0.75, 0.40).crossJoin(inside).crossJoin(metrics.modularity(edges, clusters)).crossJoin(metrics.cluster_stats(clusters)).withColumn("method", F.lit(name))  # one row each
        out = one if out is None else out.unionByName(one)
    return out


def unbounded_violations(spark, d):
    """Pairs below the tree threshold inside plain components of the experiment: what the bound prevents."""
    from neardup.operators.graph import components

    made, grams, bands, edges = _experiment(spark, d)
    comps = components(edges.where("jaccard > 0.6")).select(F.col("id").alias("doc_id"), F.col("component").alias("cluster_id"))
    return metrics.all_inside(comps, grams).agg(F.count("*").alias("pairs"), F.count(F.when(F.col("jaccard") < 0.4, 1)).alias("low_pairs"))


def order_sensitivity(spark, d):
    """Clusters by the order in which edges are folded; the guarantee holds for each."""
    made, grams, bands, edges = _experiment(spark, d)
    out = None
    for order, seed in (("similarity_desc", 0), ("pair", 0), ("shuffle", 1), ("shuffle", 2)):
        folded = cluster.fold_edges(edges, grams, 0.6, 0.4, order, seed).withColumn("cluster_id", F.col("root"))
        one = metrics.cluster_stats(folded).crossJoin(metrics.bound_violations(folded, grams, 0.4)).withColumn("variant", F.lit(f"{order}:{seed}"))  # one row each
        out = one if out is None else out.unionByName(one)
    return out


def modularity_exact(spark, d):
    """Modularity of the groups of equal texts on the graph of scored pairs above 0.2."""
    docs = documents(spark, d)
    groups = exact.exact_groups(docs).select("doc_id", F.col("rep").alias("cluster_id"))
    return metrics.modularity(_similar(spark, d, 0.2), groups)


def size_histogram(spark, d):
    return metrics.size_histogram(exact.exact_groups(table(spark, d, "documents")).select("doc_id", F.col("rep").alias("cluster_id")))


def _exact_clusters(spark, d):
    return exact.exact_groups(table(spark, d, "documents")).select("doc_id", F.col("rep").alias("cluster_id"))


def cross_edges(spark, d):
    return cluster.cross_edges(_similar(spark, d, 0.75), _exact_clusters(spark, d)).select("a", "b", "jaccard", "x", "y")


def second_round(spark, d):
    """Groups of equal texts merged where the average of their cross edges is above 0.75."""
    return cluster.second_round(_exact_clusters(spark, d), materialize(_similar(spark, d, 0.2), "edges"), 0.75)


def second_round_bounded(spark, d):
    return cluster.second_round(_exact_clusters(spark, d), materialize(_similar(spark, d, 0.2), "edges"), 0.75, "bounded")


def mst_clusters(spark, d):
    docs = documents(spark, d)
    grams = materialize(text.grams_of(docs, CFG, hashed=True), "grams")
    return cluster.fold_edges(materialize(_similar(spark, d, 0.75), "edges"), grams, 0.75, 0.40)


def common_grams(spark, d):
    return clean.common_grams(_exact_clusters(spark, d), _exploded(spark, d), 1.0)


def dedup_keep_first(spark, d):
    return clean.deduplicate(documents(spark, d), _exact_clusters(spark, d), "first").select("doc_id", "n_chars")


def dedup_keep_best(spark, d):
    return clean.deduplicate(documents(spark, d), _exact_clusters(spark, d), "best_quality", table(spark, d, "labels")).select("doc_id", "n_chars")


def dedup_keep_root(spark, d):
    return clean.deduplicate(documents(spark, d), pipeline.clusters(documents(spark, d), CLUSTERS), "root").select("doc_id", "n_chars")


def recluster_090(spark, d):
    """The second step again from stored cells, with a higher edge threshold."""
    docs, path = documents(spark, d), scratch_path(spark, "cells")
    texts = materialize(exact.representatives(docs), "texts")
    store.write_cells(banding.bands(texts, CLUSTERS), path)
    found = pipeline.recluster(spark, path, materialize(text.grams_of(texts, CLUSTERS, hashed=True), "grams"), docs, CLUSTERS.but(edge_threshold=0.90))
    return metrics.cluster_stats(found)


# --- cost, report, other tables -------------------------------------------------------------------------


def cost_model(spark, d):
    n = documents(spark, d).count()
    return costmodel.cost_table(spark, n=n, w=400, m=100, b=50, p=10)


def capacity(spark, d):
    """Documents that fit into 4 GB in each layout, and how many times the table's."""
    return costmodel.capacity_table(documents(spark, d))


def corpus_report(spark, d):
    """Pairs, groups of equal documents and clusters of the whole table."""
    docs = documents(spark, d)
    found = materialize(pipeline.near_duplicates(docs, CFG), "pairs")
    groups = exact.exact_clusters(docs)
    return found.agg(F.count("*").alias("pairs")).crossJoin(groups.agg(F.count("*").alias("exact_groups"), F.coalesce(F.max("size"), F.lit(0)).alias("largest_group"), F.coalesce(F.sum("size"), F.lit(0)).alias("exact_docs")))  # one row each


def corpus_clusters(spark, d):
    return metrics.cluster_stats(pipeline.clusters(documents(spark, d), CLUSTERS))


def basket_pairs(spark, d):
    """Customers whose sets of ordered parts are alike: sets that aren't of grams."""
    lines, orders = table(spark, d, "lineitem").select("l_orderkey", "l_partkey"), table(spark, d, "orders").select("o_orderkey", "o_custkey")
    items = lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).select(F.col("o_custkey").alias("doc_id"), F.col("l_partkey").cast("bigint").alias("gram"))
    return verify.similar_pairs(items, 0.06)


def page_pairs(spark, d):
    pages = table(spark, d, "pages").select(F.col("page_id").alias("doc_id"), F.regexp_replace("html", "<[^>]*>", " ").alias("text"))
    return verify.similar_pairs(text.grams_of(pages, CFG.but(n=5), hashed=True), 0.3)


def conversation_pairs(spark, d):
    turns = table(spark, d, "conversations").groupBy("conv_id").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("turn", "role", "text"))), lambda x: x.text), " ").alias("text"))
    return verify.similar_pairs(text.grams_of(turns.withColumnRenamed("conv_id", "doc_id"), CFG.but(n=5), hashed=True), 0.004)


def benchmark_containment(spark, d):
    """Share of each item's grams that a document holds, above a half."""
    items = text.exploded(text.grams_of(table(spark, d, "benchmark").select(F.col("item_id").alias("doc_id"), "text"), CFG)).select(F.col("doc_id").alias("item_id"), "gram")
    sizes = items.groupBy("item_id").agg(F.count("*").alias("n"))
    shared = items.join(_exploded(spark, d), "gram").groupBy("item_id", "doc_id").agg(F.count("*").alias("shared"))
    return shared.join(sizes, "item_id").select("item_id", "doc_id", (F.col("shared") / F.col("n")).alias("containment")).where("containment > 0.5")


def slice_flushes(spark, d):
    """Documents and values of each flush of 50 documents in a packed store: where a write takes longer."""
    docs = documents(spark, d).select("doc_id")
    slices = store.slice_ids(docs, store.slice_size(docs.count(), 50), ranked=True)
    return slices.groupBy(F.col("slice_id").cast("bigint").alias("slice_id")).agg(F.count("*").alias("docs")).withColumn("values", F.col("docs") * CFG.b)


def stage_times(spark, d):
    return baseline.stage_times(spark, d)


def flush_times(spark, d):
    """Seconds for one document and for the flush of each slice of 50 documents in a packed store."""
    return baseline.flush_times(spark, d)


def memory_use(spark, d):
    """Bytes that each layout holds at once while candidates are found: measured, and by the formula."""
    return baseline.memory_use(spark, d)


def times_by_documents(spark, d):
    """Seconds from text to candidates for one, two and four times the documents, for each layout."""
    return baseline.times_by_documents(spark, d)


def times_by_words(spark, d):
    """Seconds from text to candidates for texts of one, two and four times the words."""
    return baseline.times_by_words(spark, d)


def scaling_times(spark, d):
    return baseline.scaling_times(spark, d)
