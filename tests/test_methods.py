import collections
import hashlib
import random
import re

import numpy as np
import pytest
from pyspark.sql import functions as F

from neardup.config import DedupConfig, bands_for
from neardup.functions import sets, text
from neardup.functions.hashing import expected_collisions, gram_dictionary
from neardup.operators import banding, candidates, clean, cluster, community, costmodel, exact, graph, metrics, signature, store, synth, verify
from neardup.plans import pipeline, rules
from neardup.session import materialize

TEXTS = [(10, "a b c d e f g h i j"), (25, "a b c d e f g h i j"), (31, "A, b c d e f g h i j!"), (47, "q r s"), (52, ""), (60, None), (71, "x y z x y z x y z x y z x y z x")]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(TEXTS, "doc_id bigint, text string")


def rows(df):
    return sorted(tuple(r) for r in df.collect())


def test_config_refuses_bad_values():
    for bad in ({"n": 0}, {"layout": "x"}, {"tree_threshold": 0.9}, {"threshold": 1.5}):
        with pytest.raises(ValueError):
            DedupConfig(**bad)
    with pytest.raises(ValueError):
        bands_for(10, 3)
    assert DedupConfig().m == 100


@pytest.mark.parametrize(("policy", "want"), [("whole", 1), ("drop", 0), ("pad", 1)])
def test_short_documents(spark, policy, want):
    for n_words, exp in ((0, 0), (1, want), (3, want), (7, want), (8, 1), (9, 2)):
        df = spark.createDataFrame([(" ".join(map(str, range(n_words))),)], "text string")
        assert df.select(F.size(text.word_ngrams(text.words("text"), 8, policy))).first()[0] == exp


def test_words_and_shingles(spark):
    df = spark.createDataFrame([("Ähm, 12-b  c_d",)], "text string")
    assert df.select(text.words("text")).first()[0] == ["ähm", "12", "b", "c", "d"]
    assert df.select(text.char_shingles("text", 12)).first()[0] == ["Ähm, 12-b  c", "hm, 12-b  c_", "m, 12-b  c_d"]


@pytest.mark.parametrize(("word", "stem"), [("caresses", "caress"), ("ponies", "poni"), ("relational", "relat"), ("hopping", "hop"), ("agreed", "agre"), ("happy", "happi"), ("adjustment", "adjust"), ("generalizations", "gener"), ("sky", "sky"), ("oscillators", "oscil")])
def test_porter(word, stem):
    assert text.porter(word) == stem


def test_similarity_and_bounds(spark):
    df = spark.createDataFrame([([1, 2, 3, 4], [1, 2, 3, 4, 5], [2, 3, 4, 5])], "a array<int>, b array<int>, c array<int>")
    ab, bc, ac, low = df.select(sets.jaccard(F.col("a"), F.col("b")), sets.jaccard(F.col("b"), F.col("c")), sets.jaccard(F.col("a"), F.col("c")), sets.chain3(F.lit(0.8), F.lit(0.8))).first()
    assert (ab, bc, ac) == (0.8, 0.8, 0.6) and low == pytest.approx(0.6)
    assert df.select(sets.jaccard(F.array(), F.array())).first()[0] == 0
    assert df.select(sets.path_bound(F.array(F.lit(0.9), F.lit(0.8)))).first()[0] == pytest.approx(0.7)


def test_candidate_curve(spark):
    p = lambda s, b, r: spark.range(1).select(sets.candidate_probability(F.lit(s), b, r)).first()[0]
    assert p(0.5, 50, 2) == pytest.approx(0.99999943, abs=1e-8) and p(0.0, 50, 2) == 0 and p(1.0, 50, 2) == 1
    assert p(0.01, 100, 1) == pytest.approx(0.634, abs=1e-3)
    assert expected_collisions(1e12, 64) == pytest.approx(27105, rel=1e-3)


def test_band_matrix_in_both_layouts(spark, tmp_path):
    bands = spark.createDataFrame([(i, j, 4 * (i - 1) + j) for i in range(1, 5) for j in range(1, 5)], "band_id int, doc_id bigint, value bigint")
    store.write_cells(bands, f"{tmp_path}/cells")
    assert rows(store.read_cells(spark, f"{tmp_path}/cells")) == rows(bands)
    assert rows(store.read_cells(spark, f"{tmp_path}/cells", 2)) == [(2, j, 4 + j) for j in range(1, 5)]
    slices = store.slice_ids(bands.select("doc_id").distinct(), 2, ranked=True)
    packed, _ = store.pack(bands, slices)
    want = [(1, 1, [1, 2]), (1, 2, [5, 6]), (1, 3, [9, 10]), (1, 4, [13, 14]), (2, 1, [3, 4]), (2, 2, [7, 8]), (2, 3, [11, 12]), (2, 4, [15, 16])]
    assert sorted((r.slice_id + 1, r.band_id, r.value) for r in packed.collect()) == want
    store.write_packed(bands, slices, f"{tmp_path}/packed")
    assert rows(store.read_packed(spark, f"{tmp_path}/packed")) == rows(bands)
    assert candidates.banded(bands).isEmpty()
    assert store.slice_size(531, 50) == 11


def test_one_band_reads_its_folder_alone(spark, tmp_path):
    bands = spark.createDataFrame([(1, 1, 5), (2, 1, 6)], "band_id int, doc_id bigint, value bigint")
    store.write_cells(bands, f"{tmp_path}/c")
    plan = rules.plan_text(store.read_cells(spark, f"{tmp_path}/c", 2))
    assert "PartitionFilters: [isnotnull(band_id" in plan


def test_any_match_by_lists_and_by_sorting_agree(docs):
    slots = signature.slots(signature.signatures(docs, DedupConfig(b=20, r=1)))
    assert rows(candidates.inverted_lists(slots)) == rows(candidates.sorted_runs(slots)) == [(10, 25), (10, 31), (25, 31)]


def test_signature_estimates_similarity(spark):
    a, b = " ".join(f"w{i}" for i in range(100)), " ".join(f"w{i}" for i in range(30, 130))
    df = spark.createDataFrame([(1, a), (2, b)], "doc_id bigint, text string")
    for family in ("xx64", "mm32", "portable"):
        sig = {r.doc_id: r.sig for r in signature.signatures(df, DedupConfig(n=1, b=400, r=1, family=family)).collect()}
        share = sum(x == y for x, y in zip(sig[1], sig[2], strict=True)) / 400
        assert abs(share - 70 / 130) < 4 * (0.54 * 0.46 / 400) ** 0.5


def test_vectorised_signatures_are_those_of_the_lambdas(docs):
    from neardup.functions.hashing import minhashes

    for family in ("xx64", "portable"):
        cfg = DedupConfig(family=family, n=2, b=4, r=3)
        plain = signature.gram_numbers(docs, cfg).select("doc_id", minhashes(F.col("numbers"), family, 12, 42).alias("sig"))
        assert rows(signature.signatures(docs, cfg)) == rows(plain)


def test_layouts_and_rewrites_give_the_same_pairs(docs):
    want = rows(pipeline.near_duplicates(docs))
    assert [r[:2] for r in want] == [(10, 25), (10, 31), (25, 31)]
    for layout in ("cells", "packed"):
        assert rows(pipeline.near_duplicates(docs, DedupConfig(layout=layout))) == want
    plan = rules.DedupPlan(DedupConfig())
    assert rows(rules.execute(plan, docs)) == rows(rules.execute(rules.optimise(plan), docs)) == want


def test_all_pairs_and_shared_grams_agree(docs):
    grams = text.grams_of(docs, DedupConfig(n=3))
    assert rows(verify.all_pairs(grams, 0.0)) == rows(verify.shared_gram_pairs(text.exploded(grams)).select("a", "b", "jaccard"))
    with pytest.raises(ValueError):
        verify.all_pairs(grams, 0.5, most=2)


def test_plans_have_no_products(docs):
    found = rules.operators_of(pipeline.near_duplicates(docs))
    assert not {"CartesianProduct", "BroadcastNestedLoopJoin"} & set(found)


def test_components(spark):
    edges = spark.createDataFrame([(5, 6), (6, 9), (9, 2), (20, 21), (30, 30)], "a bigint, b bigint")
    assert rows(graph.components(edges)) == [(2, 2), (5, 2), (6, 2), (9, 2), (20, 20), (21, 20)]
    chain = spark.range(200).select(F.col("id").alias("a"), (F.col("id") + 1).alias("b"))
    assert {r.component for r in graph.components(chain).collect()} == {0}
    assert graph.components(edges.limit(0)).isEmpty()


def test_clusters_keep_their_guarantee(spark):
    base = spark.createDataFrame([(i, " ".join(f"d{i}w{k}" for k in range(60))) for i in range(6)], "doc_id bigint, text string")
    made = materialize(synth.inject(base, 60, 0.0, 0.1).select("doc_id", "text"), "made")
    cfg = DedupConfig(n=3, edge_threshold=0.6)
    grams = text.grams_of(made, cfg, hashed=True)
    for mode in ("sequential", "rounds"):
        found = pipeline.clusters(made, cfg.but(mode=mode))
        assert found.count() == made.count() == found.select("doc_id").distinct().count()
        assert tuple(metrics.bound_violations(found, grams, 0.4).first()) == (0, 0)
        assert metrics.cluster_stats(found).first().clusters > 0


def test_rounds_join_all_that_can_be_joined(spark):
    # The hash has these on the same side for three rounds and more.
    grams = spark.createDataFrame([(i, [1, 2, 3]) for i in (0, 2, 8, 12)], "doc_id bigint, grams array<bigint>")
    for b in (2, 8, 12):
        edges = spark.createDataFrame([(0, b, 1.0)], "a bigint, b bigint, jaccard double")
        assert len({r.root for r in cluster.rounds(edges, grams).collect()}) == 1
    edges = spark.createDataFrame([(0, 2, 1.0)], "a bigint, b bigint, jaccard double")
    with pytest.raises(RuntimeError):
        cluster.rounds(edges, grams, most=0)


def test_rounds_leave_no_joinable_roots(spark):
    r = random.Random(3)
    sets = {i: sorted(set(range(60)) - {r.randrange(60) for _ in range(5)}) for i in range(40)}
    sim = lambda x, y: len(set(sets[x]) & set(sets[y])) / len(set(sets[x]) | set(sets[y]))
    links = [(x, y, sim(x, y)) for x in sets for y in sets if x < y]
    grams = spark.createDataFrame(list(sets.items()), "doc_id bigint, grams array<bigint>")
    found = {x.doc_id: x for x in cluster.rounds(spark.createDataFrame(links, "a bigint, b bigint, jaccard double"), grams, 0.75, 0.6).collect()}
    for x, y, s in links:
        p, q = found[x], found[y]
        assert s <= 0.75 or p.root == q.root or p.bound + q.bound + sim(p.root, q.root) - 2 < 0.6 - 1e-12


def test_modularity_and_communities(spark):
    edges = spark.createDataFrame([(1, 2, 1.0), (3, 4, 1.0)], "a bigint, b bigint, jaccard double")
    own = spark.createDataFrame([(1, 1), (2, 1), (3, 3), (4, 3)], "doc_id bigint, cluster_id bigint")
    assert metrics.modularity(edges, own).first()[0] == 0.5
    assert metrics.modularity(edges, own.withColumn("cluster_id", F.lit(1))).first()[0] == 0
    assert rows(community.louvain(edges)) == rows(own)
    two = [(a, b, 1.0) for g in (range(5), range(5, 10)) for a in g for b in g if a < b] + [(0, 5, 0.1)]
    assert len(set(community.louvain_of(two, 2 * sum(w for *_, w in two)).values())) == 2


def test_exact_groups_and_cleaning(docs):
    assert rows(exact.exact_clusters(docs)) == [(10, 2)]
    assert rows(exact.exact_clusters(docs, "grams")) == [(10, 3)]
    groups = exact.exact_groups(docs, "grams").select("doc_id", F.col("rep").alias("cluster_id"))
    assert [r.doc_id for r in clean.deduplicate(docs, groups, "longest").orderBy("doc_id").collect()] == [31, 47, 52, 60, 71]
    assert clean.common_grams(groups, text.exploded(text.grams_of(docs, DedupConfig()))).count() == 3


def test_gram_numbers_are_dense(docs):
    ids = [r.gram_id for r in gram_dictionary(text.exploded(text.grams_of(docs, DedupConfig(n=2)))).collect()]
    assert sorted(ids) == list(range(len(ids)))


def test_capacity_and_costs():
    assert [round(x) for _, x in costmodel.capacity()] == [10_000_000, 500_000_000, 100_000_000]
    by = {r[0]: r for r in costmodel.costs(1000, 400, 100, 50, 10)}
    assert by["cells"][3:5] == (50_000.0, 128.0) and by["packed"][3:5] == (500.0, 64 + 64 * 100.0)


def test_second_round_merges(spark):
    clusters = spark.createDataFrame([(1, 1), (2, 1), (3, 3), (4, 4)], "doc_id bigint, cluster_id bigint")
    edges = spark.createDataFrame([(1, 3, 0.9), (2, 3, 0.8), (3, 4, 0.5)], "a bigint, b bigint, jaccard double")
    assert rows(cluster.second_round(clusters, edges, 0.75)) == [(1, 1), (2, 1), (3, 1), (4, 4)]
    assert rows(cluster.second_round(clusters, edges, 0.75, "bounded")) == [(1, 1), (2, 1), (3, 1), (4, 4)]
    assert cluster.cross_edges(edges, clusters).count() == 3


def test_empty_corpus(spark, docs):
    none = docs.limit(0)
    assert pipeline.near_duplicates(none).isEmpty()
    assert pipeline.clusters(none).isEmpty()
    assert banding.bands(docs.where("doc_id = 10"), DedupConfig()).count() == 50


def _plain_similar(sets, least):
    out = {}
    for a, x in sets.items():
        for b, y in sets.items():
            if a < b and x and y and len(x & y) / len(x | y) > least:
                out[a, b] = (len(x & y), len(x & y) / len(x | y))
    return out


def test_prefix_join_finds_all_pairs_above_a_threshold(spark):
    r, sets = random.Random(3), {}
    for d in range(80):
        base = sets[r.randrange(d)] if d and r.random() < 0.6 else set()
        sets[d] = {x for x in base if r.random() < 0.9} | {r.randrange(60) for _ in range(r.randrange(1, 12))}
    rows = spark.createDataFrame([(d, f"g{x}") for d, s in sets.items() for x in s], "doc_id bigint, gram string")
    for least in (0.05, 0.2, 0.5, 0.8):
        got = {(x.a, x.b): (x.shared, x.jaccard) for x in verify.similar_pairs(rows, least).collect()}
        assert got == _plain_similar(sets, least) and got


def test_ranks_of_a_whole_table(spark):
    from neardup.operators.ranks import ranked

    ids = [7, 3, 99, 1000, -5, 12]
    df = spark.createDataFrame([(i, f"r{i}") for i in ids], "doc_id bigint, rank_part string").repartition(4)
    assert {x.doc_id: x["rank"] for x in ranked(df, "doc_id").collect()} == {d: k for k, d in enumerate(sorted(ids))}
    assert ranked(df.limit(0), "doc_id").count() == 0
    sizes = collections.Counter(x.slice_id for x in store.slice_ids(spark.range(23).withColumnRenamed("id", "doc_id"), 5, ranked=True).collect())
    assert sizes == {0: 5, 1: 5, 2: 5, 3: 4, 4: 4}


def test_heavy_keys_and_others_join_alike(spark):
    from neardup.operators.skew import join_counted, repeated

    rows = spark.createDataFrame([(k, i) for k, n in (("a", 500), ("b", 3), ("c", 1), ("d", 2)) for i in range(n)], "k string, i int")
    counts = rows.groupBy("k").count().withColumnRenamed("count", "n").where("k <> 'd'").withColumn("x", F.concat("k", F.lit("!")))
    for heavy in (1, 4, 1000):
        got = collections.Counter((r.k, r.x) for r in join_counted(rows, counts, ["k"], heavy_keys=heavy).collect())
        assert got == {("a", "a!"): 500, ("b", "b!"): 3, ("c", "c!"): 1}
    assert collections.Counter(r.k for r in repeated(rows, ["k"]).collect()) == {"a": 500, "b": 3, "d": 2}
    assert repeated(rows.limit(0), ["k"]).count() == 0


def test_band_store_knows_its_batches_after_a_restart(spark, tmp_path):
    from neardup.streaming.neardup import BandStore, arrive

    words = [f"w{k}" for k in range(60)]
    docs = lambda *ids: spark.createDataFrame([(i, " ".join([*words, f"x{i}"])) for i in ids], "doc_id bigint, text string")
    cfg = DedupConfig()
    assert {(x.a, x.b) for x in arrive(BandStore(spark, f"{tmp_path}/s"), docs(1, 2), 0, cfg).collect()} == {(1, 2)}
    # Another object, as after a restart; a batch that runs again gives the same rows.
    for _ in range(2):
        assert {(x.a, x.b) for x in arrive(BandStore(spark, f"{tmp_path}/s"), docs(3), 1, cfg).collect()} == {(1, 3), (2, 3)}
    (tmp_path / "s" / "bands" / "batch=7").mkdir()
    assert BandStore(spark, f"{tmp_path}/s").batches("bands") == [0, 1]


def test_copies_cost_no_candidates_and_keep_their_pairs(spark):
    words = [f"w{k}" for k in range(60)]
    rows = [(i, " ".join(words)) for i in range(30)] + [(40, " ".join([*words, "more"])), (41, None), (42, ""), (43, "")]
    df = spark.createDataFrame(rows, "doc_id bigint, text string")
    run = pipeline.run(df, DedupConfig())
    assert run.candidates.count() == 1
    pairs = {(x.a, x.b) for x in run.pairs.collect()}
    assert pairs == {(a, b) for a in [*range(30), 40] for b in [*range(30), 40] if a < b}
    for mode in ("sequential", "rounds"):
        found = {x.doc_id: x.cluster_id for x in pipeline.clusters(df, DedupConfig(mode=mode)).collect()}
        assert found == {**dict.fromkeys([*range(30), 40], 0), 41: 41, 42: 42, 43: 42} or found == {**dict.fromkeys([*range(30), 40], 0), 41: 41, 42: 42, 43: 43}


def test_components_beyond_one_task_keep_the_bound(spark):
    """The same guarantee, and no two roots left that could still be joined, for several orders of the rounds."""
    from neardup.functions.text import grams_of
    from neardup.operators import cluster

    words = [f"w{k}" for k in range(200)]
    rows = [(i, " ".join(words[7 * i : 7 * i + 80])) for i in range(14)]
    df = spark.createDataFrame(rows, "doc_id bigint, text string")
    cfg = DedupConfig(n=2)
    grams, bands = grams_of(df, cfg, hashed=True), banding.bands(df, cfg)
    for most in (20_000, 3):
        folded = cluster.bounded_clusters(bands, grams, 0.6, 0.4, most_members=most)
        got = cluster.assignments(folded, df)
        x = metrics.bound_violations(got, grams, 0.4).first()
        assert (x.low_pairs, x.root_violations) == (0, 0) and got.count() == 14 and got.select("cluster_id").distinct().count() < 14
    edges = verify.scored(candidates.banded(bands), grams)
    for seed in range(4):
        state = cluster.rounds(edges, grams, 0.6, 0.4, seed=seed)
        roots = state.select("root", "bound").distinct()
        pairs = edges.where("jaccard > 0.6").join(state.select(F.col("doc_id").alias("a"), F.col("root").alias("x"), F.col("bound").alias("bx")), "a").join(state.select(F.col("doc_id").alias("b"), F.col("root").alias("y"), F.col("bound").alias("by")), "b").where("x <> y")
        both = verify.scored(pairs.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).distinct(), grams).collect()
        bound = {r.root: r.bound for r in roots.collect()}
        assert not [p for p in both if p.jaccard > 0.6 and bound[p.a] + bound[p.b] + p.jaccard - 2 >= 0.4]


def test_pairs_come_from_few_lists_of_documents(spark, monkeypatch):
    shared = list(range(1000))
    sets = {1: shared, 2: shared, 3: [*range(990, 1000), 2000], **{i: [5000, 6000 + i] for i in range(10, 20)}}
    rows = spark.createDataFrame(list(sets.items()), "doc_id bigint, grams array<bigint>")
    written = []
    monkeypatch.setattr(verify, "materialize", lambda df, name: written.append((name, out := materialize(df, name))) or out)
    monkeypatch.setattr(verify, "BLOCK", 3)
    plain = {k: set(v) for k, v in sets.items()}
    for least in (0.0, 0.2, 0.5):
        found = verify.similar_pairs(rows, least) if least else verify.shared_gram_pairs(rows)
        assert {(x.a, x.b): (x.shared, x.jaccard) for x in found.collect()} == _plain_similar(plain, least)
    # 1,000 shared grams are two lists, and those of ten documents one.
    assert written[0][0] == "lists" and sorted((len(x.ids), x.w) for x in written[0][1].collect()) == [(2, 990), (3, 10), (10, 1)]


def test_approximate_counts_keep_no_sketch_for_each_gram(spark):
    from neardup.workloads import relational

    plan = relational.agg_approx_grams(spark, "/root/testdata/sf0.001")._jdf.queryExecution().executedPlan().toString()
    keyed = [x for x in plan.splitlines() if "approx_count_distinct" in x and "keys=[]" not in x and "functions=" in x]
    assert "approx_count_distinct" in plan and not keyed


def test_all_pairs_meets_block_after_block(spark, monkeypatch):
    r = random.Random(5)
    sets = {d: {r.randrange(30) for _ in range(r.randrange(0, 9))} for d in range(0, 120, 3)}
    rows = spark.createDataFrame([(d, sorted(s)) for d, s in sets.items()], "doc_id bigint, grams array<bigint>")
    monkeypatch.setattr(verify, "ALL_PAIRS_GRAMS", 60)
    got = {(x.a, x.b): x.jaccard for x in verify.all_pairs(rows, 0.2).collect()}
    assert got == {k: j for k, (_, j) in _plain_similar(sets, 0.2).items()} and got
    assert verify.all_pairs(rows.limit(0), 0.2).isEmpty()


def _documents_read(df):
    return [x for x in df._jdf.queryExecution().optimizedPlan().collectLeaves().mkString("\n").splitlines() if "parquet" in x]


@pytest.mark.parametrize("name", ["capacity", "lsh_curve", "scan_schema_check", "source_synthetic", "udf_probability"])
def test_queries_read_the_documents_table(spark, name):
    from neardup import catalog

    assert _documents_read(catalog.queries()[name](spark, "/root/testdata/sf0.001"))


def test_a_sweep_gives_what_each_threshold_gives(spark):
    base = spark.createDataFrame([(i, " ".join(f"d{i}w{k}" for k in range(60))) for i in range(4)], "doc_id bigint, text string")
    made = materialize(synth.inject(base, 30, 0.0, 0.2).select("doc_id", "text"), "made")
    cfg = DedupConfig(n=3)
    bands, grams = materialize(banding.bands(made, cfg), "bands"), materialize(text.grams_of(made, cfg, hashed=True), "grams")
    swept = cluster.bounded_sweep(bands, grams, (0.6, 0.8), 0.4)
    for edge in (0.6, 0.8):
        want = rows(cluster.bounded_clusters(bands, grams, edge, 0.4, edges_only=False))
        assert rows(swept.where(F.col("edge") == edge).drop("edge")) == want and want


def test_orders_are_ranked_without_a_row_for_each_gram(spark):
    """Ranks against a plain sort, with copies in several tasks, equal and null ids; what is shuffled has few rows for many grams."""
    r = random.Random(8)
    texts = [" ".join(f"w{r.randrange(40)}" for _ in range(r.randrange(0, 300))) for _ in range(30)]
    data = [(i, t) for i, t in enumerate(texts)] + [(i + 30, t) for i, t in enumerate(texts[:15])] + [(3, "One, two"), (None, texts[4]), (99, None)]
    df = spark.createDataFrame(data, "doc_id bigint, text string").repartition(4)
    made = lambda t: {" ".join(w[i : i + 8]) for i in range(max(1, len(w) - 7))} if (w := re.findall(r"\w+", (t or "").lower())) else set()
    every, want = set().union(*(made(t) for _, t in data)), {}
    for slot in (0, 1):
        rank = {g: k for k, g in enumerate(sorted(every, key=lambda g: hashlib.md5(f"42:{slot}:{g}".encode()).hexdigest()), 1)}
        for d, t in data:
            if g := made(t):
                want[d, slot] = min(want.get((d, slot), len(every)), min(rank[x] for x in g))
    assert {(x.doc_id, x.slot): x.h for x in signature.minhash_permutation(df, 2).collect()} == want
    sent = df.select("doc_id", F.expr("array_join(split(lower(text), '[^a-z0-9]+'), ' ')")).mapInArrow(signature._order_keys(b"42:0:", 8), "bucket int, doc_id bigint, own bigint, keys binary")
    packed = sent.where("keys IS NOT NULL").agg(F.count("*").alias("rows"), F.sum(F.length("keys") / 8).alias("keys")).first()
    assert len(every) <= packed["keys"] <= sum(len(made(t)) for _, t in data) and sent.where("keys IS NULL").count() <= len(data)


def test_pairs_scored_in_blocks_and_counted_inside_clusters(spark):
    """Blocks of few documents against the joins that fetch both sets of each pair; the experiment's comparisons against one run over all buckets."""
    from neardup.operators import baseline, forest

    base = spark.createDataFrame([(i, " ".join(f"d{i // 2}w{k}" for k in range(40)) + f" own{i}") for i in range(8)], "doc_id bigint, text string")
    made = materialize(synth.inject(base, 40, 0.0, 0.3).select("doc_id", "text"), "made")
    cfg = DedupConfig(n=3)
    bands, grams = materialize(banding.bands(made, cfg), "bands"), materialize(text.grams_of(made, cfg, hashed=True), "grams")
    pairs = candidates.banded(bands)
    edges = materialize(verify.scored_near(pairs, grams, together=5), "edges")
    assert rows(edges) == rows(verify.scored(pairs, grams)) and not edges.isEmpty()
    assert verify.scored_near(pairs.limit(0), grams).isEmpty()
    groups = graph.components(edges).select(F.col("id").alias("doc_id"), F.col("component").alias("cluster_id"))
    want = metrics.pair_categories(metrics.all_inside(groups, grams), groups, 0.75, 0.4).select("same_high", "same_mid", "same_low")
    assert rows(metrics.inside_categories(groups, grams, 0.75, 0.4, together=5)) == rows(want) and sum(want.first()) > edges.count() / 2
    assert rows(cluster.bounded_clusters(bands, grams, scores=edges)) == rows(cluster.bounded_clusters(bands, grams))
    lists = collections.defaultdict(list)
    for x in bands.orderBy("band_id", F.col("value").cast("string"), "doc_id").collect():
        lists[x.band_id, str(x.value)].append(x.doc_id)
    known = {(x.a, x.b): x.jaccard for x in edges.collect()}
    sets_of = {x.doc_id: set(x.grams) for x in grams.collect()}
    sim = lambda x, y: known.setdefault((x, y) if x < y else (y, x), len(sets_of[x] & sets_of[y]) / len(sets_of[x] | sets_of[y]))
    candidates_, tried = len(known), set()
    forest.fold_buckets([m for m in lists.values() if len(m) > 1], lambda x, y: (tried.add((min(x, y), max(x, y))), sim(x, y))[1], 0.75, 0.4)
    row = baseline.forest_speedup(spark, grams, bands, edges).first()
    assert (row.pairs, row.forest_pairs) == (candidates_, len(tried))


def test_changes_are_made_for_the_given_ids_alone_and_texts_parted_once(spark, tmp_path):
    import numpy as np

    from neardup.sources.synthetic import SyntheticChanges, _joined, id_runs
    from neardup.workloads.relational import source_synthetic

    data = [(7, "a b c"), (8, "one"), (9, ""), (9, "x y"), (5_000_000, None), (10**15, "p  q r s t u v"), (10**15 + 1, "k l"), (-4, "n m o")]
    spark.createDataFrame(data, "doc_id bigint, text string").repartition(3).write.parquet(str(tmp_path / "documents.parquet"))
    found = source_synthetic(spark, str(tmp_path))
    want = []
    for d, t in data:
        ws = None if t is None else t.split(" ")
        if ws:
            ws[d % len(ws)] = "x" + hashlib.md5(f"change:{d}".encode()).hexdigest()[:6]
        want += [(d, 0, t), (d, 1, ws and " ".join(ws))]
    assert sorted(map(tuple, found.collect()), key=str) == sorted(want, key=str)
    assert found._jdf.queryExecution().optimizedPlan().toString().count("split(") == 1
    docs = spark.read.parquet(str(tmp_path / "documents.parquet"))
    spark.dataSource.register(SyntheticChanges)
    made = spark.read.format("synthetic_changes").option("runs", id_runs(docs)).option("partitions", "3").load()
    assert sorted(x.doc_id for x in made.collect()) == sorted({d for d, _ in data})
    assert _joined(np.array([[5, 9], [1, 4], [9, 12], [20, 20]])).tolist() == [[1, 12], [20, 20]]


def test_pairs_that_share_a_gram_are_counted_and_never_shuffled(spark, monkeypatch):
    """Pairs and their numbers against a plain count, over one block of documents and many; no plan joins or deals rows of pairs."""
    from neardup.operators import tuning

    r = random.Random(3)
    sets = {d * 7: {r.randrange(40) for _ in range(r.randrange(0, 9))} for d in range(60)}
    sets |= {1000 + i: {500, 501, *range(600, 600 + i % 4)} for i in range(30)}
    rows = spark.createDataFrame([(d, sorted(s)) for d, s in sets.items()] + [(None, [500])], "doc_id bigint, grams array<bigint>").repartition(3)
    want = _plain_similar(sets, 0.0)
    for places, held in ((4_000_000, 500_000), (25, 3)):
        monkeypatch.setattr(verify, "PLACES", places)
        monkeypatch.setattr(verify, "PAIRS_HELD", held)
        pairs, numbers = verify.shared_gram_pairs(rows), verify.shared_gram_pairs(rows, counted=True)
        plan = pairs._jdf.queryExecution().optimizedPlan().toString()
        assert "MapInArrow" in plan and not re.search("Join|Aggregate|Repartition", plan)
        assert {(x.a, x.b): (x.shared, x.jaccard) for x in pairs.collect()} == want and pairs.count() == len(want)
        assert {(x.shared, x.jaccard): x.n for x in numbers.groupBy("shared", "jaccard").agg(F.sum("n").alias("n")).collect()} == collections.Counter(want.values())
        assert tuning.expected(numbers, [(5, 2)], [0.3]).collect() == tuning.expected(pairs, [(5, 2)], [0.3]).collect()
    assert verify.shared_gram_pairs(rows.limit(0)).isEmpty() and verify.shared_gram_pairs(rows.limit(0), counted=True).isEmpty()


def test_sets_made_in_batches_are_those_of_the_built_in_functions(spark):
    r = random.Random(4)
    texts = [" ".join(r.choice(("Ä", "b", "c1", "", "d-e")) for _ in range(k)) for k in range(40)] + [None, "  ", "x " * 30]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string").repartition(3)
    for n in (1, 3, 8):
        for short in ("whole", "drop", "pad"):
            cfg = DedupConfig(n=n, short_doc=short)
            got = {x.doc_id: x.grams for x in text.gram_sets(df, cfg).collect()}
            assert got == {x.doc_id: sorted(x.grams) for x in text.grams_of(df, cfg, hashed=True).collect()} and len(got) == len(texts)
    assert text.gram_sets(df.limit(0), DedupConfig()).isEmpty()


def test_candidates_are_counted_by_their_lowest_band(spark, monkeypatch):
    """The measured grid against a plain count, over one block of documents and many; only true pairs become rows."""
    from neardup.operators import tuning

    r = random.Random(6)
    values = {3 * d: [r.randrange(6) + 10 * (r.random() < 0.7) * d for _ in range(4)] for d in range(50)} | {500 + d: [1, 2, 3, 4] for d in range(20)}
    bands = spark.createDataFrame([(d, k, v) for d, vs in values.items() for k, v in enumerate(vs)] + [(None, 0, 1)], "doc_id bigint, band_id int, value bigint").repartition(3)
    ids = sorted(values)
    first = {(a, b): f for i, a in enumerate(ids) for b in ids[i + 1 :] if (f := min((k for k in range(4) if values[a][k] == values[b][k]), default=None)) is not None}
    every = [(a, b) for i, a in enumerate(ids) for b in ids[i + 1 :]]
    true = {p: r.choice((0.25, 0.35, 0.9)) for p in r.sample(every, 300)}
    truth = spark.createDataFrame([(*p, j) for p, j in true.items()], "a bigint, b bigint, jaccard double")
    for places in (4_000_000, 20):
        monkeypatch.setattr(verify, "PLACES", places)
        found = verify.first_bands(bands, truth).collect()
        assert {(x.a, x.b): x.first for x in found if not x.n} == {p: f for p, f in first.items() if p in true}
        assert sum((collections.Counter({x.first: x.n}) for x in found if x.n), collections.Counter()) == collections.Counter(first.values())
        for x in tuning.measured(bands, [1, 2, 4], 2, truth, [0.2, 0.3]).collect():
            cand = {p for p, f in first.items() if f < x.b}
            good = {p for p, j in true.items() if j > x.t}
            assert (x.r, x.candidates, x.false_candidates, x.misses) == (2, len(cand), len(cand - good), len(good - cand))
    assert tuning.measured(bands.limit(0), [1], 2, truth.limit(0), [0.2]).isEmpty()


def test_copies_are_drawn_without_moving_all_texts(spark, monkeypatch):
    from neardup.operators import ranks

    written = []
    monkeypatch.setattr(ranks, "materialize", lambda df, name: written.append(df.columns) or materialize(df, name))
    df = spark.createDataFrame([(i * 5, f"t{i} a b c d e") for i in range(40)], "doc_id bigint, text string")
    for pool in (None, 4):
        made = synth.inject(df, 12, 0.0, 0.2, pool=pool)
        assert made.count() == 52 and made.where("doc_id > 195").select("doc_id").distinct().count() == 12
        assert all(x.text.split()[0][0] in "tx" for x in made.collect())
        assert "Exchange" not in made._jdf.queryExecution().executedPlan().toString()
    assert written and all("text" not in c for c in written)


def test_similarities_of_a_component_are_counted_in_bulk(spark, monkeypatch):
    """The forest from counts at once against one similarity after the other, also where few counts are kept; a sweep without compared pairs."""
    from neardup.operators.forest import fold_buckets

    r = random.Random(7)
    base = list(range(60))
    sets_ = [np.array(sorted({x if r.random() < 0.9 else r.randrange(1000) for x in base}), np.int64) for _ in range(40)] + [np.zeros(0, np.int64)]
    one_by_one = cluster._similarity(dict(enumerate(sets_)))
    lists = [sorted(r.sample(range(41), r.randrange(2, 12))) for _ in range(60)]
    for held in (cluster.COUNTS_HELD, 1):
        monkeypatch.setattr(cluster, "COUNTS_HELD", held)
        for edge in (0.5, 0.7):
            want, got = (fold_buckets(lists, sim, edge, 0.4) for sim in (one_by_one, cluster.Likeness(sets_)))
            assert got[1] == want[1] and (got[0].parent, got[0].bound) == (want[0].parent, want[0].bound) and want[0].bound
            assert fold_buckets(lists, cluster.Likeness(sets_), edge, 0.4, keep=False)[1] == []
    docs = spark.createDataFrame([(i, " ".join(f"w{k}" for k in range(i, i + 60))) for i in range(0, 30, 2)], "doc_id bigint, text string")
    cfg = DedupConfig(n=3)
    bands, grams = materialize(banding.bands(docs, cfg), "bands"), materialize(text.gram_sets(docs, cfg), "grams")
    full, lean = (cluster.bounded_sweep(bands, grams, (0.6, 0.8), 0.4, compared=c) for c in (True, False))
    assert rows(lean) == rows(full.where("kind = 'member'")) and not full.where("kind = 'compared'").isEmpty()
