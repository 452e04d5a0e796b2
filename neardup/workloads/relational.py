"""Queries for the relational operators, functions, sources and streams around the methods."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from neardup.functions import text
from neardup.functions.text import bound_once
from neardup.io import documents, spread_documents, table
from neardup.operators import banding, candidates, verify
from neardup.session import materialize, scratch_path, ship_package
from neardup.workloads.methods import CFG, PORTABLE, _bands, _exploded, _scored, _sets


def scan_documents(spark, d):
    return documents(spark, d).select("doc_id", "lang", "n_chars").where("n_chars > 500")


def scan_schema_check(spark, d):
    """Columns of the documents table by name, of those that a scan counts values of."""
    docs = documents(spark, d)
    counts = docs.agg(*[F.count(F.col(c)).alias(c) for c in docs.columns])
    return counts.select(F.explode(F.array(*[F.struct(F.lit(c).alias("name"), F.col(c).alias("n")) for c in docs.columns])).alias("x")).where("x.n >= 0").select("x.name")


def scan_formats(spark, d):
    """The same rows through csv, json and orc files."""
    rows, out = table(spark, d, "nation"), None
    for kind in ("csv", "json", "orc"):
        path = scratch_path(spark, kind)
        rows.write.format(kind).option("header", "true").save(path)
        back = spark.read.schema(rows.schema).option("header", "true").format(kind).load(path)
        one = back.agg(F.count("*").alias("n"), F.sum("n_nationkey").alias("keys")).select(F.lit(kind).alias("kind"), "n", "keys")
        out = one if out is None else out.unionByName(one)
    return out


def filter_documents(spark, d):
    x = documents(spark, d)
    return x.where(F.col("lang").isin("en", "de") & F.col("n_chars").between(100, 2000) & ~F.col("source").like("src1%") & F.col("lang").eqNullSafe("en")).select("doc_id", "source")


def join_broadcast_labels(spark, d):
    x = documents(spark, d).select("doc_id", "lang").join(table(spark, d, "labels"), "doc_id")
    return x.groupBy("lang", "quality", "toxic").agg(F.count("*").alias("n"))


def join_band_equi(spark, d):
    b = _bands(spark, d)
    return b.alias("x").join(b.hint("merge").alias("y"), (F.col("x.band_id") == F.col("y.band_id")) & (F.col("x.value") == F.col("y.value")) & (F.col("x.doc_id") < F.col("y.doc_id"))).groupBy(F.col("x.band_id").cast("bigint").alias("band_id")).agg(F.count("*").alias("pairs"))


def join_pairs_theta(spark, d):
    """Parts of one brand within a tenth of each other's price: an equi-join with a range condition."""
    p = table(spark, d, "part").select("p_partkey", "p_brand", "p_size", "p_retailprice")
    x, y = p.alias("x"), p.alias("y")
    near = (F.col("x.p_partkey") < F.col("y.p_partkey")) & F.col("y.p_retailprice").between(F.col("x.p_retailprice") * 0.999, F.col("x.p_retailprice") * 1.001)
    return x.join(y, (F.col("x.p_brand") == F.col("y.p_brand")) & (F.col("x.p_size") == F.col("y.p_size")) & near).select(F.col("x.p_partkey").alias("a"), F.col("y.p_partkey").alias("b"))


def join_missed_anti(spark, d):
    return documents(spark, d).select("doc_id").join(table(spark, d, "labels").select("doc_id"), "doc_id", "left_anti")


def join_kept_semi(spark, d):
    return documents(spark, d).select("doc_id", "lang").join(table(spark, d, "labels").where("quality = 1").select("doc_id"), "doc_id", "left_semi")


def join_outer_labels(spark, d):
    x = documents(spark, d).select("doc_id", "source").join(table(spark, d, "labels"), "doc_id", "full")
    return x.groupBy("source").agg(F.count("*").alias("n"), F.count("quality").alias("labelled"))


def as_of(left: DataFrame, right: DataFrame, key: str, time: str, value: str, name: str) -> DataFrame:
    """left with the latest value of right at or before its time, by one sorted pass over both for each key."""
    both = left.select("*", F.lit(None).cast(right.schema[value].dataType).alias(name), F.lit(1).alias("_side")).unionByName(right.select(key, time, F.col(value).alias(name), F.lit(0).alias("_side")), allowMissingColumns=True)
    order = Window.partitionBy(key).orderBy(time, "_side").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn(name, F.last(name, ignorenulls=True).over(order)).where("_side = 1").drop("_side")


def join_asof_events(spark, d):
    """For each purchase the value of the user's last click before or at it."""
    e = table(spark, d, "events").select("event_id", "user_id", "ts", "event_type", "value")
    kinds = [r.event_type for r in e.select("event_type").distinct().orderBy("event_type").limit(2).collect()]
    left, right = e.where(F.col("event_type") == kinds[0]).select("event_id", "user_id", "ts"), e.where(F.col("event_type") == kinds[1]).groupBy("user_id", "ts").agg(F.max("value").alias("value"))
    return as_of(left, right, "user_id", "ts", "value", "last_value").select("event_id", "last_value")


def join_interval_events(spark, d):
    """Pairs of a user's events at most ten minutes apart; the hour is part of the key, so hot users are split."""
    e = table(spark, d, "events").select("event_id", "user_id", "ts").withColumn("hour", F.floor(F.unix_timestamp(F.col("ts").cast("timestamp")) / 3600))
    y = e.select(F.col("event_id").alias("b"), F.col("user_id").alias("u"), F.col("ts").alias("tb"), F.explode(F.array(F.col("hour"), F.col("hour") - 1)).alias("h"))
    near = (F.col("user_id") == F.col("u")) & (F.col("hour") == F.col("h")) & (F.col("tb") >= F.col("ts")) & (F.col("tb") <= F.col("ts") + F.expr("INTERVAL 10 MINUTES")) & (F.col("event_id") != F.col("b"))
    return e.join(y, near).select(F.col("event_id").alias("a"), "b")


def agg_lang_source_cube(spark, d):
    return documents(spark, d).cube("lang", "source").agg(F.count("*").alias("n"), F.sum("n_chars").alias("chars"))


def agg_rollup_orders(spark, d):
    return table(spark, d, "orders").rollup("o_orderpriority", "o_orderstatus").agg(F.count("*").alias("n"))


def agg_grouping_sets(spark, d):
    documents(spark, d).createOrReplaceTempView("grouping_docs")
    return spark.sql("SELECT lang, source, count(*) AS n FROM grouping_docs GROUP BY GROUPING SETS ((lang), (source), ()) HAVING count(*) > 10")


def agg_distinct_grams(spark, d):
    return _exploded(spark, d).join(documents(spark, d).select("doc_id", "lang"), "doc_id").groupBy("lang").agg(F.countDistinct("gram").alias("grams"))


def agg_approx_grams(spark, d):
    """Approximate distinct grams lie within 5 % of the exact number."""
    # Each by itself: together Spark keeps a sketch of several kB for every distinct gram. Grams are counted by 64-bit hashes.
    grams = text.exploded(_sets(spark, d))
    x = grams.agg(F.approx_count_distinct("gram", 0.01).alias("a")).crossJoin(grams.agg(F.countDistinct("gram").alias("e")))  # one row each
    return x.select((F.abs(F.col("a") - F.col("e")) <= 0.05 * F.col("e")).alias("close"))


def window_representative(spark, d):
    w = Window.partitionBy("source", "lang").orderBy(F.desc("n_chars"), "doc_id")
    return documents(spark, d).select("doc_id", "source", "lang", "n_chars").withColumn("rank", F.row_number().over(w)).where("rank <= 3").select("doc_id", "source", "lang", F.col("rank").cast("bigint").alias("rank"))


def window_runs(spark, d):
    """Time between a user's events."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    e = table(spark, d, "events")
    return e.select("event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id").over(w).alias("after"))


def window_running_min(spark, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    o = table(spark, d, "orders")
    return o.select("o_orderkey", F.min("o_totalprice").over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("low"), F.max("o_totalprice").over(w.rowsBetween(-2, 0)).alias("high3"))


def topk_pairs(spark, d):
    return _scored(spark, d).orderBy(F.desc("jaccard"), "a", "b").limit(50)


def topk_per_doc(spark, d):
    w = Window.partitionBy("a").orderBy(F.desc("jaccard"), "b")
    return _scored(spark, d).where("jaccard > 0.2").withColumn("rank", F.row_number().over(w).cast("bigint")).where("rank <= 2").select("a", "b", "rank")


def largest_clusters(spark, d):
    from neardup.operators.exact import exact_clusters

    return exact_clusters(documents(spark, d)).orderBy(F.desc("size"), "rep").limit(10)


def set_union_bands(spark, d):
    b = _bands(spark, d)
    return candidates.banded(b.where("band_id < 10")).union(candidates.banded(b.where("band_id >= 10"))).distinct()


def set_methods_intersect(spark, d):
    return candidates.banded(_bands(spark, d)).intersect(_scored(spark, d).where("jaccard > 0.4").select("a", "b"))


def set_methods_except(spark, d):
    return _scored(spark, d).where("jaccard > 0.2").select("a", "b").exceptAll(candidates.banded(_bands(spark, d)))


def fn_string(spark, d):
    x = documents(spark, d)
    return x.select("doc_id", F.upper("lang").alias("up"), F.regexp_extract("source", "([0-9]+)", 1).alias("no"), F.md5("text").alias("md5"), F.substring("text", 1, 12).alias("head"), F.length(F.regexp_replace("text", "[aeiou]", "")).cast("bigint").alias("no_vowels"))


def fn_math(spark, d):
    o = table(spark, d, "orders")
    return o.select("o_orderkey", F.round(F.sqrt("o_totalprice"), 6).alias("root"), F.round(F.pow(F.col("o_totalprice") / 1000, 2), 6).alias("square"), F.pmod("o_custkey", F.lit(7)).cast("bigint").alias("rest"))


def fn_date(spark, d):
    o = table(spark, d, "orders")
    return o.select(F.date_format(F.date_trunc("month", F.col("o_orderdate").cast("timestamp")), "yyyy-MM").alias("month"), "o_totalprice").groupBy("month").agg(F.count("*").alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"))


def fn_array(spark, d):
    e = table(spark, d, "embeddings")
    dot = F.aggregate(F.transform("embedding", lambda x: x.cast("double") * x.cast("double")), F.lit(0.0), lambda a, x: a + x)
    return e.select("vec_id", F.round(F.sqrt(dot), 5).alias("norm"), F.size(F.filter("embedding", lambda x: x > 0)).cast("bigint").alias("positive"))


def fn_map(spark, d):
    counts = documents(spark, d).groupBy("source", "lang").agg(F.count("*").alias("n"))
    m = counts.groupBy("source").agg(F.map_from_entries(F.collect_list(F.struct("lang", "n"))).alias("m"))
    return m.select("source", F.coalesce(F.element_at("m", "en"), F.lit(0)).alias("en"), F.size(F.map_keys("m")).cast("bigint").alias("langs"))


def fn_json(spark, d):
    e = table(spark, d, "events")
    keys = F.json_object_keys("props")
    return e.select("event_id", F.size(keys).cast("bigint").alias("n_keys"), F.length(F.get_json_object("props", "$")).isNotNull().alias("valid"))


def udf_probability(spark, d):
    """The candidate curve and the similarity of sets as SQL functions, of the two halves of each document."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION lsh_probability(s DOUBLE, b INT, r INT) RETURNS DOUBLE RETURN 1 - power(1 - power(s, r), b)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION set_jaccard(x ARRAY<BIGINT>, y ARRAY<BIGINT>) RETURNS DOUBLE RETURN size(array_intersect(x, y)) / size(array_union(x, y))")
    spread_documents(spark, d).select("doc_id", text.halves("text").alias("h")).where(F.size("h.x") > 0).createOrReplaceTempView("udf_halves")
    return spark.sql("SELECT doc_id, round(lsh_probability(j, 50, 2), 9) AS p, j FROM (SELECT doc_id, set_jaccard(h.x, h.y) AS j FROM udf_halves)")


def udaf_signature(spark, d):
    """Signatures as an aggregate over grams: a minimum for each slot, combined before the shuffle."""
    from neardup.functions.hashing import LOW, PRIME, md5_number, portable_seeds

    x = _exploded(spark, d).select("doc_id", md5_number(F.col("gram")).alias("x"))
    mins = [F.min((F.lit(a) * F.shiftright("x", 30) + F.lit(b) * F.col("x").bitwiseAND(F.lit(LOW)) + F.lit(c)) % PRIME).alias(f"h{i}") for i, (a, b, c) in enumerate(portable_seeds(8, 42))]
    return x.groupBy("doc_id").agg(*mins)


def udtf_shingles(spark, d):
    """Word shingles by a table function, called from SQL."""
    from neardup.functions.tables import WordShingles

    ship_package(spark)
    spark.udtf.register("word_shingles", WordShingles)
    documents(spark, d).createOrReplaceTempView("udtf_docs")
    return spark.sql("SELECT d.doc_id, count(*) AS n_shingles FROM udtf_docs d, LATERAL word_shingles(d.text, 3) s GROUP BY d.doc_id")


def udtf_bands(spark, d):
    """Band rows of signatures by a table function."""
    from neardup.functions.tables import BandRows
    from neardup.operators.signature import signatures

    ship_package(spark)
    spark.udtf.register("band_rows", BandRows)
    materialize(signatures(documents(spark, d), PORTABLE), "signatures").createOrReplaceTempView("udtf_signatures")
    return spark.sql("SELECT s.doc_id, b.band_id, b.first FROM udtf_signatures s, LATERAL band_rows(s.sig, 2) b")


def source_synthetic(spark, d):
    """Each document and a near duplicate of it with one word changed; the changes come from the package's own data source."""
    from neardup.sources.synthetic import SyntheticChanges, id_runs

    ship_package(spark)
    spark.dataSource.register(SyntheticChanges)
    docs = documents(spark, d).select("doc_id", "text")
    changes = spark.read.format("synthetic_changes").option("runs", id_runs(docs)).option("partitions", str(2 * spark.sparkContext.defaultParallelism)).load()
    # The words are parted once for each row: a lambda that names them would part the text again for each of its words.
    changed = bound_once(F.split("text", " "), lambda ws: bound_once(F.pmod("doc_id", F.size(ws)).cast("int"), lambda at: F.array_join(F.concat(F.slice(ws, F.lit(1), at), F.array("word"), F.slice(ws, at + 2, F.size(ws))), " ")))
    both = docs.join(changes, "doc_id").select("doc_id", F.explode(F.array(F.struct(F.lit(0).alias("copy"), F.col("text").alias("text")), F.struct(F.lit(1).alias("copy"), changed.alias("text")))).alias("x"))
    return both.select("doc_id", "x.copy", "x.text")


def stream_tumbling(spark, d):
    from neardup.streaming.events import windowed

    return windowed(spark, d, "1 hour", None)


def stream_sliding(spark, d):
    from neardup.streaming.events import windowed

    return windowed(spark, d, "2 hours", "1 hour")


def stream_session(spark, d):
    from neardup.streaming.events import sessions

    return sessions(spark, d, "30 minutes")


def stream_dedup_events(spark, d):
    from neardup.streaming.events import deduplicated

    return deduplicated(spark, d)


def stream_state(spark, d):
    from neardup.streaming.events import user_state

    return user_state(spark, d)


def stream_dedup_watermark(spark, d):
    from neardup.streaming.events import once_within_watermark

    return once_within_watermark(spark, d)


def stream_late_rows(spark, d):
    from neardup.streaming.events import late_rows

    return late_rows(spark, d)


def scan_text(spark, d):
    """Documents written as lines of text and read back."""
    path = scratch_path(spark, "text")
    one_line = F.concat_ws("\t", F.col("doc_id").cast("string"), F.regexp_replace("text", "\n", " "))
    documents(spark, d).select(one_line.alias("value")).write.option("lineSep", "\n").text(path)
    rows = spark.read.option("lineSep", "\n").text(path).select(F.split("value", "\t", 2).alias("x"))
    return rows.select(F.col("x")[0].cast("bigint").alias("doc_id"), F.length(F.col("x")[1]).cast("bigint").alias("n_chars"))


def store_bucketed(spark, d):
    """Cells as a bucketed table: the join of its bands needs no exchange of either side."""
    name = f"cells_{abs(hash(scratch_path(spark, 'x')))}"
    path = scratch_path(spark, "bucketed")
    _bands(spark, d).write.bucketBy(8, "band_id", "value").sortBy("band_id", "value").option("path", path).saveAsTable(name)
    try:
        return materialize(candidates.banded(spark.table(name)), "bucketed-pairs")
    finally:
        spark.sql(f"DROP TABLE {name}")


def stream_neardup(spark, d):
    from neardup.streaming.neardup import stream_pairs

    return stream_pairs(spark, d, CFG)


def sink_partitioned(spark, d):
    """A clean corpus by language: what comes back from its folders."""
    from neardup.operators.exact import representatives

    path = scratch_path(spark, "corpus")
    documents(spark, d).join(representatives(documents(spark, d)).select("doc_id"), "doc_id", "left_semi").write.partitionBy("lang").parquet(path)
    return spark.read.parquet(path).groupBy("lang").agg(F.count("*").alias("n"), F.sum("n_chars").alias("chars"))


SQL_EVENTS = "SELECT event_id, user_id, ts, event_type, value FROM events"


def oracle_sql() -> dict[str, str]:
    from neardup.workloads import methods_sql as m

    kinds = "kd AS (SELECT event_type, row_number() OVER (ORDER BY event_type) AS k FROM (SELECT DISTINCT event_type FROM events))"
    return {
        "scan_documents": "SELECT doc_id, lang, n_chars FROM documents WHERE n_chars > 500",
        "scan_schema_check": "SELECT * FROM (VALUES ('doc_id'), ('text'), ('lang'), ('source'), ('n_chars')) x(name)",
        "scan_formats": "SELECT kind, count(*) AS n, sum(n_nationkey)::BIGINT AS keys FROM nation, (VALUES ('csv'), ('json'), ('orc')) x(kind) GROUP BY kind",
        "filter_documents": "SELECT doc_id, source FROM documents WHERE lang IN ('en', 'de') AND n_chars BETWEEN 100 AND 2000 AND source NOT LIKE 'src1%' AND lang IS NOT DISTINCT FROM 'en'",
        "join_broadcast_labels": "SELECT lang, quality, toxic, count(*) AS n FROM documents JOIN labels USING (doc_id) GROUP BY ALL",
        "join_band_equi": f"{m.BANDS_SQL} SELECT x.band_id, count(*) AS pairs FROM bd x JOIN bd y ON x.band_id = y.band_id AND x.value = y.value AND x.doc_id < y.doc_id GROUP BY x.band_id",
        "join_pairs_theta": "SELECT x.p_partkey AS a, y.p_partkey AS b FROM part x JOIN part y ON x.p_brand = y.p_brand AND x.p_size = y.p_size AND x.p_partkey < y.p_partkey AND y.p_retailprice BETWEEN x.p_retailprice * 0.999::DOUBLE AND x.p_retailprice * 1.001::DOUBLE",
        "join_missed_anti": "SELECT doc_id FROM documents WHERE NOT EXISTS (SELECT 1 FROM labels WHERE labels.doc_id = documents.doc_id)",
        "join_kept_semi": "SELECT doc_id, lang FROM documents WHERE EXISTS (SELECT 1 FROM labels WHERE labels.doc_id = documents.doc_id AND quality = 1)",
        "join_outer_labels": "SELECT source, count(*) AS n, count(quality) AS labelled FROM documents FULL JOIN labels USING (doc_id) GROUP BY source",
        "join_asof_events": f"WITH {kinds}, l AS (SELECT event_id, user_id, ts FROM events WHERE event_type = (SELECT event_type FROM kd WHERE k = 1)), r AS (SELECT user_id, ts, max(value) AS value FROM events WHERE event_type = (SELECT event_type FROM kd WHERE k = 2) GROUP BY user_id, ts) SELECT event_id, r.value AS last_value FROM l ASOF LEFT JOIN r ON l.user_id = r.user_id AND l.ts >= r.ts",
        "join_interval_events": "SELECT x.event_id AS a, y.event_id AS b FROM events x JOIN events y ON x.user_id = y.user_id AND y.ts >= x.ts AND y.ts <= x.ts + INTERVAL 10 MINUTES AND x.event_id <> y.event_id",
        "agg_lang_source_cube": "SELECT lang, source, count(*) AS n, sum(n_chars)::BIGINT AS chars FROM documents GROUP BY CUBE (lang, source)",
        "agg_rollup_orders": "SELECT o_orderpriority, o_orderstatus, count(*) AS n FROM orders GROUP BY ROLLUP (o_orderpriority, o_orderstatus)",
        "agg_grouping_sets": "SELECT lang, source, count(*) AS n FROM documents GROUP BY GROUPING SETS ((lang), (source), ()) HAVING count(*) > 10",
        "agg_distinct_grams": f"WITH {m.grams()} SELECT lang, count(DISTINCT gram) AS grams FROM g JOIN documents USING (doc_id) GROUP BY lang",
        "agg_approx_grams": "SELECT true AS close",
        "window_representative": "SELECT doc_id, source, lang, rank FROM (SELECT *, row_number() OVER (PARTITION BY source, lang ORDER BY n_chars DESC, doc_id) AS rank FROM documents) WHERE rank <= 3",
        "window_runs": "SELECT event_id, lag(event_id) OVER w AS before, lead(event_id) OVER w AS after FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)",
        "window_running_min": "SELECT o_orderkey, min(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS UNBOUNDED PRECEDING) AS low, max(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS 2 PRECEDING) AS high3 FROM orders",
        "topk_pairs": f"{m.pairs()} SELECT a, b, jaccard FROM p ORDER BY jaccard DESC, a, b LIMIT 50",
        "topk_per_doc": f"{m.pairs()}, rk AS (SELECT a, b, row_number() OVER (PARTITION BY a ORDER BY jaccard DESC, b) AS rank FROM p WHERE jaccard > 0.2) SELECT * FROM rk WHERE rank <= 2",
        "largest_clusters": "SELECT min(doc_id) AS rep, count(*) AS size FROM documents WHERE text IS NOT NULL GROUP BY text HAVING count(*) > 1 ORDER BY size DESC, rep LIMIT 10",
        "set_union_bands": m.CANDIDATES_SQL,
        "set_methods_intersect": f"{m.FULL} SELECT a, b FROM cand INTERSECT SELECT a, b FROM p WHERE jaccard > 0.4",
        "set_methods_except": f"{m.FULL} SELECT a, b FROM p WHERE jaccard > 0.2 EXCEPT ALL SELECT a, b FROM cand",
        "fn_string": "SELECT doc_id, upper(lang) AS up, regexp_extract(source, '([0-9]+)', 1) AS no, md5(text) AS md5, substring(text, 1, 12) AS head, length(regexp_replace(text, '[aeiou]', '', 'g')) AS no_vowels FROM documents",
        "fn_math": "SELECT o_orderkey, round(sqrt(o_totalprice), 6) AS root, round(pow(o_totalprice / 1000, 2), 6) AS square, o_custkey % 7 AS rest FROM orders",
        "fn_date": "SELECT strftime(date_trunc('month', o_orderdate), '%Y-%m') AS month, count(*) AS n, round(sum(o_totalprice), 2) AS total FROM orders GROUP BY 1",
        "fn_array": "SELECT vec_id, round(sqrt(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE))), 5) AS norm, len(list_filter(embedding, lambda x: x > 0)) AS positive FROM embeddings",
        "fn_map": "SELECT source, count(*) FILTER (WHERE lang = 'en') AS en, count(DISTINCT lang) AS langs FROM documents GROUP BY source",
        "fn_json": "SELECT event_id, len(json_keys(props))::BIGINT AS n_keys, json_valid(props) AS valid FROM events",
        "udf_probability": f"SELECT doc_id, round(1 - pow(1 - pow(j, 2), 50), 9) AS p, j FROM {m.halves()}",
        "udaf_signature": f"WITH {m.grams()}, {m.signature(8)} SELECT doc_id, " + ", ".join(f"max(h) FILTER (WHERE slot = {i}) AS h{i}" for i in range(8)) + " FROM sig GROUP BY doc_id",
        "udtf_shingles": f"WITH {m.grams(3)} SELECT doc_id, count(*) AS n_shingles FROM g GROUP BY doc_id",
        "udtf_bands": f"WITH {m.grams()}, {m.signature(40)} SELECT doc_id, (slot // 2)::INTEGER AS band_id, h AS first FROM sig WHERE slot % 2 = 0",
        "stream_tumbling": "SELECT strftime(time_bucket(INTERVAL 1 HOUR, ts), '%Y-%m-%d %H:%M:%S') AS start, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY 1, 2",
        "stream_sliding": "SELECT strftime(s, '%Y-%m-%d %H:%M:%S') AS start, event_type, count(*) AS n, round(sum(value), 4) AS total FROM (SELECT time_bucket(INTERVAL 1 HOUR, ts) - INTERVAL 1 HOUR * k AS s, event_type, value FROM events, (VALUES (0), (1)) x(k)) GROUP BY 1, 2",
        "stream_session": "WITH o AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 30 MINUTES THEN 0 ELSE 1 END AS new FROM events), s AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM o) SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM s GROUP BY user_id, k",
        "stream_dedup_events": "SELECT user_id, event_type, count(DISTINCT date_trunc('minute', ts)) AS n FROM events GROUP BY ALL",
        "stream_state": "SELECT user_id, count(*) AS n, max(value) AS high FROM events WHERE value IS NOT NULL GROUP BY user_id",
        "stream_dedup_watermark": "SELECT count(DISTINCT event_id) AS kept, count(DISTINCT event_id) AS distinct_events FROM events",
        "source_synthetic": "SELECT doc_id, copy, CASE WHEN copy = 0 THEN text ELSE array_to_string(list_transform(string_split(text, ' '), lambda w, i: CASE WHEN i - 1 = doc_id % len(string_split(text, ' ')) THEN 'x' || substr(md5('change:' || doc_id), 1, 6) ELSE w END), ' ') END AS text FROM documents, (VALUES (0), (1)) x(copy)",
        "scan_text": "SELECT doc_id, length(text) AS n_chars FROM documents",
        "stream_late_rows": "WITH m AS (SELECT (min(epoch_us(ts)) + max(epoch_us(ts))) / 2 AS half, max(epoch_us(ts)) // 1000 - 600000 AS mark FROM events) SELECT count(*) AS rows, count(*) FILTER (WHERE epoch_us(ts) < half AND epoch_us(ts) // 1000 <= mark) AS late FROM events, m",
        "store_bucketed": m.CANDIDATES_SQL,
        "stream_neardup": m.NEAR_SQL,
        "sink_partitioned": "SELECT lang, count(*) AS n, sum(n_chars)::BIGINT AS chars FROM documents WHERE doc_id IN (SELECT min(doc_id) FROM documents GROUP BY text) GROUP BY lang",
    }
