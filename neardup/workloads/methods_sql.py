"""DuckDB SQL with the rows of the queries in methods.py."""

from __future__ import annotations

from neardup.functions.hashing import LOW, PRIME, portable_seeds
from neardup.functions.text import LIGHT_ENDINGS
from neardup.workloads.methods import GRID, PORTABLE, TRUTH

SPLIT = r"[^\p{L}\p{N}]+"


def words(table: str = "documents", key: str = "doc_id", text: str = "text") -> str:
    return f"SELECT {key} AS doc_id, list_filter(regexp_split_to_array(lower(coalesce({text}, '')), '{SPLIT}'), lambda x: x <> '') AS ws FROM {table}"


def halves() -> str:
    """(doc_id, j): similarity of the distinct words of both halves of each text of two words or more."""
    parts = "list_distinct(ws[1:len(ws) // 2]) AS x, list_distinct(ws[len(ws) // 2 + 1:]) AS y"
    return f"(SELECT doc_id, len(list_intersect(x, y)) / (len(x) + len(y) - len(list_intersect(x, y)))::DOUBLE AS j FROM (SELECT doc_id, {parts} FROM ({words()}) WHERE len(ws) > 1))"


def gram_list(n: int = 8, ws: str = "ws") -> str:
    return f"CASE WHEN len({ws}) >= {n} THEN list_distinct(list_transform(range(1, len({ws}) - {n} + 2), lambda i: array_to_string({ws}[i:i + {n} - 1], ' '))) WHEN len({ws}) > 0 THEN [array_to_string({ws}, ' ')] ELSE []::VARCHAR[] END"


def grams(n: int = 8, table: str = "documents", key: str = "doc_id", text: str = "text") -> str:
    return f"w AS MATERIALIZED ({words(table, key, text)}), g AS MATERIALIZED (SELECT doc_id, unnest({gram_list(n)}) AS gram FROM w)"


PAIRS = """sz AS (SELECT doc_id, count(*) AS n FROM g GROUP BY doc_id),
cm AS (SELECT gram FROM g GROUP BY gram HAVING count(*) > 1), gc AS MATERIALIZED (SELECT g.* FROM g JOIN cm ON cm.gram = g.gram),
sh AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS shared FROM gc x JOIN gc y ON x.gram = y.gram AND x.doc_id < y.doc_id GROUP BY 1, 2),
p AS MATERIALIZED (SELECT a, b, shared, shared / (x.n + y.n - shared)::DOUBLE AS jaccard FROM sh JOIN sz x ON x.doc_id = a JOIN sz y ON y.doc_id = b)"""


def pairs(n: int = 8, *rest: str, **kw: str) -> str:
    return "WITH RECURSIVE " + ", ".join([grams(n, **kw), PAIRS, *rest])


def md5_number(x: str) -> str:
    return f"('0x' || substr(md5({x}), 1, 15))::BIGINT"


def signature(m: int) -> str:
    """sig(doc_id, slot, h) of the portable family."""
    rows = ", ".join(f"({i}, {a}, {b}, {c})" for i, (a, b, c) in enumerate(portable_seeds(m, PORTABLE.seed)))
    return f"sd(slot, a1, a0, c) AS (VALUES {rows}), num AS MATERIALIZED (SELECT DISTINCT doc_id, {md5_number('gram')} AS x FROM g), sig AS MATERIALIZED (SELECT doc_id, slot::BIGINT AS slot, min((a1::BIGINT * (x >> 30) + a0::BIGINT * (x & {LOW}) + c) % {PRIME})::BIGINT AS h FROM num, sd GROUP BY ALL)"


def bands(b: int = 20, r: int = 2) -> str:
    joined = "string_agg(h::VARCHAR, ',' ORDER BY slot)"
    return f"{signature(b * r)}, bd AS MATERIALIZED (SELECT doc_id, slot // {r} AS band_id, {md5_number(joined)} AS value FROM sig GROUP BY 1, 2)"


CAND = "cand AS MATERIALIZED (SELECT DISTINCT x.doc_id AS a, y.doc_id AS b FROM bd x JOIN bd y ON x.band_id = y.band_id AND x.value = y.value AND x.doc_id < y.doc_id)"
BANDS_SQL = f"WITH {grams()}, {bands()}"
CANDIDATES_SQL = f"{BANDS_SQL}, {CAND} SELECT a, b FROM cand"
ANY_SQL = f"WITH {grams()}, {signature(20)} SELECT DISTINCT x.doc_id AS a, y.doc_id AS b FROM sig x JOIN sig y ON x.slot = y.slot AND x.h = y.h AND x.doc_id < y.doc_id"
NEAR_SQL = f"{pairs()} SELECT a, b, jaccard FROM p WHERE jaccard > 0.75"
GRAM_DIGEST = "SELECT doc_id, count(gram) AS n_grams, md5(coalesce(string_agg(gram, chr(10) ORDER BY gram), '')) AS grams_md5 FROM (SELECT w.doc_id, g.gram FROM w LEFT JOIN g ON g.doc_id = w.doc_id) GROUP BY doc_id"
GROUPS = "grp AS MATERIALIZED (SELECT doc_id, min(doc_id) OVER (PARTITION BY text) AS cluster_id FROM documents WHERE text IS NOT NULL)"
GRID_ROWS = ", ".join(f"({b}, {r})" for b, r in GRID)
TRUTH_ROWS = ", ".join(f"({t})" for t in TRUTH)
EXPECTED = f"cfg AS (SELECT t::DOUBLE AS t, b, r FROM (VALUES {TRUTH_ROWS}) x(t), (VALUES {GRID_ROWS}) y(b, r)), ex AS (SELECT t, b, r, round(sum(q), 6) AS candidates, round(sum(CASE WHEN jaccard > t THEN 0.0 ELSE q END), 6) AS false_candidates, round(sum(CASE WHEN jaccard > t THEN 1 - q ELSE 0.0 END), 6) AS misses FROM (SELECT t, cfg.b AS b, r, jaccard, 1 - pow(1 - pow(jaccard, r), cfg.b) AS q FROM p, cfg) GROUP BY t, b, r)"
COMPONENTS = "e AS MATERIALIZED (SELECT a, b FROM p WHERE jaccard > 0.75), ee AS MATERIALIZED (SELECT a, b FROM e UNION SELECT b, a FROM e), cc AS (SELECT a AS id, a AS low FROM ee UNION SELECT ee.b, cc.low FROM cc JOIN ee ON ee.a = cc.id WHERE cc.low < ee.b)"
TRUTH2 = "tr AS (SELECT a, b, jaccard FROM p WHERE jaccard > 0.2)"
TRUTH4 = "tr AS (SELECT a, b, jaccard FROM p WHERE jaccard > 0.4)"
FULL = f"{pairs()}, {bands()}, {CAND}"


TEXTS = "(SELECT min(doc_id) AS doc_id, text FROM documents WHERE text IS NOT NULL GROUP BY text)"
BUCKETS = "SELECT row_number() OVER (ORDER BY band_id, value::VARCHAR) AS k, list(doc_id ORDER BY doc_id) AS m FROM bd GROUP BY band_id, value HAVING count(*) > 1"


def folded(buckets: str, edge: float | None, tree: float) -> str:
    """mem(doc_id, root, bound): the bounded forest as a recursion over the state of one sequential run.

    buckets has rows (k, m), k from 1 on without gaps. Each step takes the next pair of roots of the open bucket, or opens the next one: its
    pairs are those of its members' roots above edge, in order; without edge m is one pair, taken as it stands. The state maps each
    document to its root, rank and bound; similarities come from p.
    """
    if edge is None:
        pairs = "CASE WHEN rs[1] <> rs[2] THEN [{'x': rs[1], 'y': rs[2]}] ELSE [] END"
        roots = "list_transform(m, lambda z: root[z])"
    else:
        pairs = f"list_filter(flatten(list_transform(rs, lambda x, i: list_transform(rs[i + 1:], lambda y: {{'x': x, 'y': y}}))), lambda q: coalesce(sm[q.x::VARCHAR || '-' || q.y::VARCHAR], 0.0) > {edge})"
        roots = "list_sort(list_distinct(list_transform(m, lambda z: root[z])))"
    return f"""sims AS MATERIALIZED (SELECT coalesce(map_from_entries(list({{'k': a::VARCHAR || '-' || b::VARCHAR, 'v': jaccard}})), MAP {{}}::MAP(VARCHAR, DOUBLE)) AS sm FROM p),
bk AS MATERIALIZED ({buckets}),
ids AS (SELECT DISTINCT unnest(m) AS d FROM bk),
fold AS (SELECT 0::BIGINT AS k, []::STRUCT(x BIGINT, y BIGINT)[] AS todo, map_from_entries(list({{'k': d, 'v': d}})) AS root, map_from_entries(list({{'k': d, 'v': 0}})) AS rk, map_from_entries(list({{'k': d, 'v': 1.0::DOUBLE}})) AS bnd FROM ids HAVING count(*) > 0 UNION ALL
 SELECT nk, CASE WHEN opens THEN ntodo ELSE todo[2:] END,
  CASE WHEN ok THEN map_from_entries(list_transform(map_entries(root), lambda e: {{'k': e.key, 'v': CASE WHEN e.value = under THEN top ELSE e.value END}})) ELSE root END,
  CASE WHEN ok THEN map_concat(rk, map([top], [CASE WHEN rk[top] = rk[under] THEN rk[top] + 1 ELSE rk[top] END])) ELSE rk END,
  CASE WHEN ok THEN map_concat(bnd, map([top], [least(bnd[top], bnd[under] - (1 - s))])) ELSE bnd END
 FROM (SELECT *, NOT opens AND rx <> ry AND bnd[rx] + bnd[ry] + s - 2 >= {tree} - 1e-12 AS ok, CASE WHEN rk[rx] >= rk[ry] THEN rx ELSE ry END AS top, CASE WHEN rk[rx] >= rk[ry] THEN ry ELSE rx END AS under
  FROM (SELECT *, CASE WHEN opens THEN {pairs} END AS ntodo, coalesce(sm[least(rx, ry)::VARCHAR || '-' || greatest(rx, ry)::VARCHAR], 0.0) AS s
   FROM (SELECT fold.*, len(todo) = 0 AS opens, CASE WHEN len(todo) = 0 THEN bk.k ELSE fold.k END AS nk, CASE WHEN len(todo) = 0 THEN {roots} END AS rs, root[todo[1].x] AS rx, root[todo[1].y] AS ry
    FROM fold LEFT JOIN bk ON bk.k = fold.k + 1 WHERE len(todo) > 0 OR bk.k IS NOT NULL), sims))),
fin AS (SELECT * FROM fold WHERE len(todo) = 0 ORDER BY k DESC LIMIT 1),
mem AS MATERIALIZED (SELECT e.key AS doc_id, e.value AS root, bnd[e.value] AS bound FROM (SELECT unnest(map_entries(root)) AS e, bnd FROM fin))"""


def clustered(edge: float = 0.75, tree: float = 0.40) -> str:
    """cl(doc_id, cluster_id, root, bound) of all documents: one for each text is clustered by 50 portable bands of two rows, copies join it."""
    texts = "tx AS (SELECT doc_id, min(doc_id) OVER (PARTITION BY text) AS rep FROM documents WHERE text IS NOT NULL)"
    named = "nm AS (SELECT tx.doc_id, coalesce(mem.root, rep) AS root, coalesce(mem.bound, 1.0) AS bound FROM tx LEFT JOIN mem ON mem.doc_id = rep UNION ALL SELECT doc_id, doc_id, 1.0 FROM documents WHERE text IS NULL), cl AS MATERIALIZED (SELECT doc_id, min(doc_id) OVER (PARTITION BY root) AS cluster_id, root, bound FROM nm)"
    return f"{pairs(table=TEXTS)}, {bands(50)}, {folded(BUCKETS, edge, tree)}, {texts}, {named}"


STATS = "SELECT count(*) FILTER (WHERE n > 1) AS clusters, coalesce(max(n) FILTER (WHERE n > 1), 0) AS largest, count(*) FILTER (WHERE n = 1) AS singles, coalesce(sum(n) FILTER (WHERE n > 1), 0)::BIGINT AS clustered FROM (SELECT count(*) AS n FROM cl GROUP BY cluster_id)"


def measured(r: int, bs: str, of: str = "bd") -> str:
    """Rows of the measured grid for bands of r rows; p has the true pairs, of the bands."""
    first = f"SELECT x.doc_id AS a, y.doc_id AS b, min(x.band_id) AS first FROM {of} x JOIN {of} y ON x.band_id = y.band_id AND x.value = y.value AND x.doc_id < y.doc_id GROUP BY 1, 2"
    return f"SELECT t::DOUBLE AS t, n AS b, {r} AS r, count(*) FILTER (WHERE first < n) AS candidates, count(*) FILTER (WHERE first < n AND jaccard <= t) AS false_candidates, count(*) FILTER (WHERE jaccard > t AND NOT coalesce(first < n, false)) AS misses FROM (SELECT first, coalesce(jaccard, 0.0) AS jaccard FROM ({first}) fb FULL JOIN (SELECT * FROM p WHERE jaccard > 0.2) q ON q.a = fb.a AND q.b = fb.b), (VALUES {TRUTH_ROWS}) x(t), (VALUES {bs}) y(n) GROUP BY t, n"


def injected(copies: int, lo: float, spread: float) -> str:
    """The documents and their changed copies, (doc_id, text), as synth.inject() makes them."""
    return f"(WITH r AS (SELECT doc_id, text, row_number() OVER (ORDER BY doc_id) - 1 AS rank FROM documents), n AS (SELECT count(*) AS n, max(doc_id) AS top FROM documents), k AS (SELECT id, floor({_draw('42', chr(39) + 'source' + chr(39), 'id')} * n)::BIGINT AS rank, {lo} + {spread}::DOUBLE * {_draw('42', chr(39) + 'rate' + chr(39), 'id')} AS rate, top FROM range(0, {copies}) x(id), n), m AS (SELECT id, top + 1 + id AS doc_id, rate, string_split(text, ' ') AS ws FROM k JOIN r ON r.rank = k.rank) SELECT doc_id, array_to_string(list_transform(ws, lambda w, i: CASE WHEN {_draw('42', 'id', 'i - 1')} < rate THEN 'x' || substr(md5('w|' || id || '|' || (i - 1)), 1, 6) ELSE w END), ' ') AS text FROM m UNION ALL SELECT doc_id, text FROM documents)"


def _draw(*parts: str) -> str:
    joined = " || '|' || ".join(f"({p})::VARCHAR" for p in parts)
    return f"({md5_number(joined)} / 1152921504606846976.0::DOUBLE)"


def oracle_sql() -> dict[str, str]:
    light = "|".join(LIGHT_ENDINGS)
    out = {
        "tokens_count": f"SELECT doc_id, len(ws)::BIGINT AS n_words FROM ({words()})",
        "word_ngrams": f"WITH {grams()} {GRAM_DIGEST}",
        "char_shingles": "WITH t AS (SELECT doc_id, coalesce(text, '') AS t FROM documents), s AS (SELECT doc_id, unnest(CASE WHEN length(t) >= 4 THEN list_distinct(list_transform(range(1, length(t) - 2), lambda i: substring(t, i, 4))) WHEN length(t) > 0 THEN [t] ELSE []::VARCHAR[] END) AS s FROM t) SELECT t.doc_id, count(s) AS n_shingles, md5(coalesce(string_agg(s, chr(10) ORDER BY s), '')) AS shingles_md5 FROM t LEFT JOIN s ON s.doc_id = t.doc_id GROUP BY t.doc_id",
        "gram_multiplicity": f"WITH w AS ({words()}) SELECT doc_id, greatest(len(ws) - 7, least(len(ws), 1))::BIGINT AS n_grams, len({gram_list()})::BIGINT AS n_distinct FROM w",
        "short_documents": f"SELECT doc_id, len(ws)::BIGINT AS n_words, least(len(ws), 1)::BIGINT AS grams_whole, 0::BIGINT AS grams_drop, least(len(ws), 1)::BIGINT AS grams_pad FROM ({words()}) WHERE len(ws) < 8",
        "stem_light_ngrams": f"WITH w0 AS ({words()}), w AS MATERIALIZED (SELECT doc_id, list_transform(ws, lambda x: regexp_replace(x, '^(.{{3,}}?)({light})$', '\\1')) AS ws FROM w0), g AS MATERIALIZED (SELECT doc_id, unnest({gram_list(3)}) AS gram FROM w) {GRAM_DIGEST}",
        "gram_dictionary": f"WITH {grams()} SELECT count(DISTINCT gram) AS grams, 0::BIGINT AS low, count(DISTINCT gram) - 1 AS high, count(DISTINCT gram) AS ids FROM g",
        "hash_collisions": f"WITH {grams()}, x AS (SELECT gram, {md5_number('gram')} AS x FROM g) SELECT count(DISTINCT gram) AS grams, count(DISTINCT gram) AS ids64, count(DISTINCT x) AS ids60, count(DISTINCT x % 4294967296) AS ids32, count(DISTINCT x % 1048576) AS ids20 FROM x",
        "ngram_length": " UNION ALL ".join(f"SELECT * FROM ({pairs(n)} SELECT {n} AS n, count(*) AS pairs FROM p WHERE jaccard > 0.75)" for n in (1, 2, 3, 5, 8, 12)),
        "exact_pairs_prefix": f"{pairs()} SELECT a, b, shared, jaccard FROM p WHERE jaccard > 0.2",
        "bounded_clusters_075": f"{clustered()} SELECT doc_id, cluster_id, bound FROM cl",
        "corpus_clusters": f"{clustered()} {STATS}",
        "recluster_090": f"{clustered(0.90)} {STATS}",
        "dedup_keep_root": f"{clustered()} SELECT documents.doc_id, n_chars FROM documents JOIN cl ON cl.doc_id = documents.doc_id AND cl.root = cl.doc_id",
        "mst_clusters": f"{pairs()}, {folded('SELECT row_number() OVER (ORDER BY jaccard DESC, a, b) AS k, [a, b] AS m FROM p WHERE jaccard > 0.75', None, 0.40)} SELECT doc_id, root, bound FROM mem",
        "second_round_bounded": f"{pairs()}, {GROUPS}, sz2 AS (SELECT cluster_id, count(*) AS n FROM grp GROUP BY cluster_id), cx AS (SELECT least(x.cluster_id, y.cluster_id) AS x, greatest(x.cluster_id, y.cluster_id) AS y, min(jaccard) AS low, count(*) AS pairs FROM p JOIN grp x ON x.doc_id = a JOIN grp y ON y.doc_id = b WHERE jaccard > 0.2 AND x.cluster_id <> y.cluster_id GROUP BY 1, 2), fu AS (SELECT x, y FROM cx JOIN sz2 u ON u.cluster_id = x JOIN sz2 v ON v.cluster_id = y WHERE pairs = u.n * v.n AND low >= 0.75), pk AS (SELECT x, min(y) AS y FROM fu GROUP BY x), mg AS (SELECT min(x) AS x, y FROM pk GROUP BY y), ok AS (SELECT x, y FROM mg WHERE x NOT IN (SELECT y FROM mg)) SELECT doc_id, coalesce(ok.x, cluster_id) AS cluster_id FROM grp LEFT JOIN ok ON ok.y = cluster_id",
        "accuracy_rows_of_bands": f"{pairs(table=injected(10, 0.1, 0.0))}, {signature(100)}, " + ", ".join(f"bd{r} AS MATERIALIZED (SELECT doc_id, slot // {r} AS band_id, " + md5_number("string_agg(h::VARCHAR, ',' ORDER BY slot)") + f" AS value FROM sig WHERE slot < {20 * r} GROUP BY 1, 2)" for r in (1, 2, 3, 4, 5)) + " " + " UNION ALL ".join(measured(r, "(5), (10), (15), (20)", f"bd{r}") for r in (1, 2, 3, 4, 5)),
        "exact_pairs_all": f"{pairs()} SELECT a, b, jaccard FROM p WHERE jaccard > 0.2",
        "exact_pairs_shared": f"{pairs()} SELECT a, b, shared, jaccard FROM p WHERE jaccard > 0.2",
        "jaccard_distance": f"{pairs()} SELECT a, b, 1 - jaccard AS distance FROM p",
        "exact_clusters_text": "SELECT min(doc_id) AS rep, count(*) AS size FROM documents WHERE text IS NOT NULL GROUP BY text HAVING count(*) > 1",
        "exact_clusters_grams": f"WITH {grams()}, k AS (SELECT doc_id, md5(string_agg(gram, chr(10) ORDER BY gram)) AS k FROM g GROUP BY doc_id) SELECT min(doc_id) AS rep, count(*) AS size FROM k GROUP BY k HAVING count(*) > 1",
        "signature_portable": f"WITH {grams()}, {signature(40)} SELECT doc_id, slot, h FROM sig",
        "signature_estimate": f"{pairs()}, {signature(40)} SELECT a, b, any_value(jaccard) AS jaccard, count(*) FILTER (WHERE x.h = y.h) / 40.0::DOUBLE AS estimate FROM p JOIN sig x ON x.doc_id = a JOIN sig y ON y.doc_id = b AND y.slot = x.slot WHERE jaccard > 0.2 GROUP BY a, b",
        "estimate_error": f"{pairs()}, {signature(40)}, es AS (SELECT a, b, any_value(jaccard) AS j, count(*) FILTER (WHERE x.h = y.h) / 40.0::DOUBLE AS e FROM p JOIN sig x ON x.doc_id = a JOIN sig y ON y.doc_id = b AND y.slot = x.slot WHERE jaccard > 0.2 GROUP BY a, b) SELECT count(*) AS pairs, round(avg(abs(e - j)), 6) AS mean_error, round(max(abs(e - j)), 6) AS max_error FROM es",
        "minhash_permutation": f"WITH {grams()}, o AS (SELECT gram, slot, row_number() OVER (PARTITION BY slot ORDER BY md5('42:' || slot || ':' || gram)) AS h FROM (SELECT DISTINCT gram FROM g), (SELECT unnest(range(0, 3))::INTEGER AS slot)) SELECT doc_id, slot, min(h) AS h FROM g JOIN o ON o.gram = g.gram GROUP BY doc_id, slot",
        "bands_portable": f"{BANDS_SQL} SELECT doc_id, band_id, value FROM bd",
        "bands_uncompressed": CANDIDATES_SQL,
        "candidates_banded": CANDIDATES_SQL,
        "candidates_by_band": CANDIDATES_SQL,
        "candidates_inverted": ANY_SQL,
        "candidates_sorted": ANY_SQL,
        "cells_layout": f"{BANDS_SQL} SELECT doc_id, band_id, value FROM bd",
        "packed_layout": f"{BANDS_SQL} SELECT doc_id, band_id, value FROM bd",
        "store_read_one_band": f"{BANDS_SQL} SELECT DISTINCT x.doc_id AS a, y.doc_id AS b FROM bd x JOIN bd y ON x.band_id = 3 AND y.band_id = 3 AND x.value = y.value AND x.doc_id < y.doc_id",
        "store_operations": f"WITH {grams()}, n AS (SELECT count(DISTINCT doc_id) AS n FROM g) SELECT n * 20 AS cells, 200::BIGINT AS packed, n * 20 AS model_cells, 200::BIGINT AS model_packed FROM n",
        "near_duplicates_075": NEAR_SQL,
        "near_duplicates_cells": NEAR_SQL,
        "near_duplicates_packed": NEAR_SQL,
        "near_duplicates_mm32": NEAR_SQL,
        "near_duplicates_rewritten": NEAR_SQL,
        "sql_pairs": f"{pairs()} SELECT a, b, x.lang AS lang_a, y.lang AS lang_b FROM p JOIN documents x ON x.doc_id = a JOIN documents y ON y.doc_id = b WHERE jaccard > 0.75",
        "lsh_curve": f"SELECT s, b, r, documents, round(pow(s, r), 9) AS band_agrees, round(1 - pow(s, r), 9) AS band_differs, round(pow(1 - pow(s, r), b), 9) AS all_differ, round(1 - pow(1 - pow(s, r), b), 9) AS candidate FROM (SELECT floor(j * 20 + 0.5) / 20 AS s, count(*) AS documents FROM {halves()} GROUP BY 1), (VALUES {GRID_ROWS}) y(b, r)",
        "expected_candidates": f"{pairs()}, {EXPECTED} SELECT * FROM ex",
        "choose_bands": f"{pairs()}, {EXPECTED}, rk AS (SELECT *, row_number() OVER (PARTITION BY t ORDER BY b * r, false_candidates, b) AS k FROM ex WHERE misses <= 0.05) SELECT t, b, r, misses, false_candidates FROM rk WHERE k = 1",
        "accuracy_grid": f"{FULL}, fb AS (SELECT x.doc_id AS a, y.doc_id AS b, min(x.band_id) AS first FROM bd x JOIN bd y ON x.band_id = y.band_id AND x.value = y.value AND x.doc_id < y.doc_id GROUP BY 1, 2), al AS (SELECT coalesce(fb.a, q.a) AS a, first, coalesce(jaccard, 0.0) AS jaccard FROM fb FULL JOIN (SELECT * FROM p WHERE jaccard > 0.2) q ON q.a = fb.a AND q.b = fb.b) SELECT t::DOUBLE AS t, n AS b, 2 AS r, count(*) FILTER (WHERE first < n) AS candidates, count(*) FILTER (WHERE first < n AND jaccard <= t) AS false_candidates, count(*) FILTER (WHERE jaccard > t AND NOT coalesce(first < n, false)) AS misses FROM al, (VALUES {TRUTH_ROWS}) x(t), (VALUES (5), (10), (15), (20)) y(n) GROUP BY t, n",
        "recall_grid": f"{FULL}, {TRUTH4} SELECT count(*) AS true_pairs, count(cand.a) AS found_pairs, round(count(cand.a) / count(*)::DOUBLE, 6) AS recall FROM tr LEFT JOIN cand ON cand.a = tr.a AND cand.b = tr.b",
        "false_candidates": f"{FULL}, {TRUTH4} SELECT a, b FROM cand WHERE NOT EXISTS (SELECT 1 FROM tr WHERE tr.a = cand.a AND tr.b = cand.b)",
        "false_negatives": f"{FULL}, {TRUTH2} SELECT a, b, jaccard FROM tr WHERE NOT EXISTS (SELECT 1 FROM cand WHERE tr.a = cand.a AND tr.b = cand.b)",
        "candidate_ratio": f"{BANDS_SQL}, {CAND}, n AS (SELECT count(*) AS n FROM documents) SELECT (SELECT count(*) FROM cand) AS candidates, n * (n - 1) // 2 AS all_pairs, (SELECT count(*) FROM cand) / greatest(1, n * (n - 1) // 2)::DOUBLE AS ratio FROM n",
        "trend_violations": "SELECT 0::BIGINT AS violations",
        "triangle_violations": "SELECT 0::BIGINT AS violations",
        "path_bound": f"{pairs()}, e AS MATERIALIZED (SELECT a, b, jaccard FROM p WHERE jaccard > 0.5) SELECT x.a AS a, x.b AS b, y.b AS c, z.b AS d, round(1.0 - (1 - x.jaccard) - (1 - y.jaccard) - (1 - z.jaccard), 9) AS bound FROM e x JOIN e y ON x.b = y.a JOIN e z ON y.b = z.a",
        "components_075": f"{pairs(8, COMPONENTS)} SELECT id AS doc_id, min(low) AS component FROM cc GROUP BY id",
        "cluster_bound_violations": "SELECT 0::BIGINT AS low_pairs, 0::BIGINT AS root_violations",
        "cluster_rounds_violations": "SELECT 0::BIGINT AS low_pairs, 0::BIGINT AS root_violations",
        "modularity_exact": f"{pairs()}, {GROUPS}, e AS (SELECT jaccard AS j, x.cluster_id AS x, y.cluster_id AS y FROM p JOIN grp x ON x.doc_id = a JOIN grp y ON y.doc_id = b WHERE jaccard > 0.2), m AS (SELECT 2 * sum(j) AS m2 FROM e), dg AS (SELECT c, sum(j) AS d FROM (SELECT x AS c, j FROM e UNION ALL SELECT y, j FROM e) GROUP BY c), ins AS (SELECT x AS c, sum(j) AS i FROM e WHERE x = y GROUP BY x) SELECT round(sum(2 * coalesce(i, 0) / m2 - pow(d / m2, 2)), 6) AS modularity FROM dg LEFT JOIN ins ON ins.c = dg.c, m",
        "size_histogram": f"WITH {GROUPS} SELECT size, count(*) AS clusters FROM (SELECT cluster_id, count(*) AS size FROM grp GROUP BY cluster_id) GROUP BY size",
        "cross_edges": f"{pairs()}, {GROUPS} SELECT a, b, jaccard, x.cluster_id AS x, y.cluster_id AS y FROM p JOIN grp x ON x.doc_id = a JOIN grp y ON y.doc_id = b WHERE jaccard > 0.75 AND x.cluster_id <> y.cluster_id",
        "second_round": f"{pairs()}, {GROUPS}, mg AS MATERIALIZED (SELECT least(x.cluster_id, y.cluster_id) AS a, greatest(x.cluster_id, y.cluster_id) AS b FROM p JOIN grp x ON x.doc_id = a JOIN grp y ON y.doc_id = b WHERE jaccard > 0.2 AND x.cluster_id <> y.cluster_id GROUP BY 1, 2 HAVING avg(jaccard) > 0.75), ee AS MATERIALIZED (SELECT a, b FROM mg UNION SELECT b, a FROM mg), cc AS (SELECT a AS id, a AS low FROM ee UNION SELECT ee.b, cc.low FROM cc JOIN ee ON ee.a = cc.id WHERE cc.low < ee.b), nm AS (SELECT id, min(low) AS low FROM cc GROUP BY id) SELECT doc_id, coalesce(low, cluster_id) AS cluster_id FROM grp LEFT JOIN nm ON nm.id = cluster_id",
        "common_grams": f"WITH {grams()}, {GROUPS}, s AS (SELECT cluster_id, count(*) AS n FROM grp GROUP BY cluster_id HAVING count(*) > 1) SELECT s.cluster_id, gram, count(*) AS members FROM g JOIN grp ON grp.doc_id = g.doc_id JOIN s ON s.cluster_id = grp.cluster_id GROUP BY s.cluster_id, gram, n HAVING count(*) >= n",
        "dedup_keep_first": f"WITH {GROUPS} SELECT doc_id, n_chars FROM documents WHERE doc_id IN (SELECT cluster_id FROM grp)",
        "dedup_keep_best": f"WITH {GROUPS}, rk AS (SELECT grp.doc_id, row_number() OVER (PARTITION BY cluster_id ORDER BY coalesce(quality, -1) DESC, grp.doc_id) AS k FROM grp LEFT JOIN labels ON labels.doc_id = grp.doc_id) SELECT doc_id, n_chars FROM documents WHERE doc_id IN (SELECT doc_id FROM rk WHERE k = 1)",
        "cost_model": "WITH n AS (SELECT count(*)::DOUBLE AS n FROM documents), s AS (SELECT n, n * 400 * 100 + n * 100 + n * 50 AS ops, ceil(n / 10) AS d FROM n) SELECT * FROM (SELECT 'all_pairs' AS method, n * n * 400 AS operations, 400.0::DOUBLE AS memory_values, 0.0::DOUBLE AS writes, 0.0::DOUBLE AS write_bits, 0.0::DOUBLE AS reads, 0.0::DOUBLE AS read_values FROM s UNION ALL SELECT 'memory', ops, n * 50, 0, 0, 0, 0 FROM s UNION ALL SELECT 'cells', ops, n, n * 50, 128, 50, n FROM s UNION ALL SELECT 'packed', ops, d * 50 + n, 500, 64 + 64 * d, 50, n FROM s UNION ALL SELECT 'forest', n, n, 0, 0, 0, 0 FROM s)",
        "capacity": "SELECT layout, documents, round(documents / greatest(1, n), 6) AS tables FROM (VALUES ('memory', 1e7::DOUBLE), ('cells', 5e8::DOUBLE), ('packed', 1e8::DOUBLE)) x(layout, documents), (SELECT count(*) AS n FROM documents WHERE regexp_matches(text, '[\\p{L}\\p{N}]'))",
        "corpus_report": f"{pairs()}, gr AS (SELECT count(*) AS n FROM documents WHERE text IS NOT NULL GROUP BY text HAVING count(*) > 1) SELECT (SELECT count(*) FROM p WHERE jaccard > 0.75) AS pairs, (SELECT count(*) FROM gr) AS exact_groups, (SELECT coalesce(max(n), 0) FROM gr) AS largest_group, (SELECT coalesce(sum(n), 0)::BIGINT FROM gr) AS exact_docs",
        "basket_pairs": f"WITH g AS MATERIALIZED (SELECT DISTINCT o_custkey AS doc_id, l_partkey AS gram FROM lineitem JOIN orders ON l_orderkey = o_orderkey), {PAIRS} SELECT a, b, shared, jaccard FROM p WHERE jaccard > 0.06",
        "page_pairs": pairs(5, table="pages", key="page_id", text="regexp_replace(html, '<[^>]*>', ' ', 'g')") + " SELECT a, b, shared, jaccard FROM p WHERE jaccard > 0.3",
        "conversation_pairs": pairs(5, table="(SELECT conv_id, string_agg(text, ' ' ORDER BY turn, role, text) AS text FROM conversations GROUP BY conv_id)", key="conv_id") + " SELECT a, b, shared, jaccard FROM p WHERE jaccard > 0.004",
        "benchmark_containment": f"WITH {grams()}, bw AS ({words('benchmark', 'item_id')}), bg AS MATERIALIZED (SELECT doc_id AS item_id, unnest({gram_list()}) AS gram FROM bw), bs AS (SELECT item_id, count(*) AS n FROM bg GROUP BY item_id) SELECT bg.item_id, g.doc_id, count(*) / any_value(n)::DOUBLE AS containment FROM bg JOIN g ON g.gram = bg.gram JOIN bs ON bs.item_id = bg.item_id GROUP BY bg.item_id, g.doc_id HAVING count(*) / any_value(n)::DOUBLE > 0.5",
        "slice_flushes": "WITH n AS (SELECT count(*) AS n FROM documents), s AS (SELECT greatest(1, (n + 49) // 50) AS k FROM n) SELECT slice_id, count(*) AS docs, count(*) * 50 AS values FROM (SELECT ntile((SELECT k FROM s)) OVER (ORDER BY doc_id) - 1 AS slice_id FROM documents) GROUP BY slice_id",
        "synth_injected": f"WITH r AS (SELECT doc_id, text, row_number() OVER (ORDER BY doc_id) - 1 AS rank FROM documents), n AS (SELECT count(*) AS n, max(doc_id) AS top FROM documents), k AS (SELECT id, floor({_draw('42', chr(39) + 'source' + chr(39), 'id')} * n)::BIGINT AS rank, 0.0 + 0.2::DOUBLE * {_draw('42', chr(39) + 'rate' + chr(39), 'id')} AS rate, top FROM range(0, 100) x(id), n), m AS (SELECT id, top + 1 + id AS doc_id, r.doc_id AS origin_id, rate, string_split(text, ' ') AS ws FROM k JOIN r ON r.rank = k.rank) SELECT doc_id, origin_id, round(rate, 9) AS rate, md5(array_to_string(list_transform(ws, lambda w, i: CASE WHEN {_draw('42', 'id', 'i - 1')} < rate THEN 'x' || substr(md5('w|' || id || '|' || (i - 1)), 1, 6) ELSE w END), ' ')) AS text_md5 FROM m",
    }
    grid = out["accuracy_rows_of_bands"]
    out["choose_bands_measured"] = f"SELECT t, b, r, misses, false_candidates FROM (SELECT *, row_number() OVER (PARTITION BY t ORDER BY b * r, false_candidates, b) AS k FROM ({grid}) WHERE misses <= 0) WHERE k = 1"
    return out
