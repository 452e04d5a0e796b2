"""Queries of the operators for training data, and their SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from neardup.llm.common import documents


def op1_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    from neardup.llm.token_files import token_files_of

    return token_files_of(documents(spark, sf_dir), public_tokenizers.path("byte_bpe_50k.json"))


def op2_shingle_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    from neardup.llm.shingle_join import shingle_components

    return shingle_components(documents(spark, sf_dir))


def op3_repeated_strings(spark: SparkSession, sf_dir: str) -> DataFrame:
    from neardup.llm.substrings import removal_digests

    return removal_digests(documents(spark, sf_dir))


def op4_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    from neardup.llm.toxicity import score_documents

    return score_documents(documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/labels.parquet"))


def op5_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from neardup.llm.lines import line_dedup_report

    return line_dedup_report(documents(spark, sf_dir))


def op6_private_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    from neardup.llm.private import find_private

    return find_private(documents(spark, sf_dir))


def op7_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    from neardup.llm.shards import sharded_digests
    from neardup.session import scratch_path

    return sharded_digests(spark.read.parquet(f"{sf_dir.rstrip('/')}/documents.parquet"), scratch_path(spark, "shards"))


def op8_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    from neardup.llm.quality import quality_report

    return quality_report(documents(spark, sf_dir))


def op9_piece_encoding(spark: SparkSession, sf_dir: str) -> DataFrame:
    from neardup.llm.pieces import encode_digests

    return encode_digests(documents(spark, sf_dir), public_tokenizers.path("piece_bpe_32k.model"))


def op10_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    from neardup.llm.decontaminate import contaminated

    return contaminated(documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_token_files, op2_shingle_join, op3_repeated_strings, op4_toxicity, op5_line_dedup, op6_private_data, op7_sharding, op8_quality, op9_piece_encoding, op10_decontamination, pipeline)}


#: Sets of 5-word shingles, links at 100 * shared >= 80 * total, and the lowest id that links reach.
SHINGLES_SQL = r"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS ws FROM documents),
g AS MATERIALIZED (SELECT doc_id, unnest(CASE WHEN len(ws) >= 5 THEN list_distinct(list_transform(range(1, len(ws) - 3), lambda i: array_to_string(ws[i:i + 4], ' '))) WHEN len(ws) > 0 THEN [array_to_string(ws, ' ')] ELSE []::VARCHAR[] END) AS gram FROM w),
sz AS MATERIALIZED (SELECT doc_id, count(*) AS n FROM g GROUP BY doc_id),
cm AS (SELECT gram FROM g GROUP BY gram HAVING count(*) > 1), gc AS MATERIALIZED (SELECT g.* FROM g JOIN cm ON cm.gram = g.gram),
sh AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS shared FROM gc x JOIN gc y ON x.gram = y.gram AND x.doc_id < y.doc_id GROUP BY 1, 2),
e AS MATERIALIZED (SELECT a, b FROM sh JOIN sz x ON x.doc_id = a JOIN sz y ON y.doc_id = b WHERE 100 * shared >= 80 * (x.n + y.n - shared)),
ee AS MATERIALIZED (SELECT a, b FROM e UNION SELECT b, a FROM e),
cc AS (SELECT a AS id, a AS low FROM ee UNION SELECT ee.b, cc.low FROM cc JOIN ee ON ee.a = cc.id WHERE cc.low < ee.b),
lo AS (SELECT id, min(low) AS low FROM cc GROUP BY id)
SELECT documents.doc_id, coalesce(sz.n, 0)::BIGINT AS n_shingles, coalesce(lo.low, documents.doc_id) AS component_id
FROM documents LEFT JOIN sz ON sz.doc_id = documents.doc_id LEFT JOIN lo ON lo.id = documents.doc_id
"""
#: Rules of quality.RULES in SQL; words are runs of characters other than space and 0x09-0x0D.
QUALITY_SQL = r"""
WITH t AS (SELECT doc_id, coalesce(text, '') AS txt, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS ws FROM documents),
win AS (SELECT doc_id, unnest(range(1, len(ws) - 3)) AS p, ws FROM t WHERE len(ws) >= 5),
keyed AS (SELECT doc_id, p, list_aggregate(ws[p : p + 4], 'string_agg', chr(10)) AS k FROM win),
twice AS (SELECT doc_id, unnest(list(p)) AS p FROM keyed GROUP BY doc_id, k HAVING count(*) > 1),
covered AS (SELECT doc_id, count(*) AS n FROM (SELECT DISTINCT doc_id, p + unnest(range(0, 5)) AS q FROM twice) GROUP BY doc_id),
lines AS (SELECT doc_id, unnest(string_split(txt, chr(10))) AS l FROM t),
dup AS (SELECT doc_id, count(*) AS n_lines, count(*) - count(DISTINCT l) AS n FROM lines WHERE regexp_matches(l, '[^\x20\x09-\x0D]') GROUP BY doc_id),
f AS (SELECT t.doc_id, len(ws)::BIGINT AS n_words, length(regexp_replace(txt, '[\x20\x09-\x0D]', '', 'g'))::BIGINT AS word_chars,
  length(regexp_replace(txt, '[^#*$%&|<>]', '', 'g'))::BIGINT AS n_symbols, coalesce(dup.n, 0)::BIGINT AS n_dup_lines, coalesce(dup.n_lines, 0)::BIGINT AS n_lines, coalesce(covered.n, 0)::BIGINT AS n_repeat_words
  FROM t LEFT JOIN dup ON dup.doc_id = t.doc_id LEFT JOIN covered ON covered.doc_id = t.doc_id)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words,
  n_words < 10 OR 100 * n_repeat_words > 20 * n_words AS base_failed,
  NOT (n_words < 10 OR 100 * n_repeat_words > 20 * n_words OR 100 * word_chars < 200 * n_words OR 100 * word_chars > 2000 * n_words OR 100 * n_symbols > 40 * n_words OR 100 * n_dup_lines > 50 * n_lines) AS kept
FROM f
"""


#: All runs of 1 to 10 lines with 10 words or more (lines.WORDS); every copy but the first is deleted. Longer runs consist of such runs.
LINES_SQL = r"""
WITH l AS (SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS line, generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) AS no FROM documents),
s AS (SELECT doc_id, no, line, len(regexp_extract_all(line, '[^\x20\x09-\x0D]+')) AS w FROM l),
q AS (SELECT doc_id, no, line, w, row_number() OVER (PARTITION BY doc_id ORDER BY no) AS pos FROM s WHERE w > 0),
d AS (SELECT doc_id, list(line ORDER BY pos) AS ls, list(w ORDER BY pos) AS ws FROM q GROUP BY doc_id),
p AS (SELECT doc_id, unnest(range(1, len(ls) + 1)) AS pos, ls, ws FROM d),
n AS (SELECT doc_id, pos, unnest(range(1, 11)) AS n, ls, ws FROM p),
r AS (SELECT doc_id, pos, n, array_to_string(ls[pos : pos + n - 1], chr(10)) AS run FROM n WHERE pos + n - 1 <= len(ls) AND list_sum(ws[pos : pos + n - 1]) >= 10),
o AS (SELECT doc_id, pos, n, row_number() OVER (PARTITION BY run ORDER BY doc_id, pos) AS nth FROM r),
g AS (SELECT DISTINCT doc_id, pos + unnest(range(0, n)) AS pos FROM o WHERE nth > 1),
x AS (SELECT q.doc_id, q.no FROM q JOIN g ON g.doc_id = q.doc_id AND g.pos = q.pos),
k AS (SELECT l.doc_id, string_agg(l.line, chr(10) ORDER BY l.no) FILTER (WHERE x.no IS NULL) AS kept, count(x.no) AS gone FROM l LEFT JOIN x ON x.doc_id = l.doc_id AND x.no = l.no GROUP BY l.doc_id)
SELECT doc_id, gone AS n_lines_removed, length(coalesce(kept, '')) AS kept_chars, md5(coalesce(kept, '')) AS kept_md5 FROM k
"""


def oracle_sql() -> dict[str, str]:
    return {
        "op2_shingle_join": SHINGLES_SQL,
        "op5_line_dedup": LINES_SQL,
        "op7_sharding": "SELECT doc_id, strlen(text)::BIGINT AS n_bytes, md5(text) AS text_md5 FROM documents",
        "op8_quality": QUALITY_SQL,
    }
