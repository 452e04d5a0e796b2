"""Queries against DuckDB over the smallest tables."""

import duckdb
import pytest

import __spark_entry__
from neardup import catalog

DIR = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
NAMES = ["tokens_count", "word_ngrams", "char_shingles", "short_documents", "stem_light_ngrams", "exact_pairs_all", "exact_clusters_grams", "signature_portable", "minhash_permutation", "bands_portable", "candidates_sorted", "packed_layout", "near_duplicates_075", "near_duplicates_rewritten", "choose_bands", "accuracy_grid", "components_075", "cluster_bound_violations", "cluster_rounds_violations", "modularity_exact", "second_round", "synth_injected", "join_asof_events", "agg_lang_source_cube", "udtf_shingles", "stream_session", "stream_neardup", "fn_json"]


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{DIR}/{t}.parquet'")
    return con


@pytest.mark.parametrize("name", NAMES)
def test_query_has_the_rows_of_its_sql(spark, duck, name):
    df = catalog.queries()[name](spark, DIR)
    names = sorted(df.columns)
    want = duck.sql(catalog.oracle_sql()[name])
    assert sorted(want.columns) == names
    columns = ", ".join(f'"{c}"' for c in names)
    expected = sorted(tuple(map(str, r)) for r in duck.sql(f"SELECT {columns} FROM ({catalog.oracle_sql()[name].strip().rstrip(';')})").fetchall())
    assert sorted(tuple(map(str, r)) for r in df.select(*names).collect()) == expected


def test_entry_and_registry(spark):
    assert __spark_entry__.entry(spark).count() > 0
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())
