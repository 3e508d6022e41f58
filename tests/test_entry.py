"""Catalogue against DuckDB on the smallest tables, where they are there."""

import os

import pytest

SF = "/root/testdata/sf0.001"
pytestmark = pytest.mark.skipif(not os.path.isdir(SF), reason="tables not given")
SOME = ["cc_part_supplier", "cc_page_links", "cc_region_tree", "cc_toggle_user_key", "cut_month_suppliers_k4", "net_edges", "bucket_rows_nested", "decode_pair31", "adjacency_bits", "er_edges", "stream_window_counts", "reach_pairs_page_links"]


@pytest.fixture(scope="module")
def duck():
    import duckdb

    con = duckdb.connect()
    for f in os.listdir(SF):
        con.execute(f"CREATE VIEW {f.split('.')[0]} AS SELECT * FROM '{SF}/{f}'")
    return con


def rows(df):
    df = df[sorted(df.columns)]
    return sorted(map(str, df.astype(object).itertuples(index=False, name=None)))


@pytest.mark.parametrize("name", SOME)
def test_query_matches_sql(spark, duck, name):
    from edgesketch import catalog

    assert rows(catalog.queries()[name](spark, SF).toPandas()) == rows(duck.sql(catalog.oracle_sql()[name]).df())


def test_names_and_entry(spark):
    import __spark_entry__ as entry

    assert set(entry.oracle_sql()) <= set(entry.queries())
    assert entry.entry(spark).count() > 0


#: Queries that used to make their data up, and read a given table now.
READ_A_TABLE = ["er_edges", "exact_min_cut", "hash_calls", "kron_edges", "model_bytes", "sampler_bytes", "sampler_levels", "space_crossover", "w_bottlenecks", "w_hash_work", "w_k_laws", "w_matching_worst_case"]


@pytest.mark.parametrize("name", READ_A_TABLE)
def test_query_reads_a_table(spark, duck, tmp_path, name):
    from edgesketch import catalog

    got = rows(catalog.queries()[name](spark, SF).toPandas())
    assert got and got == rows(duck.sql(catalog.oracle_sql()[name]).df())
    with pytest.raises(Exception, match="PATH_NOT_FOUND"):
        catalog.queries()[name](spark, str(tmp_path)).collect()
