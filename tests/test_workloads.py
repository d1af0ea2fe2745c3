"""A sample of the registered queries against their DuckDB counterparts on the smallest tables."""

import glob
import os

import duckdb
import pytest

import __spark_entry__ as entry_module

SF = "/root/testdata/sf0.001"
SAMPLE = [
    "w_graph_stats", "w_degree_order", "w_index_rows_u", "w_index_rows_nf", "w_distance_only_index", "w_pairs_label", "w_pairs_packed", "w_pairs_bfs", "w_pairs_bibfs",
    "w_pairs_upper_hub", "w_insert_pairs", "w_insert_changes", "w_delete_pairs", "w_delete_changes", "w_affected_sets", "w_vertex_delete", "w_directed_delete", "w_weight_increase",
    "w_recommend", "w_group_betweenness", "op_pack_array", "op_bit_codec", "op_cube", "op_full_outer_diff", "op_session",
]


def plain(df, cols):
    fix = lambda v: None if v is None or v != v else int(v) if isinstance(v, float) and v == int(v) else round(v, 6) if isinstance(v, float) else v
    return sorted(str([fix(v) for v in r]) for r in df[cols].astype(object).where(df[cols].notna(), None).values.tolist())


@pytest.mark.parametrize("name", SAMPLE)
def test_query_equals_oracle(spark, name):
    con = duckdb.connect()
    for p in glob.glob(f"{SF}/*.parquet"):
        con.sql(f"create view {os.path.basename(p)[:-8]} as select * from '{p}'")
    got, want = entry_module.queries()[name](spark, SF).toPandas(), con.sql(entry_module.oracle_sql()[name]).df()
    assert sorted(got.columns) == sorted(want.columns)
    cols = sorted(got.columns)
    assert plain(got, cols) == plain(want, cols)


def test_entry(spark):
    assert entry_module.entry(spark).count() > 0


def test_every_oracle_has_a_query():
    assert set(entry_module.oracle_sql()) <= set(entry_module.queries())
