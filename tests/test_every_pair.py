"""Workloads without a cap or a sample."""

import glob
import os

import __spark_entry__ as entry_module
import duckdb
import pytest
from pyspark.sql import functions as F
from test_workloads import plain

from tallypath.plans import workloads

SF = "/root/testdata/sf0.001"


def test_strata_are_made_of_all_candidate_insertions(spark, monkeypatch):
    asked, first = [], workloads.first_inserts
    monkeypatch.setattr(workloads, "first_inserts", lambda spark, sf_dir, g, n: asked.append(n) or first(spark, sf_dir, g, n))
    got = workloads.skew_inserts(spark, SF).collect()
    g = workloads.load(spark, SF, "U")
    everything = first(spark, SF, g, None)
    assert asked == [None] and everything.count() == first(spark, SF, g, 10**6).count()
    assert sorted(r["stratum"] for r in got) == list(range(1, 1 + min(10, everything.count())))


@pytest.mark.parametrize("name", [f"{n}_all" for n in workloads.SAMPLED] + ["op_left_outer_default_all"])
def test_every_pair_equals_oracle(spark, name):
    con = duckdb.connect()
    for p in glob.glob(f"{SF}/*.parquet"):
        con.sql(f"create view {os.path.basename(p)[:-8]} as select * from '{p}'")
    sql = entry_module.oracle_sql()[name]
    assert "% 37" not in sql and "% 50" not in sql
    got, want = entry_module.queries()[name](spark, SF).toPandas(), con.sql(sql).df()
    cols = sorted(got.columns)
    assert cols == sorted(want.columns) and len(got)
    assert plain(got, cols) == plain(want, cols)


def test_pairs_of_some_vertices_are_made_of_these_alone(spark):
    from tallypath.operators import graph, ranking

    e = spark.createDataFrame([(i, i + 1) for i in range(1, 40)], "u long, v long")
    g = graph.make(e, ranking.by_degree(e))
    got = workloads.every_pair(g, F.col("vertex") % 5 == 0)
    want = [(s, t) for s in range(5, 41, 5) for t in range(5, 41, 5)]
    assert sorted((r["s"], r["t"]) for r in got.collect()) == want
    assert got.select("qid").distinct().count() == len(want)
    assert "Range (0, 64," in got._jdf.queryExecution().optimizedPlan().toString()
