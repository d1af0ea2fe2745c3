"""Updates whose roots search the new graph in blocks: the changes of the rounds, and the index of a build anew."""

import pytest
from pyspark.sql import functions as F
from test_searches import random_graph, rows

from tallypath.operators import delete, index, insert
from tallypath.plans import relational, workloads  # noqa: F401  relational registers its queries

CHANGE = ("side", "owner", "hub", "old_dist", "old_paths", "dist", "paths", "op")
told = lambda up: sorted((tuple(r) for r in up.changes.select(*CHANGE).collect()), key=str)


def test_changes_equal_those_of_the_rounds(spark, monkeypatch):
    g = random_graph(spark, 60, 150)
    ix = index.build(g)
    u, v = g.edges.orderBy("u", "v").first()[:2]
    gone = [delete.run(g, ix, u, v, strategy=s) for s in ("withhold", "searches")]
    assert told(gone[0]) == told(gone[1]) and told(gone[0])
    assert rows(gone[1].index.labels) == rows(index.build(gone[1].graph).labels)
    free = g.ranks.select(F.col("vertex").alias("u")).join(g.ranks.select(F.col("vertex").alias("v"))).where("u < v").join(g.edges, ["u", "v"], "left_anti")
    new = spark.createDataFrame(free.orderBy("u", "v").limit(2).collect(), "u long, v long")
    monkeypatch.setattr(insert, "settle", lambda *a, **b: pytest.fail("rounds"))
    up = insert.run(g, ix, new, dominated="purge", strategy="searches")
    monkeypatch.undo()
    assert told(insert.run(g, ix, new)) == told(up)
    assert rows(up.index.labels) == rows(index.build(up.graph).labels)


@pytest.mark.parametrize("name", ["op_cube", "op_full_outer_diff", "op_grouping_sets", "op_rollup", "w_delete_changes"])
def test_queries_run_no_rounds(spark, monkeypatch, name):
    for module in (insert, delete):
        monkeypatch.setattr(module, "settle", lambda *a, **b: pytest.fail("rounds"))
    assert workloads.QUERIES[name](spark, "/root/testdata/sf0.001").count()


@pytest.mark.parametrize("seed", [3, 4, 5])
def test_rounds_are_told_as_the_rounds_count_them(spark, seed):
    g = random_graph(spark, 60, 150, seed=seed)
    ix = index.build(g)
    u, v = g.edges.orderBy("u", "v").first()[:2]
    want = delete.run(g, ix, u, v, shortcut=False).rounds
    assert delete.run(g, ix, u, v, shortcut=False, strategy="searches", count_rounds=True).rounds == want and want


def test_bound_terms_run_no_rounds(spark, monkeypatch):
    up = workloads._deleted(spark, "/root/testdata/sf0.001")
    monkeypatch.setattr(delete, "settle", lambda *a, **b: pytest.fail("rounds"))
    got = workloads.QUERIES["w_bound_terms"](spark, "/root/testdata/sf0.001").first()
    assert (got["visits"], got["rounds"]) == (sum(r["candidates"] for r in up.rounds), len(up.rounds)) and got["visits"]


def test_a_stream_by_searches_keeps_the_index(spark, monkeypatch):
    from tallypath.streaming import hybrid

    g = random_graph(spark, 40, 80)
    ix = index.build(g)
    free = g.ranks.select(F.col("vertex").alias("u")).join(g.ranks.select(F.col("vertex").alias("v"))).where("u < v").join(g.edges, ["u", "v"], "left_anti")
    new = [tuple(r) for r in free.orderBy("u", "v").limit(3).collect()]
    old = tuple(g.edges.orderBy("u", "v").first()[:2])
    log = spark.createDataFrame([(i + 1, op, *e) for i, (op, e) in enumerate([*(("insert", e) for e in new), ("delete", old)])], "seq long, op string, u long, v long")
    for module in (insert, delete):
        monkeypatch.setattr(module, "settle", lambda *a, **b: pytest.fail("rounds"))
    state = hybrid.run_files(g, ix, log, rows_per_file=2, duplicate=True, strategy="searches")
    assert state.seq == 4 and state.graph.edges.count() == g.edges.count() + 2
    from tallypath.operators import query

    everyone = workloads.every_pair(state.graph)
    answers = lambda x: sorted(map(str, query.pairs(x, everyone).select("s", "t", "dist", "paths").collect()))
    assert answers(state.index) == answers(index.build(state.graph, strategy="searches"))


def test_the_late_duplicate_query_runs_no_rounds(spark, monkeypatch):
    for module in (insert, delete):
        monkeypatch.setattr(module, "settle", lambda *a, **b: pytest.fail("rounds"))
    assert workloads.QUERIES["op_stream_dedupe_late"](spark, "/root/testdata/sf0.001").first()["edges"]
