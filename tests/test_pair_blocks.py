"""Pairs answered in blocks of sources, where they are made: the rows of the label joins, without an exchange."""

import numpy as np
import pytest
from pyspark.sql import functions as F
from test_searches import random_graph

from tallypath.operators import graph, index, query, ranking
from tallypath.plans import workloads

plain = lambda df: sorted(map(str, df.select("s", "t", "dist", "paths").collect()))


@pytest.mark.parametrize("directed", [False, True])
def test_blocks_answer_every_pair(spark, monkeypatch, directed):
    monkeypatch.setattr(query, "SOURCES", 16)
    monkeypatch.setattr(query, "BATCH", 100)
    g = random_graph(spark, n=60, m=45, directed=directed)
    ix = index.build(g)
    got = query.in_blocks(ix)
    want = query.pairs(ix, workloads.every_pair(g))
    assert plain(got) == plain(want) and got.where("dist is null and paths = 0").count()
    some = query.in_blocks(ix, workloads.some_targets)
    assert plain(some) == plain(query.pairs(ix, workloads.some_pairs(g)))


def test_weighted_graphs_and_the_bound(spark, monkeypatch):
    e = spark.createDataFrame([(1, 2, 2), (2, 3, 1), (1, 3, 3), (5, 6, 1)], "u long, v long, w long")
    g = graph.make(e, ranking.by_degree(e), weighted=True)
    ix = index.build(g)
    assert plain(query.in_blocks(ix)) == plain(query.pairs(ix, workloads.every_pair(g)))
    monkeypatch.setattr(query, "MOST_ROWS", 3)
    assert query.in_blocks(ix) is None


@pytest.mark.parametrize("lowest", [0, -500])
def test_some_targets_are_those_of_the_condition(spark, lowest):
    v = np.arange(lowest, lowest + 4000, 7)
    pick = workloads.some_targets(v)
    for s in v[:40].tolist():
        want = spark.createDataFrame([(int(t),) for t in v], "t long").where((F.lit(s) * 7919 + F.col("t") * 104729) % 1000003 % 37 == 0) if s == v[0] else None
        got = sorted(v[pick(s)].tolist())
        if want is not None:
            assert got == [r["t"] for r in want.collect()]
        assert got == [t for t in v.tolist() if abs(s * 7919 + t * 104729) % 1000003 % 37 == 0]


def test_counts_beyond_64_bits_stop_the_answer(spark):
    """A chain of 70 diamonds, indexed with whole counts only near its ends, has 2**70 shortest paths between them."""
    far = 1 << 32
    rows = [("u", 1, 1, 0, 1), ("u", 2, 1, 1, far), ("u", 2, 2, 0, 1), ("u", 3, 1, 1, far), ("u", 3, 3, 0, 1)]
    ranks = spark.createDataFrame([(i, i) for i in (1, 2, 3)], "vertex long, rank long")
    ix = index.of_labels(spark.createDataFrame(rows, index.ROW), ranks)
    with pytest.raises(Exception, match="count_type"):
        query.in_blocks(ix).collect()


@pytest.mark.parametrize("name", ["w_pairs_disconnected", "w_pairs_disconnected_all", "op_left_outer_default_all"])
def test_the_queries_exchange_no_pairs(spark, name):
    import __spark_entry__

    plan = __spark_entry__.queries()[name](spark, "/root/testdata/sf0.001")._jdf.queryExecution().executedPlan().toString()
    assert "Join" not in plan and "Aggregate" not in plan


@pytest.mark.parametrize("directed", [False, True])
def test_blocks_answer_the_pairs_of_some_vertices(spark, directed):
    g = random_graph(spark, 60, 60, directed=directed)
    ix = index.build(g)
    some = F.col("vertex") % 3 == 0
    got = query.in_blocks(ix, of=some)
    assert "Join" not in got._jdf.queryExecution().optimizedPlan().toString()
    assert plain(got) == plain(query.pairs(ix, workloads.every_pair(g, some))) and got.count()
