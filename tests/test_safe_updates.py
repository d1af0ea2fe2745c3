"""Updates that don't fit the graph, and the deletion root by root."""

import random

import pytest
from pyspark.sql import functions as F

import reference as ref
from tallypath.operators import delete, graph, insert, maintain, query, ranking
from tallypath.operators import index as ixs
from tallypath.plans import measures, workloads
from tallypath.sources.scratch import Layered, written

PAIR = "u long, v long"


def made(spark, edges, directed=False, weighted=False):
    e = spark.createDataFrame(edges, PAIR + ", w long" * weighted)
    g = graph.make(e, ranking.natural(e), directed, weighted)
    return g, ixs.build(g)


def rows(ix):
    return {(r["side"], r["owner"], r["hub"]): (r["dist"], r["paths"]) for r in ix.labels.collect()}


def test_insertions_that_do_not_fit_change_nothing(spark):
    g, ix = workloads.indexed(spark, "/root/testdata/sf0.001", "EX")
    wrong = [(1, 2), (2, 1), (4, 4), (0, 99), (None, 3)]
    up = insert.run(g, ix, spark.createDataFrame(wrong, PAIR))
    assert up.changes.count() == 0 and rows(up.index) == rows(ix)
    assert sorted(r["problem"] for r in up.rejects.collect()) == ["edge exists", "edge exists", "null key", "self loop", "unknown vertex"]
    up = insert.run(g, ix, spark.createDataFrame([(3, 9), (9, 3), (1, 2)], PAIR))
    assert measures.exactness(up.index, up.graph).first()["exact"] == 1
    p = spark.createDataFrame([(0, 3, 9)], "qid long, s long, t long")
    assert tuple(query.pairs(up.index, p).select("dist", "paths").first()) == (1, 1) and up.graph.edges.count() == 18


def test_a_log_with_changes_that_do_not_fit(spark):
    g, ix = workloads.indexed(spark, "/root/testdata/sf0.001", "EX")
    log = [(1, "insert", 3, 9), (2, "insert", 9, 3), (3, "delete", 9, 3), (4, "delete", 3, 9), (5, "insert", 1, 2), (6, "delete", 5, 77)]
    g2, ix2, m = maintain.apply(g, ix, spark.createDataFrame(log, "seq long, op string, u long, v long"))
    assert [(r["seq"], r["rejected"]) for r in m.orderBy("seq").collect()] == [(1, 0), (2, 1), (3, 0), (4, 1), (5, 1), (6, 1)]
    assert measures.exactness(ix2, g2).first()["exact"] == 1 and g2.edges.count() == 17


def test_weights_given_in_either_order(spark):
    edges = [(0, 1, 2), (1, 2, 2), (0, 2, 5), (2, 3, 1)]
    g, ix = made(spark, edges, weighted=True)
    log = [(1, "reweight", 2, 0, 3), (2, "reweight", 1, 0, 4), (3, "reweight", 0, 1, 4), (4, "reweight", 0, 3, 1), (5, "insert", 3, 0, 1), (6, "insert", 0, 3, 7)]
    g2, ix2, m = maintain.apply(g, ix, spark.createDataFrame(log, "seq long, op string, u long, v long, w long"))
    assert [r["rejected"] for r in m.orderBy("seq").collect()] == [0, 0, 1, 1, 0, 1]
    new = [(0, 1, 4), (1, 2, 2), (0, 2, 3), (2, 3, 1), (0, 3, 1)]
    assert sorted(map(tuple, g2.edges.collect())) == sorted(new)
    assert rows(ixs.purge_dominated(ix2)) == ref.index(new, {v: v + 1 for v in range(4)})


def test_an_overlay_refuses_repeated_keys(spark):
    base = written(spark.createDataFrame([(1, 2)], "k long, x long"))
    with pytest.raises(ValueError):
        Layered(base, ("k",)).changed(spark.createDataFrame([(1, 3, False), (1, 4, False)], "k long, x long, gone boolean"))


def test_cut_searches_find_the_affected_sets(spark):
    g, ix = workloads.indexed(spark, "/root/testdata/sf0.001", "EX")
    ra, rb = query.rank_of(ix, 1), query.rank_of(ix, 2)
    want, got = delete.affected(ix, ra, rb), delete.cut_searches(g, ix, 1, 2)
    assert sorted(map(tuple, got.select(*want.columns).collect())) == sorted(map(tuple, want.collect()))


@pytest.mark.parametrize("directed", [False, True])
def test_deletion_root_by_root(spark, directed):
    r = random.Random(4 + directed)
    edges = sorted({(min(a, b), max(a, b)) if not directed else (a, b) for a, b in ((r.randrange(7), r.randrange(7)) for _ in range(15)) if a != b})
    g, ix = made(spark, edges, directed)
    ranks = {x["vertex"]: x["rank"] for x in g.ranks.collect()}
    e = edges[len(edges) // 2]
    up = delete.run(g, ix, *e, strategy="rooted", shortcut=False)
    assert rows(up.index) == ref.index([x for x in edges if x != e], ranks, directed)


def test_rooted_deletion_equals_the_other_on_the_trap(spark):
    g, ix = workloads.indexed(spark, "/root/testdata/sf0.001", "TRAP")
    up = insert.run(g, ix, spark.createDataFrame([(0, 5)], PAIR))
    for a, b in ((4, 5), (0, 5)):
        up = delete.run(up.graph, up.index, a, b, strategy="rooted")
    assert measures.exactness(up.index, up.graph).first()["exact"] == 1
    assert up.graph.edges.where((F.col("u") == 0) & (F.col("v") == 5)).count() == 0


def test_counts_beyond_64_bits(spark):
    """Layers joined completely: 16 ** 17 paths from end to end."""
    width, layers = 16, 17
    name = lambda layer, i: 1 + layer * width + i
    edges = [(0, name(0, i)) for i in range(width)] + [(name(a, i), name(a + 1, j)) for a in range(layers - 1) for i in range(width) for j in range(width)]
    last = name(layers, 0)
    edges += [(name(layers - 1, i), last) for i in range(width)]
    e = spark.createDataFrame(edges, PAIR)
    g = graph.make(e, ranking.natural(e))
    p = spark.createDataFrame([(0, 0, last)], "qid long, s long, t long")
    ix = ixs.build(g, count_type="decimal")
    assert tuple(query.pairs(ix, p).select("dist", "paths").first()) == (layers + 1, width**layers)
    up = delete.run(g, ix, name(0, 0), name(1, 0))
    assert int(query.pairs(up.index, p).first()["paths"]) == width**layers - width ** (layers - 2)
