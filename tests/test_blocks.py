"""The prune step of the build by blocks of hubs and owners."""

import numpy as np

from tallypath.operators import graph, index, ranking


def ring(spark, n=60):
    rng = np.random.default_rng(5)
    edges = {(min(a, b), max(a, b)) for a, b in ((i, (i + 1) % n) for i in range(n))} | {(min(a, b), max(a, b)) for a, b in rng.integers(0, n, (n // 2, 2)).tolist() if a != b}
    e = spark.createDataFrame(sorted(edges), "u long, v long")
    return graph.make(e, ranking.by_degree(e))


def test_several_blocks_give_the_rows_of_the_definition(spark, monkeypatch):
    monkeypatch.setattr(index, "SMALL", 0)
    monkeypatch.setattr(index, "CHUNK", 50)
    monkeypatch.setattr(index, "TABLE", 100)
    g = ring(spark)
    rows = lambda ix: sorted(map(tuple, ix.labels.collect()))
    assert rows(index.build(g)) == rows(index.build_by_definition(g))


def test_lists_are_sent_once_a_block_not_once_a_candidate(spark):
    """The rows exchanged for the prune step are lists, not (candidate, via) pairs."""
    g = ring(spark)
    level = index.self_rows(g)
    lists = index.listed(level, True)
    got = index.unbeaten(index.expand(level, g.arcs), lists, 1, 60, 200)
    plan = got._jdf.queryExecution().optimizedPlan().toString()
    assert "vias" in plan and "via#" not in plan
    assert {(r["owner"], r["hub"]) for r in got.collect()} == {(r["dst"], r["src"]) for r in g.arcs.collect() if r["dst"] > r["src"]}
