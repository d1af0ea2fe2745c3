"""The build by searches of blocks of hubs: the rows of the rounds and of the definition, whole or in part."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from tallypath.operators import graph, index, ranking, traversal


def random_graph(spark, n=150, m=260, directed=False, seed=3):
    rng = np.random.default_rng(seed)
    pairs = {(a, b) if directed else (min(a, b), max(a, b)) for a, b in rng.integers(0, n, (m, 2)).tolist() if a != b}
    e = spark.createDataFrame(sorted(pairs), "u long, v long")
    return graph.make(e, ranking.by_degree(e), directed=directed)


rows = lambda df: sorted(map(tuple, df.select("side", "owner", "hub", "dist", "paths").collect()))


@pytest.mark.parametrize("directed", [False, True])
def test_searches_give_the_rows_of_the_rounds(spark, monkeypatch, directed):
    monkeypatch.setattr(index, "STEPS", 64)
    g = random_graph(spark, directed=directed)
    want = rows(index.build(g, strategy="rounds").labels)
    assert rows(index.build(g, strategy="searches").labels) == want
    assert rows(index.build(g, max_levels=2).labels) == [r for r in want if r[3] <= 2]
    assert rows(index.build(g, top=70).labels) == [r for r in want if r[2] <= 70]


def test_a_part_by_rounds_is_the_same_part(spark, monkeypatch):
    g = random_graph(spark, 40, 60)
    want = rows(index.build(g, top=9).labels)
    monkeypatch.setattr(index, "MOST_ARCS", 10)
    assert index.searched(g) is None
    assert rows(index.build(g, top=9).labels) == want


def test_all_shortest_paths(spark):
    g = random_graph(spark)
    name = g.ranks.select(F.col("rank").alias("hub"), F.col("vertex").alias("source")).join(g.ranks.select(F.col("rank").alias("owner"), "vertex"))
    got = index.searched(g, below=False).join(name, ["hub", "owner"]).select("source", "vertex", "dist", "paths")
    want = sorted(map(tuple, traversal.search(traversal.plain_arcs(g), g.ranks.select(F.col("vertex").alias("source"))).collect()))
    assert sorted(map(tuple, got.collect())) == want
    full = index.searched(g, full=True)
    assert sorted((r["owner"], r["hub"], r["dist"], r["paths"], r["full"]) for r in full.collect()) == sorted(
        (r["owner"], r["hub"], r["dist"], r["paths"], r["full"]) for r in index.classify(index.build(g)).collect()
    )


def test_counts_beyond_64_bits_stop_the_build(spark):
    """A chain of 70 diamonds has 2**70 shortest paths between its ends."""
    e = [(3 * i + a, 3 * i + b) for i in range(70) for a, b in ((0, 1), (0, 2), (1, 3), (2, 3))]
    e = spark.createDataFrame(e, "u long, v long")
    with pytest.raises(Exception, match="count_type"):
        index.build(graph.make(e, ranking.natural(e)))
