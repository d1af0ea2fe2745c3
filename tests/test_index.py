import random

import pytest
from pyspark.sql import functions as F
from reference import EX, TRAP, index, pairs

from tallypath.operators import delete, graph, insert, query, ranking
from tallypath.operators import index as ixs
from tallypath.sources.scratch import written


def make(spark, edges, directed=False, weighted=False, natural=True):
    kind = "u long, v long" + ", w long" * weighted
    df = spark.createDataFrame([tuple(e) for e in edges], kind)
    e = graph.simple_edges(df, "u", "v", directed, "w" if weighted else None)
    return graph.make(e, ranking.natural(e) if natural else ranking.by_degree(e), directed, weighted)


def rows(ix):
    return {(r["side"], r["owner"], r["hub"]): (r["dist"], r["paths"]) for r in ix.labels.collect()}


def ranks(g):
    return {r["vertex"]: r["rank"] for r in g.ranks.collect()}


def answers(spark, ix, vs):
    p = spark.createDataFrame([(i, s, t) for i, (s, t) in enumerate((s, t) for s in vs for t in vs)], "qid long, s long, t long")
    return {(r["s"], r["t"]): (r["dist"], r["paths"]) for r in query.pairs(ix, p).collect()}


def exact(spark, ix, edges, vs, directed=False):
    true = pairs(edges, vs, directed)
    assert answers(spark, ix, vs) == {(s, t): true.get((s, t), (None, 0)) for s in vs for t in vs}


def some_graph(seed, n=12, m=20, directed=False, weights=0):
    r = random.Random(seed)
    seen = {}
    while len(seen) < m:
        u, v = r.sample(range(n), 2)
        if not directed:
            u, v = min(u, v), max(u, v)
        seen[u, v] = r.randint(1, weights) if weights else 1
    return [(u, v, w) if weights else (u, v) for (u, v), w in seen.items()]


def test_example_index_and_query(spark):
    g = make(spark, EX, natural=False)
    assert ranks(g) == {v: v + 1 for v in range(12)}
    ix = ixs.build(g)
    got = rows(ix)
    assert len(got) == 50 and got == index(EX, ranks(g))
    c = ixs.classify(ix).collect()
    assert sum(r["canonical"] for r in c) == 45
    p = spark.createDataFrame([(0, 4, 6)], "qid long, s long, t long")
    assert [tuple(r)[3:] for r in query.pairs(ix, p).collect()] == [(3, 2)]
    assert sorted(r["hub"] for r in query.explain(ix, p).collect()) == [1, 4]
    assert [tuple(r)[3:] for r in query.pairs_packed(ix, query.packed(ix), p).collect()] == [(3, 2)]


def test_example_insert(spark):
    g = make(spark, EX)
    ix = ixs.build(g)
    add = spark.createDataFrame([(3, 9)], "u long, v long")
    up = insert.run(g, ix, add)
    assert rows(up.index) == index([*EX, (3, 9)], ranks(g))
    got = sorted((r["owner"] - 1, r["hub"] - 1, r["op"]) for r in up.changes.collect())
    assert got == sorted(
        [(9, 0, "renew_dist"), (9, 2, "renew_dist"), (9, 3, "renew_dist"), (10, 3, "renew_dist"), (4, 0, "renew_count"), (10, 0, "renew_count"), (9, 1, "renew_count"), (4, 3, "renew_count"), (10, 2, "insert"), (6, 3, "insert")]
    )
    assert rows(insert.run(g, ix, add, schedule="rank").index) == rows(up.index)


def test_example_delete(spark):
    g = make(spark, EX)
    ix = ixs.build(g)
    up = delete.run(g, ix, 1, 2)
    assert rows(up.index) == index([e for e in EX if e != (1, 2)], ranks(g))
    got = sorted((r["owner"] - 1, r["hub"] - 1, r["op"]) for r in up.changes.collect())
    assert got == [(2, 1, "renew_dist"), (3, 1, "remove"), (7, 1, "renew_count"), (10, 2, "insert")]
    sets = {(r["side"], r["role"].startswith("root")): set() for r in up.sets.collect()}
    for r in up.sets.collect():
        sets[r["side"], r["role"].startswith("root")].add(r["rank"] - 1)
    assert sets == {("a", True): {1, 6, 10}, ("b", True): {2}, ("b", False): {3, 7}}


def test_trap(spark):
    edges = list(TRAP)
    for removal, last in (("always", (4, 1)), ("common_hub", (3, 1))):
        g = make(spark, edges)
        ix = ixs.build(g)
        seen = []
        p = spark.createDataFrame([(0, 2, 5)], "qid long, s long, t long")
        ask = lambda: tuple(query.pairs(ix, p).first())[3:]
        seen.append(ask())
        up = insert.run(g, ix, spark.createDataFrame([(0, 5)], "u long, v long"))
        g, ix = up.graph, up.index
        seen.append(ask())
        for a, b in ((4, 5), (0, 5)):
            up = delete.run(g, ix, a, b, removal=removal)
            g, ix = up.graph, up.index
            seen.append(ask())
        assert seen == [(3, 1), (2, 1), (2, 1), last]


@pytest.mark.parametrize("seed,directed,weights", [(1, False, 0), (2, True, 0), (3, False, 3), (4, True, 3)])
def test_mixed_updates_stay_exact(spark, seed, directed, weights):
    edges = some_graph(seed, directed=directed, weights=weights)
    r = random.Random(seed)
    g = make(spark, edges, directed, bool(weights), natural=False)
    rank = ranks(g)
    vs = sorted(rank)
    ix = ixs.build(g)
    assert rows(ix) == index(edges, rank, directed)
    kind = "u long, v long" + ", w long" * bool(weights)
    for step in range(4):
        have = {e[:2] for e in edges}
        free = [(u, v) for u in vs for v in vs if u != v and (u < v or directed) and (u, v) not in have]
        if step % 2 == 0:
            new = [(*e, r.randint(1, weights)) if weights else e for e in r.sample(free, 2)]
            up = insert.run(g, ix, spark.createDataFrame(new, kind))
            edges = edges + new
        else:
            gone = r.choice(edges)
            up = delete.run(g, ix, *gone[:2])
            edges = [e for e in edges if e != gone]
        g, ix = up.graph, up.index
        exact(spark, ix, edges, vs, directed)
    assert rows(ixs.purge_dominated(ix)) == index(edges, rank, directed)


def test_other_builders_agree(spark):
    edges = some_graph(9, 9, 14)
    g = make(spark, edges, natural=False)
    want = index(edges, ranks(g))
    assert rows(ixs.build_by_definition(g)) == want
    assert rows(ixs.build_rank_order(g, 3)) == want
    canonical = {(r["owner"], r["hub"]): r["dist"] for r in ixs.classify(ixs.build(g)).where("canonical").collect()}
    only = {(r["owner"], r["hub"]): r["dist"] for r in ixs.build(g, distance_only=True).labels.collect()}
    assert only == canonical


def test_delete_variants_agree(spark):
    edges = some_graph(12, 10, 16)
    g = make(spark, edges, natural=False)
    ix = ixs.build(g)
    a, b = edges[3]
    want = index([e for e in edges if e != (a, b)], ranks(g))
    for options in ({}, {"definition": "gap_all"}, {"strategy": "drop_then_fill"}, {"strategy": "search"}, {"schedule": "rank"}):
        assert rows(delete.run(g, ix, a, b, **options).index) == want, options


@pytest.mark.parametrize("equal", [False, True])
def test_detours_by_semi_joins_are_those_of_whole_lists(spark, equal):
    ix = ixs.build(make(spark, EX))
    labels = ix.labels.collect()
    lists = {}
    for r in labels:
        lists.setdefault(r["owner"], {})[r["hub"]] = r["dist"]
    for at in (2, 3, 4):
        cands = written(ix.labels.where("owner <> hub").select("side", "owner", "hub", F.lit(at).alias("dist"), "paths"), "candidates")
        best = lambda o, h: min((lists[o][v] + lists[h][v] for v in lists[o] if v in lists[h] and v not in (o, h)), default=99)
        want = {(r["owner"], r["hub"]) for r in labels if r["owner"] != r["hub"] and best(r["owner"], r["hub"]) < at + equal}
        for narrow in (False, True):
            got = ixs.detours(cands, ix.labels, equal, at, narrow)
            assert ({(r["owner"], r["hub"]) for r in got.collect()} if got is not None else set()) == want
