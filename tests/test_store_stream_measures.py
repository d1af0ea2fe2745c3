import uuid

import pytest
from pyspark.sql import functions as F
from reference import EX
from test_index import answers, exact, make, rows, some_graph

from tallypath.functions import codec
from tallypath.operators import delete, graph, insert, maintain, query, traversal
from tallypath.operators import index as ixs
from tallypath.plans import apps, measures
from tallypath.sources.scratch import shared_dir
from tallypath.sources.store import Store
from tallypath.streaming import hybrid


@pytest.fixture(scope="module")
def example(spark):
    g = make(spark, EX)
    return g, ixs.build(g)


def test_store_reads_its_writes(spark, example):
    g, ix = example
    store = Store(spark, f"{shared_dir(spark)}/store-{uuid.uuid4().hex}", buckets=4)
    assert store.latest() is None
    store.write_base(ix.labels, ts=1.0)
    up = delete.run(g, ix, 1, 2)
    assert store.append(up.changes, batch=0, ts=2.0) and not store.append(up.changes, batch=0, ts=3.0)
    as_set = lambda df: {tuple(r) for r in df.select("side", "owner", "hub", "dist", "paths").collect()}
    assert as_set(store.read_current()) == as_set(up.index.labels)
    assert as_set(store.as_of(1.5)) == as_set(ix.labels) and store.as_of(0.5).count() == 0
    store.compact()
    assert as_set(store.read_current()) == as_set(up.index.labels)


def test_stream_equals_batch_and_ignores_replays(spark, example):
    g, ix = example
    log = spark.createDataFrame([(1, "insert", 3, 9), (2, "delete", 1, 2), (3, "insert", 5, 11)], "seq long, op string, u long, v long")
    state = hybrid.run_files(g, ix, log, rows_per_file=2, duplicate=True)
    edges = [e for e in EX if e != (1, 2)] + [(3, 9), (5, 11)]
    exact(spark, state.index, edges, range(12))
    before = state.seq
    state.commit(log.withColumn("w", F.lit(None).cast("long")), state.batch)
    assert state.seq == before
    state.commit(log.withColumn("w", F.lit(None).cast("long")), state.batch + 1)
    assert sum(x.count() for x in state.late) >= 3
    m = state.all_metrics()
    assert measures.accumulated(m).count() == m.count() and measures.label_changes(m).count() == 2


def test_stream_goes_on_from_its_versions(spark, example):
    g, ix = example
    log = spark.createDataFrame([(1, "insert", 3, 9), (2, "delete", 1, 2), (3, "insert", 5, 11), (4, "delete", 3, 9)], "seq long, op string, u long, v long")
    edges = [e for e in EX if e != (1, 2)] + [(5, 11)]
    state = hybrid.run_restarted(g, ix, log, at=2, rows_per_file=1)
    exact(spark, state.index, edges, range(12))
    assert {tuple(r) for r in state.graph.edges.collect()} == {tuple(sorted(e)) for e in edges}
    assert state.seq == 4 and sum(m.count() for m in state.metrics) == 4 and not state.late
    again = hybrid.resume(Store(spark, state.store.folder))
    assert rows(again.index) == rows(state.index) and (again.batch, again.seq) == (state.batch, 4)
    assert {tuple(r) for r in again.graph.arcs.collect()} == {tuple(r) for r in state.graph.arcs.collect()}
    redo = log.withColumn("w", F.lit(None).cast("long"))
    again.commit(redo, again.batch)
    assert not again.late
    odd = spark.createDataFrame([(None, "insert", 3, 9), (6, "insert", 3, 9), (6, "delete", 5, 11)], "seq long, op string, u long, v long")
    again.commit(odd, again.batch + 1)  # of one seq the least change counts: the deletion
    exact(spark, again.index, [e for e in edges if e != (5, 11)], range(12))
    assert again.late[0].count() == 1 and hybrid.resume(again.store).seq == 6
    with pytest.raises(ValueError):
        again.store.append(log, batch=99)


def test_a_lost_commit_is_repeated(spark, example, monkeypatch):
    g, ix = example
    store = Store(spark, f"{shared_dir(spark)}/store-{uuid.uuid4().hex}", buckets=2)
    state = hybrid.stored(g, ix, store)
    log = spark.createDataFrame([(1, "insert", 3, 9)], "seq long, op string, u long, v long")
    put = store._put_manifest
    monkeypatch.setattr(store, "_put_manifest", lambda m: 1 / 0)
    with pytest.raises(ZeroDivisionError):
        state.commit(log, 0)
    assert (state.batch, state.seq) == (-1, 0) and hybrid.resume(Store(spark, store.folder)).batch == -1
    monkeypatch.setattr(store, "_put_manifest", put)
    state.commit(log, 0)
    back = hybrid.resume(Store(spark, store.folder))
    exact(spark, back.index, [*EX, (3, 9)], range(12))
    assert back.batch == 0 and back.seq == 1


def test_vertices_come_and_go(spark, example):
    g, ix = example
    g2, ix2 = maintain.add_vertex(g, ix, 50, [4, 8])
    exact(spark, ix2, [*EX, (4, 50), (8, 50)], [*range(12), 50])
    g3, ix3 = maintain.remove_vertex(g2, ix2, 50)
    assert rows(ixs.purge_dominated(ix3)) == rows(ix)


def test_isolated_shortcut_compares_ranks(spark):
    star = [(0, i) for i in range(1, 5)]
    g = make(spark, star)
    ix = ixs.build(g)
    for i in range(1, 5):
        up = delete.run(g, ix, 0, i)
        g, ix = up.graph, up.index
        star = [e for e in star if e != (0, i)]
        exact(spark, ix, star, range(5))


def test_searches(spark, example):
    g, ix = example
    assert traversal.bibfs_count(g, 4, 6).collect() == [(3, 2)]
    assert [r["path"] for r in traversal.list_paths(g, 4, 6).collect()] == [[4, 5, 1, 6], [4, 9, 10, 6]]
    assert measures.exactness(ix, g).collect() == [(144, 1.0)]
    assert measures.dominated(ix).first()["dominated_rows"] == 0
    changes = [("insert", 0, 1), ("insert", 3, 3), ("delete", 4, 10), ("insert", 3, 99), ("insert", 3, 9), ("insert", None, 2)]
    bad = graph.validate_changes(g, spark.createDataFrame(changes, "op string, u long, v long"))
    got = {(r["u"], r["v"]): r["problem"] for r in bad.collect()}
    assert got == {(0, 1): "edge exists", (3, 3): "self loop", (4, 10): "no such edge", (3, 99): "unknown vertex", (3, 9): None, (None, 2): "null key"}


def test_strict_pruning_miscounts(spark):
    wrong = 0
    for seed in range(3):
        edges = some_graph(seed + 20, 9, 12)
        g = make(spark, edges, natural=False)
        ix = ixs.build(g)
        free = [(u, v) for u in range(9) for v in range(u + 1, 9) if (u, v) not in edges]
        up = insert.run(g, ix, spark.createDataFrame(free[:3], "u long, v long"), prune="strict")
        wrong += measures.exactness(up.index, up.graph).first()["exact"] < 1
    assert wrong


def test_apps(spark, example):
    g, ix = example
    top = [(r["vertex"], r["paths"]) for r in apps.recommend(ix, 0).collect()]
    true = {(s, t): x for (s, t), x in answers(spark, ix, range(12)).items() if s == 0 and x[0] == 2}
    assert top == sorted(((t, c) for (_, t), (_, c) in true.items()), key=lambda x: (-x[1], x[0]))
    single = {r["vertex"]: r["score"] for r in apps.betweenness(ix, g.ranks).collect()}
    group = apps.group_betweenness(g, ix, g.ranks.where("vertex = 0")).first()["score"]
    assert abs(single[0] - group) < 1e-9


def test_count_types_and_codec(spark):
    ladder = [(2 * i + a, 2 * i + 2 + b) for i in range(1, 40) for a in (0, 1) for b in (0, 1)]
    g = make(spark, ladder)
    n = query.from_source(ixs.build(g), 2).agg(F.max("paths")).first()[0]
    assert n == 2**38
    big = spark.createDataFrame([(2**62,), (2**62,), (2**62,)], "p long")
    assert int(big.agg(codec.product_sum(F.col("p"), "decimal")).first()[0]) == 3 * 2**62
    with pytest.raises(Exception, match="OVERFLOW"):
        big.agg(codec.product_sum(F.col("p"))).collect()
    row = spark.range(1).select(codec.encode(F.lit(5).cast("long"), F.lit(7), F.lit(2**29).cast("long")).alias("c")).first()
    assert row["c"] is None


@pytest.mark.parametrize("edges", [[(0, 1)], [(0, 1), (2, 3)], [(i, i + 1) for i in range(5)], [(u, v) for u in range(5) for v in range(u)]])
def test_small_shapes(spark, edges):
    g = make(spark, edges)
    exact(spark, ixs.build(g), edges, sorted({x for e in edges for x in e}))
