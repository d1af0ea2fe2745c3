"""The derived index: kernels against plain searches, updates against those of the written index, and no label rows written."""

import numpy as np
import pytest
from test_searches import random_graph, rows
from test_update_searches import told

from tallypath.operators import delete, index, insert, kernels, query
from tallypath.plans import relational, workloads  # noqa: F401  relational registers its queries

SF = "/root/testdata/sf0.001"


def arcs(n=150, m=260, seed=3):
    pairs = {(a, b) for a, b in np.random.default_rng(seed).integers(0, n, (m, 2)).tolist() if a != b}
    both = np.array(sorted(pairs | {(b, a) for a, b in pairs}))
    return kernels.Arcs(np.concatenate([[0], np.cumsum(np.bincount(both[:, 0], minlength=n))]), both[:, 1].astype(np.int32), True)


def test_searches_without_counts_reach_the_rows_of_those_with_counts():
    a = arcs()
    found = {}
    for lo in range(0, a.n, 64):
        hubs = np.arange(lo, min(a.n, lo + 64))
        for dist, owner, place, paths, full in kernels.levels(a, hubs, full=True):
            found |= {(h, o): (dist, p == f) for h, o, p, f in zip(hubs[place].tolist(), owner.tolist(), paths.tolist(), full.tolist())}
        for alone in (False, True):
            got = {(h, o): d for d, x in enumerate(kernels.reached(a, hubs, alone=alone)) for o, h in zip(*(y.tolist() for y in kernels.spread(*x, len(hubs))))}
            assert {(h - lo, o): d for (h, o), (d, same) in found.items() if h >= lo and (same or not alone)} == got
    for owner in range(a.n):
        assert sorted(kernels.hubs_of(a, owner).tolist()) == sorted(h for h, o in found if o == owner)
    assert sorted(kernels.in_order(a).tolist()) == list(range(a.n))


def test_distances_alone_by_searches(spark):
    g = random_graph(spark, 50, 90)
    want, ix = (index.build(g, distance_only=True, strategy=s) for s in ("rounds", "derived"))
    assert rows(ix.labels) == rows(want.labels) and rows(index.in_vertices(ix)) == rows(index.in_vertices(want))


def test_updates_of_a_derived_index_are_those_of_the_written_one(spark, monkeypatch):
    g = random_graph(spark, 50, 90)
    e = [tuple(r) for r in g.edges.orderBy("u", "v").collect()]
    v = sorted({x for p in e for x in p})
    new = [(a, b) for a, b in zip(v, v[7:]) if (a, b) not in e]
    state = {s: (g, index.build(g, strategy=s)) for s in ("searches", "derived")}
    assert state["derived"][1].source is g and index.rows_in(state["derived"][1]) == state["searches"][1].labels.count()
    ways = [lambda g, ix: insert.run(g, ix, spark.createDataFrame(new[:3], "u long, v long"), strategy="searches"), lambda g, ix: delete.run(g, ix, *e[0], strategy="searches", shortcut=False)]
    for way in [*ways, lambda g, ix: insert.run(g, ix, spark.createDataFrame(new[3:5], "u long, v long"), strategy="searches")]:
        ups = {s: way(*x) for s, x in state.items()}
        assert told(ups["searches"]) == told(ups["derived"]) and told(ups["derived"])
        state = {s: (up.graph, up.index) for s, up in ups.items()}
    assert rows(state["derived"][1].labels) == rows(state["searches"][1].labels)
    assert index.rows_in(state["derived"][1]) == state["searches"][1].labels.count()


def test_differences_of_few_hubs_at_a_time():
    a, b = arcs(), arcs(seed=4)
    every = lambda owner, place: np.ones(len(owner), bool)
    hubs, none = np.arange(64), np.zeros(0, np.int64)
    assert kernels.differences(a, b, hubs, every, none, most=10) is None
    told = lambda hubs: {(int(hubs[p]), int(o)): tuple(map(int, x)) for o, p, *x in zip(*kernels.differences(a, b, hubs, every, none))}
    assert told(hubs) == told(hubs[:32]) | told(hubs[32:])


@pytest.mark.parametrize("directed", [False, True])
def test_lists_are_packed_by_columns(spark, monkeypatch, directed):
    monkeypatch.setattr(query, "PACKED", 40)
    ix = index.build(random_graph(spark, 40, 60, directed=directed))
    got = query.packed(ix)
    assert "collect_list" not in got._jdf.queryExecution().optimizedPlan().toString()
    want = {}
    for r in ix.labels.orderBy("hub").collect():
        want.setdefault((r["side"], r["owner"]), []).append((r["hub"], r["dist"], r["paths"]))
    assert {(r["side"], r["owner"]): [tuple(x) for x in r["rows"]] for r in got.collect()} == want and got.count() == len(want)


def written_names(monkeypatch):
    workloads._KEPT.clear()
    names, write = [], index.write
    monkeypatch.setattr(index, "write", lambda df, name, **x: names.append(name) or write(df, name, **x))
    return names


@pytest.mark.parametrize("name", ["op_cube", "op_full_outer_diff", "op_grouping_sets", "op_rollup", "op_stream_dedupe_late", "w_bound_terms", "w_delete_changes", "w_distance_only_index"])
def test_queries_of_changes_write_no_label_rows(spark, monkeypatch, name):
    names = written_names(monkeypatch)
    assert workloads.QUERIES[name](spark, SF).count() and "labels" not in names
