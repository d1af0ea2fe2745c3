import random

from test_index import make, some_graph

from tallypath.operators import delete, insert
from tallypath.operators import index as ixs
from tallypath.plans import invariants as inv


def test_statements_hold(spark):
    edges = some_graph(31, 10, 16)
    g = make(spark, edges, natural=False)
    ix = ixs.build(g)
    free = [(u, v) for u in range(10) for v in range(u + 1, 10) if (u, v) not in edges]
    a, b = random.Random(1).choice(free)
    up = insert.run(g, ix, spark.createDataFrame([(a, b)], "u long, v long"))
    gone = edges[4]
    cut = delete.run(g, ix, *gone, shortcut=False)
    broken = {
        "covers": inv.covers(ix, g), "counts": inv.counts_bounded(ix), "formed": inv.well_formed(ix), "monotone": inv.monotone_insert(ix, up.index),
        "factor": inv.new_paths_factor(ix, up.index, a, b), "local insert": inv.insert_locality(ix, up, a, b), "gap": inv.gap(ix, cut, *gone), "partition": inv.sets_partition(cut),
        "same side": inv.same_side_stable(ix, cut), "local delete": inv.delete_locality(cut), "after insert": inv.covers(up.index, up.graph), "after delete": inv.covers(cut.index, cut.graph),
    }
    assert {k: v.count() for k, v in broken.items()} == dict.fromkeys(broken, 0)
