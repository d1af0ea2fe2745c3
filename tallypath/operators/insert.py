"""The insert maintainer: new edges, and weights that fall."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.scratch import write, written
from .graph import Graph, apply_changes, rank_arcs, validate_changes
from .index import KEY, LabelIndex, Settled, differences, expand, lists_of, overlaid, purge_dominated, searched, settle


@dataclass
class Update:
    """An update's result: graph, index, ``changes`` (side, owner, hub, old and new distance and count, op), and ``rejects``.

    ``rejects`` (u, v[, w], problem) are the edges that the update left alone, see ``graph.validate_changes``.
    """

    graph: Graph
    index: LabelIndex
    changes: DataFrame
    rounds: list[dict]
    trace: DataFrame | None = None
    sets: DataFrame | None = None
    rejects: DataFrame | None = None
    rejected: int = 0


def roots(ix: LabelIndex, arcs: DataFrame) -> DataFrame:
    """(side, hub): the hubs of the endpoints before the insertion, from which repair starts."""
    ends = arcs.select("side", F.col("src").alias("owner")).union(arcs.select("side", F.col("dst"))).distinct()
    return lists_of(ix, ends).select("side", "hub").distinct()


def seeds(ix: LabelIndex, arcs: DataFrame) -> DataFrame:
    """Old labels of one end carried over the new arcs with their own (rank-restricted) counts."""
    return expand(ix.labels, arcs)


def run(g: Graph, ix: LabelIndex, added: DataFrame, schedule: str = "level", prune: str = "relaxed", dominated: str = "keep", trace: bool = False, strategy: str | None = None) -> Update:
    """Inserts the edges ``added`` (u, v[, w]) between known vertices, all in one repair.

    Loops, edges that are there already, repeated ones and those with unknown ends are left out and returned as ``rejects``:
    a path over an edge that is inserted twice would be counted twice.

    New top-hub paths are split at their first new edge: before it lies an old label of the edge's end, after it the
    search goes on over old and new arcs alike, adding up counts of new paths only. ``schedule='rank'`` takes the
    roots in rank order, one search each. ``prune='strict'`` stops at equal distances (distance-label baseline).
    ``dominated='purge'`` removes rows that the insertion made too long; they are kept by default.
    ``strategy='searches'``: all roots search the new graph in blocks (``index.searched``), without rounds, and rows that are new
    or other than before are the changes (a derived index is asked only for the rows of its roots, see ``index.differences``); a directed graph, or one that doesn't allow it, is repaired as by default.
    """
    columns = ["u", "v", *["w"] * g.weighted]
    tested = write(validate_changes(g, added.select(F.lit("insert").alias("op"), *columns)), "checked", wrong=F.count_if(F.col("problem").isNotNull()))
    checked = tested.df
    added, rejects = checked.where(F.col("problem").isNull()).select(*columns), checked.where(F.col("problem").isNotNull()).drop("op")
    g2 = apply_changes(g, added=added)
    arcs = written(rank_arcs(added, g.ranks, g.directed, g.weighted), "new-arcs")
    first = seeds(ix, arcs)
    by_searches = strategy == "searches" and prune == "relaxed" and not g.directed
    ends = written(roots(ix, arcs), "roots") if by_searches else None
    differ = differences(ix, g2, ends) if by_searches else None
    found = searched(g2, hubs=ends) if by_searches and differ is None else None
    if differ is not None:
        got = Settled(_told(differ.where(F.col("dist").isNotNull())), [])
    elif found is not None:
        got = Settled(_compared(ix, found, ends), [])
    elif schedule == "rank":
        base, rounds, deltas = ix.labels, [], []
        for r in roots(ix, arcs).select("hub").distinct().orderBy("hub").collect():  # two label lists at most
            got = settle(base, g2.arcs, first.where(F.col("hub") == r["hub"]), equal=prune == "strict")
            rounds += got.rounds
            deltas.append(got.delta)
            base = written(overlaid(base, got.delta), "labels")
        delta = deltas[0] if deltas else None
        for d in deltas[1:]:
            delta = delta.unionByName(d)
        got = Settled(delta if delta is not None else settle(ix.labels, g2.arcs, first).delta, rounds)
    else:
        got = settle(ix.labels, g2.arcs, first, equal=prune == "strict")
    new = ix.changed(got.delta if schedule != "rank" else _last(got.delta), g2)
    if dominated == "purge":
        new = purge_dominated(new)
    changes = got.delta.select(*KEY, "old_dist", "old_paths", "dist", "paths", "op")
    return Update(g2, new, changes, got.rounds, got.delta if trace else None, rejects=rejects, rejected=tested.seen["wrong"] or 0)


def _compared(ix: LabelIndex, found: DataFrame, hubs: DataFrame) -> DataFrame:
    """The rows of ``found`` that the index lacks or has otherwise, as ``settle`` returns them; written. The round is the distance."""
    old = ix.labels.join(hubs, ["side", "hub"], "left_semi").select(*KEY, F.col("dist").alias("old_dist"), F.col("paths").alias("old_paths"))
    rows = found.join(hubs, ["side", "hub"], "left_semi").join(old, KEY, "left")
    return _told(rows.where(F.col("old_dist").isNull() | (F.col("old_dist") != F.col("dist")) | (F.col("old_paths") != F.col("paths"))))


def _told(rows: DataFrame) -> DataFrame:
    """``rows`` (KEY, old_dist, old_paths, dist, paths) with their operation, as ``settle`` returns them; written."""
    same = F.col("old_dist") == F.col("dist")
    op = F.when(F.col("old_dist").isNull(), "insert").when(same, "renew_count").otherwise("renew_dist")
    added = F.when(same, F.col("paths") - F.col("old_paths")).otherwise(F.col("paths"))
    return written(rows.select(*KEY, "dist", "paths", added.alias("added"), "old_dist", "old_paths", op.alias("op"), F.col("dist").alias("round")), "delta")


def _last(delta: DataFrame) -> DataFrame:
    """The last row of each key: roots taken one after the other never share a hub, so keys are distinct already."""
    return delta.dropDuplicates(KEY)


def decrease_weight(g: Graph, ix: LabelIndex, changed: DataFrame, **options) -> Update:
    """Weights that fall are insertions with the new weight; rows that would raise one are rejected."""
    return run(g, ix, changed, **options)
