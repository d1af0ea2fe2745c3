"""Mixed sequences of updates, vertices that come and go, and the choice between repair and rebuild."""

from __future__ import annotations

import time
from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.scratch import written
from . import delete, insert, ranking
from .graph import Graph, validate_changes
from .index import LabelIndex, build, self_rows

METRICS = "seq long, op string, renew_count long, renew_dist long, inserted long, removed long, rounds int, ms double, bytes long, rejected long"


def metrics_row(seq: int, op: str, changes: DataFrame, rounds: int, ms: float, rejected: int = 0) -> tuple:
    """One row of update metrics; an index row counts 8 bytes; ``rejected`` edges were left alone."""
    n = {r["op"]: r["n"] for r in changes.groupBy("op").agg(F.count("*").alias("n")).collect()}  # four operations at most
    got = [n.get(k, 0) for k in ("renew_count", "renew_dist", "insert", "remove")]
    return (seq, op, *got, rounds, ms, 8 * (got[2] - got[3]), rejected)


def apply(g: Graph, ix: LabelIndex, changes: DataFrame, batch_inserts: bool = False, **options) -> tuple[Graph, LabelIndex, DataFrame]:
    """Applies ``changes`` (seq, op, u, v[, w]) in order of seq; op is insert, delete or reweight.

    ``batch_inserts`` repairs runs of consecutive insertions together. ``strategy`` is that of insertions and deletions
    ('searches' holds for both, the others are of deletions alone). The change list is a bounded batch; each
    change reads and writes only tables. Changes that don't fit the graph as it is at their turn (an edge that exists or
    doesn't, a loop, an unknown vertex) are counted as ``rejected`` and skipped. Returns graph, index and one metrics row for each repair.
    """
    spark = ix.labels.sparkSession
    kind = "u long, v long" + ", w long" * g.weighted
    rows = [r.asDict() for r in changes.orderBy("seq").collect()]
    metrics, at = [], 0
    while at < len(rows):
        r, began, upto = rows[at], time.time(), at + 1
        if r["op"] == "insert":
            while batch_inserts and upto < len(rows) and rows[upto]["op"] == "insert":
                upto += 1
            new = [(x["u"], x["v"], x["w"]) if g.weighted else (x["u"], x["v"]) for x in rows[at:upto]]
            up = insert.run(g, ix, spark.createDataFrame(new, kind), dominated=options.get("dominated", "keep"), strategy=options.get("strategy"))
        elif r["op"] == "delete":
            up = delete.run(g, ix, r["u"], r["v"], **{k: v for k, v in options.items() if k in ("removal", "definition", "strategy", "shortcut")})
        else:
            one = spark.createDataFrame([(r["u"], r["v"], r["w"])], kind)
            checked = validate_changes(g, one.withColumn("op", F.lit("reweight"))).first()
            known = checked["problem"] is None
            now = g.edges.join(spark.createDataFrame([(checked["u"], checked["v"])], "u long, v long"), ["u", "v"], "left_semi").first()["w"] if known else None
            if known and r["w"] > now:
                up = delete.increase_weight(g, ix, r["u"], r["v"], r["w"])
            else:  # a lower weight; an equal one and an unknown edge are rejected there
                up = insert.decrease_weight(g, ix, one if known else one.where(F.lit(False)))
                if not known:
                    up.rejects, up.rejected = one.withColumn("problem", F.lit(checked["problem"])), 1
        metrics.append(metrics_row(r["seq"], r["op"], up.changes, len(up.rounds), (time.time() - began) * 1000, up.rejected))
        g, ix, at = up.graph, up.index, upto
    return g, ix, spark.createDataFrame(metrics, METRICS)


def add_vertex(g: Graph, ix: LabelIndex, vertex: int, neighbors: list[int] | None = None) -> tuple[Graph, LabelIndex]:
    """A new vertex at the bottom of the order with its own label, then its edges in one repair (undirected or outgoing)."""
    spark = ix.labels.sparkSession
    new = spark.createDataFrame([(vertex,)], "vertex long")
    ranks = written(ranking.append(g.ranks, new), "ranks")
    alone = replace(g, ranks=ranks.join(new, "vertex"))
    g, ix = replace(g, ranks=ranks), replace(ix.changed(self_rows(alone).withColumn("op", F.lit("insert"))), ranks=ranks)
    if neighbors:
        up = insert.run(g, ix, spark.createDataFrame([(vertex, x) for x in neighbors], "u long, v long"))
        g, ix = up.graph, up.index
    return g, ix


def remove_vertex(g: Graph, ix: LabelIndex, vertex: int) -> tuple[Graph, LabelIndex]:
    """Deletes the edges of a vertex one by one, then its own label and place in the order."""
    edges = g.edges.where((F.col("u") == vertex) | (F.col("v") == vertex)).orderBy("u", "v").collect()
    for e in edges:
        up = delete.run(g, ix, e["u"], e["v"])
        g, ix = up.graph, up.index
    rank = g.ranks.where(F.col("vertex") == vertex).select("rank")
    own = ix.labels.join(F.broadcast(rank.withColumnRenamed("rank", "owner")), "owner", "left_semi")  # one row
    ranks = written(g.ranks.where(F.col("vertex") != vertex), "ranks")
    return replace(g, ranks=ranks), replace(ix.changed(own.withColumn("op", F.lit("remove"))), ranks=ranks)


def choose(g: Graph, ix: LabelIndex, a: int, b: int, share: float = 0.3) -> str:
    """'repair' or 'rebuild' for a deletion: rebuild if more than ``share`` of the index is in question."""
    from .query import rank_of

    ra, rb = rank_of(ix, a), rank_of(ix, b)
    sets = delete.roles(ix, delete.affected(ix, ra, rb), ra, rb)
    n = delete.suspect_rows(ix.labels, written(sets, "sets"), g.directed).count()
    return "rebuild" if n > share * ix.labels.count() else "repair"


def rebuild(g: Graph) -> LabelIndex:
    return build(g)


__all__ = ["add_vertex", "apply", "choose", "rebuild", "remove_vertex", "validate_changes"]
