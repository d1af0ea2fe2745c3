"""Statements about the index and its updates as checks: each returns the rows that break one, none if it holds."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import delete, query, traversal
from ..operators import index as ixs
from ..operators.graph import Graph
from ..operators.index import KEY, LabelIndex
from ..operators.insert import Update
from .apps import all_answers


def _true(g: Graph) -> DataFrame:
    """(s, t, d, c) of connected pairs in ranks, by search."""
    r = g.ranks
    p = traversal.all_pairs(g).join(r.select(F.col("vertex").alias("source"), F.col("rank").alias("s")), "source").join(r.select("vertex", F.col("rank").alias("t")), "vertex")
    return p.select("s", "t", F.col("dist").alias("d"), F.col("paths").alias("c"))


def covers(ix: LabelIndex, g: Graph) -> DataFrame:
    """Pairs whose query differs from brute force."""
    both = _true(g).join(all_answers(ix), ["s", "t"], "full_outer")
    return both.where(~(F.col("d").eqNullSafe(F.col("dist")) & F.col("c").eqNullSafe(F.col("paths"))))


def counts_bounded(ix: LabelIndex) -> DataFrame:
    """Rows at the pair's distance that count more than the pair has, or whose canonical mark is wrong."""
    c = ixs.classify(ix).where(F.col("dist") == F.col("true"))
    return c.where((F.col("paths") > F.col("full")) | (F.col("canonical") != (F.col("paths") == F.col("full"))))


def well_formed(ix: LabelIndex) -> DataFrame:
    """Hubs ranked below their owner, repeated keys, and missing own rows."""
    below = ix.labels.where(F.col("hub") > F.col("owner")).select(*KEY)
    twice = ix.labels.groupBy(*KEY).count().where("count > 1").select(*KEY)
    own = ix.labels.where((F.col("owner") == F.col("hub")) & (F.col("dist") == 0) & (F.col("paths") == 1)).select("owner")
    missing = ix.ranks.join(own, ix.ranks["rank"] == own["owner"], "left_anti").select(F.lit("").alias("side"), F.col("rank").alias("owner"), F.col("rank").alias("hub"))
    return below.union(twice).union(missing)


def monotone_insert(before: LabelIndex, after: LabelIndex) -> DataFrame:
    """Pairs farther apart after an insertion."""
    b = all_answers(after).select("s", "t", F.col("dist").alias("now"))
    return all_answers(before).join(b, ["s", "t"], "left").where(F.col("now").isNull() | (F.col("now") > F.col("dist")))


def new_paths_factor(before: LabelIndex, after: LabelIndex, a: int, b: int) -> DataFrame:
    """Pairs closer after inserting (a, b) whose count isn't the product of the counts to and from the edge (undirected, ranks)."""
    ra, rb = query.rank_of(before, a), query.rank_of(before, b)
    old, now = all_answers(before).select("s", "t", F.col("dist").alias("was")), all_answers(after)
    closer = now.join(old, ["s", "t"], "left").where(F.col("was").isNull() | (F.col("dist") < F.col("was")))
    to = lambda r, p: all_answers(before).where(F.col("t") == r).select(F.col("s").alias(p), F.col("dist").alias(f"d_{p}"), F.col("paths").alias(f"p_{p}"))
    ways = None
    for x, y in ((ra, rb), (rb, ra)):
        w = closer.join(to(x, "s"), "s").join(to(y, "t"), "t").where(F.col("d_s") + F.col("d_t") + 1 == F.col("dist")).select("s", "t", "dist", "paths", (F.col("p_s") * F.col("p_t")).alias("product"))
        ways = w if ways is None else ways.unionByName(w)
    return ways.groupBy("s", "t", "paths").agg(F.sum("product").alias("product")).where(F.col("product") != F.col("paths"))


def insert_locality(before: LabelIndex, up: Update, a: int, b: int) -> DataFrame:
    """Changed rows whose hub labels neither end of the inserted edge."""
    ends = [query.rank_of(before, a), query.rank_of(before, b)]
    hubs = before.labels.where(F.col("owner").isin(ends)).select("hub").distinct()
    return up.changes.join(hubs, "hub", "left_anti")


def gap(before: LabelIndex, up: Update, a: int, b: int, w: int = 1) -> DataFrame:
    """Vertices of the affected sets whose distances to the ends don't differ by the edge."""
    found = delete.affected(before, query.rank_of(before, a), query.rank_of(before, b), w).select("rank", "side")
    return up.sets.select("rank", "side").exceptAll(found)


def sets_partition(up: Update) -> DataFrame:
    """Vertices in more than one of the four sets (undirected)."""
    return up.sets.groupBy("rank").agg(F.count("*").alias("sets")).where("sets > 1")


def same_side_stable(before: LabelIndex, up: Update) -> DataFrame:
    """Pairs of one side that changed with the deletion."""
    s = up.sets.select("rank", "side")
    pairs = all_answers(before).join(s.select(F.col("rank").alias("s"), F.col("side").alias("x")), "s").join(s.select(F.col("rank").alias("t"), F.col("side").alias("y")), "t").where("x = y")
    now = all_answers(up.index).select("s", "t", F.col("dist").alias("d"), F.col("paths").alias("c"))
    return pairs.join(now, ["s", "t"], "left").where(~(F.col("d").eqNullSafe(F.col("dist")) & F.col("c").eqNullSafe(F.col("paths"))))


def delete_locality(up: Update, directed: bool = False) -> DataFrame:
    """Changed rows outside roots x touched vertices of the other side."""
    hubs, owners = delete._tables(up.sets, directed)
    inside = up.changes.join(owners, ["side", "owner"]).join(hubs, ["side", "hub", "zone"], "left_semi").select(*KEY)
    return up.changes.join(inside.distinct(), KEY, "left_anti")
