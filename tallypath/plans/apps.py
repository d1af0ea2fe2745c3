"""Applications on the index: recommendation and betweenness."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..operators import query, traversal
from ..operators.graph import Graph
from ..operators.index import LabelIndex


def recommend(ix: LabelIndex, vertex: int, distance: int = 2, k: int = 10) -> DataFrame:
    """(vertex, paths, place): those at ``distance``, most shortest paths first, smaller id among equals."""
    at = query.from_source(ix, vertex).where(F.col("dist") == distance)
    top = at.orderBy(F.desc("paths"), F.asc("vertex")).limit(k)
    return top.withColumn("place", F.row_number().over(Window.orderBy(F.desc("paths"), F.asc("vertex"))).cast("long")).select("vertex", "paths", "place")


def all_answers(ix: LabelIndex, within: int | None = None) -> DataFrame:
    """(s, t, dist, paths) of all connected ordered pairs, in ranks, by one hub join; ``within``: of those at most so far apart.

    Then rows of that distance at most are all that is read, and sums beyond it are not made.
    """
    leave, reach = query._lists(ix)
    j = leave.select(F.col("owner").alias("s"), "hub", F.col("dist").alias("d1"), F.col("paths").alias("p1")).join(reach.select(F.col("owner").alias("t"), "hub", F.col("dist").alias("d2"), F.col("paths").alias("p2")), "hub")
    if within is not None:
        j = j.where((F.col("d1") <= within) & (F.col("d2") <= within) & (F.col("d1") + F.col("d2") <= within))
    sums = j.groupBy("s", "t", (F.col("d1") + F.col("d2")).cast("int").alias("sum")).agg(F.sum(F.col("p1") * F.col("p2")).alias("paths"))
    return sums.groupBy("s", "t").agg(F.min(F.struct("sum", "paths")).alias("b")).select("s", "t", F.col("b.sum").alias("dist"), F.col("b.paths").alias("paths"))


def group_betweenness(g: Graph, ix: LabelIndex, group: DataFrame, sample: float | None = None) -> DataFrame:
    """One row (score[, stderr, pairs]): over ordered pairs outside the group, the sum of shares of shortest paths that meet it.

    Paths that avoid the group are counted by searches on the graph without it. ``sample`` takes that share of the
    source vertices by hash and scales up.
    """
    inside = ix.ranks.join(group.select("vertex").distinct(), "vertex").select("rank")
    arcs = g.arcs.where(F.col("side") == ("in" if g.directed else "u")).drop("side")
    arcs = arcs.join(inside.withColumnRenamed("rank", "src"), "src", "left_anti").join(inside.withColumnRenamed("rank", "dst"), "dst", "left_anti").select("src", "dst", "w")
    outside = ix.ranks.join(inside, "rank", "left_anti").select(F.col("rank").alias("source"))
    if sample is not None:
        outside = outside.where(F.pmod(F.xxhash64("source"), F.lit(1 << 20)) < int(sample * (1 << 20)))
    avoid = traversal.search(arcs, outside).select(F.col("source").alias("s"), F.col("vertex").alias("t"), F.col("dist").alias("d"), F.col("paths").alias("free"))
    pairs = all_answers(ix).where(F.col("s") != F.col("t")).join(outside.select(F.col("source").alias("s")), "s")
    pairs = pairs.join(inside.withColumnRenamed("rank", "t"), "t", "left_anti")
    share = F.when(F.col("d") == F.col("dist"), (F.col("paths") - F.col("free")) / F.col("paths")).otherwise(F.lit(1.0))
    shares = pairs.join(avoid, ["s", "t"], "left").select("s", F.when(F.col("d").isNull(), F.lit(1.0)).otherwise(share).alias("x"))
    if sample is None:
        return shares.agg(F.coalesce(F.sum("x"), F.lit(0.0)).alias("score"))
    by = shares.groupBy("s").agg(F.sum("x").alias("x"))
    return by.agg((F.sum("x") / sample).alias("score"), (F.stddev("x") * F.sqrt(F.count("*")) / sample).alias("stderr"), F.count("*").alias("sources"))


def betweenness(ix: LabelIndex, vertices: DataFrame) -> DataFrame:
    """(vertex, score) over ordered pairs: count(s, v) * count(v, t) / count(s, t) where distances add up."""
    mid = ix.ranks.join(vertices.select("vertex").distinct(), "vertex").select("vertex", F.col("rank").alias("v"))
    every = all_answers(ix)
    to = every.join(mid, every["t"] == mid["v"]).select("vertex", "v", "s", F.col("dist").alias("d1"), F.col("paths").alias("p1"))
    on = every.join(mid.select("v"), every["s"] == F.col("v")).select("v", "t", F.col("dist").alias("d2"), F.col("paths").alias("p2"))
    j = to.join(on, "v").where((F.col("s") != F.col("t")) & (F.col("s") != F.col("v")) & (F.col("t") != F.col("v"))).join(every, ["s", "t"]).where(F.col("d1") + F.col("d2") == F.col("dist"))
    score = j.groupBy("vertex").agg(F.sum(F.col("p1") * F.col("p2") / F.col("paths")).alias("score"))
    return mid.select("vertex").join(score, "vertex", "left").select("vertex", F.coalesce("score", F.lit(0.0)).alias("score"))
