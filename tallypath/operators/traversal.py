"""Online searches: counting BFS, bidirectional, Dijkstra, and the brute-force tables made of them.

All are one loop: keyed frontiers, one distance a round, sources together. ``arcs`` is (src, dst, w).
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.scratch import write, written
from .graph import Graph, both_ways

ROW = "source long, vertex long, dist int, paths long"


def plain_arcs(g: Graph) -> DataFrame:
    """(src, dst, w) by vertex id."""
    e = g.edges if g.directed else both_ways(g.edges)
    return e.select(F.col("u").alias("src"), F.col("v").alias("dst"), (F.col("w") if g.weighted else F.lit(1)).cast("int").alias("w"))


def search(arcs: DataFrame, sources: DataFrame, guard=None, stop: DataFrame | None = None, max_rounds: int | None = None) -> DataFrame:
    """(source, vertex, dist, paths): shortest distances and path counts from every row of ``sources`` (source).

    Each round settles the smallest pending distance. ``guard``: a condition on (source, dst) for entering a vertex.
    ``stop`` (source, vertex): a source ends when its vertex is settled (its whole level is).
    """
    spark = arcs.sparkSession
    first = sources.select("source").distinct().select("source", F.col("source").alias("vertex"), F.lit(0).alias("dist"), F.lit(1).cast("long").alias("paths"))
    done = write(first, "level")
    levels, frontier = [done.path], done.df
    pending, rounds = None, 0
    while done.seen["n"] and (max_rounds is None or rounds < max_rounds):
        rounds += 1
        settled = spark.read.schema(ROW).parquet(*levels)
        live = frontier
        if stop is not None:
            reached = settled.join(stop, ["source", "vertex"]).select("source")
            live = live.join(reached, "source", "left_anti")
        step = live.join(arcs, live["vertex"] == arcs["src"])
        if guard is not None:
            step = step.where(guard)
        step = step.groupBy("source", F.col("dst").alias("vertex"), (F.col("dist") + F.col("w")).cast("int").alias("dist")).agg(F.sum("paths").alias("paths"))
        step = step if pending is None else pending.unionByName(step)
        open_ = step.join(settled.select("source", "vertex"), ["source", "vertex"], "left_anti")
        pend = write(open_.groupBy("source", "vertex", "dist").agg(F.sum("paths").alias("paths")), "pending", least=F.min("dist"), most=F.max("dist"))
        d = pend.seen["least"]
        if d is None:
            break
        if d == pend.seen["most"]:
            done, pending = pend, None
        else:
            done = write(pend.df.where(F.col("dist") == d), "level")
            pending = pend.df.where(F.col("dist") > d)
        levels.append(done.path)
        frontier = done.df
    return spark.read.schema(ROW).parquet(*levels)


def bfs_count(g: Graph, source: int, target: int | None = None) -> DataFrame:
    """(vertex, dist, paths) from one vertex; ends with the target's level if one is given."""
    spark = g.edges.sparkSession
    stop = spark.createDataFrame([(source, target)], "source long, vertex long") if target is not None else None
    return search(plain_arcs(g), spark.createDataFrame([(source,)], "source long"), stop=stop).drop("source")


def dijkstra_count(g: Graph, source: int) -> DataFrame:
    """As ``bfs_count``; on a weighted graph the rounds are the distinct distances."""
    return bfs_count(g, source)


def all_pairs(g: Graph, strategy: str | None = None) -> DataFrame:
    """(source, vertex, dist, paths) of every connected pair.

    By searches of blocks of sources (``index.searched``, not written) where the graph allows it, or all sources together, one
    distance a round (``strategy='rounds'``).
    """
    from .index import searched

    found = searched(g, below=False, named=True) if strategy != "rounds" else None
    if found is not None:
        return found.select(F.col("hub").alias("source"), F.col("owner").alias("vertex"), "dist", "paths")
    return search(plain_arcs(g), g.ranks.select(F.col("vertex").alias("source")))


def restricted_counts(g: Graph) -> DataFrame:
    """(side, hub, owner, dist, paths) in ranks: distances and counts over paths on which the hub is top-ranked."""
    found = None
    for side in ("in", "out") if g.directed else ("u",):
        got = search(g.arcs.where(F.col("side") == side).drop("side"), g.ranks.select(F.col("rank").alias("source")), guard=F.col("dst") > F.col("source"))
        got = got.select(F.lit(side).alias("side"), F.col("vertex").alias("owner"), F.col("source").alias("hub"), "dist", "paths")
        found = got if found is None else found.unionByName(got)
    return found


def bfs_count_pairs(g: Graph, pairs: DataFrame, bidirectional: bool = True) -> DataFrame:
    """(qid, s, t, dist, paths) of ``pairs`` (qid, s, t) by search; disconnected pairs have (null, 0)."""
    if bidirectional:
        return bibfs_count_pairs(g, pairs)
    found = search(plain_arcs(g), pairs.select(F.col("s").alias("source")))
    got = found.select(F.col("source").alias("s"), F.col("vertex").alias("t"), "dist", "paths")
    return pairs.join(got, ["s", "t"], "left").select("qid", "s", "t", "dist", F.coalesce("paths", F.lit(0)).alias("paths"))


def bibfs_count_pairs(g: Graph, pairs: DataFrame) -> DataFrame:
    """Two-sided search, whole levels at a time: each round the smaller frontier of every pair grows by one level.

    The sides of a pair meet when a vertex is settled on both; then the sum of its two distances is the pair's, and
    the products of counts over the meeting vertices of the last two levels add up to its count: these vertices lie
    on one cut of the shortest paths.
    """
    spark = pairs.sparkSession
    fore = plain_arcs(g)
    back = fore.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "w") if g.directed else fore
    arcs = written(fore.withColumn("end", F.lit("s")).unionByName(back.withColumn("end", F.lit("t"))), "arcs")
    row = "qid long, end string, vertex long, dist int, paths long"
    start = pairs.select("qid", F.lit("s").alias("end"), F.col("s").alias("vertex")).unionByName(pairs.select("qid", F.lit("t").alias("end"), F.col("t").alias("vertex")))
    level = write(start.select("qid", "end", "vertex", F.lit(0).alias("dist"), F.lit(1).cast("long").alias("paths")), "level")
    paths = [level.path]
    while level.seen["n"]:
        seen = spark.read.schema(row).parquet(*paths)
        depth = seen.groupBy("qid", "end").agg(F.max("dist").alias("dist"))
        last = seen.join(depth, ["qid", "end", "dist"])
        sizes = last.groupBy("qid", "end").agg(F.count("*").alias("size"))
        met = seen.where(F.col("end") == "s").join(seen.where(F.col("end") == "t").select("qid", "vertex"), ["qid", "vertex"]).select("qid").distinct()
        smaller = sizes.groupBy("qid").agg(F.min_by("end", F.struct("size", "end")).alias("end")).join(met, "qid", "left_anti")
        way = arcs.select(F.col("end").alias("way"), "src", "dst")
        grown = last.join(smaller.select("qid", "end"), ["qid", "end"]).join(way, (F.col("vertex") == F.col("src")) & (F.col("end") == F.col("way")))
        grown = grown.groupBy("qid", "end", F.col("dst").alias("vertex"), (F.col("dist") + 1).cast("int").alias("dist")).agg(F.sum("paths").alias("paths"))
        fresh = grown.join(seen.select("qid", "end", "vertex"), ["qid", "end", "vertex"], "left_anti")
        level = write(fresh.select("qid", "end", "vertex", "dist", "paths"), "level")
        paths.append(level.path)
    seen = spark.read.schema(row).parquet(*paths)
    s, t = seen.where(F.col("end") == "s"), seen.where(F.col("end") == "t")
    deep = s.groupBy("qid").agg(F.max("dist").alias("ds"))
    meet = s.select("qid", "vertex", F.col("dist").alias("d1"), F.col("paths").alias("p1")).join(t.select("qid", "vertex", F.col("dist").alias("d2"), F.col("paths").alias("p2")), ["qid", "vertex"])
    best = meet.groupBy("qid").agg(F.min(F.col("d1") + F.col("d2")).alias("dist"))
    # Meeting vertices of one cut: those at the source side's greatest depth that takes part.
    on = meet.join(best, "qid").where(F.col("d1") + F.col("d2") == F.col("dist"))
    cut = on.groupBy("qid").agg(F.max("d1").alias("cut"))
    total = on.join(cut, "qid").where(F.col("d1") == F.col("cut")).groupBy("qid").agg(F.first("dist").alias("dist"), F.sum(F.col("p1") * F.col("p2")).alias("paths"))
    return pairs.join(total, "qid", "left").select("qid", "s", "t", "dist", F.coalesce("paths", F.lit(0)).alias("paths"))


def bibfs_count(g: Graph, s: int, t: int) -> DataFrame:
    return bibfs_count_pairs(g, g.edges.sparkSession.createDataFrame([(0, s, t)], "qid long, s long, t long")).select("dist", "paths")


def list_paths(g: Graph, s: int, t: int, limit: int = 100) -> DataFrame:
    """(path): up to ``limit`` shortest paths of a pair, for explaining results."""
    spark = g.edges.sparkSession
    arcs = plain_arcs(g)
    dist = bfs_count(g, s, t).select("vertex", "dist")
    far = dist.where(F.col("vertex") == t).first()
    walk = spark.createDataFrame([([s], s, 0)], "path array<long>, vertex long, dist int")
    d = dist.select(F.col("vertex").alias("dst"), F.col("dist").alias("at"))
    for _ in range(far["dist"] if far else 0):
        step = walk.join(arcs, walk["vertex"] == arcs["src"]).join(d, "dst").where(F.col("dist") + F.col("w") == F.col("at"))
        walk = written(step.select(F.array_append("path", F.col("dst")).alias("path"), F.col("dst").alias("vertex"), F.col("at").alias("dist")), "walk")
    return walk.where(F.col("vertex") == t).select("path").orderBy("path").limit(limit)


def distance_histogram(g: Graph) -> DataFrame:
    """(dist, pairs) over ordered connected pairs; the largest is the diameter."""
    return all_pairs(g).groupBy("dist").agg(F.count("*").alias("pairs"))
