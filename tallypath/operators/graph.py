"""Graphs as edge tables, their arcs in rank space, and changes to them."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..sources.scratch import Layered, write, written


@dataclass(frozen=True)
class Graph:
    """``edges`` (u, v[, w]) with u < v unless directed; ``ranks`` (vertex, rank), rank 1 on top; ``arcs`` (side, src, dst, w) in ranks.

    ``side`` is 'u' in an undirected graph. In a directed one 'in' holds the arcs as they are (searches that
    fill in-lists follow them) and 'out' the reversed ones.
    """

    edge_table: Layered
    ranks: DataFrame
    arc_table: Layered
    directed: bool = False
    weighted: bool = False

    @property
    def edges(self) -> DataFrame:
        return self.edge_table.rows

    @property
    def arcs(self) -> DataFrame:
        return self.arc_table.rows


def simple_edges(df: DataFrame, src: str, dst: str, directed: bool = False, weight: str | None = None) -> DataFrame:
    """Distinct edges without loops and nulls; of parallel edges the least weight."""
    a, b = F.col(src).cast("long"), F.col(dst).cast("long")
    u, v = (a, b) if directed else (F.least(a, b), F.greatest(a, b))
    pairs = df.where(a.isNotNull() & b.isNotNull() & (a != b)).select(u.alias("u"), v.alias("v"), *([F.col(weight).cast("long").alias("w")] if weight else []))
    return pairs.groupBy("u", "v").agg(F.min("w").alias("w")) if weight else pairs.distinct()


def vertices(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("u").alias("vertex")).union(edges.select("v")).distinct()


def both_ways(edges: DataFrame) -> DataFrame:
    """(u, v[, w]) of both orientations."""
    rest = [c for c in edges.columns if c not in ("u", "v")]
    return edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v"), *rest))


def degrees(edges: DataFrame) -> DataFrame:
    """(vertex, degree); in a directed graph arcs of either direction count."""
    ends = edges.select(F.explode(F.array("u", "v")).alias("vertex"))
    return ends.groupBy("vertex").agg(F.count("*").alias("degree"))


def edge_degree(edges: DataFrame, of: DataFrame | None = None) -> DataFrame:
    """(u, v, deg_product) of ``of`` (default: the edges themselves); a vertex without edges has degree 0."""
    d = degrees(edges)
    e = (of if of is not None else edges).select("u", "v")
    e = e.join(d.select(F.col("vertex").alias("u"), F.col("degree").alias("du")), "u", "left").join(d.select(F.col("vertex").alias("v"), F.col("degree").alias("dv")), "v", "left")
    return e.select("u", "v", (F.coalesce("du", F.lit(0)) * F.coalesce("dv", F.lit(0))).alias("deg_product"))


def neighbors(edges: DataFrame, of: DataFrame, directed: bool = False) -> DataFrame:
    """(vertex, neighbor) of the vertices in ``of``."""
    arcs = edges if directed else both_ways(edges)
    return arcs.join(of.select(F.col("vertex").alias("u")), "u").select(F.col("u").alias("vertex"), F.col("v").alias("neighbor"))


def to_undirected(edges: DataFrame) -> DataFrame:
    return simple_edges(edges, "u", "v", weight="w" if "w" in edges.columns else None)


def stats(edges: DataFrame) -> DataFrame:
    """One row: n, m."""
    return vertices(edges).agg(F.count("*").alias("n")).crossJoin(edges.agg(F.count("*").alias("m")))  # one row each


def rank_arcs(edges: DataFrame, ranks: DataFrame, directed: bool, weighted: bool) -> DataFrame:
    w = F.col("w") if weighted else F.lit(1)
    r = edges.join(ranks.select(F.col("vertex").alias("u"), F.col("rank").alias("ru")), "u").join(ranks.select(F.col("vertex").alias("v"), F.col("rank").alias("rv")), "v").withColumn("len", w.cast("int"))
    arc = lambda side, a, b: r.select(F.lit(side).alias("side"), F.col(a).alias("src"), F.col(b).alias("dst"), F.col("len").alias("w"))
    return arc("in", "ru", "rv").union(arc("out", "rv", "ru")) if directed else arc("u", "ru", "rv").union(arc("u", "rv", "ru"))


def make(edges: DataFrame, ranks: DataFrame, directed: bool = False, weighted: bool = False) -> Graph:
    """A graph whose tables are written, so that rounds read them without recomputing."""
    edges, ranks = write(edges, "edges"), written(ranks, "ranks")
    arcs = write(rank_arcs(edges.df, ranks, directed, weighted), "arcs")
    return Graph(Layered(edges.df, ("u", "v"), edges.seen["n"]), ranks, Layered(arcs.df, ("side", "src", "dst"), arcs.seen["n"]), directed, weighted)


def below(g: Graph, hub_rank: int) -> DataFrame:
    """Arcs of the subgraph that hub ``hub_rank`` may search: no vertex ranked above it."""
    return g.arcs.where((F.col("src") >= hub_rank) & (F.col("dst") > hub_rank))


def sides(directed: bool) -> list[str]:
    return ["in", "out"] if directed else ["u"]


def opposite(side: Column) -> Column:
    return F.when(side == "in", F.lit("out")).when(side == "out", F.lit("in")).otherwise(side)


def _canonical(changes: DataFrame, directed: bool) -> DataFrame:
    if directed:
        return changes
    some = F.col("u").isNull() | F.col("v").isNull()  # least and greatest skip nulls
    return changes.withColumns({"u": F.when(some, F.col("u")).otherwise(F.least("u", "v")), "v": F.when(some, F.col("v")).otherwise(F.greatest("u", "v"))})


def apply_changes(g: Graph, added: DataFrame | None = None, removed: DataFrame | None = None) -> Graph:
    """The graph with edges added and removed; the ranks stay. An added edge replaces one that is there (a new weight).

    Only overlays of the edge and arc tables are written, as large as the changes.
    """
    w = [F.lit(1).cast("long").alias("w")] if g.weighted else []
    parts = []
    if removed is not None:
        gone = _canonical(removed, g.directed).select("u", "v", *w).withColumn("gone", F.lit(True))
        parts.append(gone.join(_canonical(added, g.directed).select("u", "v"), ["u", "v"], "left_anti") if added is not None else gone)
    if added is not None:
        parts.append(_canonical(added, g.directed).select("u", "v", *["w"] * g.weighted).withColumn("gone", F.lit(False)))
    if not parts:
        return g
    change = parts[0] if len(parts) == 1 else parts[0].unionByName(parts[1])
    arcs = [rank_arcs(change.where(F.col("gone") == x), g.ranks, g.directed, g.weighted).withColumn("gone", F.lit(x)) for x in (True, False)]
    return replace(g, edge_table=g.edge_table.changed(change), arc_table=g.arc_table.changed(arcs[0].unionByName(arcs[1])))


def validate_changes(g: Graph, changes: DataFrame) -> DataFrame:
    """``changes`` (op, u, v[, w]; op is insert, delete or reweight) with ``problem``, null if valid; ends in canonical order.

    Problems: null key, self loop, unknown vertex, edge exists (in a weighted graph only if it is no heavier than
    the new one: a lighter parallel edge takes its place), no such edge, bad weight, repeated (another row of the list
    says the same; of parallel insertions the lightest stays).
    """
    c = _canonical(changes, g.directed).withColumn("__at", F.monotonically_increasing_id())
    weight = F.col("w") if g.weighted else F.lit(1).cast("long")
    keys = c.select("u", "v").distinct()
    there = g.edges.join(keys, ["u", "v"], "left_semi").select("u", "v", (F.col("w") if g.weighted else F.lit(1)).cast("long").alias("__have"))
    ends = keys.select(F.explode(F.array("u", "v")).alias("vertex")).distinct()
    known = g.ranks.join(ends, "vertex", "left_semi").select("vertex")
    c = c.join(there, ["u", "v"], "left")
    for end in ("u", "v"):
        c = c.join(known.select(F.col("vertex").alias(end), F.lit(True).alias(f"__k{end}")), end, "left")
    twin = F.row_number().over(Window.partitionBy("op", "u", "v").orderBy(weight, "__at"))
    problem = (
        F.when(F.col("u").isNull() | F.col("v").isNull(), "null key")
        .when(F.col("u") == F.col("v"), "self loop")
        .when(F.col("__ku").isNull() | F.col("__kv").isNull(), "unknown vertex")
        .when(F.col("op").isin("delete", "reweight") & F.col("__have").isNull(), "no such edge")
        .when(F.col("op").isin("insert", "reweight") & (weight.isNull() | (weight < 1)), "bad weight")
        .when((F.col("op") == "insert") & (F.col("__have") <= weight), "edge exists")
        .when(twin > 1, "repeated")
    )
    return c.withColumn("problem", problem).select(*changes.columns, "problem")
