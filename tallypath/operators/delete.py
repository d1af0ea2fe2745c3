"""The delete maintainer: an edge that goes, and weights that rise."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.scratch import write, written
from .graph import Graph, apply_changes, degrees
from .index import KEY, LabelIndex, Settled, differences, expand, lists_of, overlaid, searched, settle, would_be_rounds
from .insert import Update
from .query import from_rank, ranks_of, to_rank


def affected(ix: LabelIndex, a: int, b: int, w: int = 1) -> DataFrame:
    """(rank, side, dist, paths_near, paths_far): vertices whose distances to the ends (ranks ``a``, ``b``) differ by the edge.

    Side 'a' holds those nearer to a. Two single-source queries for each side answer it for all vertices at once.
    """

    def one(near: DataFrame, far: DataFrame, side: str) -> DataFrame:
        f = far.select("rank", F.col("dist").alias("far"), F.col("paths").alias("paths_far"))
        return near.join(f, "rank").where(F.col("dist") + w == F.col("far")).select("rank", F.lit(side).alias("side"), "dist", F.col("paths").alias("paths_near"), "paths_far")

    to_a, to_b = to_rank(ix, a), to_rank(ix, b)
    if not ix.directed:
        to_a, to_b = written(to_a, "from-end"), written(to_b, "from-end")
    return one(to_a, to_b, "a").unionByName(one(from_rank(ix, b), from_rank(ix, a), "b") if ix.directed else one(to_b, to_a, "b"))


def cut_searches(g: Graph, ix: LabelIndex, a: int, b: int, w: int = 1) -> DataFrame:
    """As ``affected``, by two searches on the old graph, one from each end (vertices ``a``, ``b``).

    A search goes on only at vertices whose distance to the far end, asked of the index, is longer by the edge; their shortest
    paths to the near end run over such vertices alone, so the counts it adds up are whole.
    """
    spark = g.edges.sparkSession
    ra, rb = ranks_of(ix, a, b)
    arcs = lambda side: g.arcs.where(F.col("side") == side).select("src", "dst", "w")
    found = None
    for side, near, far, way in (("a", ra, to_rank(ix, rb), "out"), ("b", rb, from_rank(ix, ra), "in")):
        far = written(far.select("rank", F.col("dist").alias("far"), F.col("paths").alias("paths_far")), "far")
        steps = arcs(way if g.directed else "u")
        pend, paths = write(spark.createDataFrame([(near, 0, 1)], "rank long, dist int, paths_near long"), "pending", least=F.min("dist")), []
        while pend.seen["n"]:
            d = pend.seen["least"]
            cut = pend.df.where(F.col("dist") == d).join(far, "rank").where(F.col("dist") + w == F.col("far"))
            level = write(cut.select("rank", F.lit(side).alias("side"), "dist", "paths_near", "paths_far"), "level")
            paths.append(level.path)
            seen = spark.read.schema(level.df.schema).parquet(*paths).select("rank")
            nxt = level.df.join(steps, F.col("rank") == F.col("src")).select(F.col("dst").alias("rank"), (F.col("dist") + F.col("w")).cast("int").alias("dist"), "paths_near")
            nxt = nxt.unionByName(pend.df.where(F.col("dist") > d)).join(seen, "rank", "left_anti")
            pend = write(nxt.groupBy("rank", "dist").agg(F.sum("paths_near").alias("paths_near")), "pending", least=F.min("dist"))
        part = spark.read.schema(level.df.schema).parquet(*paths)
        found = part if found is None else found.unionByName(part)
    return found


def upper_bounds(labels: DataFrame, side: str, hub: int) -> DataFrame:
    """(owner, bound): the distance between ``hub`` and each owner over hubs ranked above ``hub``; an upper bound."""
    mine = labels.where((F.col("owner") == hub) & (F.col("side") == {"in": "out", "out": "in", "u": "u"}[side]) & (F.col("hub") < hub)).select("hub", F.col("dist").alias("d1"))
    return labels.where((F.col("side") == side) & (F.col("hub") < hub)).join(mine, "hub").groupBy("owner").agg(F.min(F.col("dist") + F.col("d1")).alias("bound"))


def _root_by_root(g: Graph, ix: LabelIndex, sets: DataFrame, removal: str) -> tuple[DataFrame, list[dict]]:
    """Changes of a deletion: each root in order of rank searches ``g`` (the new graph), confirms or renews its rows at the far side, and loses the others there."""
    spark = g.edges.sparkSession
    hubs, owners = (written(x, "tables") for x in _tables(sets, g.directed))
    common = {r["rank"] for r in sets.where(F.col("role") == "root_hub").select("rank").distinct().collect()}  # two label lists at most
    now, parts, rounds = ix.labels, [], []
    for r in hubs.orderBy("hub", "side").toLocalIterator():  # one root after the other: this is the sequential procedure
        side, hub = r["side"], r["hub"]
        far = owners.where((F.col("side") == side) & (F.col("zone") == r["zone"])).select("owner")
        bound = written(upper_bounds(now, side, hub), "bounds")
        steps = g.arcs.where((F.col("side") == side) & (F.col("dst") > hub)).select("src", "dst", "w")
        pend, paths = write(spark.createDataFrame([(hub, 0, 1)], "owner long, dist int, paths long"), "pending", least=F.min("dist")), []
        while pend.seen["n"]:
            d = pend.seen["least"]
            level = write(pend.df.where(F.col("dist") == d).join(bound.where(F.col("bound") < d).select("owner"), "owner", "left_anti"), "level")
            rounds.append({"dist": d, "candidates": pend.seen["n"], "settled": level.seen["n"]})
            paths.append(level.path)
            seen = spark.read.schema(level.df.schema).parquet(*paths).select("owner")
            nxt = level.df.join(steps, F.col("owner") == F.col("src")).select(F.col("dst").alias("owner"), (F.col("dist") + F.col("w")).cast("int").alias("dist"), "paths")
            nxt = nxt.unionByName(pend.df.where(F.col("dist") > d)).join(seen, "owner", "left_anti")
            pend = write(nxt.groupBy("owner", "dist").agg(F.sum("paths").alias("paths")), "pending", least=F.min("dist"))
        reached = spark.read.schema(level.df.schema).parquet(*paths).join(far, "owner", "left_semi").where(F.col("owner") != hub)
        confirmed = reached.select(F.lit(side).alias("side"), "owner", F.lit(hub).cast("long").alias("hub"), "dist", "paths")
        old = now.where((F.col("side") == side) & (F.col("hub") == hub) & (F.col("owner") != hub)).join(far, "owner", "left_semi").select(*KEY, "dist", "paths")
        diff = _diff(old, confirmed)
        part = written(diff if removal == "always" or hub in common else diff.where(F.col("op") != "remove"), "changes")
        parts.append(part)
        now = written(overlaid(now, part).where(F.col("dist").isNotNull()), "labels")
    changes = parts[0] if parts else _diff(ix.labels.limit(0), ix.labels.limit(0))
    for p in parts[1:]:
        changes = changes.unionByName(p)
    return changes, rounds


def roles(ix: LabelIndex, found: DataFrame, a: int, b: int) -> DataFrame:
    """``found`` with ``role``: root_hub (hub of both ends), root_all_paths (all its paths use the edge), receiver."""
    sides = (("a", "in"), ("b", "out")) if ix.directed else (("a", "u"), ("b", "u"))
    ends = ix.labels.sparkSession.createDataFrame([(s, r) for s in sorted({s for _, s in sides}) for r in (a, b)], "side string, owner long")
    lists = lists_of(ix, ends) if ix.source is None else written(lists_of(ix, ends), "lists")
    hubs = lambda side, owner: lists.where((F.col("side") == side) & (F.col("owner") == owner)).select(F.col("hub").alias("rank"))
    common = None
    for side, labels in sides:
        both = hubs(labels, a).intersect(hubs(labels, b)).select("rank", F.lit(side).alias("side"), F.lit(True).alias("common"))
        common = both if common is None else common.unionByName(both)
    role = F.when(F.col("common").isNotNull(), "root_hub").when(F.col("paths_near") == F.col("paths_far"), "root_all_paths").otherwise("receiver")
    return found.join(common, ["rank", "side"], "left").withColumn("role", role).drop("common")


def _tables(sets: DataFrame, directed: bool) -> tuple[DataFrame, DataFrame]:
    """Roots and touched vertices keyed alike: a root's rows are in question at owners of the other side."""
    label = lambda zone: (F.when(zone == "b", F.lit("in")).otherwise(F.lit("out")) if directed else F.lit("u"))
    other = F.when(F.col("side") == "a", "b").otherwise("a")
    hubs = sets.where(F.col("role") != "receiver").select(F.col("rank").alias("hub"), other.alias("zone"))
    hubs = hubs.select(label(F.col("zone")).alias("side"), "hub", "zone")
    owners = sets.select(label(F.col("side")).alias("side"), F.col("rank").alias("owner"), F.col("side").alias("zone"))
    return hubs, owners


def suspect_rows(labels: DataFrame, sets: DataFrame, directed: bool = False) -> DataFrame:
    """Rows that may change: hub a root of one side, owner touched on the other."""
    hubs, owners = _tables(sets, directed)
    return labels.where(F.col("owner") != F.col("hub")).join(owners, ["side", "owner"]).join(hubs, ["side", "hub", "zone"], "left_semi").drop("zone").distinct()


def isolated_shortcut(g: Graph, a: int, b: int, ra: int, rb: int) -> tuple[int, int] | None:
    """(vertex, its rank) that the deletion isolates and that is ranked below its neighbour; None if there is none.

    Ranks are compared, not only degrees: ranks stay while degrees change.
    """
    if g.directed:
        return None
    deg = {r["vertex"]: r["degree"] for r in degrees(g.edges.where(F.col("u").isin(a, b) | F.col("v").isin(a, b))).where(F.col("vertex").isin(a, b)).collect()}
    for v, rv, other in ((b, rb, ra), (a, ra, rb)):
        if deg.get(v) == 1 and rv > other:
            return v, rv
    return None


def _op():
    return (
        F.when(F.col("dist").isNull(), "remove")
        .when(F.col("old_dist").isNull(), "insert")
        .when(F.col("old_dist") != F.col("dist"), "renew_dist")
        .when(F.col("old_paths") != F.col("paths"), "renew_count")
    )


def _diff(withheld: DataFrame, confirmed: DataFrame) -> DataFrame:
    old = withheld.select(*KEY, F.col("dist").alias("old_dist"), F.col("paths").alias("old_paths"))
    new = confirmed.select(*KEY, "dist", "paths")
    return old.join(new, KEY, "full_outer").withColumn("op", _op()).where(F.col("op").isNotNull()).select(*KEY, "old_dist", "old_paths", "dist", "paths", "op")


def _sets(g: Graph, g2: Graph, ix: LabelIndex, a: int, b: int, w: int, definition: str) -> DataFrame:
    sets = roles(ix, affected(ix, a, b, w), a, b)
    if definition == "gap_all":
        return sets.withColumn("role", F.when(F.col("role") == "receiver", F.lit("root_gap")).otherwise(F.col("role")))
    if definition == "real_only":
        # Only vertices whose distance to the far end really changes act; too few for counts.
        from .traversal import plain_arcs, search

        spark = g.edges.sparkSession
        name = {r["rank"]: r["vertex"] for r in g.ranks.where(F.col("rank").isin(a, b)).collect()}
        arcs = plain_arcs(g2)
        back = arcs.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "w")
        far = {}
        for side, end, way in (("a", b, back), ("b", a, arcs)):
            d = search(way, spark.createDataFrame([(name[end],)], "source long"))
            far[side] = d.join(g.ranks, "vertex").select("rank", F.lit(side).alias("side"), F.col("dist").alias("now"))
        sets = sets.join(far["a"].unionByName(far["b"]), ["rank", "side"], "left").where(F.col("now").isNull() | (F.col("now") != F.col("dist") + w)).drop("now")
        return sets.withColumn("role", F.lit("root_real"))
    return sets


def find_sets(g: Graph, ix: LabelIndex, a: int, b: int) -> DataFrame:
    """(rank, side, dist, paths_near, paths_far, role) of the vertices that deleting the edge (a, b) would touch."""
    own = g.edges.where((F.col("u").isin(a, b)) & F.col("v").isin(a, b)).agg(F.min("w")).first()[0] if g.weighted else 1
    ra, rb = ranks_of(ix, a, b)
    return written(_sets(g, g, ix, ra, rb, own, "roots"), "sets")


def run(
    g: Graph, ix: LabelIndex, a: int, b: int, weight: int | None = None, definition: str = "roots", removal: str = "always", strategy: str = "withhold",
    shortcut: bool = True, schedule: str = "level", trace: bool = False, count_rounds: bool = False,
) -> Update:
    """Deletes the edge (a, b), or raises its weight to ``weight``.

    Rows in question are set aside; what remains is exact or too long, so the rows of unaffected neighbours at the
    border of the touched area seed rounds that derive every missing row again, smallest distance first. Set-aside
    rows that are not derived again are removed: ``removal='always'``. ``'common_hub'`` removes them only for hubs of
    both ends, which is unsafe with dominated rows. ``strategy='drop_then_fill'`` is the baseline that sets aside the
    rows of all affected vertices (as ``definition='gap_all'``); ``'search'`` starts each root's search at the root.
    ``'rooted'`` is the procedure root by root: affected vertices by two cut searches, then for each root in order
    of rank a search on the new graph that the bound of the hubs above the root stops.
    ``'searches'``: all roots search the new graph in blocks (``index.searched``), without rounds, and keep what they reach
    in the touched area, and with ``count_rounds`` tell what the rounds would have seen (a derived index is asked only for the rows in question, see ``index.differences``); a directed graph, or one that doesn't allow it, is treated as by ``'withhold'``. An edge that isn't there, or a weight
    that isn't heavier, is returned in ``rejects`` and changes nothing.
    """
    spark = g.edges.sparkSession
    edge = spark.createDataFrame([(a, b)], "u long, v long")
    if not g.directed:
        edge = edge.select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v"))
    own = g.edges.join(edge, ["u", "v"], "left_semi").first()
    w = own["w"] if own and g.weighted else 1
    problem = "no such edge" if own is None else "not heavier" if weight is not None and weight <= w else None
    if problem:
        none = ix.labels.limit(0)
        return Update(g, ix, _diff(none, none), [], rejects=edge.withColumn("problem", F.lit(problem)), rejected=1)
    if weight is None:
        g2 = apply_changes(g, removed=edge)
    else:
        g2 = apply_changes(g, added=edge.withColumn("w", F.lit(weight).cast("long")))
    ra, rb = ranks_of(ix, a, b)
    if shortcut and weight is None and (alone := isolated_shortcut(g, a, b, ra, rb)):
        rank = alone[1]
        labels = ix.labels
        if ix.source is not None and ix.table.overlay is None:
            labels = searched(ix.source, hubs=lists_of(ix, spark.createDataFrame([("u", rank)], "side string, owner long")))
        gone = labels.where((F.col("owner") == rank) & (F.col("hub") != rank))
        changes = written(_diff(gone, gone.limit(0)), "changes")
        return Update(g2, ix.changed(changes, g2), changes, [], None, None)
    definition = "gap_all" if strategy == "drop_then_fill" else definition
    if strategy == "rooted":
        sets = written(roles(ix, cut_searches(g, ix, a, b, w), ra, rb), "sets")
        changes, rounds = _root_by_root(g2, ix, sets, removal)
        return Update(g2, ix.changed(changes, g2), changes, rounds, None, sets)
    sets = written(_sets(g, g2, ix, ra, rb, w, definition), "sets")
    hubs, owners = _tables(sets, g.directed)  # projections of a written table
    differ = differences(ix, g2, hubs, owners) if strategy == "searches" and removal == "always" and not trace and not (count_rounds and ix.table.overlay is not None) else None
    if differ is not None:
        changes = written(differ.withColumn("op", _op()).select(*KEY, "old_dist", "old_paths", "dist", "paths", "op"), "changes")
        return Update(g2, ix.changed(changes, g2), changes, would_be_rounds(ix, g2, hubs, owners) if count_rounds else [], None, sets)
    suspects = written(suspect_rows(ix.labels, sets, g.directed), "suspects")
    base = ix.labels.join(suspects.select(*KEY), KEY, "left_anti")

    def allowed(rows: DataFrame) -> DataFrame:
        return rows.join(owners, ["side", "owner"]).join(hubs, ["side", "hub", "zone"], "left_semi").select("side", "owner", "hub", "dist", "paths")

    # Border seeds: rows of roots at neighbours of the touched area. Only arcs into the area can lead to a row in question.
    inward = g2.arcs.join(owners.select("side", F.col("owner").alias("dst")), ["side", "dst"], "left_semi").select("side", "src", "dst", "w")
    border = base.join(hubs.select("side", "hub").distinct(), ["side", "hub"], "left_semi").select(*KEY, "dist", "paths")
    first = allowed(expand(border, inward))
    found = searched(g2, hubs=hubs) if strategy == "searches" and not g.directed else None
    if found is not None:
        confirmed = written(allowed(found), "confirmed")
        got = Settled(confirmed, _would_be_rounds(first, confirmed, g2, allowed) if count_rounds else [])
    elif strategy == "search":
        own = base.where(F.col("owner") == F.col("hub")).join(hubs.select("side", "hub").distinct(), ["side", "hub"], "left_semi")
        got = settle(_without(base, hubs, own), g2.arcs, expand(own, g2.arcs))
        confirmed = written(allowed(got.delta.select(*KEY, "dist", "paths")), "confirmed")
    elif schedule == "rank":
        now, rounds, parts = base, [], []
        for r in hubs.select("hub").distinct().orderBy("hub").collect():
            got = settle(now, inward, first.where(F.col("hub") == r["hub"]), allowed)
            rounds += got.rounds
            parts.append(got.delta)
            now = written(overlaid(now, got.delta), "labels")
        got = Settled(parts[0] if parts else settle(base, inward, first, allowed).delta, rounds)
        for p in parts[1:]:
            got.delta = got.delta.unionByName(p)
        confirmed = got.delta.select(*KEY, "dist", "paths")
    else:
        got = settle(base, inward, first, allowed)
        confirmed = got.delta.select(*KEY, "dist", "paths")
    if removal == "common_hub":
        common = sets.where(F.col("role") == "root_hub").select(F.col("rank").alias("hub")).distinct()
        stay = suspects.join(confirmed, KEY, "left_anti").join(common, "hub", "left_anti")
        confirmed = written(confirmed.unionByName(stay.select(*confirmed.columns)), "confirmed")
    changes = written(_diff(suspects, confirmed), "changes")
    return Update(g2, ix.changed(changes, g2), changes, got.rounds, got.delta if trace else None, sets)


def _would_be_rounds(first: DataFrame, confirmed: DataFrame, g2: Graph, allowed) -> list[dict]:
    """The ``rounds`` of ``settle`` from the seeds ``first`` on an unweighted graph, told from what it would settle.

    A round's candidates are the seeds of larger distances, and its own distance's seeds and one-arc extensions of the rows settled
    before, a key once. Each distance with candidates is one round.
    """
    seeds = first.select(*KEY, "dist", F.lit(1).alias("seed"), F.lit(0).alias("settled"))
    grown = allowed(expand(confirmed, g2.arcs)).select(*KEY, "dist", F.lit(0).alias("seed"), F.lit(0).alias("settled"))
    own = confirmed.select(*KEY, "dist", F.lit(0).alias("seed"), F.lit(1).alias("settled"))
    once = seeds.unionByName(grown).unionByName(own).groupBy(*KEY, "dist").agg(F.max("seed").alias("seed"), F.max("settled").alias("settled"))
    levels = once.groupBy("dist").agg(F.count("*").alias("n"), F.sum("seed").alias("seeds"), F.sum("settled").alias("settled")).orderBy("dist").collect()  # a row for each distance
    later = sum(x["seeds"] for x in levels)
    out = []
    for x in levels:
        later -= x["seeds"]
        out.append({"dist": x["dist"], "candidates": later + x["n"], "settled": x["settled"]})
    return out


def _without(base: DataFrame, hubs: DataFrame, own: DataFrame) -> DataFrame:
    """``base`` without the roots' rows but for their own, so that their searches derive them all."""
    return base.join(hubs.select("side", "hub").distinct(), ["side", "hub"], "left_anti").unionByName(own.select(*base.columns))


def increase_weight(g: Graph, ix: LabelIndex, a: int, b: int, weight: int, **options) -> Update:
    """A weight that rises: affected sets by the old weight, rows derived again on the graph with the new one."""
    return run(g, ix, a, b, weight=weight, shortcut=False, **options)
