"""Queries over the label index."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..sources.scratch import written
from .index import LabelIndex, searched

#: Label rows that ``in_blocks`` sends to the workers at most, sources it takes together, rows of a batch.
MOST_ROWS, SOURCES, BATCH = 3_000_000, 64, 1 << 16
#: Label rows that a task of ``packed`` sorts at a time; a bucket of owners holds a quarter of them.
PACKED = 1 << 20


def _lists(ix: LabelIndex) -> tuple[DataFrame, DataFrame]:
    """Labels that leave a source, and labels that reach a target."""
    if ix.directed:
        return ix.labels.where(F.col("side") == "out"), ix.labels.where(F.col("side") == "in")
    return ix.labels, ix.labels


def _hub_sums(ix: LabelIndex, pairs: DataFrame, above_source: bool = False) -> DataFrame:
    """(qid, s, t, hub, sum, product) of the common hubs of each pair."""
    leave, reach = _lists(ix)
    r = ix.ranks
    p = pairs.join(r.select(F.col("vertex").alias("s"), F.col("rank").alias("rs")), "s").join(r.select(F.col("vertex").alias("t"), F.col("rank").alias("rt")), "t")
    p = p.join(leave.select(F.col("owner").alias("rs"), "hub", F.col("dist").alias("d1"), F.col("paths").alias("p1")), "rs")
    if above_source:
        p = p.where(F.col("hub") < F.col("rs"))
    p = p.join(reach.select(F.col("owner").alias("rt"), "hub", F.col("dist").alias("d2"), F.col("paths").alias("p2")), ["rt", "hub"])
    return p.select("qid", "s", "t", "hub", (F.col("d1") + F.col("d2")).cast("int").alias("sum"), (F.col("p1") * F.col("p2")).cast(ix.labels.schema["paths"].dataType).alias("product"))


def pairs(ix: LabelIndex, pairs: DataFrame, above_source: bool = False) -> DataFrame:
    """(qid, s, t, dist, paths) of ``pairs`` (qid, s, t); disconnected pairs have (null, 0).

    ``above_source``: only hubs ranked strictly above the source, an upper bound of the distance.
    """
    sums = _hub_sums(ix, pairs, above_source).groupBy("qid", "sum").agg(F.sum("product").alias("paths"))
    best = sums.groupBy("qid").agg(F.min(F.struct("sum", "paths")).alias("b")).select("qid", F.col("b.sum").alias("dist"), F.col("b.paths").alias("paths"))
    return pairs.join(best, "qid", "left").select("qid", "s", "t", "dist", F.coalesce("paths", F.lit(0)).alias("paths"))


class _Lists:
    """Label lists of all owners as arrays, in order of ``by`` (numbers from 0): those of ``i`` are at first[i] to first[i + 1]."""

    def __init__(self, by: np.ndarray, other: np.ndarray, dist: np.ndarray, paths: np.ndarray, n: int):
        order = np.argsort(by, kind="stable")
        self.first = np.concatenate([[0], np.cumsum(np.bincount(by, minlength=n))]).astype(np.int64)
        self.other, self.dist, self.paths = other[order].astype(np.int32), dist[order], paths[order]
        self.most = int(paths.max(initial=0))


def _answer(source: int, leave: _Lists, reach: _Lists, dist: np.ndarray, paths: np.ndarray) -> np.ndarray:
    """Puts distances and counts from ``source`` into ``dist`` (FAR elsewhere) and ``paths`` (0 elsewhere); the targets put there, maybe repeated."""
    own = slice(leave.first[source], leave.first[source + 1])
    hub = leave.other[own]
    lo = reach.first[hub]
    many = reach.first[hub + 1] - lo
    at = np.arange(int(many.sum())) + np.repeat(lo - (np.cumsum(many) - many), many)
    target, total = reach.other[at], reach.dist[at] + np.repeat(leave.dist[own], many)
    np.minimum.at(dist, target, total)
    best = np.flatnonzero(total == dist[target])
    left, right, to = np.repeat(leave.paths[own], many)[best], reach.paths[at[best]], target[best]
    if len(hub) and int(leave.paths[own].max()) * reach.most * len(hub) >= 1 << 63:
        exact = np.zeros(len(paths), object)
        np.add.at(exact, to, left.astype(object) * right.astype(object))
        if max(exact) >= 1 << 63:
            raise ArithmeticError("path counts pass 64 bits; take another count_type")
    np.add.at(paths, to, left * right)
    return target


FAR = np.iinfo(np.int32).max


def in_blocks(ix: LabelIndex, wanted: Callable[[np.ndarray], Callable[[int], np.ndarray]] | None = None, of: Column | None = None) -> DataFrame | None:
    """(s, t, dist, paths) of all pairs of vertices (``of``: for which this condition on ``vertex`` holds), as ``pairs`` answers them; not written. None for more than MOST_ROWS label rows (with ``of``: of these vertices) or counts other than long.

    The label lists go to every worker, which answers SOURCES sources at a time: the lists of a source's hubs are looked up by
    hub, and pairs without a common hub are filled in as (null, 0). Pairs are made where they are answered and nothing is
    exchanged. ``wanted``: given the array of vertices, it returns a function of a source that names the places of its targets there.
    """
    rows = ix.table.base_rows if ix.table.overlay is None and of is None else None
    if ix.labels.schema["paths"].dataType.simpleString() != "bigint":
        return None
    spark = ix.labels.sparkSession
    ranks, labels = ix.ranks.select("vertex", "rank"), ix.labels
    if of is not None:
        ranks = written(ranks.where(of), "chosen")
        labels = written(labels.join(ranks.select(F.col("rank").alias("owner")), "owner", "left_semi"), "chosen-labels")
    if (labels.count() if rows is None else rows) > MOST_ROWS:
        return None
    r = ranks.toArrow()  # at most as many as label rows
    rank = np.sort(r.column("rank").to_numpy())
    names = r.column("vertex").to_numpy()[np.argsort(r.column("rank").to_numpy())]
    n = len(names)
    hubs = rank if of is None else np.sort(labels.select("hub").distinct().toArrow().column(0).to_numpy())

    def lists(labels: DataFrame, *by: str) -> list[_Lists]:
        got = labels.select("owner", "hub", "dist", "paths").toArrow()  # MOST_ROWS at most
        place = {"owner": np.searchsorted(rank, got.column("owner").to_numpy()), "hub": np.searchsorted(hubs, got.column("hub").to_numpy())}
        return [_Lists(place[c], place["hub" if c == "owner" else "owner"], got.column("dist").to_numpy(), got.column("paths").to_numpy(), len(rank if c == "owner" else hubs)) for c in by]

    out, in_ = _lists(ix) if of is None else [labels if not ix.directed else labels.where(F.col("side") == side) for side in ("out", "in")]
    leave, reach = [lists(out, "owner")[0], lists(in_, "hub")[0]] if ix.directed else lists(out, "owner", "hub")
    shared = spark.sparkContext.broadcast((leave, reach, names))
    blocks = -(-n // SOURCES)
    tasks = max(1, min(blocks, 1 + n * n // 50_000_000 + 2 * spark.sparkContext.defaultParallelism))
    todo = spark.range(blocks).select(F.col("id").alias("block"))

    def find(batches):
        leave, reach, names = shared.value
        n = len(names)
        pick = None if wanted is None else wanted(names)
        dist, paths, everyone = np.full(n, FAR, np.int32), np.zeros(n, np.int64), np.arange(n)
        held, size = [], 0

        def batch():
            s = np.repeat([x[0] for x in held], [len(x[1]) for x in held])
            t, d, p = (np.concatenate([x[i] for x in held]) for i in (1, 2, 3))
            whole = pa.RecordBatch.from_arrays([pa.array(s), pa.array(t), pa.array(d, mask=d == FAR), pa.array(p)], ["s", "t", "dist", "paths"])
            return [whole.slice(lo, BATCH) for lo in range(0, len(s), BATCH)]

        for b in batches:
            for block in b.column("block").to_pylist():
                # Blocks take every so many-th source: those on top have other lists than the rest.
                for source in range(block, n, blocks):
                    to = everyone if pick is None else pick(int(names[source]))
                    if not len(to):
                        continue
                    found = _answer(source, leave, reach, dist, paths)
                    held.append((names[source], names[to], dist[to], paths[to]))
                    dist[found], paths[found] = FAR, 0
                    size += len(to)
                    if size >= BATCH:
                        yield from batch()
                        held, size = [], 0
        if held:
            yield from batch()

    return todo.repartition(tasks).mapInArrow(find, "s long, t long, dist int, paths long")


def distance(ix: LabelIndex, of: DataFrame) -> DataFrame:
    """(qid, s, t, dist) only; counts are not read."""
    best = _hub_sums(ix, of).groupBy("qid").agg(F.min("sum").alias("dist"))
    return of.join(best, "qid", "left").select("qid", "s", "t", "dist")


def explain(ix: LabelIndex, of: DataFrame) -> DataFrame:
    """(qid, s, t, hub, dist, product): the hubs that attain each pair's distance, as vertices."""
    sums = _hub_sums(ix, of)
    best = sums.groupBy("qid").agg(F.min("sum").alias("sum"))
    hubs = ix.ranks.select(F.col("rank").alias("hub"), F.col("vertex").alias("hub_vertex"))
    return sums.join(best, ["qid", "sum"]).join(hubs, "hub").select("qid", "s", "t", F.col("hub_vertex").alias("hub"), F.col("sum").alias("dist"), "product")


def _one_to_all(mine: DataFrame, others: DataFrame) -> DataFrame:
    j = others.join(mine.select("hub", F.col("dist").alias("d1"), F.col("paths").alias("p1")), "hub")
    sums = j.groupBy("owner", (F.col("dist") + F.col("d1")).cast("int").alias("sum")).agg(F.sum(F.col("paths") * F.col("p1")).alias("paths"))
    return sums.groupBy("owner").agg(F.min(F.struct("sum", "paths")).alias("b")).select(F.col("owner").alias("rank"), F.col("b.sum").alias("dist"), F.col("b.paths").alias("paths"))


def from_rank(ix: LabelIndex, rank: int) -> DataFrame:
    """(rank, dist, paths) from one vertex to all that it reaches; of a derived index by a search from it."""
    if ix.now is not None:
        own = ix.ranks.where(F.col("rank") == rank).select(F.col("rank").alias("hub"))
        return searched(ix.now, hubs=own, below=False).select(F.col("owner").alias("rank"), "dist", "paths")
    leave, reach = _lists(ix)
    return _one_to_all(leave.where(F.col("owner") == rank), reach)


def to_rank(ix: LabelIndex, rank: int) -> DataFrame:
    if ix.now is not None:
        return from_rank(ix, rank)
    leave, reach = _lists(ix)
    return _one_to_all(reach.where(F.col("owner") == rank), leave)


def rank_of(ix: LabelIndex, vertex: int) -> int | None:
    row = ix.ranks.where(F.col("vertex") == vertex).first()
    return row["rank"] if row else None


def ranks_of(ix: LabelIndex, *vertices: int) -> list[int | None]:
    """Ranks of a few vertices, by one read."""
    found = {r["vertex"]: r["rank"] for r in ix.ranks.where(F.col("vertex").isin(*vertices)).collect()}
    return [found.get(v) for v in vertices]


def from_source(ix: LabelIndex, source: int) -> DataFrame:
    """(vertex, dist, paths) from one vertex to all."""
    found = from_rank(ix, rank_of(ix, source) or -1)
    return found.join(ix.ranks, "rank").select("vertex", "dist", "paths")


def _packed(labels: DataFrame, buckets: int) -> DataFrame:
    columns = {"owner": np.int64, "hub": np.int64, "dist": np.int32, "paths": np.int64}

    def dealt(held):
        t = pa.Table.from_batches(held)
        for side in pc.unique(t.column("side")).to_pylist():
            own = t.filter(pc.equal(t.column("side"), side))
            values = {c: own.column(c).to_numpy() for c in columns}
            bucket = values["owner"] % buckets
            order = np.argsort(bucket, kind="stable")
            at, first = np.unique(bucket[order], return_index=True)
            ends = pa.array(np.append(first, len(order)).astype(np.int32))
            lists = [pa.ListArray.from_arrays(ends, pa.array(v[order])) for v in values.values()]
            whole = pa.RecordBatch.from_arrays([pa.array([side] * len(at)), pa.array(at.astype(np.int32)), *lists], ["side", "bucket", *columns])
            yield from (whole.slice(lo, 64) for lo in range(0, len(at), 64))

    def deal(batches):
        held, size = [], 0
        for b in batches:
            held.append(b)
            size += b.num_rows
            if size >= PACKED:
                yield from dealt(held)
                held, size = [], 0
        if held:
            yield from dealt(held)

    def join(t: pa.Table) -> pa.Table:
        owner, hub, dist, paths = (np.concatenate([x.values.to_numpy()[x.offsets[0].as_py() : x.offsets[-1].as_py()] for x in t.column(c).chunks]) for c in columns)
        order = np.lexsort((hub, owner))
        at, first = np.unique(owner[order], return_index=True)
        rows = pa.StructArray.from_arrays([pa.array(hub[order]), pa.array(dist[order]), pa.array(paths[order])], ["hub", "dist", "paths"])
        lists = pa.ListArray.from_arrays(pa.array(np.append(first, len(order)).astype(np.int32)), rows)
        return pa.table([pa.array([t.column("side")[0].as_py()] * len(at)), pa.array(at), lists], ["side", "owner", "rows"])

    kinds = "side string, bucket int, owner array<bigint>, hub array<bigint>, dist array<int>, paths array<bigint>"
    sent = labels.select("side", *columns).mapInArrow(deal, kinds)
    return sent.groupBy("side", "bucket").applyInArrow(join, "side string, owner long, rows array<struct<hub:bigint,dist:int,paths:bigint>>")


def packed(ix: LabelIndex) -> DataFrame:
    """(side, owner, rows): one sorted array for each owner, the serving layout.

    Rows are exchanged as columns: a task sorts PACKED of them at a time and sends each bucket of owners one row of arrays.
    """
    if ix.labels.schema["paths"].dataType.simpleString() == "bigint":
        n = ix.table.base_rows if ix.table.overlay is None else None
        return _packed(ix.labels, max(1, -(-(ix.labels.count() if n is None else n) // (PACKED // 4))))
    return ix.labels.groupBy("side", "owner").agg(F.array_sort(F.collect_list(F.struct("hub", "dist", "paths"))).alias("rows"))


def pairs_packed(ix: LabelIndex, lists: DataFrame, of: DataFrame) -> DataFrame:
    """As ``pairs``, on the packed layout ``lists``: two key lookups and a merge of arrays, no rows exploded."""
    out, in_ = ("out", "in") if ix.directed else ("u", "u")
    r = ix.ranks
    p = of.join(r.select(F.col("vertex").alias("s"), F.col("rank").alias("rs")), "s", "left").join(r.select(F.col("vertex").alias("t"), F.col("rank").alias("rt")), "t", "left")
    p = p.join(lists.where(F.col("side") == out).select(F.col("owner").alias("rs"), F.col("rows").alias("a")), "rs", "left")
    p = p.join(lists.where(F.col("side") == in_).select(F.col("owner").alias("rt"), F.col("rows").alias("b")), "rt", "left")
    none = F.array().cast("array<struct<hub:bigint,dist:int,paths:bigint>>")
    p = p.withColumn("m", F.map_from_entries(F.transform(F.coalesce("b", none), lambda x: F.struct(x["hub"], x))))
    sums = F.transform(F.filter(F.coalesce("a", none), lambda x: F.map_contains_key("m", x["hub"])), lambda x: F.struct((x["dist"] + F.col("m")[x["hub"]]["dist"]).alias("d"), (x["paths"] * F.col("m")[x["hub"]]["paths"]).alias("p")))
    p = p.withColumn("sums", sums).withColumn("dist", F.array_min(F.transform("sums", lambda x: x["d"])))
    total = F.aggregate(F.filter("sums", lambda x: x["d"] == F.col("dist")), F.lit(0).cast("long"), lambda n, x: n + x["p"])
    return p.select("qid", "s", "t", F.col("dist").cast("int").alias("dist"), total.alias("paths"))


def register_sql(ix: LabelIndex, name: str = "path_count") -> None:
    """Makes ``SELECT * FROM path_count(s, t)`` available: a SQL table function over the label views, within Catalyst."""
    spark = ix.labels.sparkSession
    leave, reach = _lists(ix)
    for view, rows in ((f"{name}_leave", leave), (f"{name}_reach", reach)):
        rows.join(ix.ranks.select(F.col("rank").alias("owner"), "vertex"), "owner").createOrReplaceTempView(view)
    spark.sql(f"""
        CREATE OR REPLACE TEMPORARY FUNCTION {name}(s BIGINT, t BIGINT) RETURNS TABLE (dist INT, paths BIGINT)
        RETURN SELECT CAST(min(b.d) AS INT), CAST(coalesce(min_by(b.p, b.d), 0) AS BIGINT) FROM (
            SELECT l.dist + r.dist AS d, sum(l.paths * r.paths) AS p FROM {name}_leave l JOIN {name}_reach r ON l.hub = r.hub
            WHERE l.vertex = {name}.s AND r.vertex = {name}.t GROUP BY l.dist + r.dist) b""")
