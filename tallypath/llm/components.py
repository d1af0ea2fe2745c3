"""Connected components of a large set of links, by random contraction.

In each round every node hooks onto that neighbour (or itself) whose hash, drawn anew each
round, is smallest; links are relabelled and those within a node dropped. The number of nodes
with links left falls by a constant factor a round in expectation, whatever the shape of the
graph. Each round is a pre-aggregated minimum and two joins between written tables, whose
skewed keys Spark can split. Nothing but row counts reaches the driver.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import drop_written, written


def star_forest(u: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(node, smallest node of its component) of the links ``u``-``v``, nodes that are smallest themselves left out."""
    ids, inv = np.unique(np.concatenate([u, v]), return_inverse=True)
    a, b = inv[: len(u)], inv[len(u) :]
    label = np.arange(len(ids))
    while True:
        x, y = label[a], label[b]
        open_ = x != y
        if not open_.any():
            break
        a, b, x, y = a[open_], b[open_], x[open_], y[open_]
        np.minimum.at(label, np.maximum(x, y), np.minimum(x, y))
        while True:
            up = label[label]
            if (up == label).all():
                break
            label = up
    child = np.flatnonzero(label != np.arange(len(ids)))
    return ids[child], ids[label[child]]


def thinned(links: DataFrame) -> DataFrame:
    """The links of each task as stars: as many as nodes at most, with the same components."""

    def thin(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        u = v = np.zeros(0, np.int64)
        for pdf in batches:
            u, v = np.concatenate([u, pdf["u"].to_numpy(np.int64)]), np.concatenate([v, pdf["v"].to_numpy(np.int64)])
            if len(u) > 1 << 18:
                u, v = star_forest(u, v)
                if len(u) > 1 << 17:  # too many nodes for one forest: hand on and start anew
                    yield pd.DataFrame({"u": v, "v": u})
                    u = v = np.zeros(0, np.int64)
        if len(u):
            child, root = star_forest(u, v)
            yield pd.DataFrame({"u": root, "v": child})

    return links.select("u", "v").mapInPandas(thin, "u long, v long")


def components(links: DataFrame, thin: bool = True) -> DataFrame:
    """(node, component) of every node of ``links`` (u, v long, not null); component is its smallest node.

    ``thin=False`` for links that come as forests already: it saves a Python worker in their stage.
    """
    edges = written(thinned(links) if thin else links.select("u", "v"), "links")
    steps: list[DataFrame] = []
    n = edges.count()
    while n:
        seed = F.lit(len(steps) * 7919 + 17)
        both = edges.select(F.col("u").alias("node"), F.col("v").alias("to")).union(edges.select(F.col("v"), F.col("u")))
        rank = lambda c: F.struct(F.xxhash64(c, seed).alias("h"), F.col(c).alias("id"))
        least = both.groupBy("node").agg(F.min(rank("to")).alias("b"))
        parents = written(least.select("node", F.when(rank("node") < F.col("b"), F.col("node")).otherwise(F.col("b.id")).alias("parent")), "parents")
        steps.append(parents)
        pu, pv = parents.select(F.col("node").alias("u"), F.col("parent").alias("pu")), parents.select(F.col("node").alias("v"), F.col("parent").alias("pv"))
        moved = edges.join(pu, "u").join(pv, "v").where(F.col("pu") != F.col("pv"))
        nxt = written(thinned(moved.select(F.col("pu").alias("u"), F.col("pv").alias("v"))), "links")
        drop_written(edges)
        edges, n = nxt, nxt.count()
    drop_written(edges)
    if not steps:
        return edges.sparkSession.createDataFrame([], "node long, component long")
    label = steps[0].select("node", F.col("parent").alias("root"))
    for s in steps[1:]:
        label = label.join(s.select(F.col("node").alias("root"), F.col("parent").alias("up")), "root", "left").select("node", F.coalesce("up", "root").alias("root"))
    label = written(label, "labels")
    for s in steps:
        drop_written(s)
    least = label.groupBy("root").agg(F.min("node").alias("component"))
    return label.join(written(least, "least"), "root").select("node", "component")
