"""Total orders on vertices."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..sources.scratch import written
from .graph import degrees, vertices


def numbered(df: DataFrame, keys: list[Column], name: str = "rank") -> DataFrame:
    """``df`` with its place from 1 in the order of ``keys`` (which must be total).

    Rows are range-partitioned and numbered within partitions; the offsets of the partitions, one row each, come
    from a running sum. No partition holds more than its range.
    """
    parts = df.repartitionByRange(*keys).withColumn("__part", F.spark_partition_id())
    parts = written(parts.sortWithinPartitions("__part", *keys).withColumn("__at", F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1))), "ranged")
    size = parts.groupBy("__part").agg((F.max("__at") + 1).alias("size"))
    before = Window.orderBy("__part").rowsBetween(Window.unboundedPreceding, -1)
    offset = size.select("__part", F.coalesce(F.sum("size").over(before), F.lit(0)).alias("offset"))
    return parts.join(F.broadcast(offset), "__part").select(*df.columns, (F.col("offset") + F.col("__at") + 1).alias(name))


def by_degree(edges: DataFrame) -> DataFrame:
    """(vertex, rank) by falling degree, smaller id first among equals."""
    return numbered(degrees(edges), [F.desc("degree"), F.asc("vertex")]).select("vertex", "rank")


def natural(edges: DataFrame) -> DataFrame:
    return numbered(vertices(edges), [F.asc("vertex")])


def by_column(keyed: DataFrame, keys: list[Column]) -> DataFrame:
    """(vertex, rank) by any columns of ``keyed`` (vertex, ...); the id settles ties."""
    return numbered(keyed, [*keys, F.asc("vertex")]).select("vertex", "rank")


def append(ranks: DataFrame, new: DataFrame) -> DataFrame:
    """Ranks with the vertices of ``new`` (vertex) that have none at the bottom."""
    last = ranks.agg(F.coalesce(F.max("rank"), F.lit(0)).alias("last")).first()["last"]
    fresh = new.select("vertex").distinct().join(ranks, "vertex", "left_anti")
    return ranks.unionByName(numbered(fresh, [F.asc("vertex")]).withColumn("rank", F.col("rank") + last))
