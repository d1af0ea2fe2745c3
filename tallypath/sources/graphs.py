"""Graphs derived from the given tables, and the two constant ones, each with its DuckDB counterpart."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..operators import graph, ranking

# Edges of the 12-vertex example and of the 8-vertex trap.
EXAMPLE = [(0, 1), (0, 2), (1, 2), (0, 3), (2, 3), (1, 5), (2, 5), (4, 5), (1, 6), (3, 7), (4, 7), (0, 8), (3, 8), (4, 9), (6, 10), (9, 10), (0, 11)]
TRAP = [(2, 3), (3, 4), (4, 5), (0, 2), (1, 2), (1, 6), (6, 7), (5, 7)]


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def successions(spark: SparkSession, sf_dir: str, kind: str = "purchase") -> DataFrame:
    """(user_id, next_id) of consecutive events of one kind, in time order.

    The successor is found without one global window: events are numbered over range partitions, and each number is
    joined with the one before it.
    """
    e = table(spark, sf_dir, "events").where(F.col("event_type") == kind).select("ts", "event_id", "user_id")
    n = ranking.numbered(e, [F.asc("ts"), F.asc("event_id")], "at")
    nxt = n.select((F.col("at") - 1).alias("at"), F.col("user_id").alias("next_id"))
    return n.join(nxt, "at").select("at", "user_id", "next_id")


def parts_together(spark: SparkSession, sf_dir: str, least: int) -> DataFrame:
    """(a, b): parts of one order, both lines of at least ``least`` pieces."""
    lines = table(spark, sf_dir, "lineitem").where(F.col("l_quantity") >= least).select("l_orderkey", "l_partkey").distinct()
    other = lines.select("l_orderkey", F.col("l_partkey").alias("b"))
    return lines.join(other, "l_orderkey").where(F.col("l_partkey") < F.col("b")).select(F.col("l_partkey").alias("a"), "b")


def edges(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """(u, v[, w]) of a named graph: U, P40, P46, CP49, NF, UD (directed), PW (weighted), EX, TRAP."""
    if name in ("U", "UD"):
        return graph.simple_edges(successions(spark, sf_dir), "user_id", "next_id", directed=name == "UD")
    if name in ("P46", "P40"):
        return graph.simple_edges(parts_together(spark, sf_dir, int(name[1:])), "a", "b")
    if name == "CP49":
        lines = table(spark, sf_dir, "lineitem").where(F.col("l_quantity") >= 49).select("l_orderkey", "l_partkey")
        own = lines.join(table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey"), "l_orderkey")
        return graph.simple_edges(own.select((F.col("o_custkey") * 2).alias("a"), (F.col("l_partkey") * 2 + 1).alias("b")), "a", "b")
    if name == "NF":
        lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey")
        own = lines.join(table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey"), "l_orderkey")
        own = own.join(table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("o_custkey"), "c_nationkey"), "o_custkey")
        own = own.join(table(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("l_suppkey"), "s_nationkey"), "l_suppkey")
        return graph.simple_edges(own, "c_nationkey", "s_nationkey")
    if name == "PW":
        e = edges(spark, sf_dir, "P46")
        size = table(spark, sf_dir, "part").select("p_partkey", F.col("p_size").cast("long").alias("size")).dropDuplicates(["p_partkey"])
        e = e.join(size.select(F.col("p_partkey").alias("u"), F.col("size").alias("su")), "u").join(size.select(F.col("p_partkey").alias("v"), F.col("size").alias("sv")), "v")
        return e.select("u", "v", (1 + F.abs(F.col("su") - F.col("sv")) % 4).alias("w"))
    return spark.createDataFrame(EXAMPLE if name == "EX" else TRAP, "u long, v long")


def load(spark: SparkSession, sf_dir: str, name: str) -> graph.Graph:
    e = edges(spark, sf_dir, name)
    ranks = ranking.natural(e) if name in ("EX", "TRAP") else ranking.by_degree(e)
    return graph.make(e, ranks, directed=name == "UD", weighted=name == "PW")


def order_key(u, v):
    """The deterministic stand-in for a random order of pairs."""
    return (u * 7919 + v * 104729) % 1000003


_VALUES = lambda rows: "(VALUES " + ", ".join(f"({u}, {v})" for u, v in rows) + ")"

SQL_EDGES = {
    "U": """SELECT DISTINCT least(a, b) AS u, greatest(a, b) AS v FROM (SELECT user_id AS a, lead(user_id) OVER (ORDER BY ts, event_id) AS b
        FROM events WHERE event_type = 'purchase') WHERE b IS NOT NULL AND a <> b""",
    "UD": """SELECT DISTINCT a AS u, b AS v FROM (SELECT user_id AS a, lead(user_id) OVER (ORDER BY ts, event_id) AS b
        FROM events WHERE event_type = 'purchase') WHERE b IS NOT NULL AND a <> b""",
    "CP49": """SELECT DISTINCT least(2 * o_custkey, 2 * l_partkey + 1) AS u, greatest(2 * o_custkey, 2 * l_partkey + 1) AS v
        FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE l_quantity >= 49""",
    "NF": """SELECT DISTINCT CAST(least(c_nationkey, s_nationkey) AS BIGINT) AS u, CAST(greatest(c_nationkey, s_nationkey) AS BIGINT) AS v
        FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey
        WHERE c_nationkey <> s_nationkey""",
    "EX": f"SELECT CAST(u AS BIGINT) AS u, CAST(v AS BIGINT) AS v FROM {_VALUES(EXAMPLE)} t(u, v)",
    "TRAP": f"SELECT CAST(u AS BIGINT) AS u, CAST(v AS BIGINT) AS v FROM {_VALUES(TRAP)} t(u, v)",
}
for _q in (46, 40):
    SQL_EDGES[f"P{_q}"] = f"""SELECT DISTINCT a.l_partkey AS u, b.l_partkey AS v FROM lineitem a JOIN lineitem b
        ON a.l_orderkey = b.l_orderkey AND a.l_partkey < b.l_partkey WHERE a.l_quantity >= {_q} AND b.l_quantity >= {_q}"""
SQL_EDGES["PW"] = f"""SELECT u, v, CAST(1 + abs(a.p_size - b.p_size) % 4 AS BIGINT) AS w FROM ({SQL_EDGES['P46']}) JOIN part a ON u = a.p_partkey JOIN part b ON v = b.p_partkey"""
