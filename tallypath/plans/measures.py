"""Cost and accuracy measures, each a DataFrame."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..operators import index as ixs
from ..operators import traversal
from ..operators.graph import Graph, edge_degree
from ..operators.index import LabelIndex

ROW_BYTES = 8


def index_size(ix: LabelIndex) -> DataFrame:
    """One row: label rows, bytes at 8 a row, mean rows per vertex."""
    n = ix.ranks.agg(F.count("*").alias("n"))
    rows = ix.labels.agg(F.count("*").alias("label_rows")) if ix.source is None else ix.labels.sparkSession.createDataFrame([(ixs.rows_in(ix),)], "label_rows long")
    return rows.crossJoin(n).select("label_rows", (F.col("label_rows") * ROW_BYTES).alias("bytes"), F.round(F.col("label_rows") / F.col("n"), 6).alias("rows_per_vertex"))  # one row each


def update_times(metrics: DataFrame, op: str, timeout_ms: float | None = None) -> DataFrame:
    late = F.count_if(F.col("ms") > timeout_ms) if timeout_ms is not None else F.lit(0)
    return metrics.where(F.col("op") == op).agg(F.count("*").alias("updates"), F.avg("ms").alias("mean_ms"), late.alias("timeouts"))


def quartiles(metrics: DataFrame, column: str = "ms") -> DataFrame:
    q = F.percentile(column, F.array(F.lit(0.25), F.lit(0.5), F.lit(0.75)))
    return metrics.groupBy("op").agg(q.alias("q")).select("op", F.col("q")[0].alias("p25"), F.col("q")[1].alias("median"), F.col("q")[2].alias("p75"))


def label_changes(metrics: DataFrame) -> DataFrame:
    """Mean rows per update renewed in count, in distance, inserted, removed."""
    return metrics.groupBy("op").agg(*[F.avg(c).alias(c) for c in ("renew_count", "renew_dist", "inserted", "removed")])


def size_change(metrics: DataFrame) -> DataFrame:
    return metrics.groupBy("op").agg(F.sum("bytes").alias("bytes"), F.avg("bytes").alias("mean_bytes"))


def set_sizes(sets: DataFrame) -> DataFrame:
    """roots_a, roots_b, receivers_a, receivers_b; the side with more roots is a."""
    root = F.col("role") != "receiver"
    n = lambda side, r: F.count_if((F.col("side") == side) & r).alias(("roots_" if r is root else "receivers_") + side)
    c = sets.agg(n("a", root), n("b", root), F.count_if((F.col("side") == "a") & ~root).alias("receivers_a"), F.count_if((F.col("side") == "b") & ~root).alias("receivers_b"))
    swap = F.col("roots_a") < F.col("roots_b")
    pick = lambda x, y: F.when(swap, F.col(y)).otherwise(F.col(x))
    return c.select(pick("roots_a", "roots_b").alias("roots_a"), pick("roots_b", "roots_a").alias("roots_b"), pick("receivers_a", "receivers_b").alias("receivers_a"), pick("receivers_b", "receivers_a").alias("receivers_b"))


def accumulated(metrics: DataFrame) -> DataFrame:
    """(seq, total_ms, total_bytes) after each update of a stream; one row an update."""
    upto = Window.orderBy("seq").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return metrics.select("seq", F.sum("ms").over(upto).alias("total_ms"), F.sum("bytes").over(upto).alias("total_bytes"))


def skew(touched: DataFrame, g: Graph) -> DataFrame:
    """Correlation of ``touched`` (u, v, ms, rows) with the edges' degree products."""
    d = touched.join(edge_degree(g.edges, touched), ["u", "v"])
    return d.agg(F.corr("deg_product", "ms").alias("corr_ms"), F.corr("deg_product", "rows").alias("corr_rows"), F.count("*").alias("edges"))


def speedup(rebuild_ms: float, metrics: DataFrame) -> DataFrame:
    return metrics.groupBy("op").agg(F.avg("ms").alias("mean_ms")).select("op", (F.lit(rebuild_ms) / F.col("mean_ms")).alias("speedup"), F.log10(F.lit(rebuild_ms) / F.col("mean_ms")).alias("orders"))


def bound_terms(ix: LabelIndex, rounds: list[dict], sets: DataFrame | None = None) -> DataFrame:
    """Terms of the complexity bounds: rows per vertex, visits (candidates), rounds; roots and touched if sets are given."""
    spark = ix.labels.sparkSession
    visits = sum(r["candidates"] for r in rounds)
    base = index_size(ix).select("rows_per_vertex").withColumns({"visits": F.lit(visits), "rounds": F.lit(len(rounds))})
    if sets is None:
        return base
    t = sets.agg(F.count_if(F.col("role") != "receiver").alias("roots"), F.count("*").alias("touched"))
    return base.crossJoin(t) if spark else base  # one row each


def exactness(ix: LabelIndex, g: Graph) -> DataFrame:
    """One row: pairs, share of them with distance and count equal to brute force."""
    true = traversal.all_pairs(g, 'rounds').select(F.col("source").alias("s"), F.col("vertex").alias("t"), F.col("dist").alias("d"), F.col("paths").alias("c"))
    r = ix.ranks
    from .apps import all_answers

    got = all_answers(ix).join(r.select(F.col("rank").alias("s"), F.col("vertex").alias("sv")), "s").join(r.select(F.col("rank").alias("t"), F.col("vertex").alias("tv")), "t")
    both = true.join(got.select(F.col("sv").alias("s"), F.col("tv").alias("t"), "dist", "paths"), ["s", "t"], "full_outer")
    same = F.col("d").eqNullSafe(F.col("dist")) & F.col("c").eqNullSafe(F.col("paths"))
    return both.agg(F.count("*").alias("pairs"), F.avg(same.cast("double")).alias("exact"))


def dominated(ix: LabelIndex) -> DataFrame:
    """Rows kept though their pair is closer, and their share."""
    c = ixs.classify(ix)
    return c.agg(F.count_if(F.col("true") < F.col("dist")).alias("dominated_rows"), F.avg((F.col("true") < F.col("dist")).cast("double")).alias("share"))


def canonical(ix: LabelIndex) -> DataFrame:
    return ixs.classify(ix).groupBy("canonical").agg(F.count("*").alias("label_rows"))


def round_stats(ix: LabelIndex, rounds: list[dict]) -> DataFrame:
    rows = [(i, r["dist"], r["candidates"], r["settled"]) for i, r in enumerate(rounds)]
    return ix.labels.sparkSession.createDataFrame(rows, "round int, dist int, candidates long, settled long")


def query_rows(ix: LabelIndex, pairs: DataFrame) -> DataFrame:
    """Label rows read by each pair's query, the bound of its cost."""
    n = ix.labels.groupBy("owner").agg(F.count("*").alias("n")).join(ix.ranks.select(F.col("rank").alias("owner"), "vertex"), "owner")
    return pairs.join(n.select(F.col("vertex").alias("s"), F.col("n").alias("ns")), "s").join(n.select(F.col("vertex").alias("t"), F.col("n").alias("nt")), "t").select("qid", (F.col("ns") + F.col("nt")).alias("rows"))


