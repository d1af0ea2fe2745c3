"""Near-duplicate embeddings by sorted projection passes.

1. Equal vectors are one node from here on, with their number.
2. In each pass every node gets the signs of random projections, concatenated; nodes are
   ordered lexicographically by them (range partitions, sorted within) and compared with
   their neighbours in windows of at least ``WINDOW`` places by exact cosine. A task reports
   a forest of the links that it verified, so a group of close vectors costs as many rows as
   it has members. Passes use other projections; their number follows from the number of
   vectors spread evenly. Partition borders differ from pass to pass.
3. Vectors need not be spread evenly, so each pass also tells how many leading signs a pair
   must share at each vector to lie within its window. Vectors at which a pair at the
   threshold is missed by all passes so far with probability above ``MISS`` are in a denser
   place: they get further passes among themselves, or, where that is less work, every two
   of them are compared in bounded blocks. This goes on until there are none (a pair is
   safe as soon as one of its ends is).
4. Components join the passes' links. Within a component every vector's links are then
   counted exactly: it is cut into chunks by hash, and every two chunks are compared as one
   bounded block; blocks report one number for each member.

Defined cases: null, zero, and empty vectors and those with null or non-finite components link
with nothing; vectors of different lengths never link; rows that repeat a vec_id with other
vectors are vectors of their own (nodes are numbered by vector, not by vec_id), those with equal ones
copies; a null vec_id links with nothing; very large and very small components are scaled first; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import bounded, table, written
from .components import components, star_forest
from .minhash import by_block

WINDOW = 128
MISS = 1e-3
LEAST_PASSES = 12
SIGNS = 63
CHUNK = 64
DENSE = 1024  # vectors of dense places in a chunk


def passes_for(vectors: int, cosine: float, window: int = WINDOW) -> int:
    """Passes after which a pair at the threshold is missed with probability ``MISS``."""
    same = 1 - math.acos(cosine) / math.pi
    one = same ** max(0.0, 1 + math.log2(max(vectors, 2) / window))
    return LEAST_PASSES if one >= 0.99 else max(LEAST_PASSES, math.ceil(math.log(MISS) / math.log(1 - one)))


def unit_rows(raw: list[bytes]) -> np.ndarray:
    x = np.frombuffer(b"".join(raw), np.float64).reshape(len(raw), -1)
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def projections(pass_: int, dims: int) -> np.ndarray:
    return np.random.default_rng([pass_, dims, 4021]).normal(size=(dims, 2 * SIGNS))


def signs(x: np.ndarray, pass_: int) -> tuple[np.ndarray, np.ndarray]:
    """The concatenated signs as two non-negative numbers, to be ordered one after the other."""
    bits = (x @ projections(pass_, x.shape[1])) > 0
    weights = np.int64(1) << np.arange(SIGNS - 1, -1, -1, dtype=np.int64)
    return bits[:, :SIGNS] @ weights, bits[:, SIGNS:] @ weights


def common_signs(a: np.ndarray, b: np.ndarray, apart: int) -> np.ndarray:
    """Equal leading signs of each row and the one ``apart`` rows on."""
    x, y = a[apart:] ^ a[:-apart], b[apart:] ^ b[:-apart]
    return np.where(x > 0, SIGNS - np.frexp(x.astype(float))[1], 2 * SIGNS - np.frexp(y.astype(float))[1])


def cleaned(rows: DataFrame) -> DataFrame:
    """vec_id, raw: components as doubles; null where the vector can't link."""

    def clean(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            raw = []
            for v in pdf["embedding"]:
                x = None if v is None else np.array([np.nan if c is None else c for c in v] if getattr(v, "dtype", object) == object else v, np.float64)
                most = np.abs(x).max() if x is not None and len(x) and np.isfinite(x).all() else 0.0
                if most and not 1e-100 < most < 1e100:  # squares would over- or underflow
                    x = x / most
                raw.append((x + 0.0).tobytes() if most else None)
            yield pd.DataFrame({"vec_id": pdf["vec_id"].astype("Int64"), "raw": raw})

    return rows.select("vec_id", "embedding").mapInPandas(clean, "vec_id long, raw binary")


def pass_links(nodes: DataFrame, first: int, passes: int, cosine: float, tasks: int) -> DataFrame:
    """Forest links (u, v) that the passes ``first``, ``first + 1``, ... verify, and rows without v: log-probabilities ``miss`` that a pair at u is missed."""
    same = 1 - math.acos(cosine) / math.pi

    def project(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            for _, part in pdf.groupby(pdf["raw"].map(len)):
                x = unit_rows(list(part["raw"]))
                for p in range(first, first + passes):
                    a, b = signs(x, p)
                    yield pd.DataFrame({"pass": np.int32(p), "a": a, "b": b, "node": part["node"].to_numpy(), "raw": part["raw"].to_numpy()})

    def missed(pdf: pd.DataFrame) -> pd.DataFrame:
        """Rows with ``WINDOW`` rows before and after them; those at the ends of a task's part count as missed."""
        if len(pdf) <= 2 * WINDOW:
            return pd.DataFrame({"u": np.zeros(0, np.int64), "v": pd.array([], "Int64"), "miss": np.zeros(0)})
        far = common_signs(pdf["a"].to_numpy(np.int64), pdf["b"].to_numpy(np.int64), WINDOW)
        turn = pdf["pass"].to_numpy()
        far[turn[WINDOW:] != turn[:-WINDOW]] = -1
        need = 1 + np.maximum(far[:-WINDOW], far[WINDOW:])
        return pd.DataFrame({"u": pdf["node"].to_numpy(np.int64)[WINDOW:-WINDOW], "v": pd.array([None] * len(need), "Int64"), "miss": np.log1p(-np.minimum(same**need, 1 - 1e-9))})

    def compare(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held = None
        for pdf in batches:
            pdf = pdf if held is None else pd.concat([held, pdf], ignore_index=True)
            us, vs = [], []
            for _, part in pdf.groupby(["pass", pdf["raw"].map(len)], sort=False):
                node, x = part["node"].to_numpy(np.int64), unit_rows(list(part["raw"]))
                for lo in range(0, len(node), WINDOW):
                    here, near = x[lo : lo + WINDOW], x[lo : lo + 2 * WINDOW]
                    i, j = np.nonzero(np.triu(here @ near.T >= cosine, 1))
                    us.append(node[lo + i])
                    vs.append(node[lo + j])
            yield missed(pdf)
            held = pdf.iloc[-2 * WINDOW :]
            u, v = np.concatenate(us), np.concatenate(vs)
            if len(u):
                child, root = star_forest(u, v)
                yield pd.DataFrame({"u": root, "v": pd.array(child, "Int64"), "miss": np.nan})

    dealt = nodes.select("node", "raw").mapInPandas(project, "pass int, a long, b long, node long, raw binary")
    sorted_ = dealt.repartitionByRange(tasks, "pass", "a", "b", "node").sortWithinPartitions("pass", "a", "b", "node")
    return sorted_.mapInPandas(compare, "u long, v long, miss double")


def block_links(nodes: DataFrame, n: int, cosine: float) -> DataFrame:
    """Forest links (u, v) among all pairs of ``nodes``: chunks by hash, every two of them one bounded block."""
    chunks = -(-n // DENSE)
    own = F.pmod(F.xxhash64("node"), F.lit(chunks)).cast("int")
    m = nodes.select("node", "raw", own.alias("own")).select("*", F.explode(F.sequence(F.lit(0), F.lit(chunks - 1))).alias("other"))
    rows = m.select("node", "raw", F.xxhash64(F.least("own", "other"), F.greatest("own", "other")).alias("block"))

    def check(part: pd.DataFrame) -> pd.DataFrame:
        us, vs = [], []
        for _, p in part.groupby(part["raw"].map(len)):
            node, x = p["node"].to_numpy(np.int64), unit_rows(list(p["raw"]))
            for lo in range(0, len(node), WINDOW):
                i, j = np.nonzero(np.triu(x[lo : lo + WINDOW] @ x[lo:].T >= cosine, 1))
                if len(i):
                    child, root = star_forest(node[lo + i], node[lo + j])
                    us.append(root)
                    vs.append(child)
        return pd.DataFrame({"u": np.concatenate(us), "v": np.concatenate(vs)}) if us else pd.DataFrame({"u": [], "v": []}).astype(np.int64)

    return by_block(rows, ["node", "raw"], check, "u long, v long")


def all_links(nodes: DataFrame, n: int, cosine: float) -> DataFrame:
    """Forest links (u, v) of all places, dense ones included."""
    first, passes, links = 0, passes_for(n, cosine), None
    dense = nodes.select("node", "raw", F.lit(0.0).alias("missed"))
    while n:
        seen = written(pass_links(dense, first, passes, cosine, max(1, n * passes // 8192)), "passes")
        part = seen.where(F.col("v").isNotNull()).select("u", "v")
        links = part if links is None else links.unionByName(part)
        gain = seen.where(F.col("v").isNull()).groupBy(F.col("u").alias("node")).agg(F.sum("miss").alias("gain"))
        left = dense.join(gain, "node", "left").withColumn("gain", F.coalesce("gain", F.lit(0.0))).withColumn("missed", F.col("missed") + F.col("gain"))
        dense = written(left.where(F.col("missed") > math.log(MISS)), "dense")
        n, open_, won = dense.agg(F.count("*"), F.sum(F.col("missed") - math.log(MISS)), -F.sum("gain")).first()
        first, passes = first + passes, passes if not won else max(1, math.ceil(passes * open_ / won))
        if n and (not won or -(-n // DENSE) <= passes):
            return links.unionByName(block_links(dense.select("node", "raw"), n, cosine))
        dense = dense.select("node", "raw", "missed")
    return links


def counted_links(members: DataFrame, cosine: float) -> DataFrame:
    """node, links: for each member (node, component, copies, raw) the copies of all others of its component at the threshold or above."""
    sizes = members.groupBy("component").count().where(F.col("count") > CHUNK).select("component", F.ceil(F.col("count") / CHUNK).cast("int").alias("chunks"))
    m = members.join(written(sizes, "sizes"), "component", "left").withColumn("chunks", F.coalesce("chunks", F.lit(1)))
    own = F.pmod(F.xxhash64("node"), F.col("chunks")).cast("int")
    m = m.withColumn("own", own).select("*", F.explode(F.sequence(F.lit(0), F.col("chunks") - 1)).alias("other"))
    rows = m.select("node", "copies", "raw", F.xxhash64("component", F.least("own", "other"), F.greatest("own", "other")).alias("block"), F.when(F.col("own") > F.col("other"), 1).otherwise(0).alias("side"))

    def check(part: pd.DataFrame) -> pd.DataFrame:
        out = []
        for _, p in part.groupby(part["raw"].map(len)):
            x, side, copies = unit_rows(list(p["raw"])), p["side"].to_numpy(), p["copies"].to_numpy(np.int64)
            link = x @ x.T >= cosine
            np.fill_diagonal(link, False)
            if side.any() and not side.all():
                link &= side[:, None] != side[None]
            n = link @ copies
            out.append(pd.DataFrame({"node": p["node"].to_numpy()[n > 0], "links": n[n > 0]}))
        return pd.concat(out)

    return by_block(rows, ["node", "copies", "raw", "side"], check, "node long, links long").groupBy("node").agg(F.sum("links").alias("links"))


def near_duplicate_vectors(rows: DataFrame, cosine: float = 0.9) -> DataFrame:
    """vec_id, n_links, component_id, kept of every row of ``rows`` (vec_id, embedding)."""
    clean = written(cleaned(bounded(rows)).withColumn("key", F.sha2("raw", 256)), "vectors")
    same = clean.where(F.col("raw").isNotNull() & F.col("vec_id").isNotNull()).groupBy("key", "raw").agg(F.min("vec_id").alias("least"), F.count("*").alias("copies"))
    nodes = written(same.withColumn("node", F.monotonically_increasing_id()), "nodes")  # numbers are fixed by the written table
    n = nodes.count()
    found = all_links(nodes, n, cosine) if n else nodes.select(F.col("node").alias("u"), F.col("node").alias("v"))
    links = components(found, thin=False)
    members = links.join(nodes, "node")
    counts = written(counted_links(members.select("node", "component", "copies", "raw"), cosine), "counts")
    known = nodes.select("key", "node", "least", "copies").join(links, "node", "left").join(counts, "node", "left")
    known = written(known.withColumn("group", F.coalesce("component", "node")).drop("component"), "linked")
    smallest = known.groupBy("group").agg(F.min("least").alias("component"))
    known = written(known.join(smallest, "group").select("key", "component", (F.col("copies") - 1 + F.coalesce("links", F.lit(0))).alias("n")), "known")
    out = clean.select("vec_id", F.when(F.col("vec_id").isNotNull(), F.col("key")).alias("key")).join(known, "key", "left")
    component = F.coalesce("component", "vec_id")
    return out.select("vec_id", F.coalesce("n", F.lit(0)).cast("long").alias("n_links"), component.alias("component_id"), F.coalesce(component == F.col("vec_id"), F.lit(True)).alias("kept"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicate_vectors(table(spark, sf_dir, "embeddings"))


ORACLE = """
WITH RECURSIVE v AS (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS e FROM embeddings
  WHERE embedding IS NOT NULL AND len(embedding) > 0 AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
u AS (SELECT vec_id, e, sqrt(list_dot_product(e, e)) AS n FROM v WHERE list_dot_product(e, e) > 0),
l AS (SELECT a.vec_id AS a, b.vec_id AS b FROM u a JOIN u b ON a.vec_id <> b.vec_id AND len(a.e) = len(b.e)
  WHERE list_dot_product(a.e, b.e) / (a.n * b.n) >= 0.9),
r AS (SELECT a AS node, b AS reached FROM l UNION SELECT r.node, l.b FROM r JOIN l ON r.reached = l.a),
c AS (SELECT node, least(node, min(reached)) AS component FROM r GROUP BY node),
d AS (SELECT a, count(*) AS n FROM l GROUP BY a)
SELECT e.vec_id, coalesce(d.n, 0) AS n_links, coalesce(c.component, e.vec_id) AS component_id, coalesce(c.component, e.vec_id) = e.vec_id AS kept
FROM embeddings e LEFT JOIN d ON d.a = e.vec_id LEFT JOIN c ON c.node = e.vec_id
"""
