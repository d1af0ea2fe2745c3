"""Near-duplicate documents by HyperMinHash.

1. Each document becomes its set of word shingles (64-bit hashes) and ``REGISTERS`` registers:
   per bucket the leading-zero count and ``MANTISSA`` further bits of the smallest hash; empty
   buckets borrow from others by fixed random probes. Documents with equal sets are one class
   from here on, so copies cost nothing further.
2. Bands of registers are candidate keys. Sets of at most ``SMALL`` shingles, which would leave
   most buckets empty, take a hash of its own over the whole set for each register instead of a
   bucket; somewhat larger sets have both kinds of keys, so that every pair has one in common.
   A pair at the threshold shares no band with probability (1 - 0.85**7)**36, one in a million.
3. Classes that share keys form candidate groups (connected components over the keys).
   A group is checked in blocks of at most ``2 * BLOCK`` classes: larger groups are split by
   set size and by hash into chunks, and every two chunks whose sizes may match are one block.
   No pair of chunks is left out, whatever the size of the group.
4. Within a block the collision-corrected register estimate rules out pairs far below the
   threshold, and the rest are confirmed on their full sets. A block reports a forest of its
   confirmed links, not all of them.

Defined cases: null, empty and wordless texts have no shingles and link with nothing; texts
with fewer words than a shingle are one shingle; rows that repeat a doc_id with other texts are
documents of their own (classes are numbered by set, not by doc_id); a row with a null doc_id stands alone (component null, kept); an empty table gives
an empty result; other columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import bounded, release, slices, table, written
from .components import components, star_forest
from .textnum import mix, shingle_sets, utf8

BANDS, ROWS = 36, 7
REGISTERS = BANDS * ROWS
MANTISSA = 10
SMALL = 100
BLOCK = 128
_PROBE = np.random.default_rng(99).integers(0, REGISTERS, (64, REGISTERS))
_WEIGHT = (np.random.default_rng(98).integers(1, 2**62, REGISTERS, dtype=np.uint64) << np.uint64(1)) | np.uint64(1)
_BAND = np.random.default_rng(97).integers(1, 2**62, BANDS, dtype=np.uint64)


def registers(shingles: np.ndarray) -> np.ndarray:
    """Registers of a non-empty sorted set: bit length and mantissa of the smallest hash of each bucket."""
    bucket = ((shingles >> np.uint64(32)) * np.uint64(REGISTERS) >> np.uint64(32)).astype(np.int64)
    value = mix(shingles) >> np.uint64(11)
    cut = np.flatnonzero(np.concatenate([[True], bucket[1:] != bucket[:-1]]))
    least = np.minimum.reduceat(value, cut)
    out = np.zeros(REGISTERS, np.uint16)
    own = bucket[cut]
    out[own] = _compressed(least)
    full = np.zeros(REGISTERS, bool)
    full[own] = True
    open_ = np.flatnonzero(~full)
    for probe in _PROBE:
        if not len(open_):
            break
        src = probe[open_]
        hit = full[src]
        out[open_[hit]] = out[src[hit]]
        open_ = open_[~hit]
    if len(open_):
        out[open_] = out[own[0]]
    return out


def _compressed(least: np.ndarray) -> np.ndarray:
    """Bit length and leading mantissa bits of 53-bit values."""
    fraction, exponent = np.frexp(least.astype(np.float64))
    return exponent.astype(np.int64) * (1 << MANTISSA) + ((fraction * 2 - 1).clip(0) * (1 << MANTISSA)).astype(np.int64)


def full_registers(shingles: np.ndarray) -> np.ndarray:
    """Registers that each take the smallest of an own hash over the whole set."""
    return _compressed((mix(shingles[:, None] ^ _WEIGHT[None]) >> np.uint64(11)).min(0)).astype(np.uint16)


def estimated_jaccard(agree: np.ndarray, n: np.ndarray, m: np.ndarray) -> np.ndarray:
    """Jaccard from the share of equal registers, less the agreement expected by chance.

    Unrelated sets of n and m elements agree in a register with probability near
    0.17 * 2**-MANTISSA * 4nm / (n + m)**2 (HyperMinHash's approximation).
    """
    chance = 0.1699 * 2.0**-MANTISSA * 4.0 * n * m / np.maximum((n + m) ** 2, 1)
    return (agree - chance) / (1 - chance)


def _bands(regs: np.ndarray) -> np.ndarray:
    return (regs.astype(np.uint64) * _WEIGHT).reshape(BANDS, ROWS).sum(1) + _BAND


def candidate_keys(shingles: np.ndarray, percent: int) -> np.ndarray:
    n = len(shingles)
    keys = []
    if n * percent <= SMALL * 100:
        keys.append(mix(_bands(full_registers(shingles)) ^ np.uint64(0x5BD1E995)))
    if n > SMALL:
        keys.append(mix(_bands(registers(shingles))))
    return np.concatenate(keys)


def sketches(docs: DataFrame, k: int, percent: int) -> DataFrame:
    """doc_id, text_key, n (set size), set_id (hash of the whole set), keys."""

    def sketch(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in (part for batch in batches for part in slices(batch)):
            sets = shingle_sets([utf8(t) for t in pdf["text"]], k)
            yield pd.DataFrame(
                {
                    "doc_id": pdf["doc_id"].astype("Int64"),
                    "text_key": pdf["text_key"].to_numpy(),
                    "n": [len(s) for s in sets],
                    "set_id": [hashlib.blake2b(s.tobytes(), digest_size=16).digest() if len(s) else None for s in sets],
                    "keys": [candidate_keys(s, percent).astype(np.int64) if len(s) else np.zeros(0, np.int64) for s in sets],
                }
            )
        release()

    return docs.select("doc_id", "text", F.xxhash64("text").alias("text_key")).mapInPandas(sketch, "doc_id long, text_key long, n long, set_id binary, keys array<long>")


def common_counts(sets: list[np.ndarray]) -> np.ndarray:
    """Sizes of all intersections, exact: products of blocks of the incidence matrix over shared shingles."""
    owner = np.repeat(np.arange(len(sets)), [len(s) for s in sets])
    _, col, n = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    shared = n[col] > 1
    owner, col = owner[shared], col[shared]
    _, col = np.unique(col, return_inverse=True)
    order = np.argsort(col, kind="stable")
    owner, col = owner[order], col[order]
    out = np.zeros((len(sets), len(sets)), np.float64)
    width = 8192
    for lo in range(0, int(col[-1]) + 1 if len(col) else 0, width):
        a, b = np.searchsorted(col, [lo, lo + width])
        part = np.zeros((len(sets), width), np.float32)
        part[owner[a:b], col[a:b] - lo] = 1
        out += part @ part.T
    return out


def confirmed(ids: np.ndarray, side: np.ndarray, sets: list[np.ndarray], percent: int) -> tuple[np.ndarray, np.ndarray]:
    """Forest (node, root) of the links within a block; with two sides only pairs across count."""
    n = np.array([len(s) for s in sets], np.int64)
    least, most = np.minimum(n[:, None], n[None]), np.maximum(n[:, None], n[None])
    may = np.triu(100 * least >= percent * most, 1)
    if side.any() and not side.all():
        may &= side[:, None] != side[None]
    big = np.flatnonzero(n > SMALL)
    if len(big) and may.any():
        regs = np.stack([registers(sets[i]) for i in big])
        agree = np.stack([(regs == r).mean(1) for r in regs])
        est = estimated_jaccard(agree, n[big][:, None].astype(float), n[big][None].astype(float))
        # Six standard errors below the threshold: such pairs are not confirmed on their sets.
        t = percent / 100
        low = est < t - 6 * np.sqrt(t * (1 - t) / REGISTERS) - 0.06
        sub = may[np.ix_(big, big)]
        sub[low] = False
        may[np.ix_(big, big)] = sub
    i, j = np.nonzero(may)
    if not len(i):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    if len(i) <= 64:
        both = np.array([len(np.intersect1d(sets[a], sets[b], assume_unique=True)) for a, b in zip(i, j)])
    else:
        use, back = np.unique(np.concatenate([i, j]), return_inverse=True)
        c = common_counts([sets[x] for x in use])
        both = c[back[: len(i)], back[len(i) :]].astype(np.int64)
    link = 100 * both >= percent * (n[i] + n[j] - both)
    return star_forest(ids[i[link]], ids[j[link]]) if link.any() else (np.zeros(0, np.int64), np.zeros(0, np.int64))


def blocks_of(members: DataFrame) -> DataFrame:
    """``members`` (node, n, component) with ``blocks``: array of (block, side) in which the class is checked."""
    bin_ = F.floor(F.log(F.col("n").cast("double")) / F.lit(0.163)).cast("int")
    m = members.withColumn("bin", bin_)
    sizes = m.groupBy("component", "bin").count()
    large = sizes.groupBy("component").agg(F.sum("count").alias("total"), F.map_from_entries(F.collect_list(F.struct("bin", F.ceil(F.col("count") / BLOCK).cast("int")))).alias("chunks"))
    large = written(large.where(F.col("total") > BLOCK).drop("total"), "groups")
    j = m.join(large, "component", "left")
    chunks = lambda b: F.coalesce(F.try_element_at("chunks", b), F.lit(0))
    own = F.pmod(F.xxhash64("node"), chunks(F.col("bin"))).cast("int")
    j = j.withColumn("own", F.when(F.col("chunks").isNull(), F.lit(0)).otherwise(own))
    name = lambda a, i, b, k: F.xxhash64("component", a, i, b, k)
    upto = lambda n: F.when(n > 0, F.sequence(F.lit(0), n - 1)).otherwise(F.array().cast("array<int>"))
    entry = lambda block, side: F.struct(block.alias("block"), side.alias("side"))
    same = F.transform(upto(chunks(F.col("bin"))), lambda k: entry(name(F.col("bin"), F.least("own", k), F.col("bin"), F.greatest("own", k)), F.when(F.col("own") > k, 1).otherwise(0)))
    above = F.transform(upto(chunks(F.col("bin") + 1)), lambda k: entry(name(F.col("bin"), F.col("own"), F.col("bin") + 1, k), F.lit(0)))
    below = F.transform(upto(chunks(F.col("bin") - 1)), lambda k: entry(name(F.col("bin") - 1, k, F.col("bin"), F.col("own")), F.lit(1)))
    whole = F.array(entry(F.xxhash64("component", F.lit(-1)), F.lit(0)))
    return j.select("node", F.when(F.col("chunks").isNull(), whole).otherwise(F.concat(same, above, below)).alias("blocks"))


def by_block(rows: DataFrame, columns: list[str], check, schema: str) -> DataFrame:
    """Applies ``check(dict of arrays of one block)`` to every block of ``rows`` (with column ``block``); blocks are bounded."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held = None
        for pdf in batches:
            if held is not None:
                pdf = pd.concat([held, pdf], ignore_index=True)
            b = pdf["block"].to_numpy()
            cut = np.flatnonzero(b[1:] != b[:-1]) + 1
            edges = [0, *cut.tolist()]
            for lo, hi in zip(edges, edges[1:]):
                out = check(pdf.iloc[lo:hi])
                if len(out):
                    yield out
            held = pdf.iloc[edges[-1] :]
        if held is not None and len(held):
            out = check(held)
            if len(out):
                yield out
        release()

    return rows.select("block", *columns).repartition("block").sortWithinPartitions("block").mapInPandas(run, schema)


def near_duplicates(docs: DataFrame, k: int = 5, percent: int = 85) -> DataFrame:
    """doc_id, text_key (xxhash64 of the text), n_shingles, component_id, kept, first for every row of ``docs`` (doc_id, text).

    ``first`` marks one text of each group (all its rows, if rows repeat id and text); ``kept`` follows the ids alone.
    """
    sk = written(sketches(bounded(docs), k, percent), "sketches")
    named = sk.where((F.col("n") > 0) & F.col("doc_id").isNotNull())
    first = named.groupBy("set_id").agg(F.min(F.struct("doc_id", "text_key", "n", "keys")).alias("b"))
    classes = written(first.select(F.monotonically_increasing_id().alias("node"), "set_id", "b.*"), "classes")  # numbers are fixed by the written table
    keyed = classes.select("node", F.explode("keys").alias("key"))
    lead = keyed.groupBy("key").agg(F.min("node").alias("lead"), F.count("*").alias("m")).where(F.col("m") > 1).select("key", "lead")
    shared = keyed.join(written(lead, "keys"), "key").where(F.col("node") != F.col("lead"))
    groups = components(shared.select(F.col("lead").alias("u"), F.col("node").alias("v")))
    members = groups.join(classes.select("node", "n"), "node")
    blocks = written(blocks_of(members), "blocks")
    wanted = blocks.join(classes.select("node", "doc_id", "text_key"), "node")
    # One text for each class: rows that repeat it meet before they are dealt out.
    own = docs.select("doc_id", "text", F.xxhash64("text").alias("text_key"))
    texts = wanted.join(own, ["doc_id", "text_key"]).groupBy("node").agg(F.first("text").alias("text"))
    rows = blocks.join(texts, "node").select("node", "text", F.explode("blocks").alias("b")).select("node", "text", "b.block", "b.side")

    def check(part: pd.DataFrame) -> pd.DataFrame:
        sets = shingle_sets([utf8(t) for t in part["text"]], k)
        own = np.flatnonzero([len(s) > 0 for s in sets])
        child, root = confirmed(part["node"].to_numpy(np.int64)[own], part["side"].to_numpy()[own], [sets[i] for i in own], percent)
        return pd.DataFrame({"u": root, "v": child})

    found = components(by_block(rows, ["node", "text", "side"], check, "u long, v long"), thin=False)
    of_class = written(classes.select("set_id", "node", "doc_id", "text_key").join(found, "node", "left").withColumn("group", F.coalesce("component", "node")), "grouped")
    least = of_class.groupBy("group").agg(F.min(F.struct("doc_id", "text_key")).alias("least"))
    of_class = written(of_class.join(least, "group").select("set_id", F.col("least.doc_id").alias("component"), F.col("least.text_key").alias("first_key")), "found")
    out = sk.select("doc_id", "text_key", "n", "set_id").join(of_class, "set_id", "left")
    component = F.coalesce("component", "doc_id")
    return out.select("doc_id", "text_key", F.col("n").alias("n_shingles"), F.when(F.col("doc_id").isNotNull(), component).alias("component_id"), F.coalesce(component == F.col("doc_id"), F.lit(True)).alias("kept"), F.coalesce((component == F.col("doc_id")) & (F.col("first_key") == F.col("text_key")), F.lit(True)).alias("first"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents")).drop("text_key", "first")
