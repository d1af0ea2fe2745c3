"""Toxicity by a convolutional text classifier over hashed word embeddings.

Words are hashed to 64 bits; words and word beginnings seen in at least two labelled texts
(of the most frequent ones, MOST_HASHES at most) own an embedding row each, found through a table of 2**20 hash buckets with
the whole hash compared, and all others embed to zero. A word's embedding is the sum of both
rows. Several filter widths and max pooling are trained in numpy. Scores are calibrated by
language: the language is told from the text's own words (never from a column), and the
threshold that does best on held-back training rows of that language is moved to 0.5.

The classifier learns from all labelled rows, whole texts: hashes are counted over all of them; shards of about
SHARD rows train the net on the workers, and the nets are averaged, ROUNDS times; thresholds come from counts of
all held-back rows. Scoring reads whole texts of all rows.

Of known hashes that fall into one bucket of the table the last keeps it; the others embed to zero like
unknown words.

Defined cases: null and empty texts get the score of a text without known words; repeated
rows get equal scores; of rows that repeat a labelled doc_id the least text is learned; a label is 1 if any row of
``labels`` for the id says so; a null id is never learned from and counts as not held out; very long texts are
scored whole; with no labelled rows of one of the labels every score is 0; an empty
table gives an empty result; other columns are ignored, and the result's column replaces one of its name.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import bounded, drop_written, release, table, written
from .convnet import ConvNet
from .textnum import chunks, mix, utf8, words

#: Hashes that own an embedding row at most, rows that train a net together, rounds of averaging, floats of a part, steps of a calibrated logit.
MOST_HASHES, SHARD, ROUNDS, BLOCK, STEP = 1 << 17, 8000, 2, 1 << 16, 256
BUCKETS = 20
WIDTHS = (1, 2, 3)
BEGINNING = 4
SCORED = 1 << 18
_KEYS = np.cumprod(np.full(BEGINNING, 0xA24BAED4963EE407, np.uint64))


def _beginnings(w) -> np.ndarray:
    """Hash of the first bytes of each word."""
    a = np.frombuffer(w.data, np.uint8)
    h = np.zeros(len(w.start), np.uint64)
    for j in range(BEGINNING):
        at = w.start + j
        inside = at < w.end
        h[inside] += (a[at[inside]].astype(np.uint64) | np.uint64(0x20)) * _KEYS[j]
    return mix(h + np.uint64(1))


class Lexicon:
    """Row numbers (from 1) of known 64-bit hashes; 0 for all others."""

    def __init__(self, hashes: np.ndarray):
        self.hashes = np.concatenate([np.zeros(1, np.uint64), hashes])
        self.slots = np.zeros(1 << BUCKETS, np.int32)
        self.slots[(hashes >> np.uint64(64 - BUCKETS)).astype(np.int64)] = np.arange(1, len(hashes) + 1)

    def rows(self, h: np.ndarray) -> np.ndarray:
        r = self.slots[(h >> np.uint64(64 - BUCKETS)).astype(np.int64)]
        return np.where(self.hashes[r] == h, r, 0)


def _ids(texts: list[bytes], lexicon: Lexicon):
    """For each chunk: word rows, beginning rows (same numbering), first word of each text."""
    for lo, hi in chunks(texts, SCORED):
        w = words(texts[lo:hi])
        yield lexicon.rows(w.hash), lexicon.rows(_beginnings(w)), w.first


@dataclass
class ToxicModel:
    """Tables of filter responses by row, the language table, and the calibrated thresholds."""

    hashes: np.ndarray
    net: ConvNet
    languages: list[str]
    by_word: np.ndarray
    prior: np.ndarray
    thresholds: np.ndarray

    def prepare(self) -> "ToxicModel":
        self.lexicon = Lexicon(self.hashes)
        self.responses = self.net.tables()
        return self

    def raw(self, texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """Logit of each text and the number of its language."""
        pad = self.net.pad
        nf = self.net.filters[WIDTHS[0]].shape[2]
        logit, lang = [], []
        for rows, starts_of, first in _ids(texts, self.lexicon):
            n, sizes = len(first) - 1, np.diff(first)
            padded = np.zeros(int(sizes.sum()) + n * (pad + 1), np.int32)
            start = first[:-1] + np.arange(n) * (pad + 1)
            at = np.arange(len(rows)) + np.repeat(np.arange(n) * (pad + 1), sizes)
            also = padded.copy()
            padded[at], also[at] = rows, starts_of
            best, known = [], np.flatnonzero((padded > 0) | (also > 0))
            for w, per in self.responses.items():
                # Windows that hold no known word respond with 0, which the zeros after each text give anyway.
                near = np.unique((known[:, None] - np.arange(w)).ravel())
                near = near[near >= 0]
                c = np.zeros((len(near), nf), np.float32)
                for o, t in enumerate(per):
                    i = np.minimum(near + o, len(padded) - 1)
                    c += t[padded[i]]
                    c += t[also[i]]
                text = np.searchsorted(start, near, "right") - 1
                top = np.zeros((n, nf), np.float32)
                if len(near):
                    own, cut = np.unique(text, return_index=True)
                    top[own] = np.maximum(np.maximum.reduceat(c, cut), 0)
                best.append(top)
            z = self.net.logits(np.concatenate(best, 1))
            logit.append(z[:, 1] - z[:, 0])
            votes = np.repeat(self.prior[None], n, 0)
            if len(rows):
                own = np.flatnonzero(sizes)
                votes[own] += np.add.reduceat(self.by_word[rows], first[:-1][own], axis=0)
            lang.append(votes.argmax(1))
        return (np.concatenate(logit), np.concatenate(lang)) if logit else (np.zeros(0), np.zeros(0, int))

    def score(self, texts: list[bytes]) -> np.ndarray:
        z, lang = self.raw(texts)
        return 1 / (1 + np.exp(-np.clip(z - self.thresholds[lang], -60, 60).astype(np.float64)))


def _best_threshold(z: np.ndarray, clean: np.ndarray, toxic: np.ndarray, fallback: float) -> float:
    """Midway between the neighbouring scores ``z`` (with how many rows of either label) where balanced error is least; ties go to the widest gap."""
    if toxic.sum() < 5 or clean.sum() < 5:
        return fallback
    z, back = np.unique(z, return_inverse=True)
    clean, toxic = np.bincount(back, clean), np.bincount(back, toxic)
    missed = np.concatenate([[0], np.cumsum(toxic)]) / toxic.sum()
    wrong = 1 - np.concatenate([[0], np.cumsum(clean)]) / clean.sum()
    edge = np.concatenate([[z[0] - 1], z, [z[-1] + 1]])
    gap = edge[1:] - edge[:-1]
    error = missed + wrong
    good = np.flatnonzero(error <= error.min() + 1e-12)
    i = good[gap[good].argmax()]
    return float((edge[i] + edge[i + 1]) / 2)


class _PairNet(ConvNet):
    """A net whose tokens have two ids each; their embeddings are summed."""

    def fit(self, seqs, labels, weights, epochs, batch: int = 64, rate: float = 0.003, decay: float = 1e-4, seed: int = 11) -> None:
        rng = np.random.default_rng(seed)
        params = self._params()
        m, v = [np.zeros_like(p) for p in params], [np.zeros_like(p) for p in params]
        step, gap = 0, np.zeros((2, self.pad + 1), np.int32)
        for epoch in range(epochs):
            order = rng.permutation(len(seqs))
            for lo in range(0, len(order), batch):
                idx = order[lo : lo + batch]
                ids = np.concatenate([x for i in idx for x in (seqs[i], gap)], 1)
                sizes = np.array([seqs[i].shape[1] + self.pad + 1 for i in idx])
                starts = np.concatenate([[0], np.cumsum(sizes)[:-1]])
                x = self.emb[ids[0]] + self.emb[ids[1]]
                best, where = [], []
                for w, f in self.filters.items():
                    n = len(x) - w + 1
                    c = x[:n] @ f[0]
                    for o in range(1, w):
                        c += x[o : o + n] @ f[o]
                    p = np.stack([s + c[s:e].argmax(0) for s, e in zip(starts, np.minimum(starts + sizes, n))])
                    best.append(c[p, np.arange(c.shape[1])])
                    where.append(p)
                h = np.maximum(np.concatenate(best, 1) + self.bias, 0)
                z = h @ self.dense + self.top
                p = np.exp(z - z.max(1, keepdims=True))
                p /= p.sum(1, keepdims=True)
                p[np.arange(len(idx)), labels[idx]] -= 1
                p *= (weights[idx] / len(idx))[:, None]
                dh = (p @ self.dense.T) * (h > 0)
                grads = [np.zeros_like(self.emb), *[np.zeros_like(f) for f in self.filters.values()], dh.sum(0), h.T @ p, p.sum(0)]
                col = 0
                for k, (w, f) in enumerate(self.filters.items()):
                    d, pos = dh[:, col : col + f.shape[2]], where[k]
                    for o in range(w):
                        grads[1 + k][o] += np.einsum("bfd,bf->df", x[pos + o], d)
                        back = (d[:, :, None] * f[o].T[None]).reshape(-1, f.shape[1])
                        for side in ids:
                            np.add.at(grads[0], side[pos + o].ravel(), back)
                    col += f.shape[2]
                grads[0][0] = 0
                step += 1
                lr = rate * (1 - 0.9 * epoch / max(1, epochs))
                for q, g, a, b in zip(params, grads, m, v):
                    g = g + decay * q if q is not self.emb else g
                    a += 0.1 * (g - a)
                    b += 0.001 * (g * g - b)
                    q -= lr * (a / (1 - 0.9**step)) / (np.sqrt(b / (1 - 0.999**step)) + 1e-8)
                self.emb[0] = 0


def _labelled(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """(doc_id, toxic, held, text, lang) of all labelled rows whose crc32(doc_id) mod 5 isn't 0, a row for each id; ``held``: only calibrates."""
    known = labels.where(F.col("toxic").isin(0, 1) & F.col("doc_id").isNotNull()).select("doc_id", F.col("toxic").cast("int").alias("toxic"))
    known = known.where(F.pmod(F.crc32(F.col("doc_id").cast("string")), F.lit(5)) != 0).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    lang = F.col("lang") if "lang" in docs.columns else F.lit(None).cast("string")
    own = docs.select("doc_id", "text", lang.alias("lang")).join(known, "doc_id")
    own = own.groupBy("doc_id", "toxic").agg(F.min(F.struct("text", "lang")).alias("b"))
    return own.select("doc_id", "toxic", (F.pmod(F.xxhash64("doc_id"), F.lit(5)) == 0).alias("held"), "b.*")


def _counted(rows: DataFrame, names: list[str]) -> pa.Table:
    """(hash, clean, toxic, [texts of each language]) of the MOST_HASHES hashes that most texts hold, at least two; over all rows."""
    number = {x: i for i, x in enumerate(names)}

    def count(batches):
        for batch in batches:
            texts, found = [utf8(t) for t in batch.column("text").to_pylist()], []
            toxic, held = batch.column("toxic").to_numpy(), batch.column("held").to_numpy(zero_copy_only=False)
            lang = [number.get(x) for x in batch.column("lang").to_pylist()]
            at = 0
            for lo, hi in chunks(texts, SCORED):
                w = words(texts[lo:hi])
                b = _beginnings(w)
                for i in range(hi - lo):
                    s = slice(int(w.first[i]), int(w.first[i + 1]))
                    own = np.unique(w.hash[s])
                    # 0 and 1: train texts by label; 2: held ones; from 3: texts by language, words alone.
                    found.append((np.unique(np.concatenate([own, b[s]])), 2 if held[at] else int(toxic[at])))
                    if lang[at] is not None:
                        found.append((own, 3 + lang[at]))
                    at += 1
            for kind in sorted({k for _, k in found}):
                h, n = np.unique(np.concatenate([x for x, k in found if k == kind]), return_counts=True)
                for lo in range(0, len(h), 1 << 16):
                    m = len(h[lo : lo + (1 << 16)])
                    yield pa.RecordBatch.from_arrays([pa.array(h[lo : lo + m].view(np.int64)), pa.array(np.full(m, kind, np.int32)), pa.array(n[lo : lo + m].astype(np.int64))], ["hash", "kind", "n"])

    of = lambda *kinds: F.sum(F.when(F.col("kind").isin(*kinds), F.col("n")).otherwise(0))
    each = rows.mapInArrow(count, "hash long, kind int, n long").groupBy("hash").agg(of(0, 1, 2).alias("texts"), of(0).alias("clean"), of(1).alias("toxic"), F.array(*[of(3 + i) for i in range(len(names))]).alias("langs"))
    return each.where("texts > 1").orderBy(F.desc("texts"), "hash").limit(MOST_HASHES).drop("texts").toArrow()


def _start(counted: pa.Table, names: list[str], docs: np.ndarray, per: np.ndarray) -> ToxicModel:
    """A model before training. The first dimension starts at each row's smoothed log odds over all training rows, the others near zero."""
    counted = counted.sort_by("hash")
    h = counted.column("hash").to_numpy().view(np.uint64)
    net = _PairNet.fresh(len(h) + 1, 2, 8, 8, WIDTHS)
    odds = np.stack([np.concatenate([[2], 2.0 + counted.column(c).to_numpy()]) for c in ("clean", "toxic")])
    net.emb *= 0.1
    net.emb[:, 0] = np.clip(np.log(odds[1] / (4 + per[1])) - np.log(odds[0] / (4 + per[0])), -3, 3) * 0.5
    net.emb[0] = 0
    langs = counted.column("langs").combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(len(h), len(names))
    counts = np.full((len(h) + 1, len(names)), 0.5, np.float32)
    counts[1:] += langs
    by_word = np.log(counts / counts.sum(0))
    by_word = (by_word - by_word.mean(1, keepdims=True)).astype(np.float32)
    by_word[0] = 0
    return ToxicModel(h, net, names, by_word, np.log(docs / docs.sum()).astype(np.float32), np.zeros(len(names), np.float32))


def _trained(rows: DataFrame, model: ToxicModel, shards: int, epochs: int, per: np.ndarray) -> None:
    """One round: every shard of the rows trains the net on its own, and the nets are averaged, rows of the embedding by the texts that hold them."""
    spark = rows.sparkSession
    shared = spark.sparkContext.broadcast((model.hashes, model.net))
    weigh = (0.5 * per.sum() / np.maximum(per, 1)).astype(np.float32)
    shard = F.pmod(F.xxhash64("doc_id", F.lit(1)), F.lit(shards)).alias("shard")

    def learn(t: pa.Table) -> pa.Table:
        hashes, net = shared.value
        net = _PairNet(net.emb.copy(), {w: f.copy() for w, f in net.filters.items()}, net.bias.copy(), net.dense.copy(), net.top.copy())
        t = t.sort_by("doc_id")
        texts, y, pairs = [utf8(x) for x in t.column("text").to_pylist()], t.column("toxic").to_numpy().astype(int), []
        for own, also, first in _ids(texts, Lexicon(hashes)):
            pairs += [np.stack([own[a:b], also[a:b]]).astype(np.int32) for a, b in zip(first[:-1], first[1:])]
        seen = np.zeros(len(net.emb), np.float32)
        for p in pairs:
            seen[np.unique(p)] += 1
        net.fit(pairs, y, weigh[y], epochs)
        value = np.concatenate([p.ravel() for p in net._params()]).astype(np.float32)
        weight = np.full(len(value), len(y), np.float32)
        weight[: net.emb.size] = np.repeat(seen, net.emb.shape[1])
        parts = range(0, len(value), BLOCK)
        out = pa.table({"part": pa.array([lo // BLOCK for lo in parts], pa.int32()), "value": pa.array([(value[lo : lo + BLOCK] * weight[lo : lo + BLOCK]).tobytes() for lo in parts], pa.binary()), "weight": pa.array([weight[lo : lo + BLOCK].tobytes() for lo in parts], pa.binary())})
        del net, pairs, texts, value, weight
        release()
        return out

    def total(t: pa.Table) -> pa.Table:
        sums = {c: sum(np.frombuffer(x, np.float32).astype(float) for x in t.column(c).to_pylist()).astype(np.float32).tobytes() for c in ("value", "weight")}
        return pa.table({"part": pa.array([t.column("part")[0].as_py()], pa.int32()), "value": pa.array([sums["value"]], pa.binary()), "weight": pa.array([sums["weight"]], pa.binary())})

    schema = "part int, value binary, weight binary"
    nets = rows.where(~F.col("held")).select(shard, "doc_id", "toxic", "text").groupBy("shard").applyInArrow(learn, schema)
    got = nets.groupBy("part").applyInArrow(total, schema).toArrow().sort_by("part")  # as large as one net
    value, weight = (np.concatenate([np.frombuffer(x, np.float32) for x in got.column(c).to_pylist()]) for c in ("value", "weight"))
    at = 0
    for p in model.net._params():
        v, w = value[at : at + p.size].reshape(p.shape), weight[at : at + p.size].reshape(p.shape)
        p[...] = np.where(w > 0, v / np.maximum(w, 1), p)
        at += p.size
    shared.unpersist()


def _calibrated(rows: DataFrame, model: ToxicModel) -> np.ndarray:
    """Thresholds by language from all held rows: rows of either label are counted by language and score, in steps of 1 / STEP."""
    shared = rows.sparkSession.sparkContext.broadcast(model)

    def measure(batches):
        m = shared.value.prepare()
        for batch in batches:
            z, lang = m.raw([utf8(t) for t in batch.column("text").to_pylist()])
            yield pa.RecordBatch.from_arrays([pa.array(lang.astype(np.int32)), pa.array(np.round(np.clip(z, -60, 60) * STEP).astype(np.int32)), batch.column("toxic")], ["lang", "step", "toxic"])
        del m.lexicon, m.responses
        release()

    of = rows.where("held").select("toxic", "text").mapInArrow(measure, "lang int, step int, toxic int")
    got = of.groupBy("lang", "step").agg(F.count_if(F.col("toxic") == 0).alias("clean"), F.count_if(F.col("toxic") == 1).alias("toxic")).toArrow()
    lang, z, clean, toxic = (got.column(c).to_numpy() for c in ("lang", "step", "clean", "toxic"))
    fallback = _best_threshold(z / STEP, clean, toxic, 0.0)
    return np.array([_best_threshold(z[lang == i] / STEP, clean[lang == i], toxic[lang == i], fallback) for i in range(len(model.languages))], np.float32)


def train(docs: DataFrame, labels: DataFrame, epochs: int | None = None) -> ToxicModel | None:
    """Model from all labelled rows whose crc32(doc_id) mod 5 isn't 0: counts and training from four fifths, thresholds from the rest (see ``_labelled``)."""
    rows = written(_labelled(docs, labels), "labelled")
    sizes = {(r["held"], r["toxic"]): r["n"] for r in rows.groupBy("held", "toxic").agg(F.count("*").alias("n")).collect()}  # four at most
    per = np.array([sizes.get((False, y), 0) for y in (0, 1)])
    if not per.all():
        drop_written(rows)
        return None
    spoken = {r["lang"]: r["n"] for r in rows.where("lang is not null").groupBy("lang").agg(F.count("*").alias("n")).collect()}  # a row for each language
    names = sorted(spoken) or [""]
    model = _start(_counted(bounded(rows), names), names, np.array([spoken.get(x, 0) for x in names]) + 1, per)
    shards = max(1, round(int(per.sum()) / SHARD))
    rounds = 1 if shards == 1 else ROUNDS
    for _ in range(rounds):
        _trained(rows, model, shards, -(-(epochs or max(5, min(30, 40_000 // int(per.sum())))) // rounds), per)
    model.net = ConvNet(model.net.emb, model.net.filters, model.net.bias, model.net.dense, model.net.top)
    model.thresholds = _calibrated(bounded(rows), model)
    drop_written(rows)
    release()
    return model


def score(docs: DataFrame, model: ToxicModel | None, name: str = "score") -> DataFrame:
    """``docs`` with the score of whole texts in column ``name``."""
    if model is None:
        return docs.withColumn(name, F.lit(0.0))
    shared = docs.sparkSession.sparkContext.broadcast(model)

    @F.pandas_udf("double")
    def scores(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        m = shared.value.prepare()
        for texts in batches:
            yield pd.Series(m.score([utf8(t) for t in texts]))
        del m.lexicon, m.responses  # the worker keeps the broadcast model itself
        release()

    return bounded(docs).withColumn(name, scores("text"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = train(docs, table(spark, sf_dir, "labels"))
    scored = score(docs.select("doc_id", "text"), model)
    held = F.coalesce(F.pmod(F.crc32(F.col("doc_id").cast("string")), F.lit(5)) == 0, F.lit(False))
    return scored.select("doc_id", held.alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
