"""Benchmark decontamination by latent semantic retrieval.

1. Document frequencies of hashed terms over all documents (one pass, a fixed number of
   counters).
2. A randomised SVD of the TF-IDF passages of the benchmark, distributed: tasks hold the
   passages and return their part of ``A'A Q``, a matrix of fixed size; the orthonormal basis
   after a few such rounds spans the latent space. Its rank is the number of passages, at
   most ``RANK``; a passage that keeps less than ``KEPT`` of its energy there is compared by
   plain TF-IDF instead, so none is lost however many there are.
3. Candidate search: whole documents are cut into overlapping passages, projected, and
   compared by cosine with every benchmark passage, in blocks of benchmark passages. A
   passage that holds the share ``weak`` of a benchmark passage's energy is a candidate at
   any cosine: the terms of an item that is in many documents weigh little beside others.
4. Candidates are verified near the hit: the longest common subsequence of words against the
   benchmark passage, and for weaker ones (paraphrases) whether the answer, the last words of
   the item, is there as well.

A benchmark of more than ``QUERIES`` passages is searched in several blocks of whole items; the rows are the
same whatever the number of blocks.

Defined cases: null and empty texts and items have no words and match nothing; an item
shorter than ``SHORT`` words must occur with all its words in order; repeated documents give
repeated rows; rows of ``benchmark`` with one item_id (null included) are one item; a null doc_id is kept as it
is; very long texts are searched whole; empty tables give an empty result; other columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import bounded, release, slices, table, written
from .textnum import chunks, utf8, words

TERMS = 15  # 2 ** TERMS hashed terms
RANK = 256  # dimensions of the latent space at most, and of each plain group
KEPT = 0.99  # share of its energy that a passage keeps in the latent space, or it is compared plainly
BLOCK = 16  # words between passage starts; a passage has PER blocks
PER = 3
SHORT = 10
ANSWER = 5
ITEM = 96  # words of a benchmark passage at most
QUERIES = 4096  # benchmark passages held by a task at a time, about
SUMS = 64  # slices in which the tasks' matrices are added up
SLICE = 256  # blocks of a document projected at a time
_CLEAR = bytes(32 if i < 128 and not chr(i).isalnum() else i for i in range(256))


def plain(text: str | None) -> bytes:
    """UTF-8 with ASCII punctuation as spaces."""
    return utf8(text).translate(_CLEAR)


def terms(h: np.ndarray) -> np.ndarray:
    return (h >> np.uint64(64 - TERMS)).astype(np.int32)


def document_frequencies(docs: DataFrame) -> tuple[np.ndarray, int]:
    """Documents that hold each hashed term, and documents in all; tasks send 2 ** TERMS counters at most."""

    def count(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        n, df = 0, np.zeros(1 << TERMS, np.int64)
        for pdf in batches:
            texts = [plain(t) for t in pdf["text"]]
            n += len(texts)
            for lo, hi in chunks(texts):
                w = words(texts[lo:hi])
                doc = np.repeat(np.arange(hi - lo, dtype=np.int64), np.diff(w.first))
                own = np.unique((doc << TERMS) | terms(w.hash))
                df += np.bincount(own & ((1 << TERMS) - 1), minlength=1 << TERMS)
        if n:
            own = np.flatnonzero(df)
            yield pd.DataFrame({"term": np.append(own, 1 << TERMS), "n": np.append(df[own], n)})
        release()

    out = np.zeros((1 << TERMS) + 1, np.int64)
    for r in docs.select("text").mapInPandas(count, "term int, n long").groupBy("term").agg(F.sum("n").alias("n")).toLocalIterator():
        out[r["term"]] = r["n"]  # one row a term at most
    return out[:-1], int(out[-1])


def idf_weights(df: np.ndarray, n: int) -> np.ndarray:
    """Smoothed weights: a term in all documents still has a little, so a passage copied everywhere can be found."""
    return np.log((n + 1) / (df + 1)).astype(np.float32) + np.float32(0.1)


def benchmark_passages(bench: DataFrame) -> DataFrame:
    """(item_id, part, hashes, answer): items cut into passages of at most ``ITEM`` words."""

    def cut(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            rows = []
            for item, text in zip(pdf["item_id"], pdf["text"]):
                h = words([plain(text)]).hash
                parts = max(1, -(-len(h) // ITEM))
                for k, p in enumerate(np.array_split(h, parts)):
                    if len(p):
                        rows.append((item, k, p.tobytes(), h[-ANSWER:].tobytes()))
            yield pd.DataFrame(rows, columns=["item_id", "part", "hashes", "answer"])

    return bench.select("item_id", "text").mapInPandas(cut, "item_id long, part int, hashes binary, answer binary")


def live_terms(passages: DataFrame) -> np.ndarray:
    """The hashed terms of the passages: at most 2 ** TERMS, from marks of fixed size."""

    def mark(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        seen = np.zeros(1 << TERMS, bool)
        for pdf in batches:
            for x in pdf["hashes"]:
                seen[terms(np.frombuffer(x, np.uint64))] = True
        yield pd.DataFrame({"seen": [np.packbits(seen).tobytes()]})

    out = np.zeros((1 << TERMS) // 8, np.uint8)
    for r in passages.mapInPandas(mark, "seen binary").toLocalIterator():
        out |= np.frombuffer(r["seen"], np.uint8)
    return np.flatnonzero(np.unpackbits(out)).astype(np.int32)


def _summed(pdf: pd.DataFrame) -> pd.DataFrame:
    z = np.frombuffer(pdf["z"].iloc[0], "<f4").copy()
    for x in pdf["z"].iloc[1:]:
        z += np.frombuffer(x, "<f4")
    return pd.DataFrame({"slice": pdf["slice"].iloc[:1], "z": [z.tobytes()]})


def latent_basis(passages: DataFrame, idf: np.ndarray, live: np.ndarray, rank: int = RANK, rounds: int = 3, seed: int = 3) -> np.ndarray:
    """Orthonormal (live terms, rank) basis of the leading right singular vectors of the TF-IDF passages (column ``hashes``)."""
    rank = max(1, min(rank, len(live), passages.count()))
    q = np.linalg.qr(np.random.default_rng(seed).normal(size=(len(live), rank)).astype(np.float32))[0]
    z = q
    for _ in range(rounds):
        shared = passages.sparkSession.sparkContext.broadcast((q, idf, live))

        def part(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            q, idf, live = shared.value
            z, any_ = np.zeros_like(q), False
            for pdf in batches:
                for x in pdf["hashes"]:
                    t, tf = np.unique(terms(np.frombuffer(x, np.uint64)), return_counts=True)
                    a = tf * idf[t]
                    norm = np.linalg.norm(a)
                    if norm:
                        a /= norm
                        i = np.searchsorted(live, t)
                        z[i] += a[:, None] * (a @ q[i])[None]
                        any_ = True
            if any_:
                cut = np.array_split(z.ravel(), SUMS)
                yield pd.DataFrame({"slice": range(SUMS), "z": [x.astype("<f4").tobytes() for x in cut]})

        # Tasks' parts are summed by slices in the executors; one matrix of fixed size reaches the driver.
        parts = passages.mapInPandas(part, "slice int, z binary").groupBy("slice").applyInPandas(_summed, "slice int, z binary").collect()
        z = np.concatenate([np.frombuffer(r["z"], "<f4") for r in sorted(parts, key=lambda r: r["slice"])]).reshape(q.shape).copy() if parts else np.zeros_like(q)
        q = np.linalg.qr(z + 1e-7 * q)[0].astype(np.float32)
        shared.unpersist()
    q[np.abs(z).sum(1) == 0] = 0
    return q


def common_subsequence(item: np.ndarray, text: np.ndarray) -> int:
    """Length of the longest common subsequence, bit-parallel over the item's words."""
    at: dict[int, int] = {}
    for i, h in enumerate(item.tolist()):
        at[h] = at.get(h, 0) | (1 << i)
    full = (1 << len(item)) - 1
    v = full
    for h in text.tolist():
        m = at.get(h)
        if m:
            u = v & m
            v = ((v + u) | (v - u)) & full
    return len(item) - bin(v).count("1")


def near_subsequence(item: np.ndarray, text: np.ndarray) -> tuple[int, int]:
    """Best subsequence length over windows little longer than the item, and where its window starts."""
    span, step = int(1.35 * len(item)) + 2, max(1, len(item) // 6)
    inside = np.isin(text, item)
    best = (0, 0)
    for s in range(0, max(1, len(text) - span + step), step):
        if int(inside[s : s + span].sum()) > best[0]:
            best = max(best, (common_subsequence(item, text[s : s + span]), -s))
    return best[0], -best[1]


@dataclass
class Searcher:
    """Benchmark passages in the latent space, for one block of them."""

    idf: np.ndarray
    terms: np.ndarray
    basis: np.ndarray
    item: np.ndarray
    hashes: list[np.ndarray]
    answer: list[np.ndarray]
    cosine: float
    strong: float
    weak: float

    def __post_init__(self):
        self.square = self.idf**2
        own, length = [], []
        for h in self.hashes:
            t, tf = np.unique(terms(h), return_counts=True)
            a = tf * self.idf[t]
            length.append(np.linalg.norm(a))
            own.append((t, (a / max(length[-1], 1e-9)).astype(np.float32)))
        self.length = np.array(length, np.float32)
        #: Distinct words of each passage, and how many of them a text must hold at least to be verified.
        self.held = [set(h.tolist()) for h in self.hashes]
        self.fewest = [len(own) - len(h) + math.ceil((1.0 if len(h) < SHORT else min(self.weak, self.strong)) * len(h) - 1e-9) for own, h in zip(self.held, self.hashes)]
        query = np.array([a @ self.basis[np.searchsorted(self.terms, t)] for t, a in own], np.float32).reshape(len(own), self.basis.shape[1])
        whole = (query**2).sum(1) >= KEPT
        latent, short = np.flatnonzero(whole), np.flatnonzero(~whole)
        self.spaces = [self.space(latent, self.terms, self.basis, query[latent])] if len(latent) else []
        for lo in range(0, len(short), RANK):
            group = short[lo : lo + RANK]
            t = np.unique(np.concatenate([own[k][0] for k in group]))
            columns = np.zeros((len(t), len(group)), np.float32)
            for c, k in enumerate(group):
                columns[np.searchsorted(t, own[k][0]), c] = own[k][1]
            self.spaces.append(self.space(group, t, columns, None))

    def space(self, group: np.ndarray, own: np.ndarray, basis: np.ndarray, query: np.ndarray | None) -> tuple:
        """(passages, row of the basis for each term, weighted basis, queries); row -1 for terms without weight, queries None where columns are passages."""
        row = np.full(1 << TERMS, -1, np.int32)
        some = (np.abs(basis).sum(1) > 0) & (self.idf[own] > 0)
        row[own[some]] = np.flatnonzero(some)
        return group, row, basis * self.idf[own][:, None], query

    def products(self, space: tuple, t: np.ndarray, block: np.ndarray, doc: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Starting blocks of document passages, and their products with the unit passages of a space."""
        _, row_of, basis, query = space
        row = row_of[t]
        use = np.flatnonzero(row >= 0)
        vec = np.zeros((len(doc), basis.shape[1]), np.float32)
        if len(use):
            own, cut = np.unique(block[use], return_index=True)
            cut = np.append(cut, len(use))
            for lo in range(0, len(own), SLICE):
                part = cut[lo : lo + SLICE + 1]
                vec[own[lo : lo + SLICE]] = np.add.reduceat(basis[row[use[part[0] : part[-1]]]], part[:-1] - part[0], axis=0)
        passage = vec.copy()
        for k in range(1, PER):
            same = np.flatnonzero(doc[k:] == doc[:-k])
            passage[same] += vec[same + k]
        some = np.flatnonzero((passage != 0).any(1))
        return some, passage[some] if query is None else passage[some] @ query.T

    def search(self, texts: list[bytes]) -> Iterator[tuple[int, int, float, int, int, bool]]:
        """(text, item, cosine, common words, item words, answer found) of verified hits, best of each text and item."""
        held, fewest = self.held, self.fewest
        for lo, hi in chunks(texts):
            w = words(texts[lo:hi])
            if not len(w.hash):
                continue
            t = terms(w.hash)
            size = np.diff(w.first)
            blocks = -(-size // BLOCK)
            first_block = np.concatenate([[0], np.cumsum(blocks)])
            offset = np.arange(len(t)) - np.repeat(w.first[:-1], size)
            block = np.repeat(first_block[:-1], size) + offset // BLOCK
            norm2 = np.bincount(block, self.square[t], int(first_block[-1]))
            doc = np.repeat(np.arange(hi - lo), blocks)
            n2 = norm2.copy()
            for k in range(1, PER):
                same = np.flatnonzero(doc[k:] == doc[:-k])
                n2[same] += norm2[same + k]
            hits = []
            for space in self.spaces:
                some, dot = self.products(space, t, block, doc)
                norm = np.sqrt(np.maximum(n2[some], 1e-9)).astype(np.float32)
                i, j = np.nonzero(dot >= np.minimum(self.cosine * norm[:, None], self.weak * self.length[space[0]]))
                hits.append((some[i], space[0][j], dot[i, j] / norm[i]))
            best: dict[tuple[int, int], tuple] = {}
            for a, b, c in (x for h in hits for x in zip(*h)):
                d, item = int(doc[a]), self.hashes[b]
                at = int(w.first[d]) + (int(a) - int(first_block[d])) * BLOCK
                s, e = max(int(w.first[d]), at - len(item)), min(int(w.first[d + 1]), at + PER * BLOCK + len(item))
                near = w.hash[s:e]
                if len(held[b].intersection(near.tolist())) < fewest[b]:
                    continue
                key = (lo + d, int(self.item[b]))
                lcs, where = near_subsequence(item, near)
                share = lcs / len(item)
                answer = bool(len(self.answer[b])) and common_subsequence(self.answer[b], near[where : where + 2 * len(item)]) == len(self.answer[b])
                least = 1.0 if len(item) < SHORT else self.weak if answer else self.strong
                if share >= least and (key not in best or (lcs, c) > best[key][:2]):
                    best[key] = (lcs, float(c), len(item), answer)
            for (d, item), (lcs, c, n, answer) in best.items():
                yield d, item, min(1.0, c), lcs, n, answer


def find_leaks(docs: DataFrame, bench: DataFrame, cosine: float = 0.22, strong: float = 0.6, weak: float = 0.45) -> DataFrame:
    """doc_id, item_id, cosine, common_words, item_words, answer_found of every document and benchmark item that it holds."""
    spark = bounded(docs).sparkSession
    kind = "doc_id long, item_id long, cosine double, common_words int, item_words int, answer_found boolean, text_key long"
    passages = written(benchmark_passages(bench), "passages")
    n = passages.count()
    if not n:
        return spark.createDataFrame([], kind)
    idf = idf_weights(*document_frequencies(docs))
    live = live_terms(passages)
    basis = latent_basis(passages, idf, live)
    blocks = -(-n // QUERIES)
    dealt = passages.withColumn("block", F.pmod(F.xxhash64("item_id"), F.lit(blocks))).orderBy("item_id", "part")
    own = docs.select("doc_id", "text", F.xxhash64("text").alias("text_key"))

    def searched(block: list[dict]) -> DataFrame:
        shared = spark.sparkContext.broadcast((idf, live, basis, block))

        def go(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            w, own, q, rows = shared.value
            items = list({r["item_id"]: None for r in rows})  # an item is known by its place: its id may be null
            place = {x: i for i, x in enumerate(items)}
            s = Searcher(w, own, q, np.array([place[r["item_id"]] for r in rows]), [np.frombuffer(r["hashes"], np.uint64) for r in rows], [np.frombuffer(r["answer"], np.uint64) for r in rows], cosine, strong, weak)
            for pdf in (part for batch in batches for part in slices(batch, most=1 << 20)):
                ids, keys = pdf["doc_id"].astype("Int64").array, pdf["text_key"].to_numpy()
                out = [(ids[d], items[item], c, lcs, m, a, keys[d]) for d, item, c, lcs, m, a in s.search([plain(t) for t in pdf["text"]])]
                if out:
                    out = pd.DataFrame(out, columns=["doc_id", "item_id", "cosine", "common_words", "item_words", "answer_found", "text_key"])
                    yield out.assign(doc_id=out["doc_id"].astype("Int64"), item_id=out["item_id"].astype("Int64"))
            del s
            release()

        return own.mapInPandas(go, kind)

    # Each block is a bounded query set against all documents; an item lies in one block, so blocks need no merge.
    found = None
    for b in range(blocks):
        rows = [r.asDict() for r in dealt.where(F.col("block") == b).drop("block").collect()]
        if rows:
            found = searched(rows) if found is None else found.unionByName(searched(rows))
    return found


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return find_leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
