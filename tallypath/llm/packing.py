"""Best-fit packing with Martello-Toth dominance reduction.

Documents become token ids plus an end id; only longer ones are cut into capacity-sized
pieces. What is packed are piece *lengths*: the instance is the histogram of lengths, at
most ``capacity`` numbers whatever the corpus holds, so it is solved on the driver as it
stands and no piece travels there. The reduction permanently fixes the sets that provably
dominate every other set with the same largest piece; best-fit decreasing packs the rest.
The solution is a table of runs ("pieces number a..b of length s go to sequences from q on,
at offset o"), bounded by the capacity too. Pieces are numbered within their length by
salted groups of about ``GROUP`` pieces, so that one very common length does not meet in one task.

``solve`` keeps the reduced solution unless plain best fit needs fewer sequences (best fit is a heuristic
on what the reduction leaves), and says which one it took.

Defined cases: a null or empty text is the end id alone (length 1); repeated rows are
packed each on its own; a null id is kept as it is; very long texts are encoded whole and cut into pieces; an
empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import re
import zlib
from bisect import bisect_left, insort
from collections.abc import Iterator
from functools import lru_cache
from struct import pack as packed

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import bounded, table, written

MEMO = 200_000
GROUP = 100_000  # pieces of one length that are numbered together


class WordIds:
    """Ids of whole texts as little-endian bytes, each distinct word encoded once while a bounded memo holds it.

    Holds for texts of printable characters below U+0180 without special strings, where the tokenizer's normaliser
    is lower-casing by character; any other text is encoded whole by the library. New words go straight
    to the tokenizer's model.
    """

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.tok = Tokenizer.from_file(path)
        #: Two generations of at most MEMO words each: words in use move to the new one, the others go with the old one.
        self.memo: dict[str, bytes] = {}
        self.old: dict[str, bytes] = {}
        # Byte-level spelling: printable bytes stand for themselves, the others for the letters from U+0100 on.
        kept = [*range(33, 127), *range(161, 173), *range(174, 256)]
        others = [b for b in range(256) if b not in kept]
        self.spelled = {b: chr(256 + i) for i, b in enumerate(others)}
        letters = "a-zªµºß-öø-ſ"
        # The tokenizer's own split, for lower-cased texts in the plain range. Fixed value.
        self.split = re.compile(rf"'s|'t|'re|'ve|'m|'ll|'d|[{letters}]+|[0-9²³¹¼½¾]|[^\s0-9²³¹¼½¾{letters}]+").findall
        self.plain = re.compile("[^\t\n\r\x20-\x7e\xa1-\xac\xae-įı-ſ]").search

    def _learn(self, fresh: list[str]) -> None:
        """Ids of lower-cased words from the tokenizer's model itself, which takes bytes spelled as letters."""
        tokenize = self.tok.model.tokenize
        for w in fresh:
            got = tokenize(w if w.isascii() else w.encode().decode("latin1").translate(self.spelled))
            self.memo[w] = packed(f"<{len(got)}I", *[x.id for x in got])

    def ids(self, text: str) -> bytes:
        if self.plain(text) or "<|" in text:
            return np.array(self.tok.encode(text, add_special_tokens=False).ids, "<u4").tobytes()
        got = self.split(text.lower())
        fresh = [w for w in set(got) if w not in self.memo]
        if fresh:
            if len(self.memo) + len(fresh) > MEMO:
                self.old, self.memo = self.memo, {}
                fresh = list(set(got))
            old = self.old
            self.memo.update((w, old[w]) for w in fresh if w in old)
            if fresh := [w for w in fresh if w not in old]:
                self._learn(fresh)
        return b"".join(map(self.memo.__getitem__, got))


@lru_cache(2)
def word_ids(path: str) -> WordIds:
    return WordIds(path)


def pieces(docs: DataFrame, tokenizer: str, end_id: int, capacity: int) -> DataFrame:
    """One row per piece: doc_id, piece, start, length, ids_crc32."""

    def cut(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        import public_tokenizers

        enc = word_ids(str(public_tokenizers.path(tokenizer)))
        end = np.array([end_id], "<u4").tobytes()
        for pdf in batches:
            doc, piece, start, length, crc = [], [], [], [], []
            for d, text in zip(pdf["doc_id"].array, pdf["text"].array):
                ids = enc.ids(text or "") + end
                for k, at in enumerate(range(0, len(ids), 4 * capacity)):
                    part = ids[at : at + 4 * capacity]
                    doc.append(d)
                    piece.append(k)
                    start.append(at // 4)
                    length.append(len(part) // 4)
                    crc.append(zlib.crc32(part))
            yield pd.DataFrame({"doc_id": pd.array(doc, dtype="Int64"), "piece": piece, "start": start, "length": length, "ids_crc32": crc})

    return docs.select("doc_id", "text").mapInPandas(cut, "doc_id long, piece int, start long, length long, ids_crc32 long")


class _Lengths:
    """A multiset of lengths with its sorted distinct values."""

    def __init__(self, counts: dict[int, int]):
        self.n = {s: n for s, n in counts.items() if n}
        self.at = sorted(self.n)

    def take(self, size: int, k: int) -> None:
        self.n[size] -= k
        if not self.n[size]:
            del self.n[size]
            del self.at[bisect_left(self.at, size)]

    def largest_partner(self, j: int, room: int) -> int | None:
        """The largest length of at most ``room`` besides one piece of length ``j``."""
        i = bisect_left(self.at, room + 1) - 1
        if i >= 0 and self.at[i] == j and self.n[j] == 1:
            i -= 1
        return self.at[i] if i >= 0 else None

    def two_smallest(self, j: int) -> float:
        """Sum of the two smallest lengths besides one piece of length ``j``; infinite if there are fewer."""
        got = []
        for s in self.at[:3]:
            got += [s] * min(2, self.n[s] - (s == j))
        return sum(got[:2]) if len(got) > 1 else float("inf")


def reduce_by_dominance(counts: dict[int, int], capacity: int) -> tuple[list[tuple[tuple[int, ...], int]], dict[int, int]]:
    """Fixes dominating sets for good: ``([(lengths, times)], what is left)``.

    Lengths j from the largest down, with room r = capacity - j; partners are all pieces that are not fixed yet, longer
    ones included. If nothing fits, {j} stands alone. If no two others fit together, any set with j is j and one partner, and
    {j, k} with the longest partner k dominates it. If k fills the room exactly, the partners of j in any set sum to no
    more than k and can take its place, so {j, k} dominates too. Other lengths stay.
    """
    left, fixed = _Lengths(counts), []
    for j in sorted(left.n, reverse=True):
        while j in left.n:
            k = left.largest_partner(j, capacity - j)
            if k is None:
                fixed.append(((j,), left.n[j]))
                left.take(j, left.n[j])
                break
            if k != capacity - j and left.two_smallest(j) <= capacity - j:
                break
            times = left.n[j] // 2 if k == j else min(left.n[j], left.n[k])
            fixed.append(((j, k), times))
            left.take(j, times)
            left.take(k, times)
    return fixed, dict(left.n)


def best_fit_decreasing(counts: dict[int, int], capacity: int) -> list[tuple[tuple[int, ...], int]]:
    """Best fit on the histogram: equal sequences are kept as one pattern with its number of times."""
    open_: dict[int, list[tuple[tuple[int, ...], int]]] = {}  # room left -> patterns
    rooms: list[int] = []

    def put(pattern: tuple[int, ...], times: int, room: int) -> None:
        if room not in open_:
            insort(rooms, room)
            open_[room] = []
        open_[room].append((pattern, times))

    for s in sorted(counts, reverse=True):
        n = counts[s]
        while n:
            i = bisect_left(rooms, s)
            if i == len(rooms):
                each = capacity // s
                full, rest = divmod(n, each)
                if full:
                    put((s,) * each, full, capacity - each * s)
                if rest:
                    put((s,) * rest, 1, capacity - rest * s)
                break
            room = rooms[i]
            pattern, times = open_[room].pop()
            if not open_[room]:
                del open_[room], rooms[i]
            each = min(room // s, n)
            whole = min(times, n // each)
            if whole < times:
                put(pattern, times - whole, room)
            put(pattern + (s,) * each, whole, room - each * s)
            n -= each * whole
    return [x for found in open_.values() for x in found]


def solve(counts: dict[int, int], capacity: int) -> tuple[list[tuple[tuple[int, ...], int]], str]:
    """Patterns of lengths with their number of times, and the way taken: 'reduced' by dominance, then best fit; 'plain' best fit where that needs fewer sequences."""
    fixed, rest = reduce_by_dominance(counts, capacity)
    reduced = fixed + best_fit_decreasing(rest, capacity)
    plain = best_fit_decreasing(counts, capacity)
    total = lambda sol: sum(t for _, t in sol)
    return (reduced, "reduced") if total(reduced) <= total(plain) else (plain, "plain")


def runs(solution: list[tuple[tuple[int, ...], int]]) -> dict[int, np.ndarray]:
    """For each length the runs ``(first piece number, sequence of that piece, offset, pieces per step)`` in order of piece number."""
    out: dict[int, list[tuple[int, int, int]]] = {}
    seen: dict[int, int] = {}
    sequence = 0
    for pattern, times in solution:
        offset = 0
        for s in pattern:
            first = seen.get(s, 0)
            out.setdefault(s, []).append((first, sequence, offset))
            seen[s] = first + times
            offset += s
        sequence += times
    return {s: np.array(v, np.int64) for s, v in out.items()}


def numbered(parts: DataFrame, counts: dict[int, int]) -> DataFrame:
    """``parts`` with ``number``, counting from 0 within each length, by salted groups and sums of their sizes.

    ``counts`` are the pieces of each length: their number of groups follows from it.
    """
    rows = [(s, -(-n // GROUP)) for s, n in counts.items()]
    salts = F.broadcast(parts.sparkSession.createDataFrame(rows, "length long, salts long"))  # a row for each length, ``capacity`` at most
    salted = parts.join(salts, "length").withColumn("salt", F.pmod(F.xxhash64("row"), F.col("salts")).cast("int")).drop("salts")
    sizes = salted.groupBy("length", "salt").count()
    before = Window.partitionBy("length").orderBy("salt").rowsBetween(Window.unboundedPreceding, -1)
    sizes = sizes.select("length", "salt", F.coalesce(F.sum("count").over(before), F.lit(0)).alias("first"))
    within = Window.partitionBy("length", "salt").orderBy("row")
    ranked = salted.withColumn("rank", F.row_number().over(within) - 1)
    return ranked.join(sizes, ["length", "salt"]).withColumn("number", F.col("first") + F.col("rank")).drop("salt", "rank", "first")


def pack(docs: DataFrame, tokenizer: str = "word_bpe_49k.json", end_id: int = 1, capacity: int = 4096) -> DataFrame:
    """Packs ``docs`` (doc_id, text); a row per piece with its sequence and offset."""
    parts = written(pieces(bounded(docs), tokenizer, end_id, capacity).withColumn("row", F.monotonically_increasing_id()), "pieces")
    counts = {r["length"]: r["n"] for r in parts.groupBy("length").agg(F.count("*").alias("n")).collect()}  # at most ``capacity`` rows
    where = parts.sparkSession.sparkContext.broadcast(runs(solve(counts, capacity)[0]))

    def placed(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            length, number = pdf["length"].to_numpy(np.int64), pdf["number"].to_numpy(np.int64)
            sequence, offset = np.zeros(len(pdf), np.int64), np.zeros(len(pdf), np.int64)
            for s in np.unique(length):
                at = np.flatnonzero(length == s)
                r = where.value[int(s)]
                i = np.searchsorted(r[:, 0], number[at], "right") - 1
                sequence[at] = r[i, 1] + number[at] - r[i, 0]
                offset[at] = r[i, 2]
            yield pdf.drop(columns="number").assign(sequence_id=sequence, offset=offset)

    return numbered(parts, counts).select("doc_id", "piece", "start", "length", "ids_crc32", "number").mapInPandas(
        placed, "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long"
    )


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(table(spark, sf_dir, "documents"))
