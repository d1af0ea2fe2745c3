"""Removal of repeated byte strings by a common-prefix-aware distributed merge sort.

Every ``LENGTH``-byte window of a text belongs to one anchor in it: the window's ``GRAM``-byte
string of least hash (the leftmost of equal ones). Equal windows have equal anchors at equal
places, so it suffices to sort the suffixes that start at anchors, one for each run of windows
that share an anchor ("segment"), instead of those at all bytes.

1. Anchor hashes are counted over the corpus. A filter of fixed size holds those that occur
   twice or more; it only saves work: what it lets through for no reason is compared and
   found different.
2. Tasks sort the anchored suffixes that pass into runs, front-coded (length of the prefix
   shared with the suffix before, then the rest), cut by hash of the anchor. A segment equal
   to an earlier one of the same run is settled at once, so a passage that many documents
   share costs a row per run. An anchor that is in more segments than a share of 2 ** -HOT_BITS is dealt by its
   surroundings instead: a window with ``HALF`` bytes or more before the anchor holds these, any other
   window holds ``HALF`` bytes after it, so equal windows still meet.
3. Runs of a bucket are merged by a loser tree whose comparisons start where the known common
   prefixes end. The merge yields sorted suffixes with common prefix lengths; for each
   distance l from window start to anchor, windows are equal where the sorted suffixes share
   LENGTH - l bytes and the l bytes before the anchor are equal too. All but the first of
   equal windows (by doc_id, then start) are removed.
4. A segment's removed windows always overlap, so it reports one span. Spans of a document
   are united and cut out of its bytes.

Hashes only bring windows together; before anything is removed their bytes are compared.

Defined cases: a null or empty text has no bytes and nothing removed; texts shorter than
``LENGTH`` lose nothing; rows that repeat a doc_id are told apart by a hash of the text, which also orders them;
two rows of the same id and text count as one
text; a row with a null id comes before all others; an empty table gives an empty result;
other columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import bounded, release, slices, table, written
from .textnum import chunks, mix, utf8

LENGTH = 100
GRAM = 24
PIECE = 1 << 18  # bytes hashed at a time
FLUSH = 6 << 20  # bytes of text behind a run
FILTER_BITS = 27
SLICES = 64
_PLACE = np.uint64((1 << 20) - 1)
_RAND = np.random.default_rng(61).integers(1, 2**62, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_BASE = 0x9E3779B97F4A7C15
_SIZE = PIECE * 2
_POW = np.cumprod(np.full(_SIZE, _BASE, np.uint64))
_INV = np.cumprod(np.full(_SIZE, pow(_BASE, -1, 1 << 64), np.uint64))
_NULL_ID = -(1 << 63)
HALF = (LENGTH - GRAM) // 2  # 38
HOT_BITS = 14
HOT = 4096  # and at least of so many segments


def _least(v: np.ndarray, width: int) -> np.ndarray:
    """Minimum over every ``width`` neighbours, by doubling."""
    out, have = v, 1
    while 2 * have <= width:
        out = np.minimum(out[:-have], out[have:])
        have *= 2
    rest = width - have
    return np.minimum(out[:-rest], out[rest:]) if rest else out


def segments(texts: list[bytes]):
    """(text, start, windows, anchor, gram hash, content hash) arrays of the segments of ``texts``; places are within the text."""
    found = []
    parts: list[tuple[int, int, bytes]] = []  # text, offset, bytes

    def settle() -> None:
        if not parts:
            return
        data = np.frombuffer(b"".join(p[2] for p in parts), np.uint8)
        if len(data) < LENGTH:
            parts.clear()
            return
        sums = np.zeros(len(data) + 1, np.uint64)
        np.cumsum(_RAND[data] * _POW[: len(data)], out=sums[1:])
        n = len(data) - GRAM + 1
        h = mix((sums[GRAM:] - sums[:-GRAM]) * _INV[:n])
        least = _least((h & ~_PLACE) | np.arange(n, dtype=np.uint64), LENGTH - GRAM + 1)
        anchor = (least & _PLACE).astype(np.int64)
        size = np.array([len(p[2]) for p in parts])
        first = np.concatenate([[0], np.cumsum(size)])
        valid = np.zeros(len(anchor) + 1, bool)
        owner = np.zeros(len(anchor), np.int64)
        for i, (a, b) in enumerate(zip(first[:-1], first[1:])):
            if b - a >= LENGTH:
                valid[a : b - LENGTH + 1] = True
                owner[a : b - LENGTH + 1] = i
        cut = np.ones(len(anchor), bool)
        cut[1:] = (anchor[1:] != anchor[:-1]) | (valid[1:-1] != valid[:-2]) | (owner[1:] != owner[:-1])
        lo = np.flatnonzero(cut)
        hi = np.append(lo[1:], len(anchor)) - 1
        own = valid[lo]
        lo, hi = lo[own], hi[own]
        p, i = anchor[lo], owner[lo]
        content = mix((sums[hi + LENGTH] - sums[lo]) * _INV[lo] + (hi - lo).astype(np.uint64))
        text, shift = np.array([x[0] for x in parts]), np.array([x[1] for x in parts])
        off = shift[i] - first[i]
        # Least hashes are small numbers: mixed again, they spread evenly.
        found.append((text[i], lo + off, hi - lo + 1, p + off, mix(h[p] ^ np.uint64(0xC2B2AE3D27D4EB4F)), content))
        parts.clear()

    held = 0
    for t, data in enumerate(texts):
        for at in range(0, max(1, len(data) - LENGTH + 1), PIECE):
            piece = data[at : at + PIECE + LENGTH - 1]
            if len(piece) < LENGTH:
                continue
            if held and held + len(piece) > PIECE + LENGTH:
                settle()
                held = 0
            parts.append((t, at, piece))
            held += len(piece)
    settle()
    if not found:
        none = np.zeros(0, np.int64)
        return none, none, none, none, none.astype(np.uint64), none.astype(np.uint64)
    return tuple(np.concatenate(x) for x in zip(*found))


def front_coded(strings: list[bytes]) -> tuple[list[int], list[bytes]]:
    """Of sorted strings the lengths shared with the one before, and the rests."""
    shared, rest, last = [], [], b""
    for s in strings:
        n = common_prefix(last, s, 0)
        shared.append(n)
        rest.append(s[n:])
        last = s
    return shared, rest


def common_prefix(a: bytes, b: bytes, known: int) -> int:
    """Length of the common prefix of ``a`` and ``b``, of which ``known`` bytes are known to agree."""
    n = min(len(a), len(b)) - known
    if n <= 0:
        return known
    x, y = a[known : known + n], b[known : known + n]
    if x == y:
        return known + n
    differ = int.from_bytes(x, "big") ^ int.from_bytes(y, "big")
    return known + n - (differ.bit_length() + 7) // 8


def pack_run(ids, alts, starts, lefts, wins, left_bytes: list[bytes], rights: list[bytes]) -> bytes:
    """A run of sorted suffixes as bytes: its columns, then the front-coded suffixes."""
    shared, rest = front_coded(rights)
    n = np.array([len(ids)], "<u4").tobytes()
    cols = [np.asarray(ids, "<i8"), np.asarray(alts, "<i8"), np.asarray(starts, "<i8"), np.asarray(lefts, "u1"), np.asarray(wins, "u1"), np.asarray(shared, "u1"), np.asarray([len(r) for r in rest], "u1")]
    data = n + b"".join(c.tobytes() for c in cols) + b"".join(left_bytes) + b"".join(rest)
    return np.array([len(data)], "<u4").tobytes() + pa.compress(data, "zstd", asbytes=True)


class Run:
    """A packed run, its suffixes decoded one by one."""

    def __init__(self, packed: bytes):
        data = pa.decompress(packed[4:], int(np.frombuffer(packed, "<u4", 1)[0]), "zstd", asbytes=True)
        n = int(np.frombuffer(data, "<u4", 1)[0])
        at, cols = 4, []
        for kind, width in (("<i8", 8), ("<i8", 8), ("<i8", 8), ("u1", 1), ("u1", 1), ("u1", 1), ("u1", 1)):
            cols.append(np.frombuffer(data, kind, n, at))
            at += n * width
        self.ids, self.alts, self.starts, self.lefts, self.wins, shared, rest = cols
        self.n, self.shared, self.rest = n, shared.tolist(), rest.tolist()
        edge = at + np.concatenate([[0], np.cumsum(self.lefts, dtype=np.int64)])
        self.left = [data[a:b] for a, b in zip(edge[:-1], edge[1:])]
        self.data, self.at, self.next, self.now = data, int(edge[-1]), 0, b""

    def advance(self) -> int | None:
        """Moves to the next suffix; the length it shares with the one before, None at the end."""
        i = self.next
        if i == self.n:
            return None
        n, m = self.shared[i], self.rest[i]
        self.now = self.now[:n] + self.data[self.at : self.at + m]
        self.at += m
        self.next = i + 1
        return n


def merged(runs: list[Run]) -> Iterator[tuple[int, int, int, bytes]]:
    """(run, index within it, prefix shared with the suffix before, suffix) in sorted order, by a loser tree.

    Each waiting suffix keeps the length of the prefix it shares with the last winner it lost to. Of two, the
    one that shares more with the last output is smaller; only at equal lengths are bytes read, from there on.
    """
    k = len(runs)
    size = 1
    while size < k:
        size *= 2
    lcp = [0] * size
    done = [True] * size
    for i, r in enumerate(runs):
        done[i] = r.advance() is None
    loser = [0] * size

    def play(a: int, b: int) -> tuple[int, int]:
        """(winner, loser); the loser's shared length becomes that with the winner."""
        if done[a] or done[b]:
            return (b, a) if done[a] else (a, b)
        if lcp[a] != lcp[b]:
            return (a, b) if lcp[a] > lcp[b] else (b, a)
        x, y = runs[a].now, runs[b].now
        n = common_prefix(x, y, lcp[a])
        if n == len(x) or (n < len(y) and x[n] < y[n]):
            lcp[b] = n
            return a, b
        lcp[a] = n
        return b, a

    winners = list(range(size))
    level = size
    while level > 1:
        nxt = []
        for j in range(0, level, 2):
            w, lost = play(winners[j], winners[j + 1])
            loser[(level + j) // 2] = lost
            nxt.append(w)
        winners, level = nxt, level // 2
    top = winners[0]
    while not done[top]:
        r = runs[top]
        yield top, r.next - 1, lcp[top], r.now
        n = r.advance()
        if n is None:
            done[top] = True
        else:
            lcp[top] = n
        node = (size + top) // 2
        while node:
            top, loser[node] = play(top, loser[node])
            node //= 2


def repeated_spans(runs: list[Run]) -> tuple[np.ndarray, ...]:
    """(id, alt, start, end) of what the segments of one bucket lose: windows equal to an earlier one."""
    which, index, lcp, text = [], [], [], []
    for r, i, n, s in merged(runs):
        which.append(r)
        index.append(i)
        lcp.append(n)
        text.append(s)
    if not which:
        return (np.zeros(0, np.int64),) * 4
    lcp_ = np.array(lcp)
    # A suffix alone within its gram has nothing to be compared with.
    near = lcp_ >= GRAM
    near[:-1] |= near[1:].copy()
    keep = np.flatnonzero(near)
    if not len(keep):
        return (np.zeros(0, np.int64),) * 4
    get = lambda name, kind: np.array([getattr(runs[which[i]], name)[index[i]] for i in keep], kind)
    ids, alts, starts, lefts, wins = get("ids", np.int64), get("alts", np.int64), get("starts", np.int64), get("lefts", np.int64), get("wins", np.int64)
    lcp_ = lcp_[keep]
    most = int(lefts.max())
    before = np.zeros((len(keep), most), np.uint8)  # column l: the byte l + 1 places before the anchor
    for row, i in enumerate(keep):
        x = runs[which[i]].left[index[i]]
        before[row, : len(x)] = np.frombuffer(x, np.uint8)[::-1]
    order = np.lexsort((starts, alts, ids))
    rank = np.empty(len(keep), np.int64)
    rank[order] = np.arange(len(keep))
    low, high = np.full(len(keep), -1), np.full(len(keep), -1)
    hashed = np.zeros(len(keep), np.uint64)
    for l in range(most + 1):
        if l:
            hashed = hashed + _RAND[before[:, l - 1]] * _POW[l]
        sel = np.flatnonzero((lefts >= l) & (lefts - wins + 1 <= l))
        if len(sel) < 2:
            continue
        group = np.cumsum(lcp_ < LENGTH - l)[sel]
        h = hashed[sel]
        by = np.lexsort((rank[sel], h, group))
        same = (group[by][1:] == group[by][:-1]) & (h[by][1:] == h[by][:-1])
        again, first = sel[by[1:][same]], sel[by[:-1][same]]
        # The same window cannot stand twice at one place: equal places are repeated rows.
        twin = (ids[again] == ids[first]) & (alts[again] == alts[first]) & (starts[again] + lefts[again] == starts[first] + lefts[first])
        again = again[~twin & (before[again, :l] == before[first, :l]).all(1)]
        high[again] = np.maximum(high[again], l)
        low[again] = np.where(low[again] < 0, l, low[again])
    hit = np.flatnonzero(high >= 0)
    anchor = starts[hit] + lefts[hit]
    return ids[hit], alts[hit], anchor - high[hit], anchor - low[hit] + LENGTH


def united(a: np.ndarray, b: np.ndarray) -> list[tuple[int, int]]:
    """Maximal runs of the union of the spans a-b."""
    out: list[list[int]] = []
    for x, y in sorted(zip(a.tolist(), b.tolist())):
        if out and x <= out[-1][1]:
            out[-1][1] = max(out[-1][1], y)
        else:
            out.append([x, y])
    return [(x, y) for x, y in out]


def anchor_counts(docs: DataFrame) -> DataFrame:
    """(key, n): anchor hashes that occur twice or more, with the segments that have them; one row a key."""

    def count(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in (part for batch in batches for part in slices(batch, most=FLUSH)):
            texts = [utf8(t) for t in pdf["text"]]
            for lo, hi in chunks(texts, 2 * FLUSH):
                key, n = np.unique(segments(texts[lo:hi])[4], return_counts=True)
                yield pd.DataFrame({"key": key.astype(np.int64), "n": n})
        release()

    return docs.select("text").mapInPandas(count, "key long, n long").groupBy("key").agg(F.sum("n").alias("n")).where(F.col("n") > 1)


def anchor_filter(keys: DataFrame, bits: int) -> np.ndarray:
    """Bitmap of 2 ** bits bits by anchor hash: set for the ``keys``. Its size doesn't depend on the corpus."""
    width = (1 << bits) // SLICES
    place = F.shiftrightunsigned("key", 64 - bits)
    placed = keys.select(F.floor(place / width).cast("int").alias("slice"), (place % width).cast("int").alias("at"))

    def fill(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        own: dict[int, np.ndarray] = {}
        for pdf in batches:
            for s, at in pdf.groupby("slice")["at"]:
                own.setdefault(int(s), np.zeros(width, bool))[at.to_numpy()] = True
        for s, x in own.items():
            yield pd.DataFrame({"slice": [s], "bits": [np.packbits(x).tobytes()]})

    out = np.zeros((1 << bits) // 8, np.uint8)
    for r in placed.repartition(SLICES, "slice").mapInPandas(fill, "slice int, bits binary").collect():
        out[r["slice"] * (width // 8) : (r["slice"] + 1) * (width // 8)] = np.frombuffer(r["bits"], np.uint8)
    return out


def parted(texts: list[bytes], hot: np.ndarray, t, start, win, anchor, key, content):
    """The segments, those of ``hot`` anchors cut in two by how many bytes stand before the anchor, and keyed by what all their windows hold."""
    at = np.searchsorted(hot, key)
    wide = np.flatnonzero(hot[np.minimum(at, len(hot) - 1)] == key) if len(hot) else np.zeros(0, int)
    if not len(wide):
        return t, start, win, anchor, key, content
    out = []
    for i in wide.tolist():
        p, most = int(anchor[i]), int(anchor[i] - start[i])
        least, data = most - int(win[i]) + 1, texts[t[i]]
        for lo, hi, a, b in ((max(least, HALF), most, p - HALF, p + GRAM), (least, min(most, HALF - 1), p, p + GRAM + HALF)):
            if lo <= hi:
                code = [int.from_bytes(hashlib.blake2b(x, digest_size=8).digest(), "little") for x in (data[a:b], data[p - hi : p - lo + LENGTH])]
                out.append((t[i], p - hi, hi - lo + 1, p, code[0], code[1]))
    rest = np.ones(len(t), bool)
    rest[wide] = False
    new = list(zip(*out))
    return tuple(np.concatenate([x[rest], np.array(y, x.dtype)]) for x, y in zip((t, start, win, anchor, key, content), new))


def sorted_runs(docs: DataFrame, filter_: np.ndarray, bits: int, buckets: int, hot: np.ndarray) -> DataFrame:
    """Rows (bucket, run) of front-coded suffixes, and rows (id, alt, a, b) without a run: spans settled within a task, dealt to any bucket."""
    shared = docs.sparkSession.sparkContext.broadcast((filter_, hot))

    def make(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        seen, wide = shared.value
        for pdf in (part for batch in batches for part in slices(batch, most=FLUSH)):
            texts = [utf8(t) for t in pdf["text"]]
            ids, alts = pdf["id"].to_numpy(np.int64), pdf["alt"].to_numpy(np.int64)
            for lo, hi in chunks(texts, 2 * FLUSH):
                t, start, win, anchor, key, content = segments(texts[lo:hi])
                place = (key >> np.uint64(64 - bits)).astype(np.int64)
                own = np.flatnonzero((seen[place >> 3] >> (7 - (place & 7)).astype(np.uint8)) & 1)
                t, start, win, anchor, key, content = (x[own] for x in (t, start, win, anchor, key, content))
                if not len(t):
                    continue
                base = texts[lo:hi]
                t, start, win, anchor, key, content = parted(base, wide, t, start, win, anchor, key, content)
                id_, alt = ids[lo:hi][t], alts[lo:hi][t]
                left = anchor - start
                by = np.lexsort((start, alt, id_, left, win, content, key))
                same = np.zeros(len(by), bool)
                a, b = by[1:], by[:-1]
                same[1:] = (key[a] == key[b]) & (content[a] == content[b]) & (win[a] == win[b]) & (left[a] == left[b])
                for k in np.flatnonzero(same).tolist():  # equal hashes, equal bytes?
                    x, y, n = by[k], by[k - 1], int(win[by[k]]) - 1 + LENGTH
                    same[k] = base[t[x]][start[x] : start[x] + n] == base[t[y]][start[y] : start[y] + n]
                twin = np.zeros(len(by), bool)
                twin[1:] = same[1:] & (id_[a] == id_[b]) & (alt[a] == alt[b]) & (start[a] == start[b])
                later = by[same & ~twin]
                if len(later):
                    rows = []
                    order = later[np.lexsort((start[later], t[later]))]
                    cut = np.flatnonzero(t[order][1:] != t[order][:-1]) + 1
                    for part in np.split(order, cut):
                        rows += [(int(id_[part[0]]), int(alt[part[0]]), x, y) for x, y in united(start[part], start[part] + win[part] - 1 + LENGTH)]
                    yield pd.DataFrame({"bucket": np.array([abs(hash((r[0], r[2]))) % buckets for r in rows], np.int32), "run": None, "id": [r[0] for r in rows], "alt": [r[1] for r in rows], "a": [r[2] for r in rows], "b": [r[3] for r in rows]})
                one = by[~same]
                bucket = ((mix(key[one]) >> np.uint64(33)) % np.uint64(buckets)).astype(np.int64)
                one, bucket = one[np.argsort(bucket, kind="stable")], np.sort(bucket, kind="stable")
                cut = np.flatnonzero(bucket[1:] != bucket[:-1]) + 1
                names, runs = [], []
                for part, name in zip(np.split(one, cut), bucket[np.concatenate([[0], cut]).astype(int)] if len(one) else []):
                    end = start[part] + win[part] - 1 + LENGTH
                    rights = [base[x][p:e] for x, p, e in zip(t[part].tolist(), anchor[part].tolist(), end.tolist())]
                    seq = sorted(range(len(part)), key=rights.__getitem__)
                    part = part[seq]
                    lefts = [base[x][s:p] for x, s, p in zip(t[part].tolist(), start[part].tolist(), anchor[part].tolist())]
                    names.append(int(name))
                    runs.append(pack_run(id_[part], alt[part], start[part], left[part], win[part], lefts, [rights[i] for i in seq]))
                yield pd.DataFrame({"bucket": np.array(names, np.int32), "run": runs, "id": np.int64(0), "alt": np.int64(0), "a": np.int64(0), "b": np.int64(0)})

    return docs.select("id", "alt", "text").mapInPandas(make, "bucket int, run binary, id long, alt long, a long, b long")


def merged_spans(runs: DataFrame) -> DataFrame:
    """Spans (id, alt, a, b) found by merging the runs of each bucket."""

    def merge(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        name, held = None, []

        def settle() -> Iterator[pd.DataFrame]:
            i, alt, a, b = repeated_spans([Run(x) for x in held])
            if len(i):
                yield pd.DataFrame({"id": i, "alt": alt, "a": a, "b": b})

        for pdf in batches:
            local = pdf["run"].isna()
            if local.any():
                yield pdf.loc[local, ["id", "alt", "a", "b"]]
                pdf = pdf[~local]
            for bucket, run in zip(pdf["bucket"].tolist(), pdf["run"]):
                if bucket != name and held:
                    yield from settle()
                    held = []
                name = bucket
                held.append(run)
        if held:
            yield from settle()
        release()

    return runs.repartition("bucket").sortWithinPartitions("bucket").mapInPandas(merge, "id long, alt long, a long, b long")


def filter_bits(total: int) -> int:
    """About 16 bits of filter for each segment, up to the fixed bound."""
    return min(FILTER_BITS, max(16, int(np.ceil(np.log2(max(1, total) * 16 / 38)))))


def repeated(docs: DataFrame, bits: int | None = None, bucket_bytes: int = 2 << 20) -> DataFrame:
    """doc_id, text, found: the spans (a, b) that each row of ``docs`` (doc_id, text) loses, not yet united; null for none."""
    own = bounded(docs).select("doc_id", "text", F.coalesce("doc_id", F.lit(_NULL_ID)).alias("id"))
    again = written(own.groupBy("id").agg(F.count("*").alias("n")).where(F.col("n") > 1).select("id", F.lit(True).alias("again")), "repeated-ids")
    placed = own.join(again, "id", "left").withColumn("alt", F.when(F.col("again"), F.xxhash64("text")).otherwise(F.lit(0).cast("long"))).select("doc_id", "text", "id", "alt")
    total = own.agg(F.sum(F.octet_length("text").cast("long"))).first()[0] or 0
    bits = bits or filter_bits(total)
    keys = written(anchor_counts(own), "anchors")
    filter_ = anchor_filter(keys, bits)
    wide = max(HOT, (keys.agg(F.sum("n")).first()[0] or 0) >> HOT_BITS)
    hot = np.sort(np.array([r["key"] for r in keys.where(F.col("n") > wide).collect()], np.int64).astype(np.uint64))  # 2 ** HOT_BITS at most
    spans = merged_spans(sorted_runs(placed, filter_, bits, max(1, -(-total // bucket_bytes)), hot))
    by_doc = spans.groupBy("id", "alt").agg(F.collect_list("a").alias("a"), F.collect_list("b").alias("b"))
    return placed.join(by_doc, ["id", "alt"], "left").select("doc_id", "text", "a", "b")


def _cut(text: str | None, a, b) -> tuple[int, list[tuple[int, int]], bytes]:
    """Bytes of the text, its removed runs, and what remains."""
    data = utf8(text)
    gone = united(np.asarray(a, np.int64), np.asarray(b, np.int64)) if a is not None else []
    at, parts = 0, []
    for x, y in gone:
        parts.append(data[at:x])
        at = y
    return len(data), gone, b"".join([*parts, data[at:]])


def remove_repeats(docs: DataFrame, bits: int | None = None) -> DataFrame:
    """doc_id, n_bytes, spans (removed runs of bytes, from and to) and kept (the remaining bytes) of every row of ``docs``."""

    def cut(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            rows = [(d, *_cut(*x)) for d, *x in zip(pdf["doc_id"].astype("Int64").array, pdf["text"], pdf["a"], pdf["b"])]
            yield pd.DataFrame({"doc_id": pd.array([r[0] for r in rows], "Int64"), "n_bytes": [r[1] for r in rows], "spans": [[{"a": x, "b": y} for x, y in r[2]] for r in rows], "kept": [r[3] for r in rows]})

    return repeated(docs, bits).mapInPandas(cut, "doc_id long, n_bytes long, spans array<struct<a:long,b:long>>, kept binary")


def removal_digests(docs: DataFrame, bits: int | None = None) -> DataFrame:
    """As ``remove_repeats``, but only sizes and the hash of what remains leave the tasks."""

    def cut(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            rows = []
            for d, *x in zip(pdf["doc_id"].astype("Int64").array, pdf["text"], pdf["a"], pdf["b"]):
                n, gone, kept = _cut(*x)
                rows.append((d, n, n - len(kept), len(gone), digest(kept)))
            out = pd.DataFrame(rows, columns=["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"])
            yield out.assign(doc_id=out["doc_id"].astype("Int64"))

    return repeated(docs, bits).mapInPandas(cut, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return removal_digests(table(spark, sf_dir, "documents"))


def brute_force(texts: dict[int, bytes]) -> dict[int, bytes]:
    """Remaining bytes by a dictionary of all windows: the plain definition, for tests."""
    seen: set[bytes] = set()
    out = {}
    for i in sorted(texts):
        data = texts[i]
        gone = np.zeros(len(data), bool)
        for s in range(len(data) - LENGTH + 1):
            w = data[s : s + LENGTH]
            if w in seen:
                gone[s : s + LENGTH] = True
            seen.add(w)
        out[i] = np.frombuffer(data, np.uint8)[~gone].tobytes()
    return out


def digest(data: bytes) -> str:
    return hashlib.sha256(data).hexdigest()
