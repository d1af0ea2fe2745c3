"""Vectorised words of many texts: numpy passes over the joined bytes, no loop over words."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

_SPACE = np.zeros(256, bool)
_SPACE[[0x20, *range(0x09, 0x0E)]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[ord("A") : ord("Z") + 1] += 32
_RAND = np.random.default_rng(20240611).integers(1, 2**63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_POW = np.cumprod(np.full(4096, 0x9E3779B97F4A7C15, np.uint64))
CHUNK = 1 << 20


def mix(h: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser: spreads every input bit over the whole word."""
    h = h ^ (h >> np.uint64(33))
    h = h * np.uint64(0xFF51AFD7ED558CCD)
    h = h ^ (h >> np.uint64(33))
    h = h * np.uint64(0xC4CEB9FE1A85EC53)
    return h ^ (h >> np.uint64(33))


def utf8(text: str | None) -> bytes:
    return b"" if text is None else text.encode("utf-8", "surrogatepass")


@dataclass
class Words:
    """``first[i]:first[i + 1]`` are the words of text ``i``; ``start`` and ``end`` are byte offsets in ``data``."""

    data: bytes
    hash: np.ndarray
    start: np.ndarray
    end: np.ndarray
    first: np.ndarray
    base: np.ndarray


def words(texts: list[bytes]) -> Words:
    """Words are runs of bytes other than space and 09-0D; A-Z are lower-cased before hashing."""
    data = b"\n".join(texts) + b"\n"
    a = np.frombuffer(data, np.uint8)
    w = ~_SPACE[a]
    change = np.flatnonzero(w[1:] != w[:-1]) + 1
    if w.size and w[0]:
        change = np.concatenate([[0], change])
    start, end = change[0::2], change[1::2]
    base = np.zeros(len(texts) + 1, np.int64)
    np.cumsum([len(t) + 1 for t in texts], out=base[1:])
    first = np.searchsorted(start, base)
    if not len(start):
        return Words(data, np.zeros(0, np.uint64), start, end, first, base)
    size = end - start
    at = np.concatenate([[0], np.cumsum(size)[:-1]])
    off = np.arange(int(size.sum())) - np.repeat(at, size)
    value = _RAND[_LOWER[a[w]]]
    if int(size.max()) > len(_POW):
        value = value * mix((off // len(_POW)).astype(np.uint64) * np.uint64(2) + np.uint64(1))
        off = off % len(_POW)
    return Words(data, mix(np.add.reduceat(value * _POW[off], at) + size.astype(np.uint64)), start, end, first, base)


def chunks(texts: list[bytes], most: int = CHUNK):
    """Ranges of ``texts`` of about ``most`` bytes each; one long text stands alone."""
    at, held = 0, 0
    for i, t in enumerate(texts):
        if held and held + len(t) > most:
            yield at, i
            at, held = i, 0
        held += len(t)
    if at < len(texts):
        yield at, len(texts)


_STEP = np.cumprod(np.full(8, 0xD6E8FEB86659FD93, np.uint64))


def shingle_sets(texts: list[bytes], k: int = 5):
    """For each text its sorted distinct 64-bit shingle hashes: ``k`` words, or all words if there are fewer."""
    out: list[np.ndarray] = []
    for lo, hi in chunks(texts):
        w = words(texts[lo:hi])
        n = len(w.hash)
        grams = np.zeros(max(0, n - k + 1), np.uint64)
        for j in range(k):
            grams += w.hash[j : j + len(grams)] * _STEP[j]
        grams = mix(grams)
        for i in range(hi - lo):
            a, b = int(w.first[i]), int(w.first[i + 1])
            if b - a >= k:
                g = np.sort(grams[a : b - k + 1])
                keep = np.empty(len(g), bool)
                keep[0] = True
                np.not_equal(g[1:], g[:-1], out=keep[1:])
                out.append(g[keep])
            elif b > a:
                out.append(mix(np.array([(w.hash[a:b] * _STEP[: b - a]).sum() + np.uint64(b - a)], np.uint64)))
            else:
                out.append(np.zeros(0, np.uint64))
    return out
