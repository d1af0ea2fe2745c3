"""Searches from some hubs at a time on arcs held as arrays: the part of ``index.searched`` and its kin that runs in the workers."""

from __future__ import annotations

import numpy as np

#: Hubs that a search takes together at most (one bit each), most steps of a search entered at a time.
TOGETHER, STEPS = 64, 1 << 20


class Arcs:
    """Arcs leave ``v`` for the ascending ``dst[first[v]:first[v + 1]]``; ``both``: each is there both ways. Keeps arrays between searches."""

    def __init__(self, first: np.ndarray, dst: np.ndarray, both: bool = False):
        self.first, self.dst, self.both, self.n = first, dst, both, len(first) - 1
        self.size = np.diff(first)
        self.has = np.flatnonzero(self.size)
        self.key = np.repeat(np.arange(self.n, dtype=np.int64), self.size) * self.n + dst
        self.most = int(self.size.max(initial=1))
        self.hold = self.near = np.zeros(0, np.int64)

    def steps(self, lo: np.ndarray, many: np.ndarray) -> np.ndarray:
        """The heads of ``many`` arcs from each place of ``lo``."""
        return self.dst[np.arange(int(many.sum())) + np.repeat(lo - (np.cumsum(many) - many), many)]

    def onward(self, live: np.ndarray, bits: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(vertices, bits): the bits that arcs carry from the vertices ``live``, outside of which ``bits`` is 0."""
        many = self.size[live]
        if self.both and int(many.sum()) * 4 >= len(self.dst):
            # Arcs are there both ways, so a vertex gathers the bits of the heads of its own.
            near = np.bitwise_or.reduceat(bits[self.dst], self.first[self.has])
            at = np.flatnonzero(near)
            return self.has[at], near[at]
        if len(self.near) != self.n:
            self.near = np.zeros(self.n, np.uint64)
        to = self.steps(self.first[live], many)
        np.bitwise_or.at(self.near, to, np.repeat(bits[live], many))
        to = np.flatnonzero(self.near) if len(to) * 8 > self.n else np.unique(to)
        got = self.near[to]
        self.near[to] = 0
        return to, got


def _bits(hubs: np.ndarray) -> np.ndarray:
    return np.uint64(1) << np.arange(len(hubs), dtype=np.uint64)


def _frontiers(arcs: Arcs, hubs: np.ndarray, max_levels: int | None):
    """For each distance d from 0: (vertices, array of all vertices' bits: the hubs at distance d). The array is used again."""
    seen = np.zeros(arcs.n, np.uint64)
    np.bitwise_or.at(seen, hubs, _bits(hubs))
    live, level, new = np.unique(hubs), 0, seen.copy()
    while len(live):
        yield live, new
        level += 1
        if max_levels is not None and level > max_levels:
            return
        to, near = arcs.onward(live, new)
        near &= ~seen[to]
        own = np.flatnonzero(near)
        new[live] = 0
        live = to[own]
        new[live] = near[own]
        seen[live] |= near[own]


def levels(arcs: Arcs, hubs: np.ndarray, max_levels: int | None = None, full: bool = False, below: bool = True, together: int = STEPS):
    """For each distance d from 0: (d, owner, place of the hub in ``hubs``, paths[, all paths]), in order of owner and place.

    At most TOGETHER hubs. Two searches run level by level: one over all vertices, a bit for each hub, tells true
    distances; the other never enters a vertex ranked above its hub and goes on only where its distance is the true one,
    so what it reaches are label rows with their counts. ``full``: counts over all shortest paths are taken along. Not
    ``below``: those alone, of every pair that is joined. ``together``: most steps entered at a time.
    """
    n, k = arcs.n, len(hubs)
    at = np.argsort(hubs, kind="stable")
    now = (hubs[at], at, np.ones(k, np.int64))
    whole = now

    def onward(owner, place, paths, fresh, restricted):
        """One arc further, to where ``fresh`` has the hub's bit; summed by vertex and hub."""
        lo = np.searchsorted(arcs.key, owner * n + hubs[place], "right") if restricted else arcs.first[owner]
        many = arcs.first[owner + 1] - lo
        if len(paths) and int(paths.max()) > ((1 << 63) - 1) // arcs.most:
            raise ArithmeticError("path counts pass 64 bits; take another count_type")
        ends, cells, counts, a = np.cumsum(many), [], [], 0
        while a < len(owner):
            b = max(a + 1, int(np.searchsorted(ends, (ends[a - 1] if a else 0) + together, "right")))
            to = arcs.steps(lo[a:b], many[a:b]).astype(np.int64)
            hub = np.repeat(place[a:b], many[a:b])
            good = np.flatnonzero((fresh[to] >> hub.astype(np.uint64)) & np.uint64(1))
            cells.append(to[good] * k + hub[good])
            counts.append(np.repeat(paths[a:b], many[a:b])[good])
            a = b
        cell = np.concatenate(cells) if cells else np.zeros(0, np.int64)
        count = np.concatenate(counts) if counts else np.zeros(0, np.int64)
        if len(cell) * 16 < n * k:
            own, back = np.unique(cell, return_inverse=True)
            total = np.zeros(len(own), np.int64)
            np.add.at(total, back, count)
        else:
            arcs.hold = arcs.hold if len(arcs.hold) == n * k else np.zeros(n * k, np.int64)
            np.add.at(arcs.hold, cell, count)
            own = np.flatnonzero(arcs.hold)
            total = arcs.hold[own]
            arcs.hold[own] = 0
        return own // k, own % k, total

    for level, (_, new) in enumerate(_frontiers(arcs, hubs, max_levels)):
        if level:
            if full or not below:
                whole = onward(*whole, new, False)
            now = onward(*now, new, True) if below else whole
            if not len(now[0]):
                return
        if below and full:
            yield level, *now, whole[2][np.searchsorted(whole[0] * k + whole[1], now[0] * k + now[1])]
        else:
            yield level, *now


def reached(arcs: Arcs, hubs: np.ndarray, max_levels: int | None = None, alone: bool = False):
    """For each distance d from 0: (vertices, bits): the hubs, which must ascend, of whose label rows at d a vertex is the owner; no counts.

    ``alone``: only the rows whose hub is ranked above all else on every shortest path of the pair: those that distances need.
    """
    bits = np.zeros(len(hubs) + 1, np.uint64)
    bits[1:] = np.cumsum(_bits(hubs), dtype=np.uint64)
    held, last = np.zeros(arcs.n, np.uint64), None
    for level, (live, new) in enumerate(_frontiers(arcs, hubs, max_levels)):
        now = new[live]
        if not level:
            own = now if not alone else np.zeros(len(live), np.uint64)
        else:
            to, near = arcs.onward(last, held)
            own = np.zeros(len(live), np.uint64)
            at = np.searchsorted(live, to)
            good = np.flatnonzero(at < len(live))
            good = good[live[at[good]] == to[good]]
            own[at[good]] = near[good]
            above = bits[np.searchsorted(hubs, live)]  # the hubs ranked above a vertex
            # Held are the bits of whole searches, or with ``alone`` those that met a vertex ranked above their hub.
            own = now & (own | ~above) if alone else now & own & above
            held[last] = 0
        got = now & ~own if alone else own
        if not alone and not got.any():
            return
        yield live, got
        held[live] = own
        last = live if alone else live[own != 0]
        if alone and not got.any():
            return


def spread(live: np.ndarray, got: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(owner, place) of each bit, in order."""
    row, place = np.nonzero((got[:, None] >> np.arange(k, dtype=np.uint64)) & np.uint64(1))
    return live[row], place


def hubs_of(arcs: Arcs, owner: int) -> np.ndarray:
    """The hubs of an owner's label rows: vertices ranked above all else on some shortest path to it. Arcs both ways.

    The best path to a vertex is the one whose highest-ranked vertex before it is lowest.
    """
    best = np.full(arcs.n, -1, np.int64)
    best[owner] = arcs.n
    found, before = [], None
    for live, new in _frontiers(arcs, np.array([owner]), None):
        if before is not None:
            many = arcs.size[before]
            to = arcs.steps(arcs.first[before], many)
            ahead = np.flatnonzero(new[to])
            np.maximum.at(best, to[ahead], np.repeat(np.minimum(best[before], before), many)[ahead])
        found.append(live[best[live] > live])
        before = live.copy()
    return np.concatenate(found)


def differences(old: Arcs, new: Arcs, hubs: np.ndarray, allowed, keys: np.ndarray, most: int = 1 << 20):
    """(owner, place, old dist, old paths, dist, paths) of rows that differ, or whose key hub * n + owner is among the ascending ``keys``; -1 for none.

    ``allowed``: tells of owners and places which rows count. None if several hubs have more than ``most`` rows: take fewer.
    """
    n, k = old.n, len(hubs)

    def rows(arcs):
        out, total = [[], [], []], 0
        for dist, owner, place, paths in levels(arcs, hubs):
            own = np.flatnonzero(allowed(owner, place))
            for x, y in zip(out, ((owner * k + place)[own], np.full(len(own), dist, np.int32), paths[own])):
                x.append(y)
            total += len(own)
            if total > most and k > 1:
                return None
        cell, dist, paths = map(np.concatenate, out)
        order = np.argsort(cell)
        return cell[order], dist[order], paths[order]

    if (a := rows(old)) is None or (b := rows(new)) is None:
        return None
    place = np.argsort(hubs)
    more = [keys[slice(*np.searchsorted(keys, [hubs[p] * n, (hubs[p] + 1) * n]))] % n * k + p for p in place] if len(keys) else []
    cells = np.union1d(np.union1d(a[0], b[0]), np.concatenate(more)) if len(more) else np.union1d(a[0], b[0])
    out = []
    for cell, dist, paths in (a, b):
        d, p = np.full(len(cells), -1, np.int32), np.full(len(cells), -1, np.int64)
        at = np.searchsorted(cells, cell)
        d[at], p[at] = dist, paths
        out += [d, p]
    keep = (out[0] != out[2]) | (out[1] != out[3])
    if len(more):
        keep |= np.isin(cells, np.concatenate(more)) & allowed(cells // k, cells % k)
    own = np.flatnonzero(keep)
    return cells[own] // k, cells[own] % k, *[x[own] for x in out]


def rounds(old: Arcs, new: Arcs, hubs: np.ndarray, as_hub: np.ndarray, as_owner: np.ndarray):
    """(dist, n, seeds, settled), a row a distance: keys that a deletion's rounds would have as candidates, those among them that are seeds, and those that they settle.

    In question are the rows of hubs and owners of one zone (``as_hub``, ``as_owner``; 0 for none). Seeds are one arc of ``new`` further
    than rows of ``old`` not in question, the others one arc further than rows in question that ``new`` has.
    """
    k, got = len(hubs), []
    zone = np.zeros((3, new.n), bool)  # vertices next to an owner of the zone
    for z in (1, 2):
        zone[z, np.repeat(np.arange(new.n), new.size)[as_owner[new.dst] == z]] = True
    asked = lambda owner, place: as_owner[owner] == as_hub[hubs[place]]
    for kind, arcs in ((2, old), (1, new)):
        for dist, owner, place, _ in levels(arcs, hubs):
            inside = asked(owner, place)
            if kind == 1:
                own = np.flatnonzero(inside)
                got.append((np.full(len(own), dist, np.int64), owner[own] * k + place[own], np.full(len(own), 4)))
            own = np.flatnonzero((inside if kind == 1 else ~inside) & zone[as_hub[hubs[place]], owner])
            owner, place = owner[own], place[own]
            lo = np.searchsorted(new.key, owner * new.n + hubs[place], "right")
            many = new.first[owner + 1] - lo
            to, hub = new.steps(lo, many).astype(np.int64), np.repeat(place, many)
            own = np.flatnonzero(asked(to, hub))
            got.append((np.full(len(own), dist + 1, np.int64), to[own] * k + hub[own], np.full(len(own), kind)))
    dist, cell, kind = map(np.concatenate, zip(*got))
    key, back = np.unique(dist * (new.n * k) + cell, return_inverse=True)
    flags = np.zeros((3, len(key)), bool)
    for i, x in enumerate((1, 2, 4)):
        flags[i, back[kind == x]] = True
    level = (key // (new.n * k)).astype(np.int32)
    most = int(level.max(initial=-1)) + 1
    count = lambda rows: np.bincount(level[rows], minlength=most)
    n = count(np.ones(len(key), bool))
    own = np.flatnonzero(n)
    return own.astype(np.int32), n[own], count(flags[1])[own], count(flags[2])[own]


def in_order(arcs: Arcs) -> np.ndarray:
    """Vertices by component, and there by distance from its top vertex, so that neighbours come together. Arcs both ways."""
    whose = np.arange(arcs.n)
    while len(arcs.has):
        best = whose.copy()
        best[arcs.has] = np.minimum(best[arcs.has], np.minimum.reduceat(whose[arcs.dst], arcs.first[arcs.has]))
        best = best[best]
        if (best == whose).all():
            break
        whose = best
    far, live, level = np.full(arcs.n, -1, np.int64), np.flatnonzero(whose == np.arange(arcs.n)), 0
    while len(live):
        far[live] = level
        to = np.unique(arcs.steps(arcs.first[live], arcs.size[live]))
        live, level = to[far[to] < 0], level + 1
    return np.lexsort((far, whose))
