"""Plain Python counterparts: searches and the index by its definition, for small graphs."""

from __future__ import annotations

import heapq
from collections import defaultdict


def arcs_of(edges, directed=False):
    out = defaultdict(dict)
    for e in edges:
        u, v, w = (*e, 1)[:3]
        out[u][v] = w
        if not directed:
            out[v][u] = w
    return out


def counts(arcs, s, allowed=lambda v: True):
    """vertex -> (distance, number of shortest paths) from ``s`` over allowed vertices."""
    best, heap = {s: [0, 1]}, [(0, s)]
    done = set()
    while heap:
        d, x = heapq.heappop(heap)
        if x in done:
            continue
        done.add(x)
        for y, w in arcs[x].items():
            if not allowed(y):
                continue
            if y not in best or d + w < best[y][0]:
                best[y] = [d + w, best[x][1]]
                heapq.heappush(heap, (d + w, y))
            elif d + w == best[y][0]:
                best[y][1] += best[x][1]
    return {v: tuple(x) for v, x in best.items()}


def pairs(edges, vertices, directed=False):
    arcs = arcs_of(edges, directed)
    return {(s, t): x for s in vertices for t, x in counts(arcs, s).items()}


def index(edges, rank, directed=False):
    """{(side, owner rank, hub rank): (dist, paths)} by definition."""
    arcs = arcs_of(edges, directed)
    sides = {"u": arcs}
    if directed:
        sides = {"in": arcs, "out": arcs_of([(e[1], e[0], *e[2:]) for e in edges], True)}
    out = {}
    for side, a in sides.items():
        for h in rank:
            true, own = counts(a, h), counts(a, h, lambda v: rank[v] > rank[h])
            for v, (d, c) in own.items():
                if true[v][0] == d:
                    out[side, rank[v], rank[h]] = (d, c)
    return out


EX = [(0, 1), (0, 2), (1, 2), (0, 3), (2, 3), (1, 5), (2, 5), (4, 5), (1, 6), (3, 7), (4, 7), (0, 8), (3, 8), (4, 9), (6, 10), (9, 10), (0, 11)]
TRAP = [(2, 3), (3, 4), (4, 5), (0, 2), (1, 2), (1, 6), (6, 7), (5, 7)]
