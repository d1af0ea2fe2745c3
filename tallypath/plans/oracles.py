"""DuckDB SQL for graphs, searches and the index by its definition: recursive counting searches, keyed by pair."""

from __future__ import annotations

from ..sources.graphs import SQL_EDGES

SQL_EDGES["UW"] = f"SELECT u, v, CAST(1 + (u + v) % 3 AS BIGINT) AS w FROM ({SQL_EDGES['U']})"


def _search(name: str, arcs: str, guard: str = "") -> str:
    return f"""{name}(s, t, d, c) USING KEY (s, t) AS (SELECT rank, rank, 0, CAST(1 AS BIGINT) FROM rk UNION
      SELECT x.s, a.dst, x.d + 1, CAST(sum(x.c) AS BIGINT) FROM {name} x JOIN {arcs} a ON a.src = x.t {guard}
      LEFT JOIN recurring.{name} r ON r.s = x.s AND r.t = a.dst WHERE r.s IS NULL GROUP BY x.s, a.dst, x.d)"""


def ctes(name: str, added: str | None = None, removed: str | None = None, p: str = "", natural: bool = False) -> str:
    """CTEs of one state of a graph, their names prefixed by ``p``: ranks (of the unchanged graph) ``rk``, arcs, all pairs
    ``p`` (s, t, d, c), restricted ``q``, and the index ``idx`` (side, owner, hub, dist, paths), all in ranks; ``w`` is allowed.
    """
    directed, weighted = name == "UD", name in ("PW", "UW")
    base = f"SELECT u, v, {'w' if weighted else 'CAST(1 AS BIGINT) AS w'} FROM ({SQL_EDGES[name]})"
    keep = f"WHERE NOT EXISTS (SELECT 1 FROM ({removed}) z WHERE z.u = e0.u AND z.v = e0.v)" if removed else ""
    more = f"UNION ALL SELECT u, v, {'w' if weighted else '1'} FROM ({added})" if added else ""
    order = "u" if natural else "count(*) DESC, u"
    out = [
        f"{p}e0 AS ({base})",
        f"{p}a0 AS (SELECT u, v FROM {p}e0 UNION ALL SELECT v, u FROM {p}e0)",
        f"{p}rk AS (SELECT u AS vertex, row_number() OVER (ORDER BY {order}) AS rank FROM {p}a0 GROUP BY u)",
        f"{p}e AS (SELECT u, v, w FROM {p}e0 AS e0 {keep} {more})",
        f"{p}f AS (SELECT x.rank AS src, y.rank AS dst, w FROM {p}e JOIN {p}rk x ON x.vertex = u JOIN {p}rk y ON y.vertex = v)",
    ]
    back = f"SELECT dst AS src, src AS dst, w FROM {p}f"
    out.append(f"{p}w1 AS (SELECT src, dst, w FROM {p}f)" if directed else f"{p}w1 AS (SELECT src, dst, w FROM {p}f UNION ALL {back})")
    if weighted:  # unit steps over private vertices with negative numbers
        step = "-((src * 100000 + dst) * 10 + k)"
        out.append(f"""{p}arcs AS (SELECT CASE WHEN k = 0 THEN src ELSE {step} END AS src, CASE WHEN k = w - 1 THEN dst ELSE -((src * 100000 + dst) * 10 + k + 1) END AS dst
          FROM {p}w1, LATERAL (SELECT unnest(range(w)) AS k))""")
    else:
        out.append(f"{p}arcs AS (SELECT src, dst FROM {p}w1)")
    guard = "AND (a.dst < 0 OR a.dst > x.s)"
    fix = lambda s: s.replace(" rk ", f" {p}rk ")
    out.append(fix(_search(f"{p}p", f"{p}arcs")))
    out.append(fix(_search(f"{p}q", f"{p}arcs", guard)))
    if directed:
        out.append(f"{p}barcs AS (SELECT dst AS src, src AS dst FROM {p}arcs)")
        out.append(fix(_search(f"{p}qb", f"{p}barcs", guard)))
        out.append(f"""{p}idx AS (SELECT 'in' AS side, q.t AS owner, q.s AS hub, q.d AS dist, q.c AS paths FROM {p}q q JOIN {p}p p ON p.s = q.s AND p.t = q.t AND p.d = q.d
          UNION ALL SELECT 'out', q.t, q.s, q.d, q.c FROM {p}qb q JOIN {p}p p ON p.s = q.t AND p.t = q.s AND p.d = q.d)""")
    else:
        out.append(f"""{p}idx AS (SELECT 'u' AS side, q.t AS owner, q.s AS hub, q.d AS dist, q.c AS paths FROM {p}q q
          JOIN {p}p p ON p.s = q.s AND p.t = q.t AND p.d = q.d WHERE q.t > 0)""")
    return ", ".join(out)


def index_sql(name: str, **changes) -> str:
    return f"""WITH RECURSIVE {ctes(name, **changes)}
    SELECT '{name}' AS graph, side, o.vertex AS owner, h.vertex AS hub, CAST(dist AS INTEGER) AS dist, paths FROM idx JOIN rk o ON o.rank = owner JOIN rk h ON h.rank = hub"""


def pairs_sql(name: str, where: str = "true", **changes) -> str:
    """(s, t, dist, paths) of the vertex pairs that satisfy ``where`` (over s, t)."""
    return f"""WITH RECURSIVE {ctes(name, **changes)},
    pr AS (SELECT a.vertex AS s, b.vertex AS t, a.rank AS rs, b.rank AS rt FROM rk a, rk b)
    SELECT pr.s, pr.t, CAST(p.d AS INTEGER) AS dist, coalesce(p.c, 0) AS paths FROM pr LEFT JOIN p ON p.s = rs AND p.t = rt WHERE {where.replace('{s}', 'pr.s').replace('{t}', 'pr.t')}"""


def changes_sql(name: str, added: str | None = None, removed: str | None = None, natural: bool = False) -> str:
    """Operations that lead from one definition index to the next."""
    return f"""WITH RECURSIVE {ctes(name, natural=natural)}, {ctes(name, added, removed, 'n', natural)}
    SELECT o.vertex AS owner, h.vertex AS hub, CAST(i.dist AS INTEGER) AS old_dist, i.paths AS old_paths, CAST(n.dist AS INTEGER) AS dist, n.paths AS paths,
      CASE WHEN n.dist IS NULL THEN 'remove' WHEN i.dist IS NULL THEN 'insert' WHEN i.dist <> n.dist THEN 'renew_dist' ELSE 'renew_count' END AS op
    FROM idx i FULL JOIN nidx n ON i.side = n.side AND i.owner = n.owner AND i.hub = n.hub
    JOIN rk o ON o.rank = coalesce(i.owner, n.owner) JOIN rk h ON h.rank = coalesce(i.hub, n.hub)
    WHERE i.dist IS DISTINCT FROM n.dist OR i.paths IS DISTINCT FROM n.paths"""


KEY = "(u * 7919 + v * 104729) % 1000003"


def first_deletes(name: str, n: int) -> str:
    w = ", w" if name in ("PW", "UW") else ""
    return f"SELECT u, v{w} FROM ({SQL_EDGES[name]}) ORDER BY {KEY}, u, v LIMIT {n}"


def first_inserts(name: str, n: int) -> str:
    """Succession pairs of ``signup`` events that aren't edges, both ends known."""
    directed = name == "UD"
    ends = "a AS u, b AS v" if directed else "least(a, b) AS u, greatest(a, b) AS v"
    w = ", CAST(1 + (u + v) % 3 AS BIGINT) AS w" if name == "UW" else ""
    return f"""SELECT u, v{w} FROM (SELECT DISTINCT {ends} FROM (SELECT user_id AS a, lead(user_id) OVER (ORDER BY ts, event_id) AS b
      FROM events WHERE event_type = 'signup') WHERE b IS NOT NULL AND a <> b) c
      WHERE NOT EXISTS (SELECT 1 FROM ({SQL_EDGES[name]}) e WHERE e.u = c.u AND e.v = c.v)
      AND u IN (SELECT u FROM ({SQL_EDGES[name]}) UNION SELECT v FROM ({SQL_EDGES[name]})) AND v IN (SELECT u FROM ({SQL_EDGES[name]}) UNION SELECT v FROM ({SQL_EDGES[name]}))
      ORDER BY {KEY}, u, v LIMIT {n}"""
