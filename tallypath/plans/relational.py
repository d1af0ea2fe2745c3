"""The relational operators around the methods, each as a query with its DuckDB counterpart."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions import codec
from ..operators import delete, graph, index, insert, query
from ..sources import graphs
from . import oracles as o
from .workloads import ORACLES, QUERIES, _deleted, derived, every_pair, first_deletes, first_inserts, indexed, indexed_part, load

U = o.SQL_EDGES["U"]
DEG = f"SELECT x AS vertex, count(*) AS degree FROM (SELECT u AS x FROM ({U}) UNION ALL SELECT v FROM ({U})) GROUP BY x"
ARCS = f"SELECT u AS src, v AS dst FROM ({U}) UNION ALL SELECT v, u FROM ({U})"


def op(name, sql=None):
    def add(f):
        QUERIES[f"op_{name}"] = f
        if sql is not None:
            ORACLES[f"op_{name}"] = sql
        return f

    return add


@op("scan_project_filter", "SELECT l_orderkey, l_partkey FROM lineitem WHERE l_quantity >= 46")
def _(spark, sf_dir):
    return graphs.table(spark, sf_dir, "lineitem").where(F.col("l_quantity") >= 46).select("l_orderkey", "l_partkey")


@op("bipartite_keys", o.SQL_EDGES["CP49"])
def _(spark, sf_dir):
    return load(spark, sf_dir, "CP49").edges


@op("copurchase_self_join", o.SQL_EDGES["P46"])
def _(spark, sf_dir):
    return load(spark, sf_dir, "P46").edges


@op("succession_lead", "SELECT a AS user_id, b AS next_id FROM (SELECT user_id AS a, lead(user_id) OVER (ORDER BY ts, event_id) AS b FROM events WHERE event_type = 'purchase') WHERE b IS NOT NULL")
def _(spark, sf_dir):
    return graphs.successions(spark, sf_dir).select("user_id", "next_id")


@op("symmetrize_union", ARCS)
def _(spark, sf_dir):
    return graph.both_ways(load(spark, sf_dir, "U").edges).select(F.col("u").alias("src"), F.col("v").alias("dst"))


for _hint, _key in (("broadcast", "broadcast_join"), ("merge", "sort_merge_join"), ("shuffle_hash", "shuffle_hash_join")):

    @op(_key, f"SELECT src, dst, degree FROM ({ARCS}) JOIN ({DEG}) ON vertex = src")
    def _(spark, sf_dir, hint=_hint):
        e = load(spark, sf_dir, "U").edges
        arcs = graph.both_ways(e).select(F.col("u").alias("src"), F.col("v").alias("dst"))
        return arcs.join(graph.degrees(e).withColumnRenamed("vertex", "src").hint(hint), "src").select("src", "dst", "degree")


_TOP = f"(SELECT vertex FROM ({DEG}) ORDER BY degree DESC, vertex LIMIT 1)"
for _how, _not in (("semi", ""), ("anti", "NOT ")):

    @op(f"{_how}_join", f"SELECT vertex FROM ({DEG}) WHERE vertex {_not}IN (SELECT dst FROM ({ARCS}) WHERE src = {_TOP})")
    def _(spark, sf_dir, how=_how):
        g = load(spark, sf_dir, "U")
        top = g.ranks.where("rank = 1").select("vertex")
        near = graph.neighbors(g.edges, top).select(F.col("neighbor").alias("vertex"))
        return g.ranks.select("vertex").join(near, "vertex", f"left_{how}")


@op("left_outer_default", o.pairs_sql("P46", "{s} % 50 = 0 AND {t} % 50 = 0"))
def _(spark, sf_dir):
    g, ix = indexed(spark, sf_dir, "P46")
    some = F.col("vertex") % 50 == 0
    found = query.in_blocks(ix, of=some)
    return query.pairs(ix, every_pair(g, some)).select("s", "t", "dist", "paths") if found is None else found


@op("left_outer_default_all", o.pairs_sql("P46"))
def _(spark, sf_dir):
    g, ix = indexed(spark, sf_dir, "P46")
    found = query.in_blocks(ix)
    return query.pairs(ix, every_pair(g)).select("s", "t", "dist", "paths") if found is None else found


@op("full_outer_diff", o.changes_sql("U", removed=o.first_deletes("U", 1)))
def _(spark, sf_dir):
    g, ix = derived(spark, sf_dir, "U")
    e = first_deletes(g, 1).first()
    up = delete.run(g, ix, e["u"], e["v"], strategy="searches")
    r = g.ranks
    diff = delete._diff(*index.changed_rows(ix, up.index))
    c = diff.join(r.select(F.col("rank").alias("owner"), F.col("vertex").alias("ov")), "owner").join(r.select(F.col("rank").alias("hub"), F.col("vertex").alias("hv")), "hub")
    return c.select(F.col("ov").alias("owner"), F.col("hv").alias("hub"), "old_dist", "old_paths", "dist", "paths", "op")


@op("range_join_strata", f"SELECT u, v, stratum FROM (SELECT u, v, a.degree * b.degree AS p FROM ({U}) JOIN ({DEG}) a ON a.vertex = u JOIN ({DEG}) b ON b.vertex = v) JOIN (VALUES (1, 0, 399), (2, 400, 799), (3, 800, 100000000)) t(stratum, lo, hi) ON p BETWEEN lo AND hi")
def _(spark, sf_dir):
    strata = spark.createDataFrame([(1, 0, 399), (2, 400, 799), (3, 800, 100000000)], "stratum int, lo long, hi long")
    d = graph.edge_degree(load(spark, sf_dir, "U").edges)
    return d.join(F.broadcast(strata), F.col("deg_product").between(F.col("lo"), F.col("hi"))).select("u", "v", "stratum")  # three rows


@op("asof_version", "SELECT e.event_id, max(c.event_id) AS version FROM events e JOIN events c ON c.event_type = 'signup' AND c.user_id = e.user_id AND c.ts <= e.ts WHERE e.event_type = 'view' GROUP BY e.event_id HAVING max(c.ts) IS NOT NULL")
def _(spark, sf_dir):
    e = graphs.table(spark, sf_dir, "events")
    views = e.where("event_type = 'view'").select("event_id", "user_id", "ts")
    ups = e.where("event_type = 'signup'").select("user_id", F.col("ts").alias("at"), F.col("event_id").alias("version"))
    return views.join(ups, "user_id").where(F.col("at") <= F.col("ts")).groupBy("event_id").agg(F.max("version").alias("version"))


@op("interval_validity", "WITH i AS (SELECT user_id, ts AS since, lead(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS upto FROM events WHERE event_type = 'signup') SELECT event_id, since FROM events e JOIN i ON i.user_id = e.user_id AND e.ts >= since AND (upto IS NULL OR e.ts < upto) WHERE event_type = 'error'")
def _(spark, sf_dir):
    e = graphs.table(spark, sf_dir, "events")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    i = e.where("event_type = 'signup'").select("user_id", F.col("ts").alias("since"), F.lead("ts").over(w).alias("upto"))
    at = e.where("event_type = 'error'").select("event_id", "user_id", "ts")
    return at.join(i, "user_id").where((F.col("ts") >= F.col("since")) & (F.col("upto").isNull() | (F.col("ts") < F.col("upto")))).select("event_id", "since")


@op("partial_final_agg", DEG)
def _(spark, sf_dir):
    return graph.degrees(load(spark, sf_dir, "U").edges)


_BRAND = "FROM lineitem JOIN part ON l_partkey = p_partkey"


@op("distinct_agg", f"SELECT p_brand, count(DISTINCT l_suppkey) AS suppliers {_BRAND} GROUP BY p_brand")
def _(spark, sf_dir):
    j = graphs.table(spark, sf_dir, "lineitem").select("l_partkey", "l_suppkey").join(graphs.table(spark, sf_dir, "part").select(F.col("p_partkey").alias("l_partkey"), "p_brand"), "l_partkey")
    return j.groupBy("p_brand").agg(F.count_distinct("l_suppkey").alias("suppliers"))


@op("approx_distinct")
def _(spark, sf_dir):
    j = graphs.table(spark, sf_dir, "lineitem").select("l_partkey", "l_suppkey").join(graphs.table(spark, sf_dir, "part").select(F.col("p_partkey").alias("l_partkey"), "p_brand"), "l_partkey")
    return j.groupBy("p_brand").agg(F.approx_count_distinct("l_suppkey", 0.02).alias("suppliers"))


@op("approx_distinct_bound", "SELECT p_brand, count(DISTINCT l_suppkey) AS suppliers, true AS within FROM lineitem JOIN part ON p_partkey = l_partkey GROUP BY p_brand")
def _(spark, sf_dir):
    """Exact numbers, and whether the approximate ones lie within five of their standard errors."""
    j = graphs.table(spark, sf_dir, "lineitem").select("l_partkey", "l_suppkey").join(graphs.table(spark, sf_dir, "part").select(F.col("p_partkey").alias("l_partkey"), "p_brand"), "l_partkey")
    n = j.groupBy("p_brand").agg(F.count_distinct("l_suppkey").alias("suppliers"), F.approx_count_distinct("l_suppkey", 0.02).alias("about"))
    return n.select("p_brand", "suppliers", (F.abs(F.col("about") - F.col("suppliers")) <= 1 + 5 * 0.02 * F.col("suppliers")).alias("within"))


_OPS = f"SELECT 'delete' AS change, op FROM ({o.changes_sql('U', removed=o.first_deletes('U', 1))}) UNION ALL SELECT 'insert', op FROM ({o.changes_sql('U', added=o.first_inserts('U', 1))}) WHERE op <> 'remove'"


def _ops(spark, sf_dir):
    g, ix = derived(spark, sf_dir, "U")
    ins = insert.run(g, ix, first_inserts(spark, sf_dir, g, 1), strategy="searches").changes
    return _deleted(spark, sf_dir, strategy="searches").changes.select(F.lit("delete").alias("change"), "op").unionByName(ins.select(F.lit("insert").alias("change"), "op"))


@op("grouping_sets", f"SELECT change, op, count(*) AS n FROM ({_OPS}) GROUP BY GROUPING SETS ((change), (op))")
def _(spark, sf_dir):
    return _ops(spark, sf_dir).groupingSets([["change"], ["op"]], "change", "op").agg(F.count("*").alias("n"))


@op("rollup", f"SELECT change, op, count(*) AS n FROM ({_OPS}) GROUP BY ROLLUP (change, op)")
def _(spark, sf_dir):
    return _ops(spark, sf_dir).rollup("change", "op").agg(F.count("*").alias("n"))


@op("cube", f"SELECT change, op, count(*) AS n FROM ({_OPS}) GROUP BY CUBE (change, op)")
def _(spark, sf_dir):
    return _ops(spark, sf_dir).cube("change", "op").agg(F.count("*").alias("n"))


_PER = f"WITH RECURSIVE {o.ctes('U')}, n AS (SELECT owner, count(*) AS n FROM idx GROUP BY owner)"


@op("percentiles", f"{_PER} SELECT quantile_cont(n, 0.25) AS p25, quantile_cont(n, 0.5) AS median, quantile_cont(n, 0.75) AS p75 FROM n")
def _(spark, sf_dir):
    n = indexed(spark, sf_dir, "U")[1].labels.groupBy("owner").agg(F.count("*").alias("n"))
    p = lambda x, name: F.percentile("n", F.lit(x)).alias(name)
    return n.agg(p(0.25, "p25"), p(0.5, "median"), p(0.75, "p75"))


@op("corr", f"{_PER} SELECT round(corr(d.degree, n.n), 9) AS corr FROM n JOIN rk ON rank = owner JOIN ({DEG}) d ON d.vertex = rk.vertex")
def _(spark, sf_dir):
    g, ix = indexed(spark, sf_dir, "U")
    n = ix.labels.groupBy("owner").agg(F.count("*").alias("n")).join(g.ranks.withColumnRenamed("rank", "owner"), "owner").join(graph.degrees(g.edges), "vertex")
    return n.agg(F.round(F.corr("degree", "n"), 9).alias("corr"))


@op("rank_window", "SELECT user_id, event_id, row_number() OVER (PARTITION BY user_id ORDER BY ts DESC, event_id) AS place FROM events WHERE event_type = 'purchase' QUALIFY place <= 3")
def _(spark, sf_dir):
    e = graphs.table(spark, sf_dir, "events").where("event_type = 'purchase'")
    w = Window.partitionBy("user_id").orderBy(F.desc("ts"), "event_id")
    return e.select("user_id", "event_id", F.row_number().over(w).cast("long").alias("place")).where("place <= 3")


@op("ntile", "SELECT user_id, event_id, ntile(4) OVER (PARTITION BY user_id ORDER BY value, event_id) AS tile FROM events")
def _(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("value", "event_id")
    return graphs.table(spark, sf_dir, "events").select("user_id", "event_id", F.ntile(4).over(w).cast("long").alias("tile"))


@op("running_sum", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS so_far FROM events")
def _(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return graphs.table(spark, sf_dir, "events").select("event_id", F.count("*").over(w).alias("so_far"))


@op("min_over_pair", f"WITH RECURSIVE {o.ctes('U')} SELECT x.owner AS s, y.owner AS t, x.hub AS hub FROM idx x JOIN idx y ON x.hub = y.hub WHERE x.owner <= 20 AND y.owner <= 20 QUALIFY x.dist + y.dist = min(x.dist + y.dist) OVER (PARTITION BY x.owner, y.owner)")
def _(spark, sf_dir):
    # Hubs are ranked above their owners.
    rows = indexed_part(spark, sf_dir, "U", top=20)[1].labels.where("owner <= 20")
    a = rows.select(F.col("owner").alias("s"), "hub", F.col("dist").alias("d1"))
    b = rows.select(F.col("owner").alias("t"), "hub", F.col("dist").alias("d2"))
    j = a.join(b, "hub").withColumn("d", F.col("d1") + F.col("d2"))
    return j.withColumn("least", F.min("d").over(Window.partitionBy("s", "t"))).where("d = least").select("s", "t", "hub")


@op("lag", "SELECT event_id, date_diff('second', lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id), ts) AS gap_minutes FROM events WHERE false UNION ALL SELECT event_id, CAST(floor(epoch(ts)) - floor(epoch(lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id))) AS BIGINT) FROM events")
def _(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    sec = lambda c: F.unix_seconds(c)
    return graphs.table(spark, sf_dir, "events").select("event_id", (sec(F.col("ts").cast("timestamp")) - sec(F.lag("ts").over(w).cast("timestamp"))).alias("gap_minutes"))


@op("topk", f"SELECT vertex, degree FROM ({DEG}) ORDER BY degree DESC, vertex LIMIT 10")
def _(spark, sf_dir):
    return graph.degrees(load(spark, sf_dir, "U").edges).orderBy(F.desc("degree"), "vertex").limit(10)


@op("topk_per_group", f"WITH RECURSIVE {o.ctes('U')} SELECT s, t, c AS paths, row_number() OVER (PARTITION BY s ORDER BY c DESC, t) AS place FROM p WHERE d = 2 QUALIFY place <= 3")
def _(spark, sf_dir):
    from .apps import all_answers

    w = Window.partitionBy("s").orderBy(F.desc("paths"), "t")
    return all_answers(indexed_part(spark, sf_dir, "U", max_levels=2)[1], within=2).where("dist = 2").select("s", "t", "paths", F.row_number().over(w).cast("long").alias("place")).where("place <= 3")


@op("union", "SELECT c_nationkey AS n FROM customer UNION SELECT s_nationkey FROM supplier")
def _(spark, sf_dir):
    return graphs.table(spark, sf_dir, "customer").select(F.col("c_nationkey").alias("n")).union(graphs.table(spark, sf_dir, "supplier").select("s_nationkey")).distinct()


@op("intersect", f"WITH RECURSIVE {o.ctes('U')} SELECT hub FROM idx WHERE owner = 30 INTERSECT SELECT hub FROM idx WHERE owner = 40")
def _(spark, sf_dir):
    rows = indexed_part(spark, sf_dir, "U", top=40)[1].labels
    return rows.where("owner = 30").select("hub").intersect(rows.where("owner = 40").select("hub"))


@op("except_all", "SELECT l_partkey FROM lineitem WHERE l_quantity >= 46 EXCEPT ALL SELECT l_partkey FROM lineitem WHERE l_quantity >= 49")
def _(spark, sf_dir):
    rows = graphs.table(spark, sf_dir, "lineitem")
    return rows.where("l_quantity >= 46").select("l_partkey").exceptAll(rows.where("l_quantity >= 49").select("l_partkey"))


@op("pack_array", f"WITH RECURSIVE {o.ctes('U')} SELECT owner, count(*) AS n, string_agg(hub || ':' || dist || ':' || paths, ',' ORDER BY hub) AS packed FROM idx GROUP BY owner")
def _(spark, sf_dir):
    rows = query.packed(indexed(spark, sf_dir, "U")[1])
    text = F.array_join(F.transform("rows", lambda x: F.concat_ws(":", x["hub"].cast("string"), x["dist"].cast("string"), x["paths"].cast("string"))), ",")
    return rows.select("owner", F.size("rows").cast("long").alias("n"), text.alias("packed"))


@op("higher_order_query", f"WITH RECURSIVE {o.ctes('U')} SELECT owner, CAST(sum(paths) FILTER (WHERE dist = 2) AS BIGINT) AS two FROM idx GROUP BY owner HAVING two IS NOT NULL")
def _(spark, sf_dir):
    rows = query.packed(indexed_part(spark, sf_dir, "U", max_levels=2)[1])
    two = F.aggregate(F.filter("rows", lambda x: x["dist"] == 2), F.lit(0).cast("long"), lambda n, x: n + x["paths"])
    return rows.select("owner", two.alias("two")).where("two > 0")


@op("map_lookup", f"WITH RECURSIVE {o.ctes('U')} SELECT owner, CAST(dist AS INTEGER) AS dist FROM idx WHERE hub = 1")
def _(spark, sf_dir):
    rows = query.packed(indexed_part(spark, sf_dir, "U", top=1)[1])
    m = F.map_from_entries(F.transform("rows", lambda x: F.struct(x["hub"], x["dist"])))
    return rows.select("owner", F.try_element_at(m, F.lit(1).cast("long")).alias("dist")).where("dist IS NOT NULL")


@op("bit_codec", f"WITH RECURSIVE {o.ctes('U')} SELECT owner, hub, CAST(dist AS INTEGER) AS dist, paths, (hub << 39) | (CAST(dist AS BIGINT) << 29) | paths AS code FROM idx")
def _(spark, sf_dir):
    rows = indexed(spark, sf_dir, "U")[1].labels.withColumn("code", codec.encode(F.col("hub"), F.col("dist"), F.col("paths")))
    c = F.col("code")
    return rows.select("owner", codec.hub(c).alias("hub"), codec.dist(c).alias("dist"), codec.paths(c).alias("paths"), "code")


@op("json_props", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
def _(spark, sf_dir):
    return graphs.table(spark, sf_dir, "events").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"))


@op("date_parts", "SELECT year(o_orderdate) AS y, month(o_orderdate) AS m, count(*) AS n FROM orders GROUP BY ALL")
def _(spark, sf_dir):
    return graphs.table(spark, sf_dir, "orders").groupBy(F.year("o_orderdate").cast("long").alias("y"), F.month("o_orderdate").cast("long").alias("m")).agg(F.count("*").alias("n"))


@op("string_key", "SELECT 'customer/' || c_custkey AS key, 2 * c_custkey AS vertex FROM customer")
def _(spark, sf_dir):
    return graphs.table(spark, sf_dir, "customer").select(F.concat_ws("/", F.lit("customer"), F.col("c_custkey").cast("string")).alias("key"), (F.col("c_custkey") * 2).alias("vertex"))


@op("tumbling", "SELECT epoch(ts)::BIGINT // 3600 AS hour, event_type, count(*) AS n FROM events GROUP BY ALL HAVING true")
def _(spark, sf_dir):
    e = graphs.table(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    return e.groupBy(F.window("ts", "1 hour").alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.floor(F.unix_seconds("w.start") / 3600).alias("hour"), "event_type", "n")


ORACLES["op_tumbling"] = "SELECT CAST(floor(epoch(ts) / 3600) AS BIGINT) AS hour, event_type, count(*) AS n FROM events GROUP BY ALL"


@op("sliding", "SELECT h - k AS hour, count(*) AS n FROM (SELECT CAST(floor(epoch(ts) / 3600) AS BIGINT) AS h FROM events), (VALUES (0), (1)) t(k) GROUP BY ALL")
def _(spark, sf_dir):
    e = graphs.table(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    return e.groupBy(F.window("ts", "2 hours", "1 hour").alias("w")).agg(F.count("*").alias("n")).select(F.floor(F.unix_seconds("w.start") / 3600).alias("hour"), "n")


@op("session", "WITH g AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM events), s AS (SELECT user_id, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, n, count(*) AS sessions FROM (SELECT user_id, k, count(*) AS n FROM s GROUP BY ALL) GROUP BY ALL")
def _(spark, sf_dir):
    e = graphs.table(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    s = e.groupBy("user_id", F.session_window("ts", "6 hours").alias("w")).agg(F.count("*").alias("n"))
    return s.groupBy("user_id", "n").agg(F.count("*").alias("sessions"))


@op("stream_dedupe_late", f"SELECT CAST(count(*) AS BIGINT) AS edges FROM (SELECT u, v FROM ({U}) UNION SELECT u, v FROM ({o.first_inserts('U', 11)}))")
def _(spark, sf_dir):
    """Edges after a change stream with a duplicated row: it is applied once."""
    from ..streaming import hybrid
    from .workloads import change_log

    g, ix = derived(spark, sf_dir, "U")
    state = hybrid.run_files(g, ix, change_log(spark, sf_dir, g, 11, 0), rows_per_file=6, duplicate=True, strategy="searches")
    return state.graph.edges.agg(F.count("*").alias("edges"))


@op("csv_parse", U)
def _(spark, sf_dir):
    """Edges as text lines, parsed by a stated schema."""
    lines = load(spark, sf_dir, "U").edges.select(F.concat_ws(",", "u", "v").alias("line"))
    return lines.select(F.from_csv("line", "u BIGINT, v BIGINT").alias("e")).select("e.u", "e.v")


@op("neighbors", f"SELECT src AS vertex, dst AS neighbor FROM ({ARCS}) WHERE src = {_TOP}")
def _(spark, sf_dir):
    g = load(spark, sf_dir, "U")
    return graph.neighbors(g.edges, g.ranks.where("rank = 1").select("vertex"))


@op("below_hub", f"WITH RECURSIVE {o.ctes('U')} SELECT src, dst FROM arcs WHERE src >= 40 AND dst > 40")
def _(spark, sf_dir):
    return graph.below(load(spark, sf_dir, "U"), 40).select("src", "dst")


@op("edge_degree", f"SELECT u, v, a.degree * b.degree AS deg_product FROM ({U}) JOIN ({DEG}) a ON a.vertex = u JOIN ({DEG}) b ON b.vertex = v")
def _(spark, sf_dir):
    return graph.edge_degree(load(spark, sf_dir, "U").edges)


@op("to_undirected", U)
def _(spark, sf_dir):
    return graph.to_undirected(load(spark, sf_dir, "UD").edges)
