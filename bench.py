"""Times the headline queries and prints one JSON line.

Reads ``$BENCH_SF_DIR`` (default /root/testdata/sf0.1) on ``local[$BENCH_CPUS]``. Besides seconds it reports the
ratios that the published numbers are compared with: rebuild over update, and search over label query.
"""

from __future__ import annotations

import json
import os
import sys
import time
from pathlib import Path

HERE = Path(__file__).resolve().parent
sys.path.insert(0, str(HERE))


def main() -> None:
    from pyspark.sql import SparkSession
    from pyspark.sql import functions as F

    from tallypath.operators import delete, graph, insert, query, traversal
    from tallypath.operators import index as ixs
    from tallypath.plans import workloads as w
    from tallypath.sources.scratch import write

    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.driver.memory", "12g")
        .config("spark.sql.shuffle.partitions", "16")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    out: dict[str, float] = {}
    notes: dict[str, float] = {}

    def timed(name: str, f):
        began = time.time()
        got = f()
        out[name] = round(time.time() - began, 3)
        print(f"{name}: {out[name]} s", file=sys.stderr, flush=True)
        return got

    done = lambda df: write(df, "bench").seen["n"]
    g = timed("b_graph", lambda: w.load(spark, sf_dir, "U"))
    ix = timed("b_build", lambda: ixs.build(g))
    labels = ix.labels.count()
    notes["label_rows"], notes["rows_per_vertex"] = labels, round(labels / g.ranks.count(), 1)
    one = w.first_inserts(spark, sf_dir, g, 1)
    ten = w.first_inserts(spark, sf_dir, g, 10)
    timed("b_insert_1", lambda: insert.run(g, ix, one))
    up = timed("b_insert_10", lambda: insert.run(g, ix, ten))
    e = w.first_deletes(g, 1).first()
    gone = timed("b_delete_1", lambda: delete.run(g, ix, e["u"], e["v"]))
    timed("b_rebuild", lambda: ixs.rebuild_batch(g, one))
    pairs = w.written(w.every_pair(g).where((F.col("s") * 7919 + F.col("t") * 104729) % 1000003 < 4444).limit(10_000), "pairs")
    notes["pairs"] = pairs.count()
    for name, state in (("original", ix), ("inserted", up.index), ("deleted", gone.index)):
        timed(f"b_query_{name}", lambda state=state: done(query.pairs(state, pairs)))
    few = w.written(pairs.orderBy("qid").limit(200), "few")
    timed("b_bibfs_200", lambda: done(traversal.bfs_count_pairs(g, few)))
    timed("b_source_all", lambda: done(query.from_source(ix, g.ranks.where("rank = 1").first()["vertex"])))
    p = w.load(spark, sf_dir, "P46")
    notes["p46_edges"] = graph.stats(p.edges).first()["m"]
    # Of a single edge each; the share of one edge in a repair of ten together is given beside it.
    notes["rebuild_over_insert"] = round(out["b_build"] / out["b_insert_1"], 2)
    notes["rebuild_over_insert_in_a_batch_of_ten"] = round(out["b_build"] / (out["b_insert_10"] / 10), 1)
    notes["rebuild_over_delete"] = round(out["b_build"] / out["b_delete_1"], 2)
    notes["bibfs_over_query_a_pair"] = round((out["b_bibfs_200"] / 200) / (out["b_query_original"] / max(1, notes["pairs"])), 1)
    print(json.dumps({"metric": "headline_total", "value": round(sum(out.values()), 3), "unit": "sec", "queries": out, "sf": sf_dir.rsplit("sf", 1)[-1], "notes": notes}))
    spark.stop()


if __name__ == "__main__":
    main()
