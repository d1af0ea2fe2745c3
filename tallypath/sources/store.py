"""The index as versioned tables: base, overlays, manifests."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.graph import Graph, rank_arcs
from ..operators.index import KEY, ROW, LabelIndex
from .scratch import Layered, write

BUCKETS = 64


class Store:
    """A folder with base files by (side, bucket of the owner), one overlay a version, and a manifest for each version.

    A commit writes files first and its manifest last, so readers see whole versions; a version names its batch, so
    a replayed batch is recognised. Files that no manifest names (a writer was lost) are written over. Manifests are small
    JSON lines written through Spark's own file system. A folder has one writer at a time, and takes either single
    changes (``write_base``, ``append``) or whole states of graph and index (``commit``, ``restore``).
    """

    def __init__(self, spark: SparkSession, folder: str, buckets: int = BUCKETS):
        self.spark, self.folder, self.buckets = spark, folder.rstrip("/"), buckets
        self._held: dict[str, tuple[DataFrame, str]] = {}  # tables in the folder and where they lie

    def _manifests(self) -> list[dict]:
        path = self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path
        at = path(f"{self.folder}/manifest")
        if not at.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).exists(at):
            return []
        rows = self.spark.read.text(f"{self.folder}/manifest/*").collect()  # one line a version
        return sorted((json.loads(r["value"]) for r in rows), key=lambda m: m["version"])

    def _put_manifest(self, m: dict) -> None:
        self.spark.createDataFrame([(json.dumps(m),)], "value string").coalesce(1).write.mode("overwrite").text(f"{self.folder}/manifest/v={m['version']:08d}")

    def latest(self) -> dict | None:
        found = self._manifests()
        return found[-1] if found else None

    def _put_labels(self, labels: DataFrame, path: str) -> None:
        rows = labels.withColumn("bucket", F.pmod("owner", F.lit(self.buckets)).cast("int"))
        rows.repartition("side", "bucket").sortWithinPartitions("side", "bucket", "owner", "hub").write.mode("overwrite").partitionBy("side", "bucket").parquet(path)

    def write_base(self, labels: DataFrame, version: int = 0, batch: int = -1, ts: float = 0.0) -> None:
        path = f"{self.folder}/base/v={version:08d}"
        self._put_labels(labels, path)
        self._put_manifest({"version": version, "base": path, "overlays": [], "batch": batch, "ts": ts})

    def append(self, changes: DataFrame, batch: int, ts: float = 0.0) -> bool:
        """Commits ``changes`` (side, owner, hub, dist, paths, op) as an overlay; False if the batch was committed before."""
        last = self.latest()
        if "edges" in last:
            raise ValueError("this folder holds whole states: use commit")
        if batch <= last["batch"]:
            return False
        version = last["version"] + 1
        path = f"{self.folder}/overlay/v={version:08d}"
        changes.select(*KEY, "dist", "paths", "op").withColumn("version", F.lit(version)).write.mode("overwrite").parquet(path)
        self._put_manifest({**last, "version": version, "overlays": [*last["overlays"], path], "batch": batch, "ts": ts})
        return True

    def _read(self, m: dict) -> DataFrame:
        base = self.spark.read.parquet(m["base"]).select("side", "owner", "hub", "dist", "paths")
        if not m["overlays"]:
            return base
        every = self.spark.read.parquet(*m["overlays"])
        last = every.groupBy(*KEY).agg(F.max_by(F.struct("dist", "paths", "op"), "version").alias("b")).select(*KEY, "b.*")
        return base.join(last.select(*KEY), KEY, "left_anti").unionByName(last.where(F.col("op") != "remove").select(*base.columns))

    def read_current(self) -> DataFrame:
        return self._read(self.latest())

    def as_of(self, ts: float) -> DataFrame:
        """The labels of the last version committed at or before ``ts``."""
        old = [m for m in self._manifests() if m["ts"] <= ts]
        return self._read(old[-1]) if old else self.spark.createDataFrame([], ROW)

    def compact(self) -> None:
        """Folds the overlays into a new base, as a new version."""
        m = self.latest()
        version = m["version"] + 1
        path = f"{self.folder}/base/v={version:08d}"
        self._put_labels(self._read(m), path)
        self._put_manifest({**m, "version": version, "base": path, "overlays": [], "metrics": None, "late": None})

    def _kept(self, name: str, df: DataFrame | None, version: int, put=None) -> str | None:
        """Where ``df`` lies in the folder; it is written only if it isn't the table that the last version had there."""
        if df is None:
            return None
        if name not in self._held or self._held[name][0] is not df:
            path = f"{self.folder}/{name}/v={version:08d}"
            (put or (lambda rows, to: rows.write.mode("overwrite").parquet(to)))(df, path)
            self._held[name] = (df, path)
        return self._held[name][1]

    def commit(self, g: Graph, ix: LabelIndex, batch: int, seq: int, ts: float = 0.0, metrics: DataFrame | None = None, late: DataFrame | None = None) -> bool:
        """Commits graph and index after ``batch``, with its metrics and the changes it set aside; False if it was committed before.

        A version costs its overlays, as large as all changes since the last fold; base tables are written again after a fold only.
        """
        last = self.latest()
        if last is not None and "edges" not in last:
            raise ValueError("this folder holds single changes: use append")
        if last is not None and batch <= last["batch"]:
            return False
        v = last["version"] + 1 if last else 0
        labels, edges = ix.table, g.edge_table

        def put_overlay(rows: DataFrame, to: str) -> None:
            op = F.when(F.col("gone"), "remove").otherwise("insert").alias("op")
            rows.select(*KEY, "dist", "paths", op, F.lit(v).alias("version")).write.mode("overwrite").parquet(to)

        over = self._kept("overlay", labels.overlay, v, put_overlay)
        self._put_manifest(
            {
                "version": v, "batch": batch, "seq": seq, "ts": ts, "directed": g.directed, "weighted": g.weighted,
                "base": self._kept("base", labels.base, v, self._put_labels), "base_rows": labels.base_rows, "overlays": [over] if over else [],
                "edges": self._kept("edges", edges.base, v), "edge_rows": edges.base_rows, "edge_overlay": self._kept("edge-overlay", edges.overlay, v),
                "ranks": self._kept("ranks", g.ranks, v), "metrics": self._kept("metrics", metrics, v), "late": self._kept("late", late, v),
            }
        )
        return True

    def restore(self) -> tuple[Graph, LabelIndex, dict]:
        """Graph and index of the last committed state, and its manifest (``batch``, ``seq``)."""
        m, read = self.latest(), self.spark.read.parquet
        if m is None or "edges" not in m:
            raise ValueError("no state of graph and index was committed to this folder")
        base, ranks, edges = read(m["base"]).select(*KEY, "dist", "paths"), read(m["ranks"]), read(m["edges"])
        over = read(*m["overlays"]).select(*base.columns, (F.col("op") == "remove").alias("gone")) if m["overlays"] else None
        moved = read(m["edge_overlay"]) if m["edge_overlay"] else None
        table = Layered(edges, ("u", "v"), m["edge_rows"], moved)
        arcs = write(rank_arcs(table.rows, ranks, m["directed"], m["weighted"]), "arcs")
        g = Graph(table, ranks, Layered(arcs.df, ("side", "src", "dst"), arcs.seen["n"]), m["directed"], m["weighted"])
        ix = LabelIndex(Layered(base, tuple(KEY), m["base_rows"], over), ranks, m["directed"])
        held = {"base": base, "ranks": ranks, "edges": edges, "overlay": over, "edge-overlay": moved}
        at = {"base": m["base"], "ranks": m["ranks"], "edges": m["edges"], "overlay": (m["overlays"] or [None])[0], "edge-overlay": m["edge_overlay"]}
        self._held = {k: (df, at[k]) for k, df in held.items() if df is not None}
        return g, ix, m

    def logged(self, name: str) -> list[DataFrame]:
        """The tables ``metrics`` or ``late`` of all committed versions, oldest first."""
        return [self.spark.read.parquet(m[name]) for m in self._manifests() if m.get(name)]
