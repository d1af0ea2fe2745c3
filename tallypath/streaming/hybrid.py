"""Streaming maintenance: change files in, an index kept in step, versions of graph and index out where a store is given."""

from __future__ import annotations

import time
import uuid
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import maintain
from ..operators.graph import Graph
from ..operators.index import LabelIndex
from ..sources.scratch import shared_dir, written
from ..sources.store import Store

CHANGE = "seq long, ts timestamp, op string, u long, v long, w long"


@dataclass
class Maintained:
    """The state that a stream keeps: graph, index, last batch id and seq, metrics, and changes set aside (written tables).

    With a ``store`` each batch is committed there as a version before the stream counts it as done; ``resume`` goes on
    from the last version, and a batch that the stream repeats after a loss is recognised.
    """

    graph: Graph
    index: LabelIndex
    batch: int = -1
    seq: int = 0
    metrics: list[DataFrame] = field(default_factory=list)
    late: list[DataFrame] = field(default_factory=list)
    store: Store | None = None
    #: How updates are repaired, see ``maintain.apply``.
    strategy: str = "withhold"

    def commit(self, changes: DataFrame, batch: int) -> None:
        """Applies a micro-batch once: a replayed batch id does nothing; changes at or below the committed seq, or without one, are set aside.

        Of rows with one seq the least (op, u, v, w) counts. Fields change only once everything is committed.
        """
        if batch <= self.batch:
            return
        changes = written(changes, "batch")
        known = F.coalesce(F.col("seq") <= self.seq, F.lit(True))
        late = changes.where(known)
        late = None if late.isEmpty() else written(late, "late")
        rest = [c for c in changes.columns if c != "seq"]
        new = changes.where(~known).groupBy("seq").agg(F.min(F.struct("op", "u", "v", *[c for c in rest if c not in ("op", "u", "v")])).alias("c")).select("seq", "c.*")
        last = new.agg(F.max("seq")).first()[0]
        g, ix, metrics = self.graph, self.index, None
        if last is not None:
            g, ix, metrics = maintain.apply(g, ix, new, batch_inserts=True, strategy=self.strategy)
        seq = self.seq if last is None else last
        if self.store is not None:
            self.store.commit(g, ix, batch, seq, time.time(), metrics, late)
        self.graph, self.index, self.seq, self.batch = g, ix, seq, batch
        self.metrics += [] if metrics is None else [metrics]
        self.late += [] if late is None else [late]

    def all_metrics(self) -> DataFrame | None:
        out = None
        for m in self.metrics:
            out = m if out is None else out.unionByName(m)
        return out


def stored(g: Graph, ix: LabelIndex, store: Store) -> Maintained:
    """A new state whose first version is ``g`` and ``ix`` as they are."""
    store.commit(g, ix, -1, 0, time.time())
    return Maintained(g, ix, store=store)


def resume(store: Store) -> Maintained:
    """The state as of the last committed version; its stream goes on with the checkpoint that it had."""
    g, ix, m = store.restore()
    return Maintained(g, ix, m["batch"], m["seq"], store.logged("metrics"), store.logged("late"), store)


def start(source: DataFrame, state: Maintained, checkpoint: str, trigger: dict | None = None):
    """Starts the maintenance of ``state`` from a streaming DataFrame of changes; duplicates by seq within the watermark are dropped."""
    fresh = source.withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark(["seq"])
    return fresh.writeStream.foreachBatch(lambda df, i: state.commit(df, i)).option("checkpointLocation", checkpoint).trigger(**(trigger or {"availableNow": True})).start()


def put_files(changes: DataFrame, folder: str, rows_per_file: int = 11, duplicate: bool = False) -> None:
    """Writes ``changes`` (seq, op, u, v) as files of ``rows_per_file`` rows, in order of seq; ``duplicate`` repeats the first one at the end."""
    rows = changes.select("seq", (F.timestamp_seconds(F.lit(1_700_000_000) + F.col("seq"))).alias("ts"), "op", "u", "v", F.lit(None).cast("long").alias("w"))
    least, most = rows.agg(F.min("seq"), F.max("seq")).first()
    for lo in range(least, most + 1, rows_per_file) if least is not None else ():
        rows.where(F.col("seq").between(lo, lo + rows_per_file - 1)).coalesce(1).write.parquet(f"{folder}/files/f={lo}")
        time.sleep(0.01)
    if duplicate:
        rows.where(F.col("seq") == least).coalesce(1).write.parquet(f"{folder}/files/f=late")


def follow(spark: SparkSession, state: Maintained, folder: str) -> Maintained:
    """Runs the files of ``folder`` that are new to its checkpoint through ``state``, one file a batch."""
    source = spark.readStream.schema(CHANGE).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").parquet(f"{folder}/files")
    start(source, state, f"{folder}/checkpoint").awaitTermination()
    return state


def run_files(g: Graph, ix: LabelIndex, changes: DataFrame, rows_per_file: int = 11, duplicate: bool = False, strategy: str = "withhold") -> Maintained:
    """Writes ``changes`` (seq, op, u, v) as files and runs them through a file stream, one file a batch."""
    spark = ix.labels.sparkSession
    folder = f"{shared_dir(spark)}/tallypath-stream-{uuid.uuid4().hex}"
    put_files(changes, folder, rows_per_file, duplicate)
    return follow(spark, Maintained(g, ix, strategy=strategy), folder)


def run_restarted(g: Graph, ix: LabelIndex, changes: DataFrame, at: int, rows_per_file: int = 11) -> Maintained:
    """As ``run_files``, but the stream ends after seq ``at`` and goes on from the store, as a new process would."""
    spark = ix.labels.sparkSession
    folder = f"{shared_dir(spark)}/tallypath-stream-{uuid.uuid4().hex}"
    put_files(changes.where(F.col("seq") <= at), folder, rows_per_file)
    follow(spark, stored(g, ix, Store(spark, f"{folder}/versions")), folder)
    put_files(changes.where(F.col("seq") > at), folder, rows_per_file)
    return follow(spark, resume(Store(spark, f"{folder}/versions")), folder)
