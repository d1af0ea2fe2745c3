"""Written intermediate tables: the only way in which this package cuts lineage."""

from __future__ import annotations

import gc
import re
import tempfile
import uuid
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Observation, SparkSession
from pyspark.sql import functions as F


def shared_dir(spark: SparkSession) -> str:
    """``spark.checkpoint.dir`` of the session; a local folder only where none is set, as in tests."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        found = spark.sparkContext._jsc.sc().getCheckpointDir()
        if found.isDefined():
            return found.get().rstrip("/")
        if not re.fullmatch(r"local(\[[^\]]*\])?", spark.sparkContext.master):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        base = "file://" + tempfile.mkdtemp(prefix="tallypath-")
        spark.sparkContext.setCheckpointDir(base)
    return base.rstrip("/")


def clear(spark: SparkSession) -> None:
    """Deletes what this package has left in the shared folder (other runs' tables included), once no result needs it."""
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path
    fs = path(shared_dir(spark)).getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    for found in fs.globStatus(path(f"{shared_dir(spark)}/tallypath-*")) or []:
        fs.delete(found.getPath(), True)


def forget(spark: SparkSession) -> None:
    """Lets Spark delete the shuffle files of plans that nothing refers to; it learns of them when the driver collects garbage."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


@dataclass
class Written:
    """A table in the shared folder with what was observed while it was written."""

    df: DataFrame
    path: str
    seen: dict


def write(df: DataFrame, name: str, **observed: Column) -> Written:
    """Writes ``df`` as Parquet; row count ``n`` and further aggregates are observed by the same job."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/tallypath-{name}-{uuid.uuid4().hex}"
    watch = Observation()
    df.observe(watch, F.count(F.lit(1)).alias("n"), *(c.alias(k) for k, c in observed.items())).write.parquet(path)
    return Written(spark.read.schema(df.schema).parquet(path), path, watch.get)


#: An overlay larger than this share of its base is folded into a new base.
FOLD_SHARE = 0.1


@dataclass(frozen=True)
class Layered:
    """A written base table and a written overlay (its columns and ``gone``) that replaces rows by key.

    An update writes only a new overlay, as large as all changes since the last fold; the base stays as it is.
    """

    base: DataFrame
    keys: tuple[str, ...]
    base_rows: int | None = None
    overlay: DataFrame | None = None
    #: Not of a base that is not written, which a fold would find row by row.
    fold: bool = True

    @property
    def rows(self) -> DataFrame:
        if self.overlay is None:
            return self.base
        kept = self.base.join(self.overlay.select(*self.keys), list(self.keys), "left_anti")
        return kept.unionByName(self.overlay.where(~F.col("gone")).select(*self.base.columns))

    def changed(self, changes: DataFrame) -> "Layered":
        """With ``changes`` (the base's columns and ``gone``; one row a key, or it raises) on top."""
        columns = [*self.base.columns, "gone"]
        rest = [c for c in columns if c not in self.keys]
        new = changes.groupBy(*self.keys).agg(*[F.first(c).alias(c) for c in rest], F.count(F.lit(1)).alias("__n"))
        if self.overlay is not None:
            new = written(new, "changes")
            new = self.overlay.join(new.select(*self.keys), list(self.keys), "left_anti").withColumn("__n", F.lit(1).cast("long")).unionByName(new)
        layer = write(new, "overlay", most=F.max("__n"))
        if (layer.seen["most"] or 0) > 1:
            raise ValueError(f"changes repeat a key of {self.keys}")
        layer = Written(layer.df.select(*columns), layer.path, layer.seen)
        if not self.fold:
            return Layered(self.base, self.keys, overlay=layer.df, fold=False)
        n = self.base_rows if self.base_rows is not None else self.base.count()
        if layer.seen["n"] > max(1000, FOLD_SHARE * n):
            folded = write(Layered(self.base, self.keys, n, layer.df).rows, "base")
            return Layered(folded.df, self.keys, folded.seen["n"])
        return Layered(self.base, self.keys, n, layer.df)


def written(df: DataFrame, name: str = "table") -> DataFrame:
    return write(df, name).df
