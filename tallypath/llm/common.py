"""Shared pieces: where intermediate tables go, and reading by bounded batches."""

from __future__ import annotations

import ctypes
import gc
import re
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The folder that all executors share (``spark.checkpoint.dir``); a local one only where none is set and all tasks run in this process, as in tests."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        found = spark.sparkContext._jsc.sc().getCheckpointDir()
        if found.isDefined():
            base = found.get()
        else:
            if not re.fullmatch(r"local(\[[^\]]*\])?", spark.sparkContext.master):
                raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
            base = "file://" + tempfile.mkdtemp(prefix="tallypath-")
            spark.sparkContext.setCheckpointDir(base)
    return base.rstrip("/")


BATCH_BYTES = 6 << 20


def bounded(df: DataFrame) -> DataFrame:
    """``df``, with Arrow batches limited by bytes, unless the session limits them: long texts then never fill a worker."""
    key = "spark.sql.execution.arrow.maxBytesPerBatch"
    if df.sparkSession.conf.get(key, None) is None:
        df.sparkSession.conf.set(key, BATCH_BYTES)
    return df


def written(df: DataFrame, name: str) -> DataFrame:
    """``df`` as a Parquet table in the shared folder, read again: cuts lineage and survives lost executors."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/llm-{name}-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def drop_written(df: DataFrame) -> None:
    """Deletes the files of a table made by ``written`` once nothing reads it any more."""
    spark = df.sparkSession
    jvm = spark.sparkContext._jvm
    conf = spark.sparkContext._jsc.hadoopConfiguration()
    for file in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        if "/llm-" in file:
            path = jvm.org.apache.hadoop.fs.Path(file)
            path.getFileSystem(conf).delete(path, True)


def clear(spark: SparkSession) -> None:
    """Deletes what this subpackage has left in the shared folder (tables, archives, stages of other runs included), once no result needs it."""
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path
    fs = path(shared_dir(spark)).getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    for pattern in ("llm-*", "pipeline-*"):
        for found in fs.globStatus(path(f"{shared_dir(spark)}/{pattern}")) or []:
            fs.delete(found.getPath(), True)


def release() -> None:
    """Gives memory freed by a fit, or by a task whose worker lives on, back to the system, where the C library can."""
    gc.collect()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):
        return


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return bounded(spark.read.parquet(f"{sf_dir}/{name}.parquet"))


def slices(pdf, column: str = "text", most: int = 4 << 20):
    """Consecutive parts of a batch with about ``most`` characters of text each, so that work on a part stays small."""
    size, at, held = pdf[column].str.len().fillna(0).to_numpy(), 0, 0
    for i, n in enumerate(size):
        if held and held + n > most:
            yield pdf.iloc[at:i]
            at, held = i, 0
        held += n
    if at < len(pdf):
        yield pdf.iloc[at:]
