"""Readers and sinks. Zone-less timestamps become UTC timestamps, which watermarks need."""

from __future__ import annotations

import atexit
import contextlib
import os
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

ROOT = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
_written: list[tuple[SparkSession, str]] = []
TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def prepare_workers(spark: SparkSession) -> None:
    """Let Python workers import this package from where the driver found it."""
    env = spark.sparkContext.environment
    have = [p for p in env.get("PYTHONPATH", "").split(os.pathsep) if p]
    if ROOT not in have:
        env["PYTHONPATH"] = os.pathsep.join([ROOT, *have])


def load(spark: SparkSession, sf_dir: str, name: str, columns: list[str] | None = None) -> DataFrame:
    """A table by name, pruned to ``columns`` at the scan."""
    if name not in TABLES:
        raise ValueError(f"unknown table {name}")
    prepare_workers(spark)
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    df = df.select(*columns) if columns else df
    return df.withColumns({f.name: F.col(f.name).cast("timestamp") for f in df.schema if isinstance(f.dataType, T.TimestampNTZType)})


def dealt(df: DataFrame) -> DataFrame:
    """``df`` in as many partitions as the cluster has cores where it comes from fewer files; untouched, without a shuffle, from more."""
    cores = df.sparkSession.sparkContext.defaultParallelism
    return df if len(df.inputFiles()) >= cores else df.repartition(cores)


def read_typed(spark: SparkSession, path: str, schema: str | T.StructType, fmt: str = "parquet") -> DataFrame:
    """JSON, CSV, ORC or Parquet with an explicit schema; malformed rows fail."""
    return spark.read.schema(schema).option("mode", "FAILFAST").option("header", "true").format(fmt).load(path)


def stream(spark: SparkSession, path: str, schema: str | T.StructType, files_per_trigger: int = 1) -> DataFrame:
    """A directory of Parquet files as a stream, in file order."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def write_partitioned(df: DataFrame, path: str, *by: str) -> None:
    df.write.mode("overwrite").partitionBy(*by).parquet(path)


def write_bucketed(df: DataFrame, table: str, path: str, buckets: int, *by: str) -> None:
    """An external bucketed table: later joins on ``by`` need no exchange."""
    df.write.mode("overwrite").option("path", path).bucketBy(buckets, *by).sortBy(*by).format("parquet").saveAsTable(table)


def shared_dir(spark: SparkSession) -> str:
    """The folder of ``spark.checkpoint.dir``; a temporary one where that is unset, which only a local master allows."""
    sc = spark.sparkContext
    if not sc._jsc.sc().getCheckpointDir().isDefined():
        found = sc.getConf().get("spark.checkpoint.dir", None)
        if not found:
            if not sc.master.startswith("local"):
                raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
            found = "file://" + tempfile.mkdtemp(prefix="strata-")
        sc.setCheckpointDir(found)
    return sc._jsc.sc().getCheckpointDir().get()


def checkpointed(df: DataFrame) -> DataFrame:
    """Cut lineage in the shared folder."""
    shared_dir(df.sparkSession)
    return df.checkpoint()


def new_path(spark: SparkSession, label: str) -> str:
    """A path of our own in the shared folder, removed when the driver ends unless ``remove`` came first."""
    path = f"{shared_dir(spark)}/strata-{label}-{uuid.uuid4().hex}"
    _written.append((spark, path))
    return path


def remove(spark: SparkSession, path: str) -> None:
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)
    _written[:] = [x for x in _written if x[1] != path]


@atexit.register
def _forget() -> None:
    for spark, path in list(_written):
        with contextlib.suppress(Exception):  # the session may be gone; its folder then goes with the application's
            remove(spark, path)


def staged(df: DataFrame, label: str = "frame") -> DataFrame:
    """``df`` as Parquet in the shared folder, read back: what several jobs read is computed once, pruned and columnar."""
    path = new_path(df.sparkSession, label)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def append_batches(df: DataFrame, path: str, checkpoint: str, once: bool = True):
    """A running query that appends each micro-batch under its number: a batch that runs again replaces what it wrote."""

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={number}")

    out = df.writeStream.foreachBatch(write).option("checkpointLocation", checkpoint)
    return (out.trigger(availableNow=True) if once else out).start()
