"""Helpers shared by the training-data operators: reading, shared-folder staging, worker paths, sizes."""

from __future__ import annotations

import atexit
import contextlib
import ctypes
import os
import tempfile
import uuid

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

REPO_ROOT = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
#: Rows of an Arrow batch at most: whole texts, some of them long, travel in them.
BATCH = 1000
_written: list[tuple[SparkSession, str]] = []


def prepare_workers(spark: SparkSession) -> None:
    """Let Python workers import this package from where the driver found it (a no-op when it is installed there)."""
    env = spark.sparkContext.environment
    parts = [p for p in env.get("PYTHONPATH", "").split(os.pathsep) if p]
    if REPO_ROOT not in parts:
        env["PYTHONPATH"] = os.pathsep.join([REPO_ROOT, *parts])
    if int(spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")) > BATCH:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(BATCH))


def trim() -> None:
    """Give memory that a worker has freed back to the system; workers live on between tasks."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):
        ctypes.CDLL(None).malloc_trim(0)


def load(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    """One of the given tables; only Spark's reader touches the path."""
    prepare_workers(spark)
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``; a temporary one where it is unset, which only a local master allows."""
    found = spark.sparkContext.getConf().get("spark.checkpoint.dir", None)
    if not found:
        jvm = spark.sparkContext._jsc.sc().getCheckpointDir()
        if jvm.isDefined():
            return jvm.get()
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        found = "file://" + tempfile.mkdtemp(prefix="strata-shared-")
        spark.sparkContext.setCheckpointDir(found)
        return spark.sparkContext._jsc.sc().getCheckpointDir().get()
    return found.rstrip("/")


def new_path(spark: SparkSession, label: str) -> str:
    path = f"{shared_dir(spark)}/strata-{label}-{uuid.uuid4().hex}"
    _written.append((spark, path))
    return path


def remove_path(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    where = jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)
    _written[:] = [x for x in _written if x[1] != path]


@atexit.register
def _forget() -> None:
    for spark, path in list(_written):
        with contextlib.suppress(Exception):  # the session may be gone; the folder then goes with the application's
            remove_path(spark, path)


def stage(df: DataFrame, label: str) -> tuple[DataFrame, str]:
    """Write ``df`` into the shared folder and read it back: cuts lineage, survives lost executors."""
    spark = df.sparkSession
    path = new_path(spark, label)
    df.write.option("compression", "zstd").parquet(path)
    return spark.read.schema(df.schema).parquet(path), path


def text_bytes(df: DataFrame, text_col: str) -> int:
    """Total UTF-8 bytes of a text column; one column-pruned pass."""
    return df.agg(F.sum(F.octet_length(F.coalesce(F.col(text_col).cast("string"), F.lit(""))).cast("long")).alias("b")).first()["b"] or 0


def parts(spark: SparkSession) -> int:
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))


def bucket_of(id_col: str, modulus: int):
    """crc32 of the id as text, modulo ``modulus``: the folds that the contracts fix."""
    return F.crc32(F.col(id_col).cast("string").cast("binary")) % F.lit(modulus)
