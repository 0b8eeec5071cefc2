"""Scratch tables in the folder that driver and executors share."""

from __future__ import annotations

import re
import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

BATCH_BYTES = 6 << 20
_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def shared_dir(spark: SparkSession) -> str:
    """A fresh folder URI below ``spark.checkpoint.dir``, removed at JVM exit.  A
    temporary folder of this machine only where the session names none and runs
    in this one process (tests); a cluster without the setting is refused."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not re.match(r"local(\[|$)", spark.sparkContext.master):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        base = "file://" + tempfile.gettempdir() + "/checkpoints"
    path = f"{base.rstrip('/')}/tickspace-{uuid.uuid4().hex}"
    jvm = spark._jvm
    hpath = jvm.org.apache.hadoop.fs.Path(path)
    fs = hpath.getFileSystem(spark._jsc.hadoopConfiguration())
    fs.mkdirs(hpath)
    fs.deleteOnExit(hpath)
    full = fs.makeQualified(hpath).toString()
    return re.sub("^file:/+", "file:///", full)


def remove(spark: SparkSession, path: str) -> None:
    hpath = spark._jvm.org.apache.hadoop.fs.Path(path)
    hpath.getFileSystem(spark._jsc.hadoopConfiguration()).delete(hpath, True)


def bounded(df: DataFrame) -> DataFrame:
    """``df``, whose session will hand Python batches of some megabytes at most:
    whatever the length of the texts, a worker holds little at a time."""
    conf = df.sparkSession.conf
    if int(str(conf.get("spark.sql.execution.arrow.maxBytesPerBatch")).rstrip("b")) > BATCH_BYTES:
        conf.set("spark.sql.execution.arrow.maxBytesPerBatch", f"{BATCH_BYTES}b")
    return df


@contextmanager
def _freeing(spark: SparkSession) -> Iterator[None]:
    """Shuffle files of the jobs within go as soon as a job is done, not when the
    driver happens to collect its garbage: what it wrote replaces them."""
    before = spark.conf.get(_CLEANUP, None)
    spark.conf.set(_CLEANUP, "true")
    try:
        yield
    finally:
        spark.conf.unset(_CLEANUP) if before is None else spark.conf.set(_CLEANUP, before)


def materialise(df: DataFrame, name: str = "t", base: str | None = None) -> DataFrame:
    """Write ``df`` as Parquet to the shared folder and read it back: cuts the
    lineage in a way that survives the loss of any executor."""
    spark = df.sparkSession
    path = f"{base or shared_dir(spark)}/{name}"
    with _freeing(spark):
        df.write.mode("overwrite").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
