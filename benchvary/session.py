"""Session helpers: nothing here changes settings that are fixed at start."""

from __future__ import annotations

import os
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def local_session(cpus: str = "8", **conf: str) -> SparkSession:
    """A local session for tests and the bench; clusters bring their own."""
    builder = (
        SparkSession.builder.master(f"local[{cpus}]")
        .appName("benchvary")
        .config("spark.sql.shuffle.partitions", cpus)
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.driver.memory", "8g")
    )
    for key, value in conf.items():
        builder = builder.config(key, value)
    spark = builder.getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: the session's checkpoint folder.

    Only where the setting is absent and the master is local (tests, notebooks) a temporary folder is made.
    """
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not found:
        if not spark.sparkContext.master.startswith("local["):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        found = "file://" + tempfile.mkdtemp(prefix="benchvary-")
        spark.sparkContext.setCheckpointDir(found)
    return found.rstrip("/")


def scratch_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/benchvary/{spark.sparkContext.applicationId}/{name}-{uuid.uuid4().hex}"


#: Whether shuffle files go with the execution that made them; absent in older releases of Spark.
CLEAN_UP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def materialize(df: DataFrame, name: str) -> DataFrame:
    """Write df once as Parquet in the shared folder and read it back: cuts lineage and survives lost executors.

    Shuffle files of the write go when it ends, not when the driver happens to collect its garbage; a later use of df
    itself makes them again.
    """
    spark = df.sparkSession
    path = scratch_path(spark, name)
    try:
        before = spark.conf.get(CLEAN_UP)
    except Exception:  # this release doesn't know the setting
        before = None
    if before == "false":
        spark.conf.set(CLEAN_UP, "true")
    try:
        df.write.parquet(path)
    finally:
        if before == "false":
            spark.conf.set(CLEAN_UP, before)
    return spark.read.schema(df.schema).parquet(path)


#: Bytes of an Arrow batch: what a task holds several times over, outside the heap and in its Python worker.
BATCH_BYTES = 8 << 20


def modest_batches(spark: SparkSession) -> None:
    """Arrow batches of at most BATCH_BYTES from here on, unless the session asks for fewer; long texts make the default ones large."""
    key = "spark.sql.execution.arrow.maxBytesPerBatch"
    try:
        now = spark.conf.get(key)
    except Exception:  # this release doesn't know the setting
        return
    if now.endswith("b") and now[:-1].isdigit() and int(now[:-1]) > BATCH_BYTES:
        spark.conf.set(key, f"{BATCH_BYTES}b")


def forget(df: DataFrame) -> None:
    """Delete the files behind a frame made by materialize(), once nothing reads it any more."""
    spark = df.sparkSession
    jvm = spark.sparkContext._jvm
    for parent in {os.path.dirname(f) for f in df.inputFiles() if "/benchvary/" in f}:
        path = jvm.org.apache.hadoop.fs.Path(parent)
        path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def clean_up(spark: SparkSession) -> None:
    """Delete every intermediate table of this application; results that were not written elsewhere go with them."""
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{shared_dir(spark)}/benchvary/{spark.sparkContext.applicationId}")
    path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)
