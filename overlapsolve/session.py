"""Session helpers: a local session for tests, and the folder that driver and executors share."""

from __future__ import annotations

import os
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def local_session(cores: int | str = "*", shuffle_partitions: int = 8) -> SparkSession:
    """A session for tests and benchmarks on one machine; clusters bring their own."""
    return (
        SparkSession.builder.master(f"local[{cores}]")
        .config("spark.sql.shuffle.partitions", str(shuffle_partitions))
        .config("spark.ui.enabled", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.driver.memory", os.environ.get("OVERLAPSOLVE_DRIVER_MEMORY", "8g"))
        .config("spark.checkpoint.dir", tempfile.mkdtemp(prefix="overlapsolve-ckpt-"))
        .getOrCreate()
    )


def shared_dir(spark: SparkSession) -> str:
    """The folder in spark.checkpoint.dir. A local session without one gets a temporary folder; on a cluster it has to be named."""
    sc = spark.sparkContext
    path = spark.conf.get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if path is None:
        if not sc.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
        path = tempfile.mkdtemp(prefix="overlapsolve-ckpt-")
    if sc.getCheckpointDir() is None:
        sc.setCheckpointDir(path)
    return path


def scratch(spark: SparkSession) -> str:
    """Where this application writes its intermediate tables, within the shared folder."""
    return f"{shared_dir(spark)}/overlapsolve-{spark.sparkContext.applicationId}"


def checkpoint(df: DataFrame) -> DataFrame:
    """df written to the shared folder as Parquet and read back: lineage is cut, and a lost executor costs a reread.

    Sizes are then those of the files. Spark's own checkpoint keeps the estimate of the plan that made it, which grows
    with the square of itself in a loop that joins its iterate with itself.
    """
    if "_written" in df.__dict__:
        return df
    spark = df.sparkSession
    path = f"{scratch(spark)}/{uuid.uuid4().hex}"
    df.write.parquet(path)
    back = spark.read.schema(df.schema).parquet(path)
    back._written = path
    return back


def together(frames: list[DataFrame]) -> DataFrame:
    """The rows of several checkpoints of one schema, by a single scan however many there are."""
    spark = frames[0].sparkSession
    return spark.read.schema(frames[0].schema).parquet(*[df._written for df in frames])


def discard(*frames: DataFrame) -> None:
    """Delete the files of checkpoints that nothing refers to any more. A frame that is no checkpoint is left alone."""
    for df in frames:
        path = df.__dict__.pop("_written", None)
        if path:
            remove(df.sparkSession, path)


def remove(spark: SparkSession, path: str) -> None:
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


def clean(spark: SparkSession) -> None:
    """Delete all that this application has written to the shared folder; results that haven't been read yet go too."""
    remove(spark, scratch(spark))
