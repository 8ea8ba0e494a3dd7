"""Tables written in the cluster's shared folder, to cut lineage.

A written Parquet table survives the loss of any executor, compresses better
than an RDD checkpoint and, being a file scan, lets the adaptive planner split
skewed joins on it.
"""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

SETTING = "spark.checkpoint.dir"


def shared_folder(spark: SparkSession) -> str:
    """The folder of spark.checkpoint.dir; a local one only where it is unset."""
    sc = spark.sparkContext
    where = sc.getConf().get(SETTING, None) or spark.conf.get(SETTING, None)
    if not where:
        chosen = sc._jsc.sc().getCheckpointDir()
        where = chosen.get() if chosen.isDefined() else None
    if not where:
        if not sc.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that all machines share")
        where = "file://" + tempfile.mkdtemp(prefix="hushgrad-")
        sc.setCheckpointDir(where)
    return where.rstrip("/")


def fresh_path(spark: SparkSession, name: str) -> str:
    """An unused path in the shared folder, deleted when the driver's JVM ends."""
    path = f"{shared_folder(spark)}/hushgrad/{name}-{uuid.uuid4().hex}"
    jvm = spark.sparkContext._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).deleteOnExit(p)
    return path


def settle(df: DataFrame, name: str) -> DataFrame:
    """Write df once as Parquet in the shared folder and return a scan of it."""
    spark = df.sparkSession
    path = fresh_path(spark, name)
    df.write.option("compression", "zstd").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def drop(df: DataFrame) -> None:
    """Delete a settled table that nothing lazy depends on any more."""
    spark = df.sparkSession
    jvm = spark.sparkContext._jvm
    for folder in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        if "/hushgrad/" in folder:
            p = jvm.org.apache.hadoop.fs.Path(folder)
            p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


BATCH_ROWS = "spark.sql.execution.arrow.maxRecordsPerBatch"
MOST_ROWS = 2000


def small_batches(spark: SparkSession) -> None:
    """At most MOST_ROWS rows in an Arrow batch of this session: documents are long rows, and a batch
    exists in the JVM and in the worker at once.  A smaller setting stays."""
    if not 0 < int(spark.conf.get(BATCH_ROWS)) <= MOST_ROWS:
        spark.conf.set(BATCH_ROWS, MOST_ROWS)


def partitions(df: DataFrame, factor: int = 1) -> int:
    """Shuffle partitions of the session, times factor."""
    return max(1, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))) * factor
