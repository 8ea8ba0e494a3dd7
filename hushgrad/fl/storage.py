"""Round tables written to the shared folder of spark.checkpoint.dir.

A round's table is written once and read by the next; a replayed task reads the
same input and sends the same message.
"""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def folder(spark: SparkSession) -> str:
    sc = spark.sparkContext
    where = sc.getConf().get("spark.checkpoint.dir", None) or spark.conf.get("spark.checkpoint.dir", None)
    if not where:
        chosen = sc._jsc.sc().getCheckpointDir()
        where = chosen.get() if chosen.isDefined() else None
    if not where:  # a session without one, as in tests
        if not sc.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that all machines share")
        where = "file://" + tempfile.mkdtemp(prefix="hushgrad-rounds-")
        sc.setCheckpointDir(where)
    return where.rstrip("/")


def _path(spark: SparkSession, text: str):  # noqa: ANN202
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(text)
    return p, p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())


def settle(df: DataFrame, name: str) -> DataFrame:
    spark = df.sparkSession
    path = f"{folder(spark)}/hushgrad-fl/{name}-{uuid.uuid4().hex}"
    p, fs = _path(spark, path)
    fs.deleteOnExit(p)
    # the files of its shuffles go when it is written, not when the driver happens to collect its garbage
    before = spark.conf.get(CLEANUP, None)
    spark.conf.set(CLEANUP, "true")
    try:
        df.write.parquet(path)
    finally:
        spark.conf.set(CLEANUP, before) if before is not None else spark.conf.unset(CLEANUP)
    return spark.read.schema(df.schema).parquet(path)


def drop(df: DataFrame) -> None:
    for where in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        if "/hushgrad-fl/" in where:
            p, fs = _path(df.sparkSession, where)
            fs.delete(p, True)
