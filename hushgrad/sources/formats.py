"""Samples in other formats, and partitioned, idempotent sinks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hushgrad.fl import storage
from hushgrad.sources.tables import load

ROW = "l_orderkey bigint, l_linenumber int, l_quantity double, l_returnflag string"


def _part(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_quantity", "l_returnflag")


def _fresh(spark: SparkSession, name: str) -> str:
    import uuid

    path = f"{storage.folder(spark)}/hushgrad-fl/{name}-{uuid.uuid4().hex}"
    p, fs = storage._path(spark, path)
    fs.deleteOnExit(p)
    return path


def _summary(df: DataFrame) -> DataFrame:
    return df.groupBy("l_returnflag").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("l_quantity").cast("long")).alias("qty"), F.sum("l_orderkey").alias("keys"))


def _through(kind: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        path = _fresh(spark, kind)
        _part(spark, sf_dir).write.format(kind).save(path)
        return _summary(spark.read.format(kind).schema(ROW).load(path))

    run.__name__ = f"roundtrip_{kind}"
    return run


def write_sparse(df: DataFrame, path: str) -> None:
    """label idx:val ... lines, indices from 1, zeros left out."""
    pairs = F.zip_with(F.sequence(F.lit(1), F.size("features")), "features", lambda i, v: F.when(v != 0, F.concat_ws(":", i, v)))
    df.select(F.concat_ws(" ", F.col("label").cast("int").cast("string"), F.array_join(F.array_compact(pairs), " "))).write.text(path)


def read_sparse(spark: SparkSession, path: str, size: int) -> DataFrame:
    """(label, features): dense vectors of the given size; an index beyond it is an error in the data and fails the read."""
    parts = F.split("value", " ")
    pairs = F.transform(F.filter(F.slice(parts, 2, F.greatest(F.size(parts) - 1, F.lit(0))), lambda x: x != ""), lambda x: F.split(x, ":"))
    m = F.map_from_entries(F.transform(pairs, lambda p: F.struct(p[0].cast("int"), p[1].cast("double"))))
    rows = spark.read.text(path).select(parts[0].cast("double").alias("label"), m.alias("m"))
    bad = F.exists(F.map_keys("m"), lambda k: (k < 1) | (k > size))
    dense = F.transform(F.sequence(F.lit(1), F.lit(size)), lambda i: F.coalesce(F.element_at("m", i), F.lit(0.0)))
    return rows.select("label", F.when(bad, F.raise_error(F.lit("an index is out of range"))).otherwise(dense).alias("features"))


def roundtrip_sparse(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = load(spark, sf_dir, "lineitem").select(
        F.when(F.col("l_returnflag") == "R", 1.0).otherwise(-1.0).alias("label"),
        F.array(F.col("l_quantity"), F.lit(0.0), F.col("l_linenumber").cast("double")).alias("features"),
    )
    path = _fresh(spark, "sparse")
    write_sparse(rows, path)
    back = read_sparse(spark, path, 3)
    return back.groupBy("label").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("features")[0].cast("long")).alias("qty"), F.sum(F.col("features")[2].cast("long")).alias("lines"))


def write_trace(trace: DataFrame, path: str) -> None:
    """A trace by run; writing a run again replaces its rows and no others."""
    trace.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("run").parquet(path)


def sink_trace(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Writes a table by run twice; the second write of a run replaces the first."""
    path = _fresh(spark, "trace")
    o = load(spark, sf_dir, "orders").select(F.col("o_orderstatus").alias("run"), "o_orderkey")
    write_trace(o, path)
    write_trace(o.filter("run = 'F'"), path)
    return spark.read.parquet(path).groupBy("run").agg(F.count(F.lit(1)).alias("n"), F.sum("o_orderkey").alias("keys"))


def bucketed(df: DataFrame, name: str, key: str, buckets: int = 8) -> str:
    """df as a table bucketed and sorted by key, in a folder of its own; tables bucketed alike join without a shuffle."""
    path = _fresh(df.sparkSession, name)
    table = f"{name}_{path[-32:]}"
    df.write.bucketBy(buckets, key).sortBy(key).option("path", path).format("parquet").saveAsTable(table)
    return table


def bucketed_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Lines and orders bucketed by order, joined bucket by bucket (merge hint: neither side is to be broadcast)."""
    li = bucketed(load(spark, sf_dir, "lineitem").select("l_orderkey", "l_quantity"), "hg_lines", "l_orderkey")
    o = bucketed(load(spark, sf_dir, "orders").select("o_orderkey", "o_orderstatus"), "hg_orders", "o_orderkey")
    j = spark.table(li).join(spark.table(o).hint("merge"), F.col("l_orderkey") == F.col("o_orderkey"))
    return j.groupBy("o_orderstatus").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("l_quantity").cast("long")).alias("qty"))


QUERIES = {f.__name__: f for f in (bucketed_join, *(_through(k) for k in ("csv", "json", "orc", "parquet")), roundtrip_sparse, sink_trace)}
_SUMMARY = "SELECT l_returnflag, count(*) AS n, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS qty, CAST(sum(l_orderkey) AS BIGINT) AS keys FROM lineitem GROUP BY 1"
SQL = {f"roundtrip_{k}": _SUMMARY for k in ("csv", "json", "orc", "parquet")} | {
    "roundtrip_sparse": """SELECT (CASE WHEN l_returnflag = 'R' THEN 1.0 ELSE -1.0 END)::DOUBLE AS label, count(*) AS n, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS qty,
      CAST(sum(l_linenumber) AS BIGINT) AS lines FROM lineitem GROUP BY 1""",
    "bucketed_join": "SELECT o_orderstatus, count(*) AS n, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS qty FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1",
    "sink_trace": "SELECT o_orderstatus AS run, count(*) AS n, CAST(sum(o_orderkey) AS BIGINT) AS keys FROM orders GROUP BY 1",
}
