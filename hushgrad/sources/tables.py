"""Loaders with asserted schemas; inference is refused."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

SCHEMAS = {
    "region": "r_regionkey int, r_name string",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
    "customer": "c_custkey bigint, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string",
    "supplier": "s_suppkey bigint, s_name string, s_nationkey int, s_acctbal double",
    "part": "p_partkey bigint, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
    "orders": "o_orderkey bigint, o_custkey bigint, o_orderstatus string, o_totalprice double, o_orderdate timestamp_ntz, o_orderpriority string",
    "lineitem": "l_orderkey bigint, l_partkey bigint, l_suppkey bigint, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, "
    "l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp_ntz",
    "events": "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string",
    "documents": "doc_id bigint, text string, lang string, source string, n_chars bigint",
    "labels": "doc_id bigint, quality int, toxic int",
    "embeddings": "vec_id bigint, embedding array<float>, label int",
    "pages": "page_id bigint, url string, html string",
    "benchmark": "item_id bigint, text string",
    "conversations": "conv_id bigint, turn bigint, role string, text string",
}


class SchemaError(ValueError):
    pass


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table, read with what its files declare and held against the asserted names and kinds.

    Widths may differ (int for bigint, float for double); names and kinds may not.
    """
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    wanted = spark.createDataFrame([], SCHEMAS[name]).schema
    kinds = {"int": "number", "bigint": "number", "float": "real", "double": "real", "array<float>": "reals", "array<double>": "reals", "timestamp_ntz": "time", "timestamp": "time"}
    kind = lambda t: kinds.get(t.simpleString(), t.simpleString())
    for field in wanted:
        if field.name not in df.columns:
            raise SchemaError(f"{name} lacks {field.name}")
        if kind(df.schema[field.name].dataType) != kind(field.dataType):
            raise SchemaError(f"{name}.{field.name} is {df.schema[field.name].dataType.simpleString()}, not {field.dataType.simpleString()}")
    return df.select(*[F.col(f.name).cast(f.dataType) for f in wanted])


def check_vectors(df: DataFrame, column: str, size: int) -> DataFrame:
    """df, after an error with counts if a vector is null, of another length, or has a null, NaN or infinite entry."""
    v = F.col(column)
    odd = F.coalesce(F.exists(v, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == F.lit(float("inf")))), F.lit(False))
    r = df.agg(
        F.count_if(v.isNull()).alias("null"), F.count_if(F.size(v) != size).alias("length"), F.count_if(odd).alias("entry")
    ).first()
    if any(r):
        raise SchemaError(f"{column}: {r['null']} null, {r['length']} of another length than {size}, {r['entry']} with a bad entry")
    return df
