"""SQL surface: views, SQL functions and a table function, so that a round can be written in SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hushgrad.plans import native as nt
from hushgrad.plans import oracle
from hushgrad.sources.tables import load

FUNCTIONS = {
    "hg_uniform": "(k STRING) RETURNS DOUBLE RETURN CAST(conv(substring(md5(k), 1, 13), 16, 10) AS DOUBLE) / 4503599627370496D",
    "hg_dot": "(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, v) -> s + v)",
    "hg_clip_scale": "(n DOUBLE, g DOUBLE) RETURNS DOUBLE RETURN CASE WHEN n > g THEN g / n ELSE 1D END",
    "hg_shift_step": "(w DOUBLE) RETURNS DOUBLE RETURN sqrt((1 + 2 * w) / (2 * power(1 + w, 3)))",
}


@F.udtf(returnType="coord int, value double")
class ExpandMessage:
    """A packed message, "coord:value,..." , as rows."""

    def eval(self, packed: str):  # noqa: ANN201
        for part in (packed or "").split(","):
            if part:
                c, v = part.split(":")
                yield int(c), float(v)


def register(spark: SparkSession, sf_dir: str) -> None:
    for name, body in FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name} {body}")
    spark.udtf.register("hg_expand_message", ExpandMessage)
    nt.samples(spark, sf_dir).createOrReplaceTempView("hg_samples")


def sql_margins(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Margins of the samples at the start model, in SQL."""
    register(spark, sf_dir)
    x = ", ".join(f"{v!r}D" for v in nt.START)
    return spark.sql(f"SELECT client_id, count_if(hg_dot(f, array({x})) * y > 0) AS right, count(*) AS n FROM hg_samples GROUP BY client_id")


def shift_step_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The step of the reference for each message size: as many of 123 coordinates as a line's quantity says."""
    register(spark, sf_dir)
    load(spark, sf_dir, "lineitem").createOrReplaceTempView("hg_message_sizes")
    return spark.sql("SELECT w AS omega, round(hg_shift_step(w), 9) AS gamma FROM (SELECT DISTINCT 123D / l_quantity - 1D AS w FROM hg_message_sizes WHERE l_quantity BETWEEN 1 AND 123)")


def udtf_expand_message(spark: SparkSession, sf_dir: str) -> DataFrame:
    register(spark, sf_dir)
    load(spark, sf_dir, "orders").createOrReplaceTempView("hg_message_orders")
    return spark.sql(
        "SELECT o_orderstatus, coord, count(*) AS n, sum(CAST(value AS BIGINT)) AS total FROM (SELECT o_orderstatus, concat('0:', o_orderkey % 7, ',1:', o_orderkey % 5) AS packed "
        "FROM hg_message_orders), LATERAL hg_expand_message(packed) GROUP BY o_orderstatus, coord"
    )


QUERIES = {"sql_margins": sql_margins, "shift_step_table": shift_step_table, "udtf_expand_message": udtf_expand_message}
SQL = {
    "sql_margins": f"WITH {oracle.SAMPLES} SELECT client_id, count(*) FILTER ({oracle.dot('f', oracle.vec(nt.START))} * y > 0) AS right, count(*) AS n FROM samples GROUP BY 1",
    "shift_step_table": "SELECT w AS omega, round(sqrt((1 + 2 * w) / (2 * pow(1 + w, 3))), 9) AS gamma FROM (SELECT DISTINCT 123.0::DOUBLE / l_quantity - 1.0::DOUBLE AS w FROM lineitem WHERE l_quantity BETWEEN 1 AND 123)",
    "udtf_expand_message": """SELECT o_orderstatus, coord, count(*) AS n, CAST(sum(value) AS BIGINT) AS total FROM (SELECT o_orderstatus, 0::INTEGER AS coord, o_orderkey % 7 AS value FROM orders
      UNION ALL SELECT o_orderstatus, 1::INTEGER, o_orderkey % 5 FROM orders) GROUP BY 1, 2""",
}
