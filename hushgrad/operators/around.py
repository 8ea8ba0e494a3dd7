"""Operators around training: features, clients, joins, windows, cubes, text, time, and their SQL."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hushgrad.functions import digest
from hushgrad.sources.tables import load


def scan_samples(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pruned scan with a pushed filter."""
    li = load(spark, sf_dir, "lineitem").filter((F.col("l_quantity") >= 25) & F.col("l_returnflag").isin("R", "A"))
    return li.groupBy("l_returnflag").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("l_quantity").cast("long")).alias("qty"))


def features_onehot(spark: SparkSession, sf_dir: str) -> DataFrame:
    li = load(spark, sf_dir, "lineitem")
    hot = [F.sum((F.col("l_returnflag") == v).cast("int")).alias(f"flag_{v.lower()}") for v in "ANR"]
    hot += [F.sum((F.col("l_linestatus") == v).cast("int")).alias(f"status_{v.lower()}") for v in "FO"]
    return li.groupBy(F.width_bucket("l_quantity", F.lit(0.0), F.lit(50.0), F.lit(10)).cast("int").alias("qty_bucket")).agg(*hot)


def features_scaled(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Standardised quantity by return flag, over the whole table's mean and deviation (one row, broadcast)."""
    li = load(spark, sf_dir, "lineitem")
    m = li.agg(F.avg("l_quantity").alias("mu"), F.stddev_pop("l_quantity").alias("sd"))
    z = li.crossJoin(F.broadcast(m)).withColumn("z", (F.col("l_quantity") - F.col("mu")) / F.col("sd"))
    return z.groupBy("l_returnflag").agg(F.round(F.avg("z"), 5).alias("mean_z"), F.round(F.max("z"), 5).alias("max_z"))


def split_train_test(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A fifth of the documents, by digest, is for testing."""
    d = load(spark, sf_dir, "documents")
    test = digest.uniform("split", F.col("doc_id")) < 0.2
    return d.groupBy(F.when(test, "test").otherwise("train").alias("part"), "lang").agg(F.count(F.lit(1)).alias("n"))


def assign_clients_hash(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ten clients of equal size: rank of a digest, modulo ten.  The rank comes from digest buckets
    and the counts before them, so no task sorts the whole table."""
    d = load(spark, sf_dir, "documents").select("doc_id", digest.uniform("client", F.col("doc_id")).alias("u"))
    d = d.withColumn("bucket", F.floor(F.col("u") * 4096))
    counts = d.groupBy("bucket").agg(F.count(F.lit(1)).alias("n"))
    before = counts.select("bucket", F.expr("coalesce(sum(n) over (order by bucket rows between unbounded preceding and 1 preceding), 0L)").alias("before"))
    ranked = d.withColumn("r", F.expr("row_number() over (partition by bucket order by u, doc_id)")).join(F.broadcast(before), "bucket")
    return ranked.select("doc_id", ((F.col("before") + F.col("r") - 1) % 10).cast("long").alias("client_id"))


def assign_clients_natural(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Clients by supplier, of unequal size, with weights n * m_i / sum of m."""
    m = load(spark, sf_dir, "lineitem").groupBy(F.col("l_suppkey").alias("client_id")).agg(F.count(F.lit(1)).alias("m"))
    total = m.agg(F.count(F.lit(1)).alias("n"), F.sum("m").alias("total"))
    return m.crossJoin(F.broadcast(total)).select("client_id", "m", F.round(F.col("n") * F.col("m") / F.col("total"), 6).alias("weight"))


def join_star_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    li, o, c, p = (load(spark, sf_dir, t) for t in ("lineitem", "orders", "customer", "part"))
    wide = (
        li.join(o, li["l_orderkey"] == o["o_orderkey"]).join(c, F.col("o_custkey") == F.col("c_custkey")).join(p, F.col("l_partkey") == F.col("p_partkey"))
    )
    return wide.groupBy("c_mktsegment", "o_orderpriority").agg(
        F.count(F.lit(1)).alias("n"), F.sum(F.col("l_quantity").cast("long")).alias("qty"), F.sum("p_size").cast("long").alias("size_sum")
    )


def labelled_docs(spark: SparkSession, sf_dir: str) -> DataFrame:
    d, lab = load(spark, sf_dir, "documents"), load(spark, sf_dir, "labels")
    j = d.join(lab, "doc_id", "left")
    return j.groupBy("lang", F.coalesce("quality", F.lit(-1)).alias("quality")).agg(F.count(F.lit(1)).alias("n"), F.sum("n_chars").alias("chars"))


def unlabelled_docs(spark: SparkSession, sf_dir: str) -> DataFrame:
    d, lab = load(spark, sf_dir, "documents"), load(spark, sf_dir, "labels")
    return d.join(lab, "doc_id", "left_anti").groupBy("source").agg(F.count(F.lit(1)).alias("n"))


def labelled_semi(spark: SparkSession, sf_dir: str) -> DataFrame:
    d, lab = load(spark, sf_dir, "documents"), load(spark, sf_dir, "labels")
    return d.join(lab.filter("toxic = 1"), "doc_id", "left_semi").select("doc_id", "lang", "n_chars")


def outer_suppliers(spark: SparkSession, sf_dir: str) -> DataFrame:
    s, c = load(spark, sf_dir, "supplier"), load(spark, sf_dir, "customer")
    a = s.groupBy(F.col("s_nationkey").alias("k")).agg(F.count(F.lit(1)).alias("suppliers"))
    b = c.groupBy(F.col("c_nationkey").alias("k")).agg(F.count(F.lit(1)).alias("customers"))
    return a.join(b, "k", "full").select("k", F.coalesce("suppliers", F.lit(0)).alias("suppliers"), F.coalesce("customers", F.lit(0)).alias("customers"))


MODELS = [(0, 0.5, -0.2), (1, -0.3, 0.4), (2, 0.1, 0.1)]


def predict_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every model against every line; the models are three rows."""
    li = load(spark, sf_dir, "lineitem")
    m = spark.createDataFrame(MODELS, "model int, a double, b double")
    z = F.col("a") * F.col("l_quantity") / 50.0 + F.col("b") * F.col("l_discount") * 10.0
    return li.crossJoin(F.broadcast(m)).groupBy("model").agg(F.count_if(z > 0.1).alias("positive"), F.count(F.lit(1)).alias("n"))


def events_in_round(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events within ten minutes after a purchase of the same user: a range join by time slots.

    A purchase opens two slots at most, and an event looks in its own."""
    e = load(spark, sf_dir, "events").withColumn("s", F.unix_micros(F.col("ts").cast("timestamp")))
    span = 600_000_000
    slot = lambda c: F.floor(c / F.lit(span))
    p = e.filter("event_type = 'purchase'").select(F.col("event_id").alias("round_id"), F.col("user_id").alias("u"), F.col("s").alias("s0"))
    p = p.withColumn("slot0", F.explode(F.array(slot(F.col("s0")), slot(F.col("s0")) + 1)))
    j = e.withColumn("slot", slot(F.col("s"))).join(p, (F.col("user_id") == F.col("u")) & (F.col("slot") == F.col("slot0")))
    inside = j.filter((F.col("s") > F.col("s0")) & (F.col("s") <= F.col("s0") + span))
    return inside.groupBy("round_id").agg(F.count(F.lit(1)).alias("n"))


def asof_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    """For each click the user's last purchase at or before it: union and a running last value."""
    e = load(spark, sf_dir, "events")
    u = e.select("user_id", "ts", "event_id", "event_type", F.when(F.col("event_type") == "purchase", F.col("event_id")).alias("p"))
    w = "partition by user_id order by ts, case when event_type = 'purchase' then 0 else 1 end, event_id rows between unbounded preceding and current row"
    return u.withColumn("model_id", F.expr(f"last_value(p, true) over ({w})")).filter("event_type = 'click'").select("event_id", "model_id")


def cost_rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = load(spark, sf_dir, "orders")
    return o.rollup("o_orderstatus", "o_orderpriority").agg(F.count(F.lit(1)).alias("n"), F.grouping_id().cast("long").alias("level"))


def cost_cube(spark: SparkSession, sf_dir: str) -> DataFrame:
    li = load(spark, sf_dir, "lineitem")
    return li.cube("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("l_quantity").cast("long")).alias("qty"))


def cost_grouping_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    load(spark, sf_dir, "lineitem").createOrReplaceTempView("hg_lines")
    return spark.sql(
        "SELECT l_returnflag, l_linenumber, count(*) AS n FROM hg_lines GROUP BY GROUPING SETS ((l_returnflag), (l_linenumber), ())"
    )


def best_stepsize(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The best value per group: the discount with the highest mean quantity for each flag, with ranks."""
    li = load(spark, sf_dir, "lineitem")
    m = li.groupBy("l_returnflag", F.round(F.col("l_discount") * 100).cast("int").alias("step")).agg((F.sum(F.col("l_quantity").cast("long")) / F.count(F.lit(1))).alias("score"))
    r = m.withColumn("rank", F.expr("rank() over (partition by l_returnflag order by score desc, step)")).withColumn(
        "dense", F.expr("dense_rank() over (partition by l_returnflag order by score desc, step)")
    )
    return r.filter("rank <= 3").select("l_returnflag", "step", F.round("score", 6).alias("score"), F.col("rank").cast("long").alias("rank"), F.col("dense").cast("long").alias("dense"))


def trace_running(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Running mean, lag and three-row moving range of each user's values, in order."""
    e = load(spark, sf_dir, "events").withColumn("v", F.round(F.col("value") * 100).cast("long"))
    w = "partition by user_id order by ts, event_id"
    return e.select(
        "event_id",
        F.round(F.expr(f"sum(v) over ({w} rows between unbounded preceding and current row) / count(v) over ({w} rows between unbounded preceding and current row)"), 4).alias("running_mean"),
        F.expr(f"v - lag(v) over ({w})").alias("step"),
        F.expr(f"max(v) over ({w} rows between 2 preceding and current row) - min(v) over ({w} rows between 2 preceding and current row)").alias("spread"),
    )


def trace_pivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = load(spark, sf_dir, "events")
    kinds = ["click", "error", "purchase", "view"]
    return e.groupBy(F.hour("ts").cast("long").alias("hour")).pivot("event_type", kinds).agg(F.count(F.lit(1))).select(
        "hour", *[F.coalesce(k, F.lit(0)).alias(k) for k in kinds]
    )


def hashed_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Lower-case words hashed to 122 places."""
    d = load(spark, sf_dir, "documents").select("lang", F.explode(F.split(F.lower("text"), "[ \\n]+")).alias("w")).filter("w <> ''")
    place = (F.conv(F.substring(F.md5("w"), 1, 8), 16, 10).cast("long") % 122).alias("place")
    return d.groupBy("lang", place).agg(F.count(F.lit(1)).alias("n"))


def time_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = load(spark, sf_dir, "orders")
    return o.groupBy(F.year("o_orderdate").cast("long").alias("y"), F.month("o_orderdate").cast("long").alias("m")).agg(
        F.count(F.lit(1)).alias("n"), F.sum(F.datediff(F.col("o_orderdate").cast("date"), F.lit("1992-01-01").cast("date"))).cast("long").alias("days")
    )


def json_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = load(spark, sf_dir, "events")
    k = F.get_json_object("props", "$.k").cast("long")
    return e.groupBy("event_type").agg(F.sum(k).alias("k_sum"), F.max(k).alias("k_max"))


def page_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Tags and entities out, runs of white space to one blank, then words."""
    p = load(spark, sf_dir, "pages")
    text = F.regexp_replace(F.regexp_replace("html", "<[^>]*>", " "), "&[a-z#0-9]+;", " ")
    words = F.filter(F.split(F.regexp_replace(text, "[ \\t\\n\\r]+", " "), " "), lambda w: w != "")
    return p.select("page_id", F.size(words).cast("long").alias("n_words"), F.char_length("html").cast("long").alias("n_html"))


def conversation_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Turns in order as one text for each conversation."""
    c = load(spark, sf_dir, "conversations").groupBy("conv_id").agg(F.array_sort(F.collect_list(F.struct("turn", "role", "text"))).alias("z"))
    return c.select(
        "conv_id", F.size("z").cast("long").alias("turns"), F.md5(F.concat_ws("\n", F.transform("z", lambda t: F.concat_ws(": ", t["role"], t["text"])))).alias("text_md5")
    )


def window_tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The batch twin of the tumbling-window stream."""
    e = load(spark, sf_dir, "events").withColumn("t", F.col("ts").cast("timestamp"))
    g = e.groupBy(F.window("t", "1 hour").alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return g.select(F.unix_seconds("w.start").alias("start"), "event_type", "n")


def window_sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = load(spark, sf_dir, "events").withColumn("t", F.col("ts").cast("timestamp"))
    g = e.groupBy(F.window("t", "2 hours", "1 hour").alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return g.select(F.unix_seconds("w.start").alias("start"), "n")


def window_session(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sessions of a user: events less than six hours apart."""
    e = load(spark, sf_dir, "events").withColumn("t", F.col("ts").cast("timestamp"))
    g = e.groupBy("user_id", F.session_window("t", "6 hours").alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return g.groupBy("user_id").agg(F.count(F.lit(1)).alias("sessions"), F.max("n").alias("longest"))


def late_messages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events that arrive (in id order) more than an hour behind the latest time seen so far, by user."""
    e = load(spark, sf_dir, "events").withColumn("s", F.unix_micros(F.col("ts").cast("timestamp")))
    seen = F.expr("max(s) over (partition by user_id order by event_id rows between unbounded preceding and current row)")
    return e.withColumn("seen", seen).groupBy("user_id").agg(F.count_if(F.col("s") < F.col("seen") - 3_600_000_000).alias("late"), F.count(F.lit(1)).alias("n"))


def map_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = load(spark, sf_dir, "customer").groupBy("c_nationkey").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("c_custkey", "c_mktsegment")))).alias("m"))
    return c.select("c_nationkey", F.size("m").cast("long").alias("n"), F.array_min(F.map_keys("m")).alias("first_key"))


def scalar_subquery(spark: SparkSession, sf_dir: str) -> DataFrame:
    load(spark, sf_dir, "orders").createOrReplaceTempView("hg_orders")
    load(spark, sf_dir, "customer").createOrReplaceTempView("hg_customer")
    return spark.sql(
        """SELECT c_mktsegment, count(*) AS n FROM hg_customer c WHERE EXISTS (SELECT 1 FROM hg_orders o WHERE o.o_custkey = c.c_custkey AND o.o_orderstatus = 'F')
        AND c_acctbal > (SELECT avg(c_acctbal) FROM hg_customer) GROUP BY c_mktsegment"""
    )


def approx_clients(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Exact and sketched numbers of customers; the sketch is held to a tenth of the exact number."""
    o = load(spark, sf_dir, "orders").groupBy("o_orderstatus").agg(F.countDistinct("o_custkey").alias("exact"), F.approx_count_distinct("o_custkey", 0.02).alias("near"))
    return o.select("o_orderstatus", "exact", (F.abs(F.col("near") - F.col("exact")) <= 0.1 * F.col("exact")).alias("close"))


def joint_moments(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Covariance and correlation of two features, and a sketched median held to the exact one."""
    return load(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(
        F.round(F.covar_pop("l_quantity", "l_discount"), 6).alias("cov"), F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("cor"),
        (F.abs(F.percentile_approx("l_quantity", 0.5, 10_000) - F.percentile("l_quantity", 0.5)) <= 1).alias("median_close"),
    )


def rank_shares(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Quarters and relative ranks of a user's events by value."""
    w = "partition by user_id order by value, event_id"
    return load(spark, sf_dir, "events").select("event_id", F.expr(f"ntile(4) over ({w})").cast("long").alias("quarter"), F.round(F.expr(f"percent_rank() over ({w})"), 9).alias("share"))


def frame_values(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The first value and the next one of a user, and the sum over the hour before, by time."""
    e = load(spark, sf_dir, "events").withColumn("v", F.round(F.col("value") * 100).cast("long")).withColumn("s", F.unix_seconds(F.col("ts").cast("timestamp")))
    w = "partition by user_id order by ts, event_id"
    return e.select(
        "event_id", F.expr(f"first_value(v) over ({w})").alias("first_v"), F.expr(f"lead(v) over ({w})").alias("next_v"),
        F.expr("sum(v) over (partition by user_id order by s range between 3600 preceding and current row)").alias("hour_sum"),
    )


def top_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The ten dearest orders: a limit over an order, which each task answers with ten rows."""
    return load(spark, sf_dir, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(10).select("o_orderkey", F.round("o_totalprice", 2).alias("price"))


def best_by_status(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The dearest order of each status, without sorting."""
    by = F.struct("o_totalprice", -F.col("o_orderkey"))
    return load(spark, sf_dir, "orders").groupBy("o_orderstatus").agg(F.max_by("o_orderkey", by).alias("o_orderkey"))


def trace_unpivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The pivoted counts back in long form."""
    return trace_pivot(spark, sf_dir).unpivot("hour", ["click", "error", "purchase", "view"], "event_type", "n").filter("n > 0")


def json_structs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Properties read as a struct, and a struct of two fields written as JSON."""
    e = load(spark, sf_dir, "events").select("event_id", F.from_json("props", "k bigint").alias("p"))
    return e.select("event_id", F.to_json(F.struct(F.col("p.k").alias("k"), (F.col("p.k") % 3).alias("r"))).alias("j"))


def arrow_scale(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A scalar function over Arrow arrays: clip factors of quantities at half of the largest."""

    @F.arrow_udf("double")
    def scale(v: pa.Array) -> pa.Array:
        return pa.array(np.minimum(1.0, 25.0 / v.to_numpy(zero_copy_only=False)))

    return load(spark, sf_dir, "lineitem").groupBy("l_linenumber").agg(F.sum(F.round(scale("l_quantity") * 1_000_000).cast("long")).alias("micro"))


def arrow_groups(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A grouped function over Arrow tables: a nation's customers, with the largest balance.  Nations bound a group's number, not its size;
    `best_by_status` is the form for large groups."""

    def largest(t: pa.Table) -> pa.Table:
        return pa.table({"c_nationkey": t.column("c_nationkey")[:1], "n": [t.num_rows], "top": [pc.max(t.column("c_acctbal")).as_py()]})

    return load(spark, sf_dir, "customer").select("c_nationkey", "c_acctbal").groupBy("c_nationkey").applyInArrow(largest, "c_nationkey int, n bigint, top double")


NAMES = [
    approx_clients, joint_moments, rank_shares, frame_values, top_orders, best_by_status, trace_unpivot, json_structs, arrow_scale, arrow_groups,
    scan_samples, features_onehot, features_scaled, split_train_test, assign_clients_hash, assign_clients_natural, join_star_features, labelled_docs,
    unlabelled_docs, labelled_semi, outer_suppliers, predict_grid, events_in_round, asof_model, cost_rollup, cost_cube, cost_grouping_sets, best_stepsize,
    trace_running, trace_pivot, hashed_tokens, time_features, json_features, page_tokens, conversation_features, window_tumbling, window_sliding,
    window_session, late_messages, map_features, scalar_subquery,
]
QUERIES = {f.__name__: f for f in NAMES}

_U = "(CAST('0x' || substr(md5(concat_ws('|', {})), 1, 13) AS BIGINT) / 4503599627370496.0)"
_SPLIT, _CLIENT = _U.format("'split', doc_id"), _U.format("'client', doc_id")

SQL = {
    "approx_clients": "SELECT o_orderstatus, count(DISTINCT o_custkey) AS exact, true AS close FROM orders GROUP BY 1",
    "joint_moments": "SELECT l_returnflag, round(covar_pop(l_quantity, l_discount), 6) AS cov, round(corr(l_quantity, l_extendedprice), 6) AS cor, true AS median_close FROM lineitem GROUP BY 1",
    "rank_shares": "SELECT event_id, ntile(4) OVER w AS quarter, round(percent_rank() OVER w, 9) AS share FROM events WINDOW w AS (PARTITION BY user_id ORDER BY value, event_id)",
    "frame_values": """WITH e AS (SELECT *, CAST(round(value * 100) AS BIGINT) AS v, CAST(floor(epoch(ts)) AS BIGINT) AS s FROM events)
      SELECT event_id, first_value(v) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS first_v, lead(v) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS next_v,
      CAST(sum(v) OVER (PARTITION BY user_id ORDER BY s RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS BIGINT) AS hour_sum FROM e""",
    "top_orders": "SELECT o_orderkey, round(o_totalprice, 2) AS price FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10",
    "best_by_status": "SELECT o_orderstatus, o_orderkey FROM (SELECT *, row_number() OVER (PARTITION BY o_orderstatus ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) WHERE r = 1",
    "trace_unpivot": "SELECT hour(ts) AS hour, event_type, count(*) AS n FROM events WHERE event_type IN ('click', 'error', 'purchase', 'view') GROUP BY 1, 2",
    "json_structs": """WITH e AS (SELECT event_id, CAST(regexp_extract(props, '"k": *([0-9]+)', 1) AS BIGINT) AS k FROM events) SELECT event_id, '{"k":' || k || ',"r":' || (k % 3) || '}' AS j FROM e""",
    "arrow_scale": "SELECT l_linenumber, CAST(sum(CAST(round(least(1.0, 25.0 / l_quantity) * 1000000) AS BIGINT)) AS BIGINT) AS micro FROM lineitem GROUP BY 1",
    "arrow_groups": "SELECT c_nationkey, count(*) AS n, max(c_acctbal) AS top FROM customer GROUP BY 1",
    "scan_samples": "SELECT l_returnflag, count(*) AS n, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS qty FROM lineitem WHERE l_quantity >= 25 AND l_returnflag IN ('R', 'A') GROUP BY 1",
    "features_onehot": """SELECT CAST(CASE WHEN l_quantity >= 50 THEN 11 ELSE floor(l_quantity / 5.0) + 1 END AS INTEGER) AS qty_bucket,
      count(*) FILTER (l_returnflag = 'A') AS flag_a, count(*) FILTER (l_returnflag = 'N') AS flag_n, count(*) FILTER (l_returnflag = 'R') AS flag_r,
      count(*) FILTER (l_linestatus = 'F') AS status_f, count(*) FILTER (l_linestatus = 'O') AS status_o FROM lineitem GROUP BY 1""",
    "features_scaled": """WITH m AS (SELECT avg(l_quantity) AS mu, stddev_pop(l_quantity) AS sd FROM lineitem)
      SELECT l_returnflag, round(avg((l_quantity - mu) / sd), 5) AS mean_z, round(max((l_quantity - mu) / sd), 5) AS max_z FROM lineitem, m GROUP BY 1""",
    "split_train_test": f"SELECT CASE WHEN {_SPLIT} < 0.2 THEN 'test' ELSE 'train' END AS part, lang, count(*) AS n FROM documents GROUP BY 1, 2",
    "assign_clients_hash": f"SELECT doc_id, (row_number() OVER (ORDER BY {_CLIENT}, doc_id) - 1) % 10 AS client_id FROM documents",
    "assign_clients_natural": """WITH m AS (SELECT l_suppkey AS client_id, count(*) AS m FROM lineitem GROUP BY 1)
      SELECT client_id, m, round((SELECT count(*) FROM m) * m / (SELECT sum(m) FROM m), 6) AS weight FROM m""",
    "join_star_features": """SELECT c_mktsegment, o_orderpriority, count(*) AS n, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS qty, CAST(sum(p_size) AS BIGINT) AS size_sum
      FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN part ON l_partkey = p_partkey GROUP BY 1, 2""",
    "labelled_docs": "SELECT lang, coalesce(quality, -1) AS quality, count(*) AS n, CAST(sum(n_chars) AS BIGINT) AS chars FROM documents LEFT JOIN labels USING (doc_id) GROUP BY 1, 2",
    "unlabelled_docs": "SELECT source, count(*) AS n FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels) GROUP BY 1",
    "labelled_semi": "SELECT doc_id, lang, n_chars FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE toxic = 1)",
    "outer_suppliers": """WITH a AS (SELECT s_nationkey AS k, count(*) AS suppliers FROM supplier GROUP BY 1), b AS (SELECT c_nationkey AS k, count(*) AS customers FROM customer GROUP BY 1)
      SELECT k, coalesce(suppliers, 0) AS suppliers, coalesce(customers, 0) AS customers FROM a FULL JOIN b USING (k)""",
    "predict_grid": """WITH m(model, a, b) AS (VALUES (0, 0.5::DOUBLE, -0.2::DOUBLE), (1, -0.3::DOUBLE, 0.4::DOUBLE), (2, 0.1::DOUBLE, 0.1::DOUBLE))
      SELECT model, count(*) FILTER (a * l_quantity / 50.0 + b * l_discount * 10.0 > 0.1) AS positive, count(*) AS n FROM lineitem, m GROUP BY 1""",
    "events_in_round": """SELECT p.event_id AS round_id, count(*) AS n FROM events p JOIN events e ON e.user_id = p.user_id AND e.ts > p.ts AND e.ts <= p.ts + INTERVAL 10 MINUTE
      WHERE p.event_type = 'purchase' GROUP BY 1""",
    "asof_model": """SELECT e.event_id, (SELECT arg_max(p.event_id, (p.ts, p.event_id)) FROM events p WHERE p.user_id = e.user_id AND p.event_type = 'purchase' AND p.ts <= e.ts) AS model_id
      FROM events e WHERE e.event_type = 'click'""",
    "cost_rollup": "SELECT o_orderstatus, o_orderpriority, count(*) AS n, CAST(grouping(o_orderstatus, o_orderpriority) AS BIGINT) AS level FROM orders GROUP BY ROLLUP (o_orderstatus, o_orderpriority)",
    "cost_cube": "SELECT l_returnflag, l_linestatus, count(*) AS n, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS qty FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)",
    "cost_grouping_sets": "SELECT l_returnflag, l_linenumber, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linenumber), ())",
    "best_stepsize": """WITH m AS (SELECT l_returnflag, CAST(round(l_discount * 100) AS INTEGER) AS step, sum(CAST(l_quantity AS BIGINT))::DOUBLE / count(*) AS score FROM lineitem GROUP BY 1, 2)
      SELECT * FROM (SELECT l_returnflag, step, round(score, 6) AS score, rank() OVER w AS rank, dense_rank() OVER w AS dense FROM m WINDOW w AS (PARTITION BY l_returnflag ORDER BY m.score DESC, step)) WHERE rank <= 3""",
    "trace_running": """WITH e AS (SELECT *, CAST(round(value * 100) AS BIGINT) AS v FROM events)
      SELECT event_id, round(sum(v) OVER (w ROWS UNBOUNDED PRECEDING)::DOUBLE / count(v) OVER (w ROWS UNBOUNDED PRECEDING), 4) AS running_mean, v - lag(v) OVER (w) AS step,
      max(v) OVER (w ROWS 2 PRECEDING) - min(v) OVER (w ROWS 2 PRECEDING) AS spread FROM e WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)""",
    "trace_pivot": """SELECT hour(ts) AS hour, count(*) FILTER (event_type = 'click') AS click, count(*) FILTER (event_type = 'error') AS error,
      count(*) FILTER (event_type = 'purchase') AS purchase, count(*) FILTER (event_type = 'view') AS view FROM events GROUP BY 1""",
    "hashed_tokens": """SELECT lang, CAST('0x' || substr(md5(w), 1, 8) AS BIGINT) % 122 AS place, count(*) AS n FROM
      (SELECT lang, unnest(string_split_regex(lower(text), '[ \\n]+')) AS w FROM documents) WHERE w <> '' GROUP BY 1, 2""",
    "time_features": "SELECT year(o_orderdate) AS y, month(o_orderdate) AS m, count(*) AS n, CAST(sum(date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE))) AS BIGINT) AS days FROM orders GROUP BY 1, 2",
    "json_features": "WITH e AS (SELECT event_type, CAST(regexp_extract(props, '\"k\": *([0-9]+)', 1) AS BIGINT) AS k FROM events) SELECT event_type, CAST(sum(k) AS BIGINT) AS k_sum, max(k) AS k_max FROM e GROUP BY 1",
    "page_tokens": """WITH t AS (SELECT page_id, html, regexp_replace(regexp_replace(regexp_replace(html, '<[^>]*>', ' ', 'g'), '&[a-z#0-9]+;', ' ', 'g'), '[ \\t\\n\\r]+', ' ', 'g') AS x FROM pages)
      SELECT page_id, len(list_filter(string_split(x, ' '), lambda w: w <> '')) AS n_words, length(html) AS n_html FROM t""",
    "conversation_features": """SELECT conv_id, count(*) AS turns, md5(string_agg(role || ': ' || text, chr(10) ORDER BY turn)) AS text_md5 FROM conversations GROUP BY 1""",
    "window_tumbling": "SELECT CAST(epoch(date_trunc('hour', ts)) AS BIGINT) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2",
    "window_sliding": """WITH h AS (SELECT CAST(epoch(date_trunc('hour', ts)) AS BIGINT) AS h FROM events)
      SELECT start, count(*) AS n FROM (SELECT h AS start FROM h UNION ALL SELECT h - 3600 FROM h) GROUP BY 1""",
    "window_session": """WITH e AS (SELECT user_id, ts, event_id, CASE WHEN lag(ts) OVER w IS NULL OR ts >= lag(ts) OVER w + INTERVAL 6 HOUR THEN 1 ELSE 0 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),
      s AS (SELECT user_id, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS k FROM e), c AS (SELECT user_id, k, count(*) AS n FROM s GROUP BY 1, 2)
      SELECT user_id, count(*) AS sessions, max(n) AS longest FROM c GROUP BY 1""",
    "late_messages": """WITH e AS (SELECT user_id, ts, max(ts) OVER (PARTITION BY user_id ORDER BY event_id ROWS UNBOUNDED PRECEDING) AS seen FROM events)
      SELECT user_id, count(*) FILTER (ts < seen - INTERVAL 1 HOUR) AS late, count(*) AS n FROM e GROUP BY 1""",
    "map_features": "SELECT c_nationkey, count(*) AS n, min(c_custkey) AS first_key FROM customer GROUP BY 1",
    "scalar_subquery": """SELECT c_mktsegment, count(*) AS n FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders WHERE o_orderstatus = 'F')
      AND c_acctbal > (SELECT avg(c_acctbal) FROM customer) GROUP BY 1""",
}
