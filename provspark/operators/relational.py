"""Relational operators around the methods, as DataFrame functions with their SQL twins."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.dnf import noisy_or
from ..sources.tables import hash_pi, load, register, stored


def semi_guard(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders of the customers that a demand asks for."""
    need = load(spark, sf_dir, "customer").where("c_mktsegment = 'BUILDING'").select("c_custkey")
    orders = load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    return orders.join(need, orders["o_custkey"] == need["c_custkey"], "left_semi")


def anti_delta(spark: SparkSession, sf_dir: str) -> DataFrame:
    customers, orders = load(spark, sf_dir, "customer").select("c_custkey"), load(spark, sf_dir, "orders")
    return customers.join(orders, customers["c_custkey"] == orders["o_custkey"], "left_anti")


def full_outer_merge(spark: SparkSession, sf_dir: str) -> DataFrame:
    old = load(spark, sf_dir, "labels").where("quality = 1").select("doc_id", F.lit(1).cast("long").alias("old"))
    new = load(spark, sf_dir, "labels").where("toxic = 1").select("doc_id", F.lit(1).cast("long").alias("fresh"))
    return old.join(new, "doc_id", "full_outer").select("doc_id", (F.coalesce("old", F.lit(0)) + 2 * F.coalesce("fresh", F.lit(0))).alias("state"))


def asof_pi(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each purchase with the latest view of its user before it: one sort per user, no pairs."""
    events = load(spark, sf_dir, "events").select("user_id", "ts", "event_id", "event_type")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    seen = events.withColumn("view_id", F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(w))
    return seen.where("event_type = 'purchase'").select("event_id", "view_id")


def interval_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders by band of total price: a range join against a handful of bands."""
    bands = spark.createDataFrame([(0, 0.0, 50000.0), (1, 50000.0, 150000.0), (2, 150000.0, 1e12)], "band long, low double, high double")
    orders = load(spark, sf_dir, "orders").select("o_totalprice")
    return orders.join(F.broadcast(bands), (F.col("o_totalprice") >= F.col("low")) & (F.col("o_totalprice") < F.col("high"))).groupBy("band").agg(F.count("*").alias("n"))


def cube_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "orders").cube("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))


def rollup_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "orders").rollup("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))


def grouping_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = load(spark, sf_dir, "part")
    return df.groupingSets([[df.p_brand], [df.p_type]], df.p_brand, df.p_type).agg(F.count("*").alias("n"))


def pivot_matrix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "lineitem").groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).agg(F.count("l_orderkey"))


def topk_window(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return load(spark, sf_dir, "orders").select("o_custkey", "o_orderkey", "o_totalprice").withColumn("rn", F.row_number().over(w)).where("rn <= 2").select("o_custkey", "o_orderkey", F.col("rn").cast("long").alias("rn"))


def frames(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    e = load(spark, sf_dir, "events")
    return e.select("event_id", F.count("*").over(w.rowsBetween(-2, 0)).alias("recent"), F.lag("event_id").over(w).alias("before"))


def set_ops(spark: SparkSession, sf_dir: str) -> DataFrame:
    a = load(spark, sf_dir, "supplier").select(F.col("s_nationkey").alias("n"))
    b = load(spark, sf_dir, "customer").select(F.col("c_nationkey").alias("n"))
    parts = {"union": a.union(b).distinct(), "intersect": a.intersect(b), "except": b.exceptAll(b.intersectAll(a))}
    out = None
    for k, df in parts.items():
        row = df.agg(F.lit(k).alias("op"), F.count("*").alias("n")).select("op", "n")
        out = row if out is None else out.unionByName(row)
    return out


def string_functions(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "part").select("p_partkey", F.upper("p_brand").alias("brand"), F.substring_index("p_brand", "#", -1).alias("number"), F.length("p_name").cast("long").alias("size"), F.concat_ws("|", "p_brand", "p_type").alias("both"))


def date_functions(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = F.col("o_orderdate")
    return load(spark, sf_dir, "orders").groupBy(F.year(d).cast("long").alias("year"), F.month(d).cast("long").alias("month")).agg(F.count("*").alias("n"))


def math_functions(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = hash_pi(F.col("c_custkey"))
    return load(spark, sf_dir, "customer").select("c_custkey", F.round(F.log(p), 6).alias("log"), F.round(F.pow(p, F.lit(2.0)), 6).alias("square"), (F.col("c_custkey") % 7).alias("rest"))


def array_functions(spark: SparkSession, sf_dir: str) -> DataFrame:
    words = F.array_distinct(F.split("text", " "))
    return load(spark, sf_dir, "benchmark").select("item_id", F.size(words).cast("long").alias("distinct_words"), F.array_contains(words, "the").alias("has_the"))


def map_json(spark: SparkSession, sf_dir: str) -> DataFrame:
    k = F.get_json_object("props", "$.k").cast("long")
    return load(spark, sf_dir, "events").groupBy(k.alias("k")).agg(F.count("*").alias("n"))


def approx_distinct(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Whether the sketch is within a tenth of the exact count."""
    e = load(spark, sf_dir, "orders").agg(F.approx_count_distinct("o_custkey", 0.02).alias("about"), F.count_distinct("o_custkey").alias("exact"))
    return e.select("exact", (F.abs(F.col("about") - F.col("exact")) <= 0.1 * F.col("exact")).alias("near"))


def percentile(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "customer").groupBy("c_mktsegment").agg(F.round(F.percentile("c_acctbal", 0.5), 4).alias("mid"))


def noisy_or_by_nation(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "customer").groupBy("c_nationkey").agg(F.round(noisy_or(hash_pi(F.col("c_custkey")) / 100), 6).alias("p"))


def recursive_cte(spark: SparkSession, sf_dir: str) -> DataFrame:
    load(spark, sf_dir, "conversations").select("conv_id", "turn").distinct().createOrReplaceTempView("_turns")
    return spark.sql("WITH RECURSIVE c(conv_id, turn, d) AS (SELECT conv_id, turn, 1 FROM _turns WHERE turn = 0 UNION ALL SELECT t.conv_id, t.turn, c.d + 1 FROM c JOIN _turns t ON t.conv_id = c.conv_id AND t.turn = c.turn + 1 WHERE c.d < 50) SELECT conv_id, CAST(max(d) AS BIGINT) AS depth FROM c GROUP BY conv_id")


def source_roundtrip(spark: SparkSession, sf_dir: str) -> DataFrame:
    return stored(load(spark, sf_dir, "nation"), "roundtrip").select("n_nationkey", "n_name")


def udtf_explanations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Explanations of small formulas as rows: {k}, {k, k + 1}, {k + 1, k + 2} leaves two."""
    from ..functions.sql import register

    register(spark)
    load(spark, sf_dir, "nation").select(F.col("n_nationkey").cast("long").alias("k")).createOrReplaceTempView("_keys")
    return spark.sql("SELECT k, CAST(size AS BIGINT) AS size FROM _keys, LATERAL minimal_explanations(array(array(k), array(k, k + 1), array(k + 1, k + 2)))")


def udaf_noisy_or(spark: SparkSession, sf_dir: str) -> DataFrame:
    from ..functions.sql import noisy_or_agg

    facts = load(spark, sf_dir, "customer").select("c_nationkey", (hash_pi(F.col("c_custkey")) / 100).alias("p"))
    return facts.groupBy("c_nationkey").agg(F.round(noisy_or_agg("p"), 6).alias("p"))


def generated_graph(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Edges that the source grows over the customers, in order of their keys: by nation of the customer that joins."""
    from ..sources.generated import register

    register(spark)
    customers = load(spark, sf_dir, "customer").select("c_custkey", "c_nationkey")
    placed = stored(customers.withColumn("node", F.row_number().over(Window.orderBy("c_custkey")).cast("long") - 1), "nodes")
    edges = spark.read.format("uncertain_graph").option("nodes", placed.count()).option("edges", 1).load()
    ends = edges.join(placed.select(F.col("node").alias("src"), "c_nationkey"), "src").join(placed.select(F.col("node").alias("dst")), "dst")
    return ends.groupBy("c_nationkey").agg(F.count("*").alias("edges"), F.count_if((F.col("pi") > 0) & (F.col("pi") <= 1)).alias("sound"))


def unpivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    wide = load(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.count("*").cast("double").alias("lines"), F.count_distinct("l_orderkey").cast("double").alias("orders"))
    return wide.unpivot("l_returnflag", ["lines", "orders"], "measure", "value")


def richest(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "customer").groupBy("c_nationkey").agg(F.max_by("c_custkey", F.struct("c_acctbal", "c_custkey")).alias("first"), F.min_by("c_custkey", F.struct("c_acctbal", "c_custkey")).alias("last"))


def histogram(spark: SparkSession, sf_dir: str) -> DataFrame:
    bucket = F.width_bucket(F.col("c_acctbal").cast("double"), F.lit(-1000.0), F.lit(10000.0), F.lit(11))
    return load(spark, sf_dir, "customer").groupBy(bucket.cast("long").alias("bucket")).agg(F.count("*").alias("n"))


def expected(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Expected number of facts and expected sum over all worlds, by linearity."""
    pi = hash_pi(F.col("c_custkey"))
    return load(spark, sf_dir, "customer").groupBy("c_nationkey").agg(F.round(F.sum(pi), 6).alias("number"), F.round(F.sum(pi * F.col("c_acctbal").cast("double")), 3).alias("total"))


def sampled_world(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Facts of one world, drawn by a hash of the fact against its probability: no shuffle, the same on every run."""
    draw = (F.col("c_custkey").cast("long") * 7907 % 1009).cast("double") / F.lit(1009).cast("double")
    return load(spark, sf_dir, "customer").where(draw < hash_pi(F.col("c_custkey"))).groupBy("c_nationkey").agg(F.count("*").alias("n"))


_SUBQUERIES = """SELECT o_orderpriority, count(*) AS n FROM orders WHERE o_totalprice > (SELECT avg(o_totalprice) FROM orders)
AND EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey AND l_quantity > 40) AND o_custkey IN (SELECT c_custkey FROM customer WHERE c_mktsegment = 'BUILDING') GROUP BY 1"""
_LATERAL = "SELECT n_nationkey, t.n FROM nation, LATERAL (SELECT count(*) AS n FROM supplier WHERE s_nationkey = n_nationkey) AS t"


def subqueries(spark: SparkSession, sf_dir: str) -> DataFrame:
    register(spark, sf_dir)
    return spark.sql(_SUBQUERIES)


def lateral(spark: SparkSession, sf_dir: str) -> DataFrame:
    register(spark, sf_dir)
    return spark.sql(_LATERAL)


def sorted_top(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").select("o_orderkey", "o_totalprice").limit(10)


def salted_join(spark: SparkSession, sf_dir: str, salts: int = 8) -> DataFrame:
    """A join on a hot key: the large side is dealt over salts, the small side repeated once a salt."""
    events = load(spark, sf_dir, "events").select("event_type", "event_id").withColumn("salt", F.pmod(F.xxhash64("event_id"), F.lit(salts)))
    kinds = load(spark, sf_dir, "events").groupBy("event_type").agg(F.count_distinct("user_id").alias("users"))
    spread = kinds.withColumn("salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(salts - 1).cast("long"))))
    return events.join(spread.hint("merge"), ["event_type", "salt"]).groupBy("event_type").agg(F.count("*").alias("n"), F.max("users").alias("users"))


def grouped_map(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Longest pause of each user, group by group in pandas."""

    def pause(frame: pd.DataFrame) -> pd.DataFrame:
        gaps = frame["at"].sort_values().diff().max()
        return pd.DataFrame({"user_id": frame["user_id"].iloc[:1], "pause": [0 if pd.isna(gaps) else int(gaps)]})

    events = load(spark, sf_dir, "events").select("user_id", F.unix_timestamp(F.col("ts").cast("timestamp")).alias("at"))
    return events.groupBy("user_id").applyInPandas(pause, "user_id long, pause long")


def cogrouped(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers and suppliers of a nation, counted side by side."""

    def both(key: tuple, left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"nation": [key[0]], "customers": [len(left)], "suppliers": [len(right)]})

    left = load(spark, sf_dir, "customer").select(F.col("c_nationkey").cast("long").alias("nation"))
    right = load(spark, sf_dir, "supplier").select(F.col("s_nationkey").cast("long").alias("nation"))
    return left.groupBy("nation").cogroup(right.groupBy("nation")).applyInPandas(both, "nation long, customers long, suppliers long")


def dnf_in_sql(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Formulas from SQL: ({k} or {k, k+1}) and ({k+2} or {k}) is {k} after absorption."""
    from ..functions.sql import register as functions

    functions(spark)
    load(spark, sf_dir, "nation").select(F.col("n_nationkey").cast("long").alias("k")).createOrReplaceTempView("_keys")
    return spark.sql("SELECT k, size(f) AS size, dnf_equal(f, array(array(k))) AS equal FROM (SELECT k, dnf_absorb(dnf_and(dnf_or(array(array(k)), array(array(k, k + 1))), array(array(k + 2), array(k)))) AS f FROM _keys)")


OPERATORS = {
    "udtf_explanations": (udtf_explanations, "SELECT CAST(n_nationkey AS BIGINT) AS k, s AS size FROM nation, (SELECT CAST(1 AS BIGINT) AS s UNION ALL SELECT 2)"),
    "source_generated_graph": (generated_graph, "SELECT c_nationkey, count(*) AS edges, count(*) AS sound FROM customer WHERE c_custkey > (SELECT min(c_custkey) FROM customer) GROUP BY 1"),
    "op_semi_guard": (semi_guard, "SELECT o_orderkey, o_custkey FROM orders WHERE o_custkey IN (SELECT c_custkey FROM customer WHERE c_mktsegment = 'BUILDING')"),
    "op_anti_delta": (anti_delta, "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders)"),
    "op_full_outer_merge": (full_outer_merge, "SELECT doc_id, CAST((CASE WHEN quality = 1 THEN 1 ELSE 0 END) + 2 * (CASE WHEN toxic = 1 THEN 1 ELSE 0 END) AS BIGINT) AS state FROM labels WHERE quality = 1 OR toxic = 1"),
    "op_asof_pi": (asof_pi, "SELECT event_id, view_id FROM (SELECT event_id, event_type, last_value(CASE WHEN event_type = 'view' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS view_id FROM events) WHERE event_type = 'purchase'"),
    "op_interval_join": (interval_join, "SELECT CAST(CASE WHEN o_totalprice < 50000 THEN 0 WHEN o_totalprice < 150000 THEN 1 ELSE 2 END AS BIGINT) AS band, count(*) AS n FROM orders GROUP BY 1"),
    "op_cube_report": (cube_report, "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)"),
    "op_rollup_report": (rollup_report, "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY ROLLUP (o_orderstatus, o_orderpriority)"),
    "op_grouping_sets": (grouping_sets, "SELECT p_brand, p_type, count(*) AS n FROM part GROUP BY GROUPING SETS ((p_brand), (p_type))"),
    "op_pivot_matrix": (pivot_matrix, "SELECT l_returnflag, nullif(count(*) FILTER (l_linestatus = 'F'), 0) AS \"F\", nullif(count(*) FILTER (l_linestatus = 'O'), 0) AS \"O\" FROM lineitem GROUP BY 1"),
    "op_topk_window": (topk_window, "SELECT o_custkey, o_orderkey, rn FROM (SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS rn FROM orders) WHERE rn <= 2"),
    "op_frames": (frames, "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS recent, lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS before FROM events"),
    "op_set_ops": (set_ops, "SELECT 'union' AS op, count(*) AS n FROM (SELECT s_nationkey FROM supplier UNION SELECT c_nationkey FROM customer) UNION ALL SELECT 'intersect', count(*) FROM (SELECT s_nationkey FROM supplier INTERSECT SELECT c_nationkey FROM customer) UNION ALL SELECT 'except', count(*) FROM (SELECT c_nationkey FROM customer EXCEPT ALL (SELECT c_nationkey FROM customer INTERSECT ALL SELECT s_nationkey FROM supplier))"),
    "op_string": (string_functions, "SELECT p_partkey, upper(p_brand) AS brand, split_part(p_brand, '#', -1) AS number, CAST(length(p_name) AS BIGINT) AS size, p_brand || '|' || p_type AS both FROM part"),
    "op_date": (date_functions, "SELECT CAST(year(o_orderdate) AS BIGINT) AS year, CAST(month(o_orderdate) AS BIGINT) AS month, count(*) AS n FROM orders GROUP BY 1, 2"),
    "op_math": (math_functions, "SELECT c_custkey, round(ln(p), 6) AS log, round(p * p, 6) AS square, c_custkey % 7 AS rest FROM (SELECT c_custkey, CAST((c_custkey * 7919) % 997 + 1 AS DOUBLE) / CAST(1000 AS DOUBLE) AS p FROM customer)"),
    "op_array": (array_functions, "SELECT item_id, CAST(len(list_distinct(string_split(text, ' '))) AS BIGINT) AS distinct_words, list_contains(string_split(text, ' '), 'the') AS has_the FROM benchmark"),
    "op_map_json": (map_json, "SELECT CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, count(*) AS n FROM events GROUP BY 1"),
    "op_approx_distinct": (approx_distinct, "SELECT count(DISTINCT o_custkey) AS exact, true AS near FROM orders"),
    "op_percentile": (percentile, "SELECT c_mktsegment, round(quantile_cont(c_acctbal, 0.5), 4) AS mid FROM customer GROUP BY 1"),
    "op_noisy_or": (noisy_or_by_nation, "SELECT c_nationkey, round(1 - product(1 - CAST((c_custkey * 7919) % 997 + 1 AS DOUBLE) / CAST(1000 AS DOUBLE) / 100), 6) AS p FROM customer GROUP BY 1"),
    "udaf_noisy_or": (udaf_noisy_or, "SELECT c_nationkey, round(1 - product(1 - CAST((c_custkey * 7919) % 997 + 1 AS DOUBLE) / CAST(1000 AS DOUBLE) / 100), 6) AS p FROM customer GROUP BY 1"),
    "op_recursive_cte": (recursive_cte, "WITH RECURSIVE t AS (SELECT DISTINCT conv_id, turn FROM conversations), c(conv_id, turn, d) AS (SELECT conv_id, turn, 1 FROM t WHERE turn = 0 UNION ALL SELECT t.conv_id, t.turn, c.d + 1 FROM c JOIN t ON t.conv_id = c.conv_id AND t.turn = c.turn + 1) SELECT conv_id, CAST(max(d) AS BIGINT) AS depth FROM c GROUP BY 1"),
    "source_roundtrip": (source_roundtrip, "SELECT n_nationkey, n_name FROM nation"),
    "op_unpivot": (unpivot, "SELECT l_returnflag, 'lines' AS measure, CAST(count(*) AS DOUBLE) AS value FROM lineitem GROUP BY 1 UNION ALL SELECT l_returnflag, 'orders', CAST(count(DISTINCT l_orderkey) AS DOUBLE) FROM lineitem GROUP BY 1"),
    "op_max_by": (richest, "SELECT c_nationkey, max(c_custkey) FILTER (a = 1) AS first, max(c_custkey) FILTER (z = 1) AS last FROM (SELECT c_nationkey, c_custkey, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey DESC) AS a, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal, c_custkey) AS z FROM customer) GROUP BY 1"),
    "op_histogram": (histogram, "SELECT CAST(CASE WHEN c_acctbal < -1000 THEN 0 WHEN c_acctbal >= 10000 THEN 12 ELSE floor((c_acctbal + 1000) / 1000) + 1 END AS BIGINT) AS bucket, count(*) AS n FROM customer GROUP BY 1"),
    "op_expected": (expected, "SELECT c_nationkey, round(sum(p), 6) AS number, round(sum(p * CAST(c_acctbal AS DOUBLE)), 3) AS total FROM (SELECT c_nationkey, c_acctbal, CAST((c_custkey * 7919) % 997 + 1 AS DOUBLE) / CAST(1000 AS DOUBLE) AS p FROM customer) GROUP BY 1"),
    "op_sampled_world": (sampled_world, "SELECT c_nationkey, count(*) AS n FROM customer WHERE CAST(c_custkey * 7907 % 1009 AS DOUBLE) / CAST(1009 AS DOUBLE) < CAST((c_custkey * 7919) % 997 + 1 AS DOUBLE) / CAST(1000 AS DOUBLE) GROUP BY 1"),
    "op_subqueries": (subqueries, _SUBQUERIES),
    "op_lateral": (lateral, _LATERAL),
    "op_sorted_top": (sorted_top, "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10"),
    "op_salted_join": (salted_join, "SELECT event_type, count(*) AS n, count(DISTINCT user_id) AS users FROM events GROUP BY 1"),
    "op_grouped_map": (grouped_map, "SELECT user_id, CAST(coalesce(max(gap), 0) AS BIGINT) AS pause FROM (SELECT user_id, floor(epoch(ts)) - lag(floor(epoch(ts))) OVER (PARTITION BY user_id ORDER BY ts) AS gap FROM events) GROUP BY 1"),
    "op_cogroup": (cogrouped, "SELECT n AS nation, CAST(sum(c) AS BIGINT) AS customers, CAST(sum(s) AS BIGINT) AS suppliers FROM (SELECT CAST(c_nationkey AS BIGINT) AS n, 1 AS c, 0 AS s FROM customer UNION ALL SELECT s_nationkey, 0, 1 FROM supplier) GROUP BY 1"),
    "sql_dnf_functions": (dnf_in_sql, "SELECT CAST(n_nationkey AS BIGINT) AS k, 1 AS size, true AS equal FROM nation"),
}
