"""Operators, sources, sinks and functions around the methods."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Window
from pyspark.sql import functions as F

from callweave.plans.registry import query
from callweave.tables import load, settle, shared_path


def revenue():
    return F.col("l_extendedprice") * (1 - F.col("l_discount"))


# Sources and sinks


@query("SELECT count(*) AS n, round(sum(l_extendedprice), 2) AS total FROM lineitem WHERE l_shipdate >= TIMESTAMP '2000-01-01'")
def scan_prune(t, spark):
    late = t("lineitem").where(F.col("l_shipdate") >= F.lit("2000-01-01").cast("timestamp_ntz"))
    return late.agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_extendedprice"), 2).alias("total"))


@query("SELECT r_name AS value FROM region")
def scan_text_lines(t, spark):
    path = shared_path(spark)
    t("region").select("r_name").write.text(path)
    return spark.read.text(path)


@query("SELECT n_nationkey, n_name, n_regionkey FROM nation")
def scan_json(t, spark):
    path = shared_path(spark)
    t("nation").write.json(path)
    return spark.read.schema("n_nationkey int, n_name string, n_regionkey int").json(path)


@query("SELECT p_partkey, p_name, p_size FROM part")
def scan_csv(t, spark):
    path = shared_path(spark)
    t("part").select("p_partkey", "p_name", "p_size").write.option("header", True).csv(path)
    return spark.read.schema("p_partkey long, p_name string, p_size int").option("header", True).csv(path)


@query("SELECT n_nationkey, n_name FROM nation")
def scan_orc(t, spark):
    path = shared_path(spark)
    t("nation").select("n_nationkey", "n_name").write.orc(path)
    return spark.read.orc(path)


@query("""WITH k AS (SELECT CAST(floor(o_orderkey / 500e0) * 500 AS BIGINT) AS id FROM orders), n AS (SELECT id, count(*) AS n FROM k GROUP BY 1)
          SELECT r.id, coalesce(n.n, 0) AS n FROM (SELECT unnest(range((SELECT min(id) FROM k), (SELECT max(id) + 1 FROM k), 500)) AS id) r LEFT JOIN n ON r.id = n.id""")
def scan_range(t, spark):
    """A range source over the span of the order keys; of each step of 500 keys the number of orders, none among them."""
    n = t("orders").where("o_orderkey IS NOT NULL").groupBy((F.floor(F.col("o_orderkey") / 500) * 500).cast("long").alias("id")).agg(F.count(F.lit(1)).alias("n"))
    n = settle(n)
    low, high = n.agg(F.min("id"), F.max("id")).first()
    steps = spark.range(low, high + 1, 500) if low is not None else spark.range(0)
    return steps.join(n, "id", "left").select("id", F.coalesce("n", F.lit(0).cast("long")).alias("n"))


@query("SELECT o_orderkey, o_orderpriority FROM orders WHERE o_orderstatus = 'F'")
def sink_roundtrip(t, spark):
    """Written by status; reading one status touches one folder."""
    path = shared_path(spark)
    t("orders").select("o_orderkey", "o_orderpriority", "o_orderstatus").write.partitionBy("o_orderstatus").parquet(path)
    return spark.read.parquet(path).where("o_orderstatus = 'F'").select("o_orderkey", "o_orderpriority")


@query("SELECT c_custkey % 8 AS bucket, count(*) AS n FROM customer GROUP BY 1")
def sink_sorted_buckets(t, spark):
    path = shared_path(spark)
    rows = t("customer").select("c_custkey", (F.col("c_custkey") % 8).alias("bucket"))
    rows.repartition("bucket").sortWithinPartitions("bucket", "c_custkey").write.partitionBy("bucket").parquet(path)
    return spark.read.schema("c_custkey long, bucket long").parquet(path).groupBy("bucket").agg(F.count(F.lit(1)).alias("n"))


# Projection and filter


@query("""SELECT p_partkey, upper(p_brand) AS brand, CASE WHEN p_size < 10 THEN 'small' WHEN p_size < 30 THEN 'medium' ELSE 'large' END AS class FROM part
          WHERE p_size BETWEEN 5 AND 40 AND p_size IN (7, 9, 15, 22, 31, 38) AND p_type LIKE '%E%' AND p_name IS NOT NULL AND p_brand IS NOT DISTINCT FROM p_brand""")
def filter_project(t, spark):
    p = t("part")
    keep = F.col("p_size").between(5, 40) & F.col("p_size").isin(7, 9, 15, 22, 31, 38) & F.col("p_type").like("%E%") & F.col("p_name").isNotNull() & F.col("p_brand").eqNullSafe(F.col("p_brand"))
    return p.where(keep).select("p_partkey", F.upper("p_brand").alias("brand"), F.when(F.col("p_size") < 10, "small").when(F.col("p_size") < 30, "medium").otherwise("large").alias("class"))


# Joins

REVENUE = "SELECT n_name, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey GROUP BY 1"


@query(REVENUE)
def join_inner(t, spark):
    """The two large sides meet on the order key; customers and nations follow, broadcast where their measured size allows."""
    orders = t("orders").select("o_orderkey", "o_custkey").join(t("customer").select("c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey"))
    items = t("lineitem").select("l_orderkey", "l_extendedprice", "l_discount").join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
    by_nation = items.groupBy("c_nationkey").agg(F.sum(revenue()).alias("r"))
    return by_nation.join(t("nation"), F.col("c_nationkey") == F.col("n_nationkey")).select("n_name", F.round("r", 2).alias("revenue"))


PRIORITY = "SELECT o_orderpriority, count(*) AS n, round(sum(l_quantity), 2) AS quantity FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1"


def _by_priority(t, hint):
    j = t("lineitem").select("l_orderkey", "l_quantity").join(t("orders").select("o_orderkey", "o_orderpriority").hint(hint), F.col("l_orderkey") == F.col("o_orderkey"))
    return j.groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_quantity"), 2).alias("quantity"))


@query(PRIORITY)
def join_smj(t, spark):
    return _by_priority(t, "merge")


@query(PRIORITY)
def join_shj(t, spark):
    return _by_priority(t, "shuffle_hash")


@query("SELECT d.doc_id IS NOT NULL AS has_doc, l.doc_id IS NOT NULL AS has_label, count(*) AS n FROM (SELECT doc_id FROM documents WHERE lang <> 'en') d FULL JOIN labels l ON d.doc_id = l.doc_id GROUP BY ALL")
def join_outer(t, spark):
    d, lab = t("documents").where("lang <> 'en'").select("doc_id").alias("d"), t("labels").select("doc_id").alias("l")
    j = d.join(lab, F.col("d.doc_id") == F.col("l.doc_id"), "full")
    return j.groupBy(F.col("d.doc_id").isNotNull().alias("has_doc"), F.col("l.doc_id").isNotNull().alias("has_label")).agg(F.count(F.lit(1)).alias("n"))


@query("SELECT doc_id, quality FROM documents LEFT JOIN labels USING (doc_id)")
def join_left(t, spark):
    return t("documents").select("doc_id").join(t("labels").select("doc_id", "quality"), "doc_id", "left")


IN_2001 = "o_orderdate >= TIMESTAMP '2001-01-01' AND o_orderdate < TIMESTAMP '2001-07-01'"


@query(f"SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders WHERE {IN_2001})")
def join_semi(t, spark):
    return t("customer").select("c_custkey").join(t("orders").where(IN_2001.replace("TIMESTAMP", "TIMESTAMP_NTZ")), F.col("c_custkey") == F.col("o_custkey"), "left_semi")


@query(f"SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders WHERE {IN_2001})")
def join_anti(t, spark):
    return t("customer").select("c_custkey").join(t("orders").where(IN_2001.replace("TIMESTAMP", "TIMESTAMP_NTZ")), F.col("c_custkey") == F.col("o_custkey"), "left_anti")


@query("SELECT a.s_suppkey AS low, b.s_suppkey AS high FROM supplier a JOIN supplier b ON a.s_nationkey = b.s_nationkey AND a.s_acctbal < b.s_acctbal")
def join_theta(t, spark):
    a, b = t("supplier").alias("a"), t("supplier").alias("b")
    return a.join(b, (F.col("a.s_nationkey") == F.col("b.s_nationkey")) & (F.col("a.s_acctbal") < F.col("b.s_acctbal"))).select(F.col("a.s_suppkey").alias("low"), F.col("b.s_suppkey").alias("high"))


INTERVAL = "SELECT c.event_id AS click_id, p.event_id AS purchase_id FROM events c JOIN events p ON c.user_id = p.user_id AND p.ts >= c.ts AND p.ts < c.ts + INTERVAL 1 HOUR WHERE c.event_type = 'click' AND p.event_type = 'purchase'"


@query(INTERVAL)
def join_interval(t, spark):
    """Range join by time buckets: a click enters its hour and the next, so that the join is on equal user and hour."""
    e = t("events").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    hour = 3_600_000_000
    bucket = F.floor(F.col("us") / hour)
    c = e.where("event_type = 'click'").select(F.col("event_id").alias("click_id"), "user_id", F.col("us").alias("c_us"), F.explode(F.array(bucket, bucket + 1)).alias("bucket"))
    p = e.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), "user_id", F.col("us").alias("p_us"), bucket.alias("bucket"))
    return c.join(p, ["user_id", "bucket"]).where((F.col("p_us") >= F.col("c_us")) & (F.col("p_us") < F.col("c_us") + hour)).select("click_id", "purchase_id")


@query("""WITH w AS (SELECT c_nationkey, count(*) AS workers FROM customer GROUP BY 1), s AS (SELECT o_orderpriority, count(*) AS shards FROM orders GROUP BY 1)
          SELECT c_nationkey, o_orderpriority, workers, shards, workers * shards AS links FROM w, s""")
def join_cross_grid(t, spark):
    """Links between the customers of each nation, as workers, and the orders of each priority, as shards."""
    w = t("customer").groupBy("c_nationkey").agg(F.count(F.lit(1)).alias("workers"))
    s = t("orders").groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("shards"))
    return w.crossJoin(F.broadcast(s)).select("c_nationkey", "o_orderpriority", "workers", "shards", (F.col("workers") * F.col("shards")).alias("links"))


# Aggregates


@query("""SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS quantity, round(avg(l_discount), 6) AS discount, min(l_extendedprice) AS low, max(l_extendedprice) AS high, round(stddev_samp(l_tax), 6) AS tax_std FROM lineitem GROUP BY 1, 2""")
def agg_basic(t, spark):
    return t("lineitem").groupBy("l_returnflag", "l_linestatus").agg(
        F.count(F.lit(1)).alias("n"), F.round(F.sum("l_quantity"), 2).alias("quantity"), F.round(F.avg("l_discount"), 6).alias("discount"), F.min("l_extendedprice").alias("low"), F.max("l_extendedprice").alias("high"), F.round(F.stddev_samp("l_tax"), 6).alias("tax_std")
    )


def _segments(t):
    return t("customer").join(t("nation"), F.col("c_nationkey") == F.col("n_nationkey"))


SEGMENTS = "SELECT c_mktsegment, n_name, CAST(grouping(c_mktsegment) * 2 + grouping(n_name) AS BIGINT) AS gid, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY "


@query(SEGMENTS + "CUBE (c_mktsegment, n_name)")
def agg_cube(t, spark):
    return _segments(t).cube("c_mktsegment", "n_name").agg(F.grouping_id().alias("gid"), F.count(F.lit(1)).alias("n"))


@query(SEGMENTS + "ROLLUP (c_mktsegment, n_name)")
def agg_rollup(t, spark):
    return _segments(t).rollup("c_mktsegment", "n_name").agg(F.grouping_id().alias("gid"), F.count(F.lit(1)).alias("n"))


@query(SEGMENTS + "GROUPING SETS ((c_mktsegment), (n_name), ())")
def agg_sets(t, spark):
    return _segments(t).groupingSets([["c_mktsegment"], ["n_name"], []], "c_mktsegment", "n_name").agg(F.grouping_id().alias("gid"), F.count(F.lit(1)).alias("n"))


@query("SELECT event_type, count(DISTINCT user_id) AS users, count(DISTINCT (user_id, props)) AS pairs FROM events GROUP BY 1")
def agg_distinct(t, spark):
    return t("events").groupBy("event_type").agg(F.countDistinct("user_id").alias("users"), F.countDistinct("user_id", "props").alias("pairs"))


@query("SELECT user_id, count(*) FILTER (value > 100) AS costly, round(coalesce(sum(value) FILTER (event_type = 'purchase'), 0), 2) AS bought FROM events GROUP BY 1")
def agg_filtered(t, spark):
    bought = F.sum(F.when(F.col("event_type") == "purchase", F.col("value")))
    return t("events").groupBy("user_id").agg(F.count_if(F.col("value") > 100).alias("costly"), F.round(F.coalesce(bought, F.lit(0.0)), 2).alias("bought"))


@query("SELECT o_orderstatus, count(*) FILTER (o_orderpriority LIKE '1%') AS urgent, count(*) FILTER (o_orderpriority LIKE '2%') AS high, count(*) FILTER (o_orderpriority LIKE '5%') AS low FROM orders GROUP BY 1")
def agg_pivot(t, spark):
    p = t("orders").withColumn("p", F.substring("o_orderpriority", 1, 1)).groupBy("o_orderstatus").pivot("p", ["1", "2", "5"]).agg(F.count(F.lit(1)))
    return p.select("o_orderstatus", *[F.coalesce(F.col(a), F.lit(0)).alias(b) for a, b in (("1", "urgent"), ("2", "high"), ("5", "low"))])


@query("SELECT p_brand, string_agg(DISTINCT p_size, ',' ORDER BY p_size) AS sizes FROM part GROUP BY 1")
def agg_collect(t, spark):
    sizes = F.array_sort(F.collect_set("p_size"))
    return t("part").groupBy("p_brand").agg(F.array_join(F.transform(sizes, lambda s: s.cast("string")), ",").alias("sizes"))


@query("SELECT p_brand, p_partkey, p_retailprice FROM (SELECT *, row_number() OVER (PARTITION BY p_brand ORDER BY p_retailprice DESC, p_partkey DESC) AS r FROM part) WHERE r = 1")
def agg_maxby(t, spark):
    top = F.max(F.struct("p_retailprice", "p_partkey")).alias("m")
    return t("part").groupBy("p_brand").agg(top).select("p_brand", "m.p_partkey", "m.p_retailprice")


@query("SELECT o_custkey, string_agg(o_orderkey, ',' ORDER BY o_orderkey) AS orders, count(*) AS n FROM orders GROUP BY 1")
def agg_sort_vs_hash(t, spark):
    keys = F.transform(F.array_sort(F.collect_list("o_orderkey")), lambda k: k.cast("string"))
    return t("orders").groupBy("o_custkey").agg(F.array_join(keys, ",").alias("orders"), F.count(F.lit(1)).alias("n"))


@query("SELECT event_type, true AS within_five_percent FROM events GROUP BY 1")
def agg_approx_distinct(t, spark):
    """The sketch against the exact count."""
    near = F.abs(F.approx_count_distinct("event_id", 0.02) / F.countDistinct("event_id") - 1) < 0.05
    return t("events").groupBy("event_type").agg(near.alias("within_five_percent"))


@query("SELECT l_returnflag, round(quantile_cont(l_quantity, 0.25), 4) AS q1, round(median(l_quantity), 4) AS q2 FROM lineitem GROUP BY 1")
def agg_percentile(t, spark):
    return t("lineitem").groupBy("l_returnflag").agg(F.round(F.percentile("l_quantity", 0.25), 4).alias("q1"), F.round(F.median("l_quantity"), 4).alias("q2"))


# Windows


@query("""SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority) AS rk, dense_rank() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority) AS dr, CAST(ntile(4) OVER w AS INTEGER) AS quarter
          FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey)""".replace("row_number() OVER w AS rn, rank() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority) AS rk, dense_rank() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority) AS dr", "CAST(row_number() OVER w AS INTEGER) AS rn, CAST(rank() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority) AS INTEGER) AS rk, CAST(dense_rank() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority) AS INTEGER) AS dr"))
def win_rank(t, spark):
    w, p = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey"), Window.partitionBy("o_custkey").orderBy("o_orderpriority")
    return t("orders").select("o_orderkey", F.row_number().over(w).alias("rn"), F.rank().over(p).alias("rk"), F.dense_rank().over(p).alias("dr"), F.ntile(4).over(w).alias("quarter"))


@query("SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY event_id ROWS UNBOUNDED PRECEDING), 3) AS running FROM events")
def win_running(t, spark):
    w = Window.partitionBy("user_id").orderBy("event_id").rowsBetween(Window.unboundedPreceding, 0)
    return t("events").select("event_id", F.round(F.sum("value").over(w), 3).alias("running"))


@query("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch(ts)::BIGINT RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS n FROM events")
def win_range_frame(t, spark):
    e = t("events").withColumn("s", F.round(F.unix_micros(F.col("ts").cast("timestamp")) / 1_000_000).cast("long"))
    return e.select("event_id", F.count(F.lit(1)).over(Window.partitionBy("user_id").orderBy("s").rangeBetween(-3600, 0)).alias("n"))


@query("""WITH g AS (SELECT event_id, user_id, epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY event_id) AS gap FROM events)
          SELECT event_id, gap, CAST(1 + sum(CASE WHEN gap > 7200000000 THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY event_id) AS BIGINT) AS session FROM g""")
def win_lag(t, spark):
    w = Window.partitionBy("user_id").orderBy("event_id")
    e = t("events").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    g = e.withColumn("gap", F.col("us") - F.lag("us").over(w))
    return g.select("event_id", "gap", (1 + F.sum(F.when(F.col("gap") > 7_200_000_000, 1).otherwise(0)).over(w)).alias("session"))


# Sort and limit


@query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10")
def topk_global(t, spark):
    return t("orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(10)


@query("SELECT conv_id, turn, CAST(length(text) AS INTEGER) AS n FROM (SELECT *, row_number() OVER (PARTITION BY conv_id ORDER BY length(text) DESC, turn) AS r FROM conversations) WHERE r <= 3")
def topk_group(t, spark):
    w = Window.partitionBy("conv_id").orderBy(F.desc("n"), "turn")
    return t("conversations").select("conv_id", "turn", F.length("text").alias("n")).withColumn("r", F.row_number().over(w)).where("r <= 3").drop("r")


@query("SELECT o_orderkey FROM orders ORDER BY o_orderdate, o_orderkey LIMIT 50 OFFSET 100")
def sort_limit_offset(t, spark):
    return t("orders").orderBy("o_orderdate", "o_orderkey").select("o_orderkey").offset(100).limit(50)


# Sets

C, S = "SELECT c_nationkey AS k FROM customer", "SELECT s_nationkey AS k FROM supplier"


def _keys(t):
    return t("customer").select(F.col("c_nationkey").alias("k")), t("supplier").select(F.col("s_nationkey").alias("k"))


@query(f"{C} UNION {S}")
def set_union(t, spark):
    a, b = _keys(t)
    return a.union(b).distinct()


@query(f"{C} UNION ALL {S}")
def set_union_all(t, spark):
    a, b = _keys(t)
    return a.unionAll(b)


@query(f"{C} INTERSECT {S}")
def set_intersect(t, spark):
    a, b = _keys(t)
    return a.intersect(b)


@query(f"{C} INTERSECT ALL {S}")
def set_intersect_all(t, spark):
    a, b = _keys(t)
    return a.intersectAll(b)


@query("SELECT n_nationkey AS k FROM nation EXCEPT SELECT s_nationkey FROM supplier WHERE s_acctbal < 0")
def set_except(t, spark):
    return t("nation").select(F.col("n_nationkey").alias("k")).subtract(t("supplier").where("s_acctbal < 0").select("s_nationkey"))


@query(f"{C} EXCEPT ALL {S}")
def set_except_all(t, spark):
    a, b = _keys(t)
    return a.exceptAll(b)


# Functions


@query("""SELECT p_partkey, trim(lower(p_name)) AS low, string_split(p_type, ' ')[1] AS head, regexp_replace(p_name, '[aeiou]', '_', 'g') AS masked, substring(p_brand, 1, 5) AS brand, concat_ws('-', p_brand, p_type) AS both, CAST(length(p_name) AS INTEGER) AS n, md5(p_name) AS digest, CAST(levenshtein(p_name, p_type) AS INTEGER) AS edits FROM part""")
def fn_string(t, spark):
    return t("part").select(
        "p_partkey", F.trim(F.lower("p_name")).alias("low"), F.split("p_type", " ")[0].alias("head"), F.regexp_replace("p_name", "[aeiou]", "_").alias("masked"), F.substring("p_brand", 1, 5).alias("brand"),
        F.concat_ws("-", "p_brand", "p_type").alias("both"), F.length("p_name").alias("n"), F.md5(F.col("p_name").cast("binary")).alias("digest"), F.levenshtein("p_name", "p_type").alias("edits"),
    )


@query("""SELECT o_orderkey, CAST(date_trunc('month', o_orderdate) AS DATE) AS month, CAST(year(o_orderdate) AS INTEGER) AS y, CAST(quarter(o_orderdate) AS INTEGER) AS q, CAST(CAST(o_orderdate AS DATE) + INTERVAL 3 MONTH AS DATE) AS due, CAST(DATE '2010-01-01' - CAST(o_orderdate AS DATE) AS INTEGER) AS age FROM orders""")
def fn_date(t, spark):
    d = F.col("o_orderdate").cast("date")
    return t("orders").select("o_orderkey", F.trunc(d, "month").alias("month"), F.year(d).alias("y"), F.quarter(d).alias("q"), F.add_months(d, 3).alias("due"), F.datediff(F.lit("2010-01-01").cast("date"), d).alias("age"))


@query("""SELECT event_id, round(value, 1) AS r, CAST(ceil(value) AS BIGINT) AS c, CAST(floor(value) AS BIGINT) AS f, round(sqrt(value), 6) AS s, round(pow(value / 100, 2), 6) AS p, event_id % 7 AS m, greatest(user_id, event_id) AS g FROM events""")
def fn_math(t, spark):
    v = F.col("value")
    return t("events").select("event_id", F.round(v, 1).alias("r"), F.ceil(v).alias("c"), F.floor(v).alias("f"), F.round(F.sqrt(v), 6).alias("s"), F.round(F.pow(v / 100, 2), 6).alias("p"), F.pmod("event_id", F.lit(7)).alias("m"), F.greatest("user_id", "event_id").alias("g"))


@query("""SELECT vec_id, round(list_sum(list_transform(CAST(embedding AS DOUBLE[]), lambda x: x * x)), 5) AS norm, CAST(len(list_filter(embedding, lambda x: x > 0)) AS INTEGER) AS positive, list_sort(list_slice(embedding, 1, 3)) AS head FROM embeddings""")
def fn_array(t, spark):
    e = F.col("embedding")
    norm = F.aggregate(F.transform(e, lambda v: v.cast("double") * v.cast("double")), F.lit(0.0), lambda s, v: s + v)
    return t("embeddings").select("vec_id", F.round(norm, 5).alias("norm"), F.size(F.filter(e, lambda v: v > 0)).alias("positive"), F.sort_array(F.slice(e, 1, 3)).alias("head"))


@query("""SELECT user_id, CAST(coalesce(count(*) FILTER (event_type = 'click'), 0) AS BIGINT) AS clicks, string_agg(DISTINCT event_type, ',' ORDER BY event_type) AS kinds FROM events GROUP BY 1""")
def fn_map(t, spark):
    counts = t("events").groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n"))
    by_type = counts.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return by_type.select("user_id", F.coalesce(F.try_element_at("m", F.lit("click")), F.lit(0)).alias("clicks"), F.array_join(F.sort_array(F.map_keys("m")), ",").alias("kinds"))


@query("SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k2, '{\"k\":' || json_extract_string(props, '$.k') || '}' AS again FROM events")
def fn_json(t, spark):
    parsed = F.from_json("props", "k bigint")
    return t("events").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"), F.variant_get(F.parse_json("props"), "$.k", "bigint").alias("k2"), F.to_json(parsed).alias("again"))


# User-defined functions


@query("SELECT l_orderkey, l_linenumber, l_partkey, round(l_extendedprice * (1 + l_tax), 4) AS gross FROM lineitem")
def udf_scalar(t, spark):
    @F.udf("double")
    def gross(price, tax):
        return price * (1 + tax)

    return t("lineitem").select("l_orderkey", "l_linenumber", "l_partkey", F.round(gross("l_extendedprice", "l_tax"), 4).alias("gross"))


@query("SELECT event_id, round(value * 1.5 + 2, 4) AS v FROM events")
def udf_pandas(t, spark):
    @F.pandas_udf("double")
    def line(v: pd.Series) -> pd.Series:
        return v * 1.5 + 2

    return t("events").select("event_id", F.round(line("value"), 4).alias("v"))


@query("SELECT event_type, round(exp(avg(ln(value))), 4) AS geo FROM events GROUP BY 1")
def udaf_grouped(t, spark):
    @F.pandas_udf("double")
    def geometric(v: pd.Series) -> float:
        import numpy as np

        return float(np.exp(np.log(v).mean()))

    return t("events").groupBy("event_type").agg(F.round(geometric("value"), 4).alias("geo"))


@query("SELECT event_id, round((value - avg(value) OVER w) / stddev_samp(value) OVER w, 4) AS z FROM events WINDOW w AS (PARTITION BY user_id)")
def udf_grouped_map(t, spark):
    def z(frame: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"event_id": frame["event_id"], "z": (frame["value"] - frame["value"].mean()) / frame["value"].std()})

    return t("events").select("event_id", "user_id", "value").groupBy("user_id").applyInPandas(z, "event_id long, z double").select("event_id", F.round("z", 4).alias("z"))


@query("SELECT item_id, CAST(unnest(range(len(w))) AS INTEGER) AS pos, unnest(w) AS token FROM (SELECT item_id, string_split(text, ' ') AS w FROM benchmark)")
def udtf_tokens(t, spark):
    @F.udtf(returnType="pos int, token string")
    class Tokens:
        def eval(self, text: str):
            yield from enumerate(text.split(" "))

    spark.udtf.register("callweave_tokens", Tokens)
    t("benchmark").createOrReplaceTempView("callweave_benchmark")
    return spark.sql("SELECT item_id, pos, token FROM callweave_benchmark, LATERAL callweave_tokens(text)")


@query("""WITH o AS (SELECT o_custkey AS k, count(*) AS orders FROM orders GROUP BY 1), c AS (SELECT c_custkey AS k, c_acctbal FROM customer)
          SELECT coalesce(o.k, c.k) AS custkey, CAST(coalesce(orders, 0) AS BIGINT) AS orders, c_acctbal AS balance FROM o FULL JOIN c ON o.k = c.k""")
def cogroup_merge(t, spark):
    def merge(key, orders: pd.DataFrame, customers: pd.DataFrame) -> pd.DataFrame:
        balance = customers["c_acctbal"].iloc[0] if len(customers) else None
        return pd.DataFrame({"custkey": [key[0]], "orders": [len(orders)], "balance": [balance]})

    o, c = t("orders").select("o_custkey"), t("customer").select("c_custkey", "c_acctbal")
    return o.groupBy("o_custkey").cogroup(c.groupBy("c_custkey")).applyInPandas(merge, "custkey long, orders long, balance double")


@query("SELECT count(*) AS n, CAST(sum(l_linenumber) AS BIGINT) AS lines FROM lineitem")
def map_iterator(t, spark):
    def totals(frames):
        n = lines = 0
        for f in frames:
            n, lines = n + len(f), lines + int(f["l_linenumber"].sum())
        yield pd.DataFrame({"n": [n], "lines": [lines]})

    return t("lineitem").select("l_linenumber").mapInPandas(totals, "n long, lines long").agg(F.sum("n").alias("n"), F.sum("lines").alias("lines"))


@query("""SELECT word, n, CAST(round(n / 10.0) AS BIGINT) AS tens FROM (SELECT word, count(*) AS n FROM (SELECT unnest(list_filter(string_split_regex(lower(text), '\\s+'), lambda x: x <> '')) AS word FROM benchmark) GROUP BY word) WHERE n >= 15""")
def sql_surface(t, spark):
    from callweave.plans.surface import register

    register(spark)
    t("benchmark").createOrReplaceTempView("callweave_texts")
    return spark.sql("SELECT word, count(*) AS n, callweave_steps(count(*) * 10 - 49, 100) AS tens FROM callweave_texts, LATERAL callweave_words(text) GROUP BY word HAVING count(*) >= 15")
