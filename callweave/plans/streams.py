"""Workloads of Structured Streaming: replayed event tables against the batch answer."""

from __future__ import annotations

from pyspark.sql import functions as F

from callweave.plans.registry import query
from callweave.plans.relational import INTERVAL
from callweave.streaming import streams as st
from callweave.tables import settle, shared_path


def _events(t):
    return st.with_time(t("events"))


@query("SELECT epoch_us(date_trunc('day', ts)) AS start_us, event_type, count(*) AS n, round(sum(value), 3) AS total FROM events GROUP BY ALL")
def stream_tumbling(t, spark):
    w = st.count_windows(st.replay(_events(t), 4, "ts"), "1 day")
    return st.settle_stream(w, "complete").select("start_us", "event_type", "n", F.round("total", 3).alias("total"))


@query("""SELECT s AS start_us, event_type, count(*) AS n, round(sum(value), 3) AS total FROM (SELECT *, unnest(list_transform(range(0, 6), lambda i: (epoch_us(ts) // 3600000000 - i) * 3600000000)) AS s FROM events) GROUP BY ALL""")
def stream_sliding(t, spark):
    w = st.count_windows(st.replay(_events(t), 3, "ts"), "6 hours", "1 hour")
    return st.settle_stream(w, "update", ["start_us", "event_type"]).select("start_us", "event_type", "n", F.round("total", 3).alias("total"))


@query("""WITH g AS (SELECT user_id, epoch_us(ts) AS us, lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY event_id) AS prev FROM events),
          s AS (SELECT *, sum(CASE WHEN prev IS NULL OR us - prev >= 7200000000 THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY us) AS k FROM g)
          SELECT user_id, min(us) AS start_us, max(us) AS end_us, count(*) AS n FROM s GROUP BY user_id, k""")
def stream_session(t, spark):
    return st.settle_stream(st.sessions(st.replay(_events(t), 1, "ts"), "2 hours"), "complete")


@query("SELECT event_id, user_id FROM events")
def stream_dedupe(t, spark):
    """The files arrive twice; the second copy falls within the watermark's reach."""
    e, path = _events(t).select("event_id", "user_id", "ts"), shared_path(spark)
    for _ in range(2):
        e.coalesce(1).write.mode("append").parquet(path)
    stream = st.read_stream(spark, e.schema, path, one_per_batch=False)
    return st.settle_stream(stream.withWatermark("ts", "60 days").dropDuplicatesWithinWatermark(["event_id"])).select("event_id", "user_id")


@query("SELECT event_id, n_name FROM events JOIN customer ON user_id = c_custkey JOIN nation ON c_nationkey = n_nationkey")
def stream_static_join(t, spark):
    names = t("customer").join(t("nation"), F.col("c_nationkey") == F.col("n_nationkey")).select(F.col("c_custkey").alias("user_id"), "n_name")
    stream = st.replay(_events(t).select("event_id", "user_id", "ts"), 2, "ts")
    return st.settle_stream(stream.join(names, "user_id").select("event_id", "n_name"))


@query(INTERVAL)
def stream_stream_join(t, spark):
    stream = st.replay(_events(t).select("event_id", "user_id", "event_type", "ts"), 1, "ts")
    c = stream.where("event_type = 'click'").select(F.col("event_id").alias("click_id"), F.col("user_id").alias("u"), F.col("ts").alias("c_ts")).withWatermark("c_ts", "1 hour")
    p = stream.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), "user_id", F.col("ts").alias("p_ts")).withWatermark("p_ts", "1 hour")
    near = (F.col("u") == F.col("user_id")) & (F.col("p_ts") >= F.col("c_ts")) & (F.col("p_ts") < F.col("c_ts") + F.expr("INTERVAL 1 HOUR"))
    return st.settle_stream(c.join(p, near).select("click_id", "purchase_id"))


@query("SELECT user_id, count(*) AS n, CAST(sum(CAST(round(value * 100) AS BIGINT)) AS BIGINT) AS total_cents FROM events GROUP BY 1")
def stream_stateful(t, spark):
    counts = st.running_counts(st.replay(_events(t).select("user_id", "value", "ts"), 3, "ts"))
    return st.settle_stream(counts, "update", ["user_id"])


@query("""SELECT epoch_us(date_trunc('day', ts)) AS start_us, count(*) AS n FROM events WHERE date_trunc('day', ts) <> TIMESTAMP '2024-01-04' GROUP BY 1""")
def stream_late_drop(t, spark):
    """The fourth of January arrives after everything else and a closing row, beyond the watermark's reach: it is dropped."""
    e, path = _events(t).select("event_id", "ts"), shared_path(spark)
    late = (F.col("ts") >= F.lit("2024-01-04").cast("timestamp")) & (F.col("ts") < F.lit("2024-01-05").cast("timestamp"))
    closing = spark.createDataFrame([(-1,)], "event_id long").withColumn("ts", F.lit("2030-01-01").cast("timestamp"))
    for part in (e.where(~late), closing, e.where(late)):
        part.coalesce(1).write.mode("append").parquet(path)
    w = st.read_stream(spark, e.schema, path).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 day").alias("w")).agg(F.count(F.lit(1)).alias("n"))
    out = st.settle_stream(w.select(F.unix_micros("w.start").alias("start_us"), "n"), "update", ["start_us"])
    return out.where(F.col("start_us") < F.unix_micros(F.lit("2030-01-01").cast("timestamp")))


@query("SELECT o_orderstatus, count(*) AS n, CAST(sum(o_orderkey) AS BIGINT) AS keys FROM orders GROUP BY 1")
def stream_trigger_fn(t, spark):
    """A function per arriving file; the stream is started again from its log, and nothing takes effect twice."""
    orders, out, log = t("orders").select("o_orderkey", "o_orderstatus", "o_orderdate"), shared_path(spark), shared_path(spark)
    stream = st.replay(orders, 3, "o_orderdate")
    summary = lambda b: b.groupBy("o_orderstatus").agg(F.count(F.lit(1)).alias("n"), F.sum("o_orderkey").alias("keys"))
    for _ in range(2):
        st.on_arrival(stream, summary, out, log)
    parts = spark.read.schema("o_orderstatus string, n long, keys long").parquet(f"{out}/*")
    return parts.groupBy("o_orderstatus").agg(F.sum("n").alias("n"), F.sum("keys").alias("keys"))


@query("""WITH RECURSIVE m AS (SELECT dense_rank() OVER (ORDER BY l_returnflag) AS n, avg(l_quantity / 50) AS mx, avg((l_quantity / 50) * (l_quantity / 50)) AS mxx, avg(l_extendedprice / 100000) AS my,
              avg(l_quantity / 50 * l_extendedprice / 100000) AS mxy FROM lineitem GROUP BY l_returnflag),
          w(version, b, s) AS (SELECT 0::BIGINT, 0e0, 0e0 UNION ALL SELECT version + 1, b - 0.5e0 * (b + mx * s - my), s - 0.5e0 * (mx * b + mxx * s - mxy) FROM w JOIN m ON n = version + 1)
          SELECT version, round(b, 6) AS bias, round(s, 6) AS slope FROM w""")
def stream_param_server(t, spark):
    """A batch of each return flag is one synchronous step; the stream stops before the last one and goes on from its stored model."""
    rows = settle(t("lineitem").select((F.col("l_quantity") / 50).alias("x"), (F.col("l_extendedprice") / 100000).alias("y"), "l_returnflag"))
    path, model, log = (shared_path(spark) for _ in range(3))
    flags = [r[0] for r in rows.select("l_returnflag").distinct().orderBy("l_returnflag").collect()]
    for some in (flags[:-1], flags[-1:]):
        for flag in some:
            rows.where(F.col("l_returnflag") == flag).coalesce(1).write.mode("append").parquet(path)
        versions = st.stream_training(st.read_stream(spark, rows.schema, path), "x", "y", 0.5, model, log)
    return versions.groupBy("version").agg(*[F.round(F.max(F.when(F.col("idx") == i, F.col("weight"))), 6).alias(c) for i, c in enumerate(("bias", "slope"))])
