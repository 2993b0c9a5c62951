"""Workloads of the cost, time and balance measures over the event table as task trace."""

from __future__ import annotations

from decimal import Decimal

from pyspark.sql import functions as F

from callweave.measures import trace as m
from callweave.operators import stages
from callweave.plans.registry import query
from callweave.tables import as_trace


@query("SELECT event_type AS phase, count(*) AS n, round(avg(value * 1000), 4) AS mean_ms, round(stddev_samp(value * 1000), 4) AS std_ms, round(quantile_cont(value * 1000, 0.95), 4) AS p95_ms FROM events GROUP BY 1")
def phase_time_summary(t, spark):
    return m.phase_summary(as_trace(t("events")))


@query("SELECT event_type AS phase, round(avg(value), 4) AS mean_s, round(sum(value) / sum(sum(value)) OVER (), 6) AS share FROM events GROUP BY 1")
def time_breakdown(t, spark):
    return m.time_breakdown(as_trace(t("events"))).select("phase", F.round(F.col("mean_ms") / 1000, 4).alias("mean_s"), F.round("share", 6).alias("share"))


@query("""WITH w AS (SELECT user_id, sum(length(props)) / sum(value) AS rate FROM events GROUP BY 1)
          SELECT count(*) AS workers, round(avg(rate), 6) AS mean_rate, round(sum(rate), 4) AS total_rate FROM w""")
def flops_summary(t, spark):
    return m.throughput(as_trace(t("events"))).select("workers", F.round("mean_rate", 6).alias("mean_rate"), F.round("total_rate", 4).alias("total_rate"))


@query("SELECT CAST(floor(value / 25) AS BIGINT) AS bin, count(*) AS n FROM events GROUP BY 1")
def bandwidth_histogram(t, spark):
    return m.histogram(t("events"), F.col("value"), 25.0)


@query("""WITH e AS (SELECT epoch_us(ts) AS s, epoch_us(ts) + CAST(round(value * 6e7) AS BIGINT) AS f FROM events),
          c AS (SELECT us, sum(d) AS d FROM (SELECT s AS us, 1 AS d FROM e UNION ALL SELECT f, -1 FROM e) GROUP BY us),
          r AS (SELECT us, sum(d) OVER (ORDER BY us) AS active, lead(us) OVER (ORDER BY us) - us AS lasts FROM c)
          SELECT CAST(max(active) AS BIGINT) AS peak, round(CAST(sum(active * lasts) AS DOUBLE) / CAST(sum(lasts) AS DOUBLE), 6) AS mean_active FROM r""")
def concurrency_peak(t, spark):
    stretched = as_trace(t("events")).withColumn("duration_ms", F.round(F.col("duration_ms") * 60, 3))
    return m.concurrency(stretched).select("peak", F.round("mean_active", 6).alias("mean_active"))


@query("""WITH s AS (SELECT p, event_id % p AS slot, sum(value) AS busy FROM events, unnest([1, 4, 16, 64]) u(p) GROUP BY ALL)
          SELECT CAST(p AS INTEGER) AS p, round(max(busy), 3) AS makespan_s, round(sum(busy) / (p * max(busy)), 6) AS efficiency FROM s GROUP BY p""")
def wave_makespan(t, spark):
    out = m.wave_makespan(as_trace(t("events")), [1, 4, 16, 64])
    return out.select("p", F.round(F.col("makespan_ms") / 1000, 3).alias("makespan_s"), F.round("efficiency", 6).alias("efficiency"))


@query("WITH d AS (SELECT event_type, median(value) AS mid FROM events GROUP BY 1) SELECT event_id AS call_id, event_type AS phase FROM events JOIN d USING (event_type) WHERE value > 3 * mid")
def straggler_flags(t, spark):
    trace = t("events").select(F.col("event_id").alias("call_id"), F.col("event_type").alias("phase"), "value")
    return m.flag_stragglers(trace, 3.0, "value").select("call_id", "phase")


SHARES = (0.1, 0.25, 0.5, 0.75, 1.0)
RATES = """WITH u AS (SELECT dense_rank() OVER (ORDER BY user_id) AS r, value FROM events), m AS (SELECT max(r) AS users FROM u),
          p AS (SELECT share, max(CAST(ceil(share * users) AS INTEGER)) AS workers, sum(value) AS rate FROM u, m, unnest([0.1e0, 0.25e0, 0.5e0, 0.75e0, 1e0]) s(share) WHERE r <= ceil(share * users) GROUP BY share)"""


def _rates_of_workers(t):
    """(workers, rate): total value of the first tenth, quarter, half, ... of all users, and how many these are."""
    from pyspark.sql import Window

    each = t("events").groupBy("user_id").agg(F.sum("value").alias("v"))  # a row a user
    ranked = each.withColumn("r", F.row_number().over(Window.orderBy("user_id")))
    users = F.broadcast(each.agg(F.count(F.lit(1)).alias("users")))
    counts = F.transform(F.array(*map(F.lit, SHARES)), lambda s: F.ceil(s * F.col("users")).cast("int"))
    sums = ranked.crossJoin(users).select("v", "r", F.explode(counts).alias("workers")).where("r <= workers")
    return sums.groupBy("workers").agg(F.sum("v").alias("rate"))


@query(RATES + " SELECT round(regr_slope(rate, workers), 4) AS slope, round(regr_r2(rate, workers), 6) AS r2 FROM p")
def scaling_linearity(t, spark):
    return m.linearity(_rates_of_workers(t), "workers", "rate").select(F.round("slope", 4).alias("slope"), F.round("r2", 6).alias("r2"))


@query("""SELECT event_type AS phase, count(*) AS calls, CAST(sum(CAST(ceil(value * 1000 / 100) AS BIGINT)) AS BIGINT) AS steps,
          CAST(sum(CAST(ceil(value * 1000 / 100) AS DECIMAL(18,0)) * CAST(0.0000025 AS DECIMAL(10,7))) AS DECIMAL(38,7)) AS usd FROM events GROUP BY 1""")
def billing_100ms(t, spark):
    d = F.col("duration_ms")
    out = as_trace(t("events")).groupBy("phase").agg(F.count(F.lit(1)).alias("calls"), F.sum(F.ceil(d / 100)).alias("steps"), F.sum(m.call_charge(d)).alias("usd"))
    return out.withColumn("usd", F.col("usd").cast("decimal(38,7)"))


@query("""WITH c AS (SELECT CAST(sum(CAST(ceil(value * 1000 / 100) AS DECIMAL(18,0)) * CAST(0.0000025 AS DECIMAL(10,7))) AS DECIMAL(28,7)) AS calls_usd FROM events)
          SELECT calls_usd, CAST(30 * 1.17 * 205 / 3600 AS DECIMAL(28,7)) AS nodes_usd FROM c""")
def job_cost_prorated(t, spark):
    cost = m.job_cost(as_trace(t("events")), 30, Decimal("1.17"), 204.4)
    return cost.select(F.col("calls_usd").cast("decimal(28,7)").alias("calls_usd"), "nodes_usd")


@query("""WITH w AS (SELECT user_id, CAST(sum(CAST(round(value * 100) AS BIGINT)) AS DOUBLE) / 100 / count(value) AS bw FROM events GROUP BY 1)
          SELECT user_id AS worker, CAST(mem AS INTEGER) AS memory_mb, CAST(lim AS INTEGER) AS limit_s, round(mem / bw, 4) AS fill_s, round(lim - 2 * (mem / bw), 4) AS compute_s, round(2 * (mem / bw) / lim, 6) AS io_share, round(bw * lim * 0.25e0 / 2, 3) AS memory_at_quarter
          FROM w, unnest([512e0, 1536e0, 3008e0]) a(mem), unnest([300e0, 900e0]) c(lim) WHERE bw > 0""")
def balance_rule(t, spark):
    """Each worker's mean bandwidth (hundredths are summed whole) against sizes of memory and limits of time."""
    cents = F.sum(F.round(F.col("value") * 100).cast("long")).cast("double")
    workers = t("events").where("value IS NOT NULL").groupBy(F.col("user_id").alias("worker")).agg((cents / 100 / F.count("value")).alias("bw"))
    sizes = F.explode(F.array(*map(F.lit, (512, 1536, 3008))))
    g = workers.where("bw > 0").select("*", sizes.alias("memory_mb")).select("*", F.explode(F.array(F.lit(300), F.lit(900))).alias("limit_s"))
    b = m.balance(F.col("memory_mb"), F.col("bw"), F.col("limit_s"))
    quarter = m.memory_for(F.col("limit_s"), F.col("bw"), 0.25)
    return g.select("worker", "memory_mb", "limit_s", F.round(b["fill_s"], 4).alias("fill_s"), F.round(b["compute_s"], 4).alias("compute_s"), F.round(b["io_share"], 6).alias("io_share"), F.round(quarter, 3).alias("memory_at_quarter"))


@query("""WITH f AS (SELECT regr_intercept(value * 1000, length(props)) AS a, regr_slope(value * 1000, length(props)) AS b FROM events WHERE event_id % 10 = 0)
          SELECT round(sum(greatest(a + b * length(props), 0)) / 1000, 2) AS predicted_s, round(sum(value), 2) AS actual_s FROM events, f WHERE event_id % 10 <> 0""")
def predict_cost_regression(t, spark):
    out = m.predict_cost(as_trace(t("events")), F.col("call_id") % 10 == 0)
    return out.select(F.round(F.col("predicted_ms") / 1000, 2).alias("predicted_s"), F.round(F.col("actual_ms") / 1000, 2).alias("actual_s"))


@query(RATES + " SELECT workers, round(rate / lag(rate) OVER (ORDER BY workers) - 1, 6) AS change FROM p")
def speedup_change(t, spark):
    return m.relative_change(_rates_of_workers(t), "workers", "rate").select("workers", F.round("change", 6).alias("change"))


@query("SELECT event_type AS phase, round(quantile_cont(value * 1000, 0.5), 4) AS p50, round(quantile_cont(value * 1000, 0.9), 4) AS p90, round(quantile_cont(value * 1000, 0.99), 4) AS p99 FROM events GROUP BY 1")
def latency_quantiles(t, spark):
    q = m.latency_quantiles(as_trace(t("events")))
    return q.select("phase", *[F.round(c, 4).alias(c) for c in ("p50", "p90", "p99")])


@query("SELECT round(sum(CASE WHEN event_type IN ('view', 'search') THEN value ELSE 0 END) / sum(value), 6) AS overhead_share FROM events")
def overhead_share(t, spark):
    return m.overhead_share(as_trace(t("events")), ["view", "search"]).select(F.round("overhead_share", 6).alias("overhead_share"))


@query("SELECT min(epoch_us(ts)) AS start_us, max(epoch_us(ts) + CAST(round(value * 1000000) AS BIGINT)) AS end_us FROM events")
def trace_makespan(t, spark):
    return m.makespan(as_trace(t("events"))).select("start_us", "end_us")


@query("SELECT CAST(max(n) AS BIGINT) AS most, round(avg(n), 4) AS mean, round(max(n) / avg(n), 6) AS skew FROM (SELECT user_id % 16 AS s, count(*) AS n FROM events GROUP BY 1)")
def shard_skew(t, spark):
    from callweave.sources.kv import shard_load
    from callweave.tables import as_key_values

    return m.shard_skew(shard_load(as_key_values(t("events"), 16))).select("most", F.round("mean", 4).alias("mean"), F.round("skew", 6).alias("skew"))


@query("""WITH b AS (SELECT user_id, CAST(sum(CAST(round(value * 100) AS BIGINT)) AS DOUBLE) AS busy FROM events GROUP BY 1), x AS (SELECT max(busy) AS most FROM b)
          SELECT user_id AS server, p AS premium, round(busy / most, 6) AS utilisation, busy / most * p > 1 AS servers_cheaper, round(1 / p, 6) AS break_even FROM b, x, unnest([1.5e0, 2e0, 3e0]) a(p) WHERE most > 0""")
def premium_break_even(t, spark):
    """Utilisation is a server's busy time (hundredths are summed whole) as a share of the busiest one's."""
    busy = t("events").groupBy(F.col("user_id").alias("server")).agg(F.sum(F.round(F.col("value") * 100).cast("long")).cast("double").alias("busy"))
    most = busy.agg(F.max("busy").alias("most")).where("most > 0")
    g = busy.crossJoin(F.broadcast(most)).select("server", F.explode(F.array(*map(F.lit, (1.5, 2.0, 3.0)))).alias("premium"), (F.col("busy") / F.col("most")).alias("u"))
    return g.select("server", "premium", F.round("u", 6).alias("utilisation"), m.servers_cheaper(F.col("premium"), F.col("u")).alias("servers_cheaper"), F.round(1 / F.col("premium"), 6).alias("break_even"))


@query("""WITH m AS (SELECT avg(value) FILTER (event_type = 'view') AS a, avg(value) FILTER (event_type = 'click') AS b, avg(value) AS bw, count(*) AS n, sum(length(props)) AS bytes,
                            sum(CASE WHEN event_type = 'signup' THEN value ELSE 0 END) / sum(value) AS launch FROM events),
          r AS (SELECT sum(rate) AS total FROM (SELECT user_id % 16 AS w, sum(length(props)) / sum(value) AS rate FROM events GROUP BY 1))
          SELECT v.name, round(v.value, 4) AS value FROM m, r, LATERAL (VALUES ('slowdown_percent', 100 * (a / b - 1)), ('intermediate_files', CAST(ceil(bytes / 1e5) * ceil(bytes / 1e5) AS DOUBLE)), ('fill_seconds', 1536 / bw),
               ('compute_seconds_of_300', 300 - 2 * (1400 / bw)), ('launch_share_percent', 100 * launch), ('bytes_s_of_16_calls', total)) v(name, value)""")
def published_arithmetic(t, spark):
    """The kinds of figures that the reference derives, by this library's own measures, over the event table as trace.

    A value is a call's bandwidth for the rule of balance, its time for the rest; a task holds 100 kB.
    """
    from callweave.operators.rangesort import required_tasks, shuffle_files

    trace = as_trace(t("events"))
    rule = {k: m.balance(F.lit(float(memory)), F.avg("duration_ms") / 1000, F.lit(300.0))[k] for k, memory in (("fill_s", 1536), ("compute_s", 1400))}
    means = [F.avg(F.when(F.col("phase") == p, F.col("duration_ms"))).alias(p) for p in ("view", "click")]
    sums = trace.agg(*means, F.sum("bytes").alias("bytes"), *[v.alias(k) for k, v in rule.items()])
    sixteen = m.throughput(trace.withColumn("worker", F.col("worker") % 16)).select("total_rate")
    found = sums.crossJoin(m.overhead_share(trace, ["signup"])).crossJoin(sixteen).first()  # one row

    rows = [
        ("slowdown_percent", 100 * m.slowdown(found["view"], found["click"])),
        ("intermediate_files", float(shuffle_files(required_tasks(found["bytes"], 1e5)))),
        ("fill_seconds", found["fill_s"]),
        ("compute_seconds_of_300", found["compute_s"]),
        ("launch_share_percent", 100 * found["overhead_share"]),
        ("bytes_s_of_16_calls", found["total_rate"]),
    ]
    return spark.createDataFrame(rows, "name string, value double").withColumn("value", F.round("value", 4))


@query("SELECT * FROM (VALUES ('nation', 0), ('region', 0), ('customer', 1), ('supplier', 1), ('orders', 2), ('lineitem', 3)) v(stage, level)")
def stage_levels(t, spark):
    waits = {"customer": ["nation", "region"], "supplier": ["nation"], "orders": ["customer"], "lineitem": ["orders", "supplier"]}
    return spark.createDataFrame([(s, i) for i, names in enumerate(stages.plan_stages(waits)) for s in names], "stage string, level int")


@query("SELECT user_id AS job, n AS calls, CAST(slots AS INTEGER) AS slots, CAST(ceil(n / slots) * 300 AS DOUBLE) AS seconds FROM (SELECT user_id, count(*) AS n FROM events GROUP BY 1), unnest([10, 100, 1000]) b(slots)")
def elastic_makespan(t, spark):
    """A user's events as the calls of a job, each of five minutes, on as many slots as it is given."""
    jobs = t("events").groupBy(F.col("user_id").alias("job")).agg(F.count(F.lit(1)).alias("calls"))
    g = jobs.select("*", F.explode(F.array(F.lit(10), F.lit(100), F.lit(1000))).alias("slots"))
    return g.withColumn("seconds", m.ideal_makespan(F.col("calls"), F.col("slots"), 300).cast("double"))
