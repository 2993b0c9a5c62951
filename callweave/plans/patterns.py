"""Workloads of the layered models: sweeps, simulation, features, learners, map-reduce, supersteps, sort, parameter server."""

from __future__ import annotations

import math

from pyspark.sql import functions as F

from callweave.functions import features as feat
from callweave.learn import linear
from callweave.operators import bsp, gather, mapreduce, paramserver, rangesort, sweep
from callweave.plans.registry import query
from callweave.tables import settle, shared_path, spread

LAMBDAS = (0.0, 1.0, 10.0, 100.0, 1000.0)
RIDGE_SQL = """WITH s AS (SELECT l_returnflag, count(*) AS n, sum(x * x) AS xx, sum(x * y) AS xy, sum(y * y) AS yy FROM (SELECT l_returnflag, l_quantity / 50 AS x, l_extendedprice / 100000 AS y FROM lineitem) GROUP BY 1),
    g AS (SELECT l_returnflag, pow(10, p) * (p >= 0)::INT AS lam, n, xx, xy, yy, xy / (xx + pow(10, p) * (p >= 0)::INT * n / 100) AS w FROM s, unnest([-1, 0, 1, 2, 3]) AS u(p))"""
HEX = lambda col, salt: f"CAST('0x' || substr(md5(CAST({col} AS VARCHAR) || ':{salt}'), 1, 6) AS BIGINT)"


def _ridge_grid(t):
    rows = t("lineitem").select("l_returnflag", (F.col("l_quantity") / 50).alias("x"), (F.col("l_extendedprice") / 100000).alias("y"))
    x, y = F.col("x"), F.col("y")
    stats = rows.groupBy("l_returnflag").agg(F.count(F.lit(1)).alias("n"), F.sum(x * x).alias("xx"), F.sum(x * y).alias("xy"), F.sum(y * y).alias("yy"))
    points = stats.withColumn("lam", F.explode(F.array(*map(F.lit, LAMBDAS)))).withColumn("w", F.col("xy") / (F.col("xx") + F.col("lam") * F.col("n") / 100))
    mse = (F.col("yy") - 2 * F.col("w") * F.col("xy") + F.col("w") * F.col("w") * F.col("xx")) / F.col("n")
    return points.select("l_returnflag", "lam", F.round("w", 6).alias("w"), F.round(mse, 6).alias("mse"))


@query(RIDGE_SQL + " SELECT l_returnflag, CAST(lam AS DOUBLE) AS lam, round(w, 6) AS w, round((yy - 2 * w * xy + w * w * xx) / n, 6) AS mse FROM g")
def sweep_ridge_grid(t, spark):
    return _ridge_grid(t)


@query(RIDGE_SQL + " SELECT l_returnflag, CAST(arg_min(lam, mse * 1e6 + lam) AS DOUBLE) AS lam, round(min(mse), 6) AS mse FROM (SELECT l_returnflag, lam, round((yy - 2 * w * xy + w * w * xx) / n, 6) AS mse FROM g) GROUP BY 1")
def sweep_best(t, spark):
    scored = _ridge_grid(t).select("l_returnflag", (F.col("mse") * 1e6 + F.col("lam")).alias("score"), F.col("lam").alias("point_id"), "mse")
    return sweep.best(scored, ["l_returnflag"]).select("l_returnflag", F.col("point_id").alias("lam"), "mse")


@query("""SELECT CAST(g AS INTEGER) AS degree, CAST(50 * (g + 1) AS DOUBLE) AS score FROM range(0, 12) r(g)""")
def sweep_calls(t, spark):
    """A Python training function once per grid point."""
    points = sweep.grid(degree=list(range(12)), scale=[50])
    scores = sweep.sweep(spark, lambda p, data: p["scale"] * (p["degree"] + data), points, data=1)
    return scores.select(F.col("params")["degree"].cast("int").alias("degree"), "score")


@query(f"""WITH u AS (SELECT {HEX('event_id', 'x')} AS x, {HEX('event_id', 'y')} AS y FROM events)
          SELECT count(*) AS n, CAST(count(*) FILTER (x * x + y * y <= 281474976710656) AS BIGINT) AS inside, round(4.0 * count(*) FILTER (x * x + y * y <= 281474976710656) / count(*), 6) AS estimate FROM u""")
def monte_carlo_pi(t, spark):
    x, y = (sweep.hashed_uniform(F.col("event_id"), s) for s in "xy")
    inside = F.count(F.when(x * x + y * y <= 1 << 48, 1))
    return t("events").agg(F.count(F.lit(1)).alias("n"), inside.alias("inside"), F.round(4.0 * inside / F.count(F.lit(1)), 6).alias("estimate"))


@query("""WITH w AS (SELECT r, o_totalprice AS x, CAST('0x' || substr(md5(CAST(o_orderkey AS VARCHAR) || ':' || r), 1, 2) AS INTEGER) AS h FROM orders, range(0, 8) t(r)),
          c AS (SELECT r, x, (h >= 94)::INT + (h >= 188)::INT + (h >= 235)::INT + (h >= 251)::INT AS k FROM w)
          SELECT CAST(r AS INTEGER) AS replicate, round(sum(k * x) / sum(k), 4) AS mean_price, CAST(sum(k) AS BIGINT) AS draws FROM c GROUP BY r""")
def monte_carlo_bootstrap(t, spark):
    rows = t("orders").select("o_orderkey", "o_totalprice", F.explode(F.sequence(F.lit(0), F.lit(7))).alias("replicate"))
    h = F.conv(F.substring(F.md5(F.concat_ws(":", F.col("o_orderkey").cast("string"), F.col("replicate").cast("string")).cast("binary")), 1, 2), 16, 10).cast("int")
    # Cumulative shares of a Poisson(1) count, of 256.
    k = sum((F.when(h >= c, 1).otherwise(0) for c in (94, 188, 235, 251)), F.lit(0))
    drawn = rows.withColumn("k", k)
    return drawn.groupBy("replicate").agg(F.round(F.sum(F.col("k") * F.col("o_totalprice")) / F.sum("k"), 4).alias("mean_price"), F.sum("k").alias("draws"))


@query("""WITH c AS (SELECT s, vec_id, embedding FROM embeddings, range(0, 5) t(s)), m AS (SELECT s, min(CAST('0x' || substr(md5(vec_id || ':' || s), 1, 8) AS BIGINT) * 10000000 + vec_id) % 10000000 AS centre FROM c GROUP BY s),
          d AS (SELECT m.s, m.centre, sum(1 - list_inner_product(CAST(e.embedding AS DOUBLE[]), CAST(x.embedding AS DOUBLE[]))) AS loss FROM m JOIN embeddings x ON x.vec_id = m.centre, embeddings e GROUP BY ALL)
          SELECT CAST(arg_min(s, loss) AS INTEGER) AS seed, CAST(arg_min(centre, loss) AS BIGINT) AS centre, round(min(loss), 4) AS loss FROM d""")
def restarts_best(t, spark):
    """Seeds choose a centre by hash; the one with the least total cosine distance wins. Five candidates are broadcast."""
    e = t("embeddings").select("vec_id", F.transform("embedding", lambda v: v.cast("double")).alias("v"))
    seeds = e.select("vec_id", F.explode(F.sequence(F.lit(0), F.lit(4))).alias("seed"))
    h = F.conv(F.substring(F.md5(F.concat_ws(":", F.col("vec_id").cast("string"), F.col("seed").cast("string")).cast("binary")), 1, 8), 16, 10).cast("long")
    chosen = seeds.groupBy("seed").agg(F.min_by("vec_id", F.struct(h, "vec_id")).alias("centre"))
    centres = chosen.join(e.withColumnRenamed("v", "c"), F.col("centre") == F.col("vec_id")).select("seed", "centre", "c")
    dot = F.aggregate(F.zip_with("v", "c", lambda a, b: a * b), F.lit(0.0), lambda s, x: s + x)
    losses = e.crossJoin(F.broadcast(centres)).groupBy("seed", "centre").agg(F.sum(1 - dot).alias("score")).withColumnRenamed("seed", "point_id")
    return sweep.best(losses).select(F.col("point_id").alias("seed"), "centre", F.round("score", 4).alias("loss"))


PIXELS = "(SELECT vec_id, i - 1 AS i, CAST(embedding[i] AS DOUBLE) AS v FROM embeddings, range(1, 65) t(i))"


@query(f"""SELECT vec_id, CAST((i // 8 - 1) // 2 * 3 + (i % 8 - 1) // 2 AS INTEGER) AS cell, round(avg(v), 6) AS v FROM {PIXELS} WHERE i // 8 BETWEEN 1 AND 6 AND i % 8 BETWEEN 1 AND 6 GROUP BY ALL""")
def featurize_crop_scale(t, spark):
    px = F.transform("embedding", lambda v: v.cast("double"))
    small = feat.scale(feat.crop(px, 8, 1, 1, 6, 6), 6, 6, 2)
    return spread(t("embeddings").select("vec_id", "embedding"), "vec_id").select("vec_id", F.posexplode(small).alias("cell", "v")).withColumn("v", F.round("v", 6))


@query(f"""WITH p AS (SELECT vec_id, i // 8 - 1 AS r, i % 8 - 1 AS c, v FROM {PIXELS} WHERE i // 8 BETWEEN 1 AND 6 AND i % 8 BETWEEN 1 AND 6),
          g AS (SELECT a.vec_id, a.r, a.c, x.v - a.v AS dx, y.v - a.v AS dy FROM p a JOIN p x ON a.vec_id = x.vec_id AND x.r = a.r AND x.c = a.c + 1 JOIN p y ON a.vec_id = y.vec_id AND y.c = a.c AND y.r = a.r + 1),
          e AS (SELECT vec_id, CAST((r // 3 * 2 + c // 3) * 4 + (dx < 0)::INT + 2 * (dy < 0)::INT AS INTEGER) AS slot, sum(abs(dx) + abs(dy)) AS e FROM g GROUP BY ALL)
          SELECT v.vec_id, CAST(s AS INTEGER) AS slot, round(coalesce(e, 0), 5) AS energy FROM (SELECT vec_id FROM embeddings) v CROSS JOIN range(0, 16) t(s) LEFT JOIN e ON e.vec_id = v.vec_id AND e.slot = s""")
def featurize_descriptor(t, spark):
    px = F.transform("embedding", lambda v: v.cast("double"))
    desc = feat.gradient_descriptor(feat.crop(px, 8, 1, 1, 6, 6), 6, 6)
    return spread(t("embeddings").select("vec_id", "embedding"), "vec_id").select("vec_id", F.posexplode(desc).alias("slot", "energy")).withColumn("energy", F.round("energy", 5))


@query("""WITH w AS (SELECT *, list_filter(string_split_regex(lower(text), '\\s+'), lambda x: x <> '') AS ws FROM documents)
          SELECT doc_id, CAST(len(ws) AS INTEGER) AS n_tokens, CAST(len(list_distinct(ws)) AS INTEGER) AS n_distinct, CAST(coalesce(list_sum(list_transform(ws, lambda x: length(x))), 0) AS BIGINT) AS token_chars,
            CAST(length(regexp_replace(text, '[^0-9]', '', 'g')) AS INTEGER) AS n_digits, CAST(len(string_split(text, chr(10))) AS INTEGER) AS n_lines, CAST(length(regexp_replace(text, '[^A-Z]', '', 'g')) AS INTEGER) AS n_capitals,
            array_to_string(list_transform(string_split('0,1,2,3,4,5,6,7,8,9,a,b,c,d,e,f', ','), lambda h: len(list_filter(ws, lambda x: substr(md5(x), 1, 1) = h))), ',') AS hashed FROM w""")
def featurize_text(t, spark):
    return feat.text_features(spread(t("documents").select("doc_id", "text"), "doc_id")).drop("text").withColumn("hashed", F.array_join(F.transform("hashed", lambda n: n.cast("string")), ","))


@query("""SELECT page_id, regexp_extract(url, '^https?://([^/?#]+)', 1) AS host, length(html) AS n_html, CAST(len(regexp_extract_all(html, '(?i)<a[ >]')) AS BIGINT) AS n_links, CAST(len(regexp_extract_all(html, '(?i)<p[ >]')) AS BIGINT) AS n_paragraphs,
          CAST(len(regexp_extract_all(html, '(?i)<li[ >]')) AS BIGINT) AS n_items, CAST(len(regexp_extract_all(html, '(?i)<script[ >]')) AS BIGINT) AS n_scripts FROM pages""")
def featurize_pages(t, spark):
    return feat.page_features(t("pages")).drop("html", "url")


@query(f"SELECT CAST(a.i AS INTEGER) AS i, CAST(b.i AS INTEGER) AS j, round(sum(a.v * b.v), 5) AS v FROM {PIXELS} a JOIN {PIXELS} b USING (vec_id) GROUP BY ALL")
def gather_gram(t, spark):
    g = gather.gram(t("embeddings"), "embedding")
    return g.select("i", "j", F.round("v", 5).alias("v"))


@query(f"SELECT label, CAST(i AS INTEGER) AS dim, round(avg(v), 6) AS mean FROM (SELECT label, i - 1 AS i, CAST(embedding[i] AS DOUBLE) AS v FROM embeddings, range(1, 65) t(i)) GROUP BY ALL")
def gather_class_centroids(t, spark):
    mapped = lambda df: df.select("label", F.posexplode("embedding").alias("dim", "x"))
    reduced = lambda df: df.groupBy("label", "dim").agg(F.round(F.avg(F.col("x").cast("double")), 6).alias("mean"))
    return gather.map_then_gather(t("embeddings"), mapped, reduced, where="tree")


@query("SELECT label, count(*) AS n FROM embeddings GROUP BY label")
def gather_in_task(t, spark):
    """The one-machine reduce itself: all mapped rows meet in a single task, behind a check of their size."""
    count = lambda f: f.groupby("label", as_index=False).size().rename(columns={"size": "n"})
    return gather.map_then_gather(t("embeddings"), lambda df: df.select("label"), count, where="task", schema="label int, n long", max_bytes=64 << 20)


@query("SELECT l_returnflag, l_linestatus, round(regr_slope(l_extendedprice, l_quantity), 4) AS slope, round(regr_intercept(l_extendedprice, l_quantity), 3) AS intercept, count(*) AS n FROM lineitem GROUP BY ALL")
def linear_fit_1d(t, spark):
    y, x = "l_extendedprice", "l_quantity"
    return t("lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.round(F.regr_slope(y, x), 4).alias("slope"), F.round(F.regr_intercept(y, x), 3).alias("intercept"), F.count(F.lit(1)).alias("n"))


@query()
def linear_classifier_eval(t, spark):
    e = t("embeddings")
    model = linear.fit_ridge_spread(e, "embedding", "label")
    return linear.confusion(model.apply(e, "embedding"), "label", "predicted")


def _labelled_text(t):
    rows = feat.text_features(t("documents").select("doc_id", "text")).join(t("labels").select("doc_id", "quality"), "doc_id")
    n = F.greatest(F.col("n_tokens"), F.lit(1))
    chars = F.greatest(F.col("token_chars"), F.lit(1))
    x = F.array(F.log1p("n_tokens"), F.col("n_distinct") / n, F.col("token_chars") / n, F.col("n_digits") / chars, F.col("n_lines") / n, F.col("n_capitals") / chars)
    return rows.select("doc_id", "quality", x.alias("x"))


def _learn_text(t, spark, fit):
    import numpy as np

    def learn(table):
        x = linear.standardise(np.stack(table["x"].to_pylist()))
        return x, np.array(table["quality"].to_pylist()), table["doc_id"].to_pylist()

    x, y, ids = gather.map_then_gather(_labelled_text(t), lambda df: df.orderBy("doc_id"), learn, max_bytes=256 << 20)
    model = fit(x, y)
    return spark.createDataFrame([(int(i), int(a), int(b)) for i, a, b in zip(ids, y, model.predict(x))], "doc_id long, quality int, predicted int")


@query()
def quality_classifier_eval(t, spark):
    """The plain order: map to features, gather on one machine behind a size check, dense algebra there."""
    return linear.confusion(_learn_text(t, spark, lambda x, y: linear.fit_ridge(x, y.tolist())), "quality", "predicted")


@query()
def svm_hinge_fit(t, spark):
    return linear.confusion(_learn_text(t, spark, linear.fit_hinge), "quality", "predicted")


@query()
def logistic_fit(t, spark):
    return linear.confusion(_learn_text(t, spark, linear.fit_logistic), "quality", "predicted")


WORDS = "SELECT {by} unnest(list_filter(string_split_regex(lower(text), '\\s+'), lambda x: x <> '')) AS word FROM {t}"
COUNT = "SELECT word, count(*) AS n FROM (" + WORDS.format(by="", t="documents") + ") GROUP BY word"


@query(COUNT)
def word_count_documents(t, spark):
    return mapreduce.word_count(t("documents"))


@query("SELECT word, count(*) AS n FROM (SELECT unnest(regexp_extract_all(lower(text), '[a-z]+')) AS word FROM documents) GROUP BY word")
def word_count_ascii(t, spark):
    return mapreduce.word_count(t("documents"), pattern="[a-z]+")


@query(COUNT)
def word_count_nocombine(t, spark):
    return mapreduce.word_count(t("documents"), combine=False)


@query(COUNT)
def word_count_objects(t, spark):
    return mapreduce.word_count(t("documents"), shuffle="objects", parts=8)


@query(COUNT)
def word_count_opaque_objects(t, spark):
    """Stateless calls with their shuffle by stored objects."""
    return mapreduce.word_count_opaque(t("documents"), shuffle="objects")


@query(COUNT)
def word_count_opaque(t, spark):
    return mapreduce.word_count_opaque(t("documents"))


@query("SELECT lang, word, count(*) AS n FROM (" + WORDS.format(by="lang,", t="documents") + ") GROUP BY ALL")
def word_count_by_lang(t, spark):
    return mapreduce.word_count(t("documents"), by=["lang"])


@query("SELECT word, count(*) AS n FROM (" + WORDS.format(by="", t="conversations") + ") GROUP BY word ORDER BY n DESC, word LIMIT 25")
def word_count_top(t, spark):
    return mapreduce.word_count(t("conversations")).orderBy(F.desc("n"), "word").limit(25)


@query("SELECT l_returnflag || l_linestatus AS key, CAST(sum(CAST(round(l_extendedprice * 100) AS BIGINT)) AS BIGINT) AS result FROM lineitem GROUP BY 1")
def mapreduce_revenue(t, spark):
    rows = t("lineitem").select("l_returnflag", "l_linestatus", F.round(F.col("l_extendedprice") * 100).cast("long").alias("cents"))
    return mapreduce.map_reduce(rows, lambda r: [(r["l_returnflag"] + r["l_linestatus"], r["cents"])], "sum", "string", "long", "long")


@query("SELECT p_brand AS key, CAST(max(p_size) - min(p_size) AS BIGINT) AS result FROM part GROUP BY 1")
def mapreduce_opaque(t, spark):
    return mapreduce.map_reduce(t("part").select("p_brand", "p_size"), lambda r: [(r["p_brand"], r["p_size"])], lambda k, v: max(v) - min(v), "string", "long", "long", parts=8)


@query("SELECT word, CAST(item_id // 64 AS BIGINT) AS block, string_agg(item_id, ',' ORDER BY item_id) AS ids FROM (SELECT DISTINCT item_id, unnest(list_filter(string_split_regex(lower(text), '\\s+'), lambda x: x <> '')) AS word FROM benchmark) GROUP BY ALL")
def mapreduce_inverted_index(t, spark):
    """Postings in blocks of 64 ids: no row grows with the frequency of its word."""
    rows = mapreduce.postings(t("benchmark"), "item_id", "text", 64)
    return rows.select("word", "block", F.array_join(F.transform("ids", lambda i: i.cast("string")), ",").alias("ids"))


@query("SELECT mode, count(*) AS n, CAST(sum(length(line)) AS BIGINT) AS chars FROM (SELECT unnest(string_split(text, chr(10))) AS line FROM documents), (VALUES ('blocks'), ('whole')) v(mode) GROUP BY mode")
def read_blocks_or_whole(t, spark):
    """The same text objects by parallel block reads and by one read each; experiments time them."""
    path = shared_path(spark)
    t("documents").select("text").coalesce(1).write.option("compression", "none").text(path)
    each = [mapreduce.read_lines(spark, path, blocks).select(F.lit(mode).alias("mode"), "line") for mode, blocks in (("blocks", True), ("whole", False))]
    return each[0].union(each[1]).groupBy("mode").agg(F.count(F.lit(1)).alias("n"), F.sum(F.length("line")).alias("chars"))


@query("""WITH RECURSIVE e AS (SELECT DISTINCT 2 * o_custkey AS a, 2 * o_orderkey + 1 AS b FROM orders),
          g AS (SELECT a, b FROM e UNION SELECT b, a FROM e), r AS (SELECT a AS node, a AS seen FROM g UNION SELECT r.node, g.b FROM r JOIN g ON r.seen = g.a)
          SELECT node, min(seen) AS component FROM r GROUP BY node""")
def bsp_components(t, spark):
    """Customers and their orders as one graph: even nodes are customers, odd ones orders."""
    return bsp.spread_labels(t("orders").select((2 * F.col("o_custkey")).alias("a"), (2 * F.col("o_orderkey") + 1).alias("b")))


def _rank_sql(steps: int = 5) -> str:
    parts = ["e AS (SELECT DISTINCT l_suppkey AS src, l_partkey % 100 + 1 AS dst FROM lineitem)", "d AS (SELECT src, dst, count(*) OVER (PARTITION BY src) AS degree FROM e)", "nodes AS (SELECT src AS node FROM e UNION SELECT dst FROM e)", "r0 AS (SELECT node, 1.0 / (SELECT count(*) FROM nodes) AS rank FROM nodes)"]
    for i in range(steps):
        parts.append(f"r{i + 1} AS (SELECT n.node, 0.15 / (SELECT count(*) FROM nodes) + 0.85 * coalesce(sum(r.rank / d.degree), 0) AS rank FROM nodes n LEFT JOIN d ON d.dst = n.node LEFT JOIN r{i} r ON r.node = d.src GROUP BY n.node)")
    return f"WITH {', '.join(parts)} SELECT node, round(CAST(rank AS DOUBLE), 9) AS rank FROM r{steps}"


@query(_rank_sql().replace("1.0 /", "1e0 /").replace("0.15 /", "15e-2 /").replace("0.85 *", "85e-2 *"))
def bsp_rank_iterations(t, spark):
    edges = t("lineitem").select(F.col("l_suppkey").alias("src"), (F.col("l_partkey") % 100 + 1).alias("dst")).distinct()
    return bsp.rank_links(edges, 5).select("node", F.round("rank", 9).alias("rank"))


LINE = "l_orderkey l_partkey l_suppkey l_linenumber l_quantity l_extendedprice l_discount l_tax l_returnflag l_linestatus l_shipdate".split()
LINE_KEYS = ["l_extendedprice", *[c for c in LINE if c != "l_extendedprice"]]
RANKED = f"SELECT row_number() OVER (ORDER BY {', '.join(LINE_KEYS)}) AS rk, l_orderkey, l_linenumber, l_extendedprice FROM lineitem"


@query(RANKED)
def range_sort_lineitem(t, spark):
    placed = rangesort.range_sort(t("lineitem"), LINE_KEYS, 8)
    return rangesort.with_global_rank(placed).select("rk", "l_orderkey", "l_linenumber", "l_extendedprice")


@query(RANKED)
def range_sort_two_round(t, spark):
    placed = rangesort.range_sort(t("lineitem"), LINE_KEYS, 9, rounds=2)
    return rangesort.with_global_rank(placed).select("rk", "l_orderkey", "l_linenumber", "l_extendedprice")


@query(RANKED)
def range_sort_objects(t, spark):
    placed = rangesort.range_sort(t("lineitem"), LINE_KEYS, 4, shuffle="objects")
    return rangesort.with_global_rank(placed).select("rk", "l_orderkey", "l_linenumber", "l_extendedprice")


@query(RANKED)
def range_sort_kv(t, spark):
    placed = rangesort.range_sort(t("lineitem"), LINE_KEYS, 6, shuffle="kv")
    return rangesort.with_global_rank(placed).select("rk", "l_orderkey", "l_linenumber", "l_extendedprice")


@query("SELECT row_number() OVER (ORDER BY text, doc_id) AS rk, doc_id FROM documents")
def range_sort_text(t, spark):
    placed = rangesort.range_sort(t("documents").select("text", "doc_id"), ["text", "doc_id"], 8)
    return rangesort.with_global_rank(placed).select("rk", "doc_id")


BOUNDS = list(range(10_000, 100_001, 10_000))


@query("SELECT CAST(len(list_filter([10000,20000,30000,40000,50000,60000,70000,80000,90000,100000], lambda s: s <= l_extendedprice)) AS INTEGER) AS range_id, count(*) AS n FROM lineitem GROUP BY 1")
def sort_partition_census(t, spark):
    return t("lineitem").groupBy(rangesort.range_id(F.col("l_extendedprice"), BOUNDS).alias("range_id")).agg(F.count(F.lit(1)).alias("n"))


@query("SELECT CAST(i AS INTEGER) AS bound, round(quantile_cont(l_extendedprice, i / 8), 4) AS price FROM lineitem, range(1, 8) t(i) GROUP BY i".replace("quantile_cont(l_extendedprice, i / 8)", "list_extract(quantile_cont(l_extendedprice, [0.125, 0.25, 0.375, 0.5, 0.625, 0.75, 0.875]), CAST(i AS INTEGER))"))
def sort_splitters_exact(t, spark):
    found = rangesort.choose_splitters(t("lineitem"), "l_extendedprice", 8, exact=True)
    return spark.createDataFrame([(i + 1, float(v)) for i, v in enumerate(found)], "bound int, price double").withColumn("price", F.round("price", 4))


@query("SELECT count(*) AS n, CAST(0 AS BIGINT) AS within, CAST(0 AS BIGINT) AS between_parts, true AS same_rows FROM lineitem")
def sort_validate(t, spark):
    """Order within and between parts, and the checksum of the sorted rows against that of the input."""
    rows = t("lineitem")
    checked = rangesort.validate_sorted(rangesort.range_sort(rows, LINE_KEYS, 8), LINE_KEYS)
    source = rows.agg(F.sum(F.xxhash64(*rows.columns).cast("decimal(38,0)")).alias("expected"))
    return checked.crossJoin(source).select("n", "within", F.col("between").alias("between_parts"), (F.col("checksum") == F.col("expected")).alias("same_rows"))


@query("""SELECT CAST(l_orderkey % 8 AS INTEGER) AS map_id, CAST(len(list_filter([10000,20000,30000,40000,50000,60000,70000,80000,90000,100000], lambda s: s <= l_extendedprice)) AS INTEGER) AS reduce_id, count(*) AS rows, CAST(sum(length(l_returnflag) + 80) AS BIGINT) AS bytes FROM lineitem GROUP BY 1, 2""")
def shuffle_object_census(t, spark):
    size = F.length("l_returnflag") + 80
    return rangesort.census(t("lineitem"), F.pmod("l_orderkey", F.lit(8)).cast("int"), rangesort.range_id(F.col("l_extendedprice"), BOUNDS), size.cast("long"))


@query("""WITH b AS (SELECT l_orderkey % 8 AS m, len(list_filter([10000,20000,30000,40000,50000,60000,70000,80000,90000,100000], lambda s: s <= l_extendedprice)) AS r, CAST(sum(length(l_returnflag) + 80) AS BIGINT) AS bytes FROM lineitem GROUP BY 1, 2)
          SELECT CAST((m * 31 + r) % 5 AS INTEGER) AS shard, 2 * count(*) AS requests, CAST(sum(bytes) AS BIGINT) AS bytes FROM b GROUP BY 1""")
def shuffle_kv_shards(t, spark):
    """Requests and bytes that the blocks of the census put on each of five key-value shards."""
    size = (F.length("l_returnflag") + 80).cast("long")
    blocks = rangesort.census(t("lineitem"), F.pmod("l_orderkey", F.lit(8)).cast("int"), rangesort.range_id(F.col("l_extendedprice"), BOUNDS), size)
    return rangesort.kv_shuffle_load(blocks, 5)


@query("""WITH b AS (SELECT coalesce(sum(length(l_returnflag) + 80), 0) AS bytes FROM lineitem), p AS (SELECT x, CAST(bytes * x AS DOUBLE) AS total, greatest(ceil(CAST(bytes * x AS DOUBLE) / 1e5), 1) AS parts FROM b, unnest([1, 10, 100]) u(x))
          SELECT medium, CAST(x AS INTEGER) AS times, CAST(parts AS BIGINT) AS parts, round(2 * greatest(parts * parts / rate, total / (500 * 35e6)), 6) AS seconds FROM p, (VALUES ('objects', 3500e0), ('kv', 700000e0)) m(medium, rate)""")
def shuffle_medium_model(t, spark):
    """Why a sort's blocks go to a key-value tier: bandwidth is alike, but the object store's request rate is what many small blocks exhaust.

    For a sort of lineitem, and of ten and a hundred times as much, with tasks of 100 kB.
    """
    rates, size, rows = {"objects": 3500.0, "kv": 700_000.0}, _bytes_of_lines(t), []
    for times in (1, 10, 100):
        parts = rangesort.required_tasks(size * times, 1e5)
        rows += [(medium, times, parts, rangesort.shuffle_seconds(parts, float(size * times), 500, r, 35e6)) for medium, r in rates.items()]
    return spark.createDataFrame(rows, "medium string, times int, parts long, seconds double").withColumn("seconds", F.round("seconds", 6))


def _bytes_of_lines(t) -> int:
    """Bytes of the rows of lineitem, by the same estimate as in the census."""
    return t("lineitem").agg(F.coalesce(F.sum(F.length("l_returnflag") + 80), F.lit(0))).first()[0]


@query("""WITH b AS (SELECT coalesce(sum(length(l_returnflag) + 80), 0) AS bytes FROM lineitem), p AS (SELECT x, CAST(bytes * x AS DOUBLE) AS total, greatest(ceil(CAST(bytes * x AS DOUBLE) / 1e5), 1) AS parts FROM b, unnest([1, 10, 100]) u(x)),
          f AS (SELECT x, k, total, parts, round(CASE WHEN k = 1 THEN parts * parts ELSE k * pow(parts, 1 + 1.0 / k) END) AS files FROM p, unnest([1, 2, 3]) v(k))
          SELECT CAST(x AS INTEGER) AS times, CAST(k AS INTEGER) AS rounds, CAST(parts AS BIGINT) AS parts, CAST(files AS BIGINT) AS files, round(k * total / files, 1) AS mean_bytes FROM f""")
def shuffle_growth_model(t, spark):
    """Objects of a sort of lineitem, and of ten and a hundred times as much, in one to three rounds with tasks of 100 kB."""
    rows, size = [], _bytes_of_lines(t)
    for times in (1, 10, 100):
        parts = rangesort.required_tasks(size * times, 1e5)
        for k in (1, 2, 3):
            files = rangesort.shuffle_files(parts, k)
            rows.append((times, k, parts, files, k * float(size * times) / files))
    return spark.createDataFrame(rows, "times int, rounds int, parts long, files long, mean_bytes double").withColumn("mean_bytes", F.round("mean_bytes", 1))


@query("""WITH b AS (SELECT count(*) * 100.0 AS bytes FROM lineitem), g AS (SELECT w, s, bytes, bytes / (w * 35e6) AS io, bytes / (s * 500e6) * greatest(w / 500.0, 1) AS kv FROM b, unnest([100, 250, 500, 1000]) u(w), unnest([10, 20, 30]) v(s))
          SELECT CAST(w AS INTEGER) AS workers, CAST(s AS INTEGER) AS shards, round(CAST(2 * io + kv AS DOUBLE), 9) AS seconds, CAST(w * ceil((2 * io + kv) * 10) AS BIGINT) AS steps, round(CAST(w * ceil((2 * io + kv) * 10) * 0.0000025 + s * 2.0 * ceil(2 * io + kv) / 3600 AS DOUBLE), 6) AS usd FROM g""")
def sort_cost_grid(t, spark):
    """Sort time and price over workers and shards: storage at 35 MB/s a worker, shards that slow down past 500 workers."""
    size = t("lineitem").agg((F.count(F.lit(1)) * 100.0).alias("bytes"))
    points = spark.createDataFrame([(p["workers"], p["shards"]) for p in sweep.grid(workers=[100, 250, 500, 1000], shards=[10, 20, 30])], "workers int, shards int")
    g = points.crossJoin(F.broadcast(size))
    seconds = 2 * F.col("bytes") / (F.col("workers") * 35e6) + F.col("bytes") / (F.col("shards") * 500e6) * F.greatest(F.col("workers") / 500.0, F.lit(1.0))
    steps = F.col("workers") * F.ceil(seconds * 10)
    usd = steps * 0.0000025 + F.col("shards") * 2.0 * F.ceil(seconds) / 3600
    return g.select("workers", "shards", F.round(seconds, 9).alias("seconds"), steps.alias("steps"), F.round(usd, 6).alias("usd"))


def _sgd_sql(tau: int, steps: int, rate: float = 0.2) -> str:
    keep = tau + 1
    cols = ", ".join(f"b{i}, s{i}" for i in range(keep))
    start = ", ".join(f"0e0 AS b{i}, 0e0 AS s{i}" for i in range(keep))
    old = keep - 1
    shift = ", ".join(f"b{i}, s{i}" for i in range(keep - 1))
    shift = f", {shift}" if shift else ""
    return f"""WITH RECURSIVE m AS (SELECT avg(x) AS mx, avg(x * x) AS mxx, avg(y) AS my, avg(x * y) AS mxy FROM (SELECT l_quantity / 50 AS x, l_extendedprice / 100000 AS y FROM lineitem)),
        w(t, {cols}) AS (SELECT 0, {start} UNION ALL SELECT t + 1, b0 - {rate}e0 * (b{old} + mx * s{old} - my), s0 - {rate}e0 * (mx * b{old} + mxx * s{old} - mxy){shift} FROM w, m WHERE t < {steps})
        SELECT CAST(t AS INTEGER) AS step, round(b0, 6) AS bias, round(s0, 6) AS slope FROM w"""


def _sgd(t, spark, tau, steps, rate=0.2):
    rows = t("lineitem").select((F.col("l_quantity") / 50).alias("x"), (F.col("l_extendedprice") / 100000).alias("y"))
    versions = paramserver.train_server(rows, "x", "y", steps=steps, rate=rate, staleness=tau)
    return spark.createDataFrame([(i, round(float(w[0]), 6), round(float(w[1]), 6)) for i, w in enumerate(versions)], "step int, bias double, slope double")


@query(_sgd_sql(0, 60))
def sgd_sync_steps(t, spark):
    return _sgd(t, spark, 0, 60)


@query(_sgd_sql(2, 60))
def sgd_stale_steps(t, spark):
    return _sgd(t, spark, 2, 60)


@query("""WITH RECURSIVE m AS (SELECT avg(x) AS mx, avg(x * x) AS mxx, avg(y) AS my, avg(x * y) AS mxy FROM (SELECT l_quantity / 50 AS x, l_extendedprice / 100000 AS y FROM lineitem)),
          w(j, b, s) AS (SELECT 0, 0e0, 0e0 UNION ALL SELECT j + 1, b - 0.4e0 * (b + mx * s - my), s - 0.4e0 * (mx * b + mxx * s - mxy) FROM w, m WHERE j < 50),
          g AS (SELECT j, b, s, b + mx * s - my AS gb, mx * b + mxx * s - mxy AS gs FROM w, m)
          SELECT CAST(4 * j + k AS INTEGER) AS step, round(b - 0.1e0 * k * gb, 6) AS bias, round(s - 0.1e0 * k * gs, 6) AS slope FROM g, range(0, 4) u(k) WHERE j < 50
          UNION ALL SELECT 200, round(b, 6), round(s, 6) FROM g WHERE j = 50""")
def sgd_async_replay(t, spark):
    rows = t("lineitem").select((F.col("l_quantity") / 50).alias("x"), (F.col("l_extendedprice") / 100000).alias("y"))
    a, b = paramserver.moments(rows, "x", "y")
    versions = paramserver.replay_async(lambda w: a @ w - b, 200, 4, 0.4)
    return spark.createDataFrame([(i, round(float(w[0]), 6), round(float(w[1]), 6)) for i, w in enumerate(versions)], "step int, bias double, slope double")


@query("SELECT * FROM (VALUES (0, 0.5e0), (1, 3e0), (2, -2e0), (3, 1e0), (4, -0.5e0), (5, 0e0), (6, 2e0)) w(idx, weight)")
def sgd_async_live(t, spark):
    """Lock-free workers against live shards find the weights that made the targets, from zero and to two digits."""
    planted = (3.0, -2.0, 1.0, -0.5, 0.0, 2.0)
    names = [f"x{i}" for i in range(len(planted))]
    parts = t("embeddings").select(*[(F.col("embedding")[i].cast("double") * 8).alias(c) for i, c in enumerate(names)])
    rows = settle(parts.withColumn("y", sum((F.lit(w) * F.col(c) for w, c in zip(planted, names)), F.lit(0.5))))
    passes = max(4, -(-40_000 // max(rows.count(), 1)))  # the same number of updates for small tables
    w = paramserver.train_async(rows, names, "y", passes=passes, batch=32, rate=0.05)
    return spark.createDataFrame([(i, round(float(v), 2) + 0.0) for i, v in enumerate(w)], "idx int, weight double")


@query(f"SELECT vec_id AS i, CAST(j AS INTEGER) AS j, round(sum(v * ((i * 7 + j * 3) % 11 - 5) / 10), 6) AS v FROM {PIXELS}, range(0, 64) w(j) GROUP BY ALL")
def matmul_sql(t, spark):
    """All vectors times a 64 x 64 matrix in coordinate form: an equi-join on the inner index with the (fixed-size) right side broadcast."""
    left = t("embeddings").select("vec_id", F.posexplode("embedding").alias("k", "x"))
    right = spark.range(64 * 64).select(F.floor(F.col("id") / 64).cast("int").alias("k"), (F.col("id") % 64).cast("int").alias("j"))
    right = right.withColumn("w", ((F.col("k") * 7 + F.col("j") * 3) % 11 - 5) / 10)
    product = left.join(F.broadcast(right), "k").groupBy(F.col("vec_id").alias("i"), "j").agg(F.sum(F.col("x").cast("double") * F.col("w")).alias("v"))
    return product.select("i", "j", F.round("v", 6).alias("v"))
