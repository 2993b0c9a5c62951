import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from callweave.functions.features import crop, gradient_descriptor, gradient_descriptor_numpy, scale
from callweave.learn import linear
from callweave.operators import bsp, gather, mapreduce, paramserver, rangesort, stages, sweep


def test_word_count_variants_agree(spark, t):
    docs = t("documents")
    want = sorted(map(tuple, mapreduce.word_count(docs).collect()))
    for other in (mapreduce.word_count(docs, combine=False), mapreduce.word_count(docs, combine=False, parts=3), mapreduce.word_count(docs, shuffle="objects", parts=4), mapreduce.word_count_opaque(docs, parts=3)):
        assert sorted(map(tuple, other.collect())) == want


def test_word_count_odd_texts(spark):
    rows = spark.createDataFrame([(None,), ("",), ("  \n",), ("Ä ä a" + " w" * 5000,)], "text string")
    assert dict(map(tuple, mapreduce.word_count(rows).collect())) == {"ä": 2, "a": 1, "w": 5000}


def test_map_reduce_native_and_opaque(spark, t):
    rows = t("part").select("p_brand", "p_size")
    pairs = lambda r: [(r["p_brand"], r["p_size"])]
    a = mapreduce.map_reduce(rows, pairs, "sum", "string", "long", "long")
    b = mapreduce.map_reduce(rows, pairs, lambda k, v: sum(v), "string", "long", "long", parts=3)
    c = mapreduce.map_reduce(rows, pairs, "sum", "string", "long", "long", combine=False, shuffle="objects", parts=3)
    assert sorted(a.collect()) == sorted(b.collect()) == sorted(c.collect())


def test_word_count_plan_combines_before_one_shuffle(t):
    plan = mapreduce.word_count(t("documents"))._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning(word") == 1 and "partial_count" in plan and "ReadSchema: struct<text:string>" in plan


@pytest.mark.parametrize("keys", [["v"], ["v", "i"]])
@pytest.mark.parametrize("options", [{}, {"rounds": 2}, {"shuffle": "objects"}])
def test_sort_with_ties_and_a_heavy_key(spark, keys, options):
    df = spark.range(3000).select(F.when(F.col("id") % 10 < 9, 7).otherwise(F.pmod(F.xxhash64("id"), F.lit(1000))).alias("v"), F.col("id").alias("i"))
    placed = rangesort.range_sort(df, keys, 9, **options)
    checked = rangesort.validate_sorted(placed, keys).first()
    assert (checked["n"], checked["within"], checked["between"]) == (3000, 0, 0)
    assert checked["checksum"] == df.agg(F.sum(F.xxhash64("v", "i").cast("decimal(38,0)"))).first()[0]


def test_ranks_equal_order_by(spark):
    df = spark.range(500).select(F.pmod(F.xxhash64("id"), F.lit(97)).alias("v"), F.col("id").alias("i"))
    ranked = rangesort.with_global_rank(rangesort.range_sort(df, ["v", "i"], 6))
    assert [r["i"] for r in ranked.orderBy("rk").collect()] == [r["i"] for r in df.orderBy("v", "i").collect()]
    assert [r["rk"] for r in ranked.orderBy("rk").collect()] == list(range(1, 501))


def test_more_ranges_than_rows_and_equal_keys(spark):
    for df in (spark.range(3).select(F.col("id").alias("v")), spark.range(50).select(F.lit(1).alias("v")), spark.range(0).select(F.col("id").alias("v"))):
        n = df.count()
        assert rangesort.validate_sorted(rangesort.range_sort(df, ["v"], 8), ["v"]).first()["n"] == n


def test_breaks_of_order_are_found(spark):
    bad = spark.createDataFrame([(0, 0, 5), (0, 1, 4), (0, 2, 9), (1, 0, 1)], "part_id int, pos long, v int")
    for chunk in (1, 2, 100):
        r = rangesort.validate_sorted(bad, ["v"], chunk).first()
        assert (r["n"], r["within"], r["between"]) == (4, 1, 1)


def test_ranks_need_no_second_shuffle(spark):
    ranked = rangesort.with_global_rank(rangesort.range_sort(spark.range(100).select(F.col("id").alias("v")), ["v"], 4))
    plan = ranked._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastHashJoin" in plan and "SortMergeJoin" not in plan and "Window [row_number" not in plan


def test_shuffle_media(spark):
    assert rangesort.shuffle_seconds(2500, 1e12, 500, 3500, 35e6) > 5 * rangesort.shuffle_seconds(2500, 1e12, 500, 700_000, 35e6)


def test_splitters(spark):
    df = spark.range(10_000).select(F.col("id").cast("double").alias("v"))
    exact = rangesort.choose_splitters(df, "v", 4, exact=True)
    assert np.allclose(exact, [2499.75, 4999.5, 7499.25])
    sampled = rangesort.choose_splitters(df, "v", 4, share=0.2)
    assert sampled == rangesort.choose_splitters(df.repartition(7), "v", 4, share=0.2) and np.allclose(sampled, exact, atol=600)
    assert rangesort.choose_splitters(df, "v", 1) == []


def test_published_sizes():
    assert rangesort.required_tasks(1e12) == 2500 and rangesort.shuffle_files(2500) == 6_250_000
    assert rangesort.shuffle_files(250_000, 2) == 250_000_000 < rangesort.shuffle_files(250_000)


@settings(max_examples=8, deadline=None)
@given(st.lists(st.tuples(st.integers(0, 12), st.integers(0, 12)), min_size=1, max_size=20))
def test_components_equal_union_find(spark, pairs):
    parent = {x: x for p in pairs for x in p}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in pairs:
        a, b = find(a), find(b)
        parent[max(a, b)] = min(a, b)
    got = bsp.spread_labels(spark.createDataFrame(pairs, "a long, b long"))
    assert dict(map(tuple, got.collect())) == {x: find(x) for x in parent}


def test_long_chain_halves(spark):
    edges = spark.range(300).select(F.col("id").alias("a"), (F.col("id") + 1).alias("b"))
    assert bsp.spread_labels(edges, max_steps=20).where("component <> 0").isEmpty()


def test_bsp_counts_steps(spark):
    state, steps = bsp.bsp_run(spark.createDataFrame([(0,)], "v int"), lambda s, i: s.withColumn("v", F.col("v") + 1), 10, lambda a, b: b.first()["v"] >= 4, store_every=2)
    assert (state.first()["v"], steps) == (4, 4)


def test_link_ranks_sum_to_one(spark):
    edges = spark.createDataFrame([(1, 2), (2, 3), (3, 1), (1, 3)], "src long, dst long")
    assert abs(bsp.rank_links(edges, 20).agg(F.sum("rank")).first()[0] - 1) < 1e-9


def test_gather_guard_and_places(spark, t):
    e = t("embeddings")
    with pytest.raises(gather.TooLarge):
        gather.map_then_gather(e, lambda d: d.select("embedding"), len, max_bytes=1000)
    n = gather.map_then_gather(e, lambda d: d.select("label"), lambda table: table.num_rows)
    task = gather.map_then_gather(e, lambda d: d.select("label"), lambda f: f.groupby("label", as_index=False).size().rename(columns={"size": "n"}), where="task", schema="label int, n long")
    tree = gather.map_then_gather(e, lambda d: d.select("label"), lambda d: d.groupBy("label").agg(F.count(F.lit(1)).alias("n")), where="tree")
    assert n == 500 and sorted(task.collect()) == sorted(tree.collect())


def test_gram_equals_numpy(t):
    x = np.stack(t("embeddings").toPandas()["embedding"]).astype(float)
    g = gather.gram(t("embeddings"), "embedding").toPandas()
    full = np.zeros((64, 64))
    full[g["i"], g["j"]] = g["v"]
    assert np.allclose(full, x.T @ x, atol=1e-9)


def test_ridge_spread_equals_one_machine(spark, t):
    e = t("embeddings")
    pdf = e.toPandas()
    x = np.stack(pdf["embedding"]).astype(float)
    one, spread = linear.fit_ridge(x, pdf["label"].tolist()), linear.fit_ridge_spread(e, "embedding", "label")
    assert np.allclose(one.weights, spread.weights, atol=1e-8)
    xb = np.c_[x, np.ones(len(x))]
    y = np.where(pdf["label"].to_numpy()[:, None] == np.array(one.classes), 1.0, -1.0)
    assert np.abs((xb.T @ xb + 1e-2 * np.eye(65)) @ one.weights.T - xb.T @ y).max() < 1e-8
    native = {r["vec_id"]: r["predicted"] for r in one.apply(e, "embedding").collect()}
    assert [native[i] for i in pdf["vec_id"]] == one.predict(x)
    assert linear.accuracy(one.apply(e, "embedding"), "label", "predicted").first()["accuracy"] > 0.2


def test_singular_design_is_solvable_with_ridge():
    x = np.ones((10, 3))
    assert np.isfinite(linear.fit_ridge(x, [0, 1] * 5).weights).all()


def test_hinge_loss_falls_and_learners_separate():
    rng = np.random.default_rng(0)
    x = rng.standard_normal((300, 4))
    y = (x @ [1, -2, 0.5, 0] > 0).astype(int)
    losses = [linear.hinge_loss(linear.fit_hinge(x, y, steps=s), x, y) for s in (1, 10, 200)]
    assert losses[0] > losses[1] > losses[2]
    for fit in (linear.fit_hinge, linear.fit_logistic):
        assert np.mean(np.array(fit(x, y).predict(x)) == y) > 0.95


def test_image_features(spark):
    rng = np.random.default_rng(1)
    img = rng.random((5, 8, 8))
    df = spark.createDataFrame([(i, img[i].ravel().tolist()) for i in range(5)], "id long, px array<double>")
    out = df.select("id", crop(F.col("px"), 8, 2, 1, 4, 6).alias("c")).withColumn("s", scale(F.col("c"), 6, 4, 2)).orderBy("id").collect()
    for i, r in enumerate(out):
        want = img[i, 2:6, 1:7]
        assert np.allclose(r["c"], want.ravel()) and np.allclose(r["s"], want.reshape(2, 2, 3, 2).mean(axis=(1, 3)).ravel())
    native = df.select("id", gradient_descriptor(F.col("px"), 8, 8).alias("descriptor")).orderBy("id").collect()
    arrow = gradient_descriptor_numpy(df, "id", "px", 8, 8).orderBy("id").collect()
    assert np.allclose([r["descriptor"] for r in native], [r["descriptor"] for r in arrow])


def test_sweep_simulation_restarts_and_optimiser(spark):
    points = sweep.grid(a=[1, 2, 3], b=[0, 10])
    best = sweep.best(sweep.sweep(spark, lambda p, d: (p["a"] - d) ** 2 + p["b"], points, data=2)).first()
    assert best["params"] == {"a": 2.0, "b": 0.0}

    def dart(seed):
        import random

        r = random.Random(seed)
        return 4.0 * (r.random() ** 2 + r.random() ** 2 <= 1)

    r = sweep.simulate_calls(spark, dart, 3000).first()
    assert r["n"] == 3000 and abs(r["estimate"] - np.pi) < 4 * r["error"]
    top = sweep.best_of_restarts(spark, lambda s: {"loss": float((s - 3) ** 2), "answer": float(s)}, 6).first()
    assert (top["point_id"], top["answer"]) == (3, 3.0)
    point, value, trace = sweep.optimise_loop(spark, lambda p: (p[0] - 1) ** 2 + (p[1] + 2) ** 2, [0.0, 0.0], rounds=8)
    assert value < 0.5 and trace == sorted(trace, reverse=True)


def test_parameter_server(spark):
    a, b = np.array([[1.0, 0.5], [0.5, 0.4]]), np.array([0.6, 0.35])
    gradient = lambda w: a @ w - b
    exact = np.linalg.solve(a, b)
    sync, stale0 = paramserver.train(gradient, 400, 0.5), paramserver.train(gradient, 400, 0.5, staleness=0)
    assert np.array_equal(sync[-1], stale0[-1]) and np.abs(sync[-1] - exact).max() < 1e-2
    assert np.array_equal(paramserver.replay_async(gradient, 50, 1, 0.5)[-1], paramserver.train(gradient, 50, 0.5)[-1])
    high = np.linalg.eigvalsh(a).max()
    for tau in (1, 2):
        edge = paramserver.stable_rate(high, tau)
        assert np.abs(paramserver.train(gradient, 3000, 0.95 * edge, tau)[-1] - exact).max() < 0.1
        assert np.abs(paramserver.train(gradient, 3000, 1.1 * edge, tau)[-1]).max() > 1e3
    df = spark.range(400).select((F.col("id") / 400).alias("x")).withColumn("y", 2 * F.col("x") + 1)
    am, bm = paramserver.moments(df, "x", "y")
    assert np.allclose(paramserver.gradient_step(df, "x", "y", [0.3, 0.7]), am @ [0.3, 0.7] - bm)
    assert np.abs(paramserver.train_async(df, "x", "y", passes=60, rate=0.5) - [1, 2]).max() < 0.25
    assert paramserver.model_frame(spark, [1, 2, 3], 2, 7).where("shard = 0").count() == 2


def test_live_parameter_server(spark):
    third = F.when(F.col("id") % 3 == 0, 1.0).otherwise(0.0)
    df = spark.range(600).select((F.col("id") / 600).alias("x"), third.alias("z")).withColumn("y", 2 * F.col("x") - F.col("z") + 1)
    data = df.toPandas().to_numpy()
    rows = np.c_[np.ones(600), data[:, :2]]
    a, b = rows.T @ rows / 600, rows.T @ data[:, 2] / 600
    for tau, shards in ((0, 1), (2, 3)):
        live = paramserver.train_server(df, ["x", "z"], "y", steps=40, rate=0.3, staleness=tau, shards=shards, workers=3)
        plain = paramserver.train(lambda w: a @ w - b, 40, 0.3, tau, start=(0, 0, 0))
        assert live.shape == (41, 3) and np.allclose(live, plain, atol=1e-9)
        last = paramserver.train_server(df, ["x", "z"], "y", steps=40, rate=0.3, staleness=tau, shards=shards, workers=3, history=False)
        assert np.allclose(last, plain[-1:], atol=1e-9)
    assert np.allclose(paramserver.gradient_step(df, ["x", "z"], "y", [0.3, 0.7, 0.1]), a @ [0.3, 0.7, 0.1] - b)
    odd = df.unionByName(spark.createDataFrame([(None, 1.0, 5.0), (1.0, 1.0, None)], "x double, z double, y double"))
    assert np.allclose(paramserver.train_server(odd, ["x", "z"], "y", steps=5, rate=0.3)[-1], paramserver.train(lambda w: a @ w - b, 5, 0.3, start=(0, 0, 0))[-1])
    assert np.array_equal(paramserver.train_server(df.limit(0), "x", "y", steps=3, rate=0.3, start=[1, 2]), [[1, 2]] * 4)
    with pytest.raises(Exception, match="exceed 100 bytes"):
        paramserver.train_server(df, "x", "y", steps=1, rate=0.3, worker_bytes=100)
    found = paramserver.train_async(df, ["x", "z"], "y", passes=150, batch=32, rate=0.3, shards=3)
    assert np.abs(found - [1, 2, -1]).max() < 0.01


def test_stages(spark):
    levels = stages.plan_stages({"c": ["a", "b"], "b": ["a"], "d": ["c"]})
    assert levels == [["a"], ["b"], ["c"], ["d"]]
    with pytest.raises(ValueError, match="cycle"):
        stages.plan_stages({"a": ["b"], "b": ["a"]})
    done = stages.run_stages(spark, {"sum": ["n"], "n": []}, {"n": lambda r: spark.range(5).count(), "sum": lambda r: r["n"] + 1})
    assert done == {"n": 5, "sum": 6}
