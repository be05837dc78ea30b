"""Learning, streams, sources and the SQL surface."""

import numpy as np
import pytest
from pyspark.sql import functions as F
from pyspark.sql import types as T

from tuplestat import schema
from tuplestat.functions import sqlfns
from tuplestat.operators import metrics, relops, schemes
from tuplestat.plans import learning as L
from tuplestat.sources import catalog, synthetic
from tuplestat.streaming import windows

SF = "/root/testdata/sf0.001"


def train(spark, n=60, m=40, d=3, seed=0):
    rng = np.random.default_rng(seed)
    x, z = rng.normal(size=(n, d)), rng.normal(size=(m, d)) + 0.8
    rows = [(0, f"a{i:03}", v.tolist()) for i, v in enumerate(x)] + [(1, f"b{i:03}", v.tolist()) for i, v in enumerate(z)]
    return x, z, spark.createDataFrame(rows, "cls int, key string, features array<double>")


def test_full_gradient_against_brute_force(spark):
    x, z, df = train(spark)
    w = np.array([0.5, -0.3, 0.2])
    gap = 1 + (x @ w)[:, None] - (z @ w)[None]
    r = L.full_gradient(df, w.tolist()).first()
    assert r.loss == pytest.approx(np.maximum(0, gap).mean())
    want = ((gap > 0)[:, :, None] * (x[:, None] - z[None])).mean(axis=(0, 1))
    assert [r.g0, r.g1, r.g2] == pytest.approx(want.tolist())


def test_hand_checked_gradient(spark):
    rows = [(0, "a", [0.0]), (0, "b", [2.0]), (1, "c", [1.0]), (1, "d", [2.5])]
    r = L.full_gradient(spark.createDataFrame(rows, "cls int, key string, features array<double>"), [1.0]).first()
    assert (r.loss + 0.05, r.g0 + 0.1) == (pytest.approx(0.675), pytest.approx(0.225))


def test_descent_lowers_the_risk(spark):
    _, _, df = train(spark)
    _, losses = L.fit_gd(df, np.zeros(3), 5, rate=0.2)
    assert losses[-1] < losses[0]


def test_modes_agree_and_momentum(spark):
    _, _, df = train(spark)
    a, trace = L.fit_sgd(df, np.zeros(3), 4, 4, 10, 2, 5)
    b, _ = L.fit_sgd(df, np.zeros(3), 4, 4, 10, 2, 5, mode="barrier")
    assert a == pytest.approx(b) and [t[1] for t in trace] == [1, 1, 2, 2]
    assert a == pytest.approx(L.fit_sgd(df, np.zeros(3), 4, 4, 10, 2, 5, mode="driver_sync")[0])
    many = [L.fit_sgd(df, np.zeros(3), 2, 200, 5, 1, 5, mode=m)[0] for m in ("lookup", "driver_sync")]  # workers without rows
    assert many[0] == pytest.approx(many[1]) and np.abs(many[0]).max() > 0
    c, _ = L.fit_sgd(df, np.zeros(3), 4, 4, 10, None, 5)
    assert not np.allclose(a, c)


def test_shuffles_lower_the_variance_of_the_gradient(spark):
    x, z, _ = train(spark, 40, 8)
    w = np.array([0.5, -0.3, 0.2])
    g = ((1 + (x @ w)[:, None] - (z @ w)[None]) > 0)[:, :, None] * (x[:, None] - z[None])

    def one(rng, rounds):
        out = []
        for _ in range(rounds):
            p, q = rng.permutation(40), rng.permutation(8)
            out.append(np.mean([g[np.ix_(p[k::4], q[k::4])].mean(axis=(0, 1)) for k in range(4)], axis=0))
        return np.mean(out, axis=0)

    v = {t: np.var([one(np.random.default_rng([t, k]), t) for k in range(400)], axis=0) for t in (1, 4)}
    assert (v[4] < 0.5 * v[1]).all()
    assert np.mean([one(np.random.default_rng([9, k]), 1) for k in range(400)], axis=0) == pytest.approx(g.mean(axis=(0, 1)), abs=0.03)


def test_erm_and_simulation(spark):
    x, z, df = train(spark)
    r = {q.candidate: q for q in L.erm_select(df, [[0.5, 0.5, 0.5], [-1.0, 0.0, 0.0]]).collect()}
    assert r[0].best and not r[1].best
    t = L.simulate(spark, x, z, x, z, 2, 10, 4, 10, (1, None), 3, eval_every=5, monitor_pairs=500)
    assert t.where("metric = 'test_auc'").agg(F.min("value")).first()[0] >= 0 and t.count() == 2 * 2 * 3 * 4
    few = L.simulate(spark, x, z[:2], x, z, 1, 10, 4, 10, (1,), 3, eval_every=5, monitor_pairs=500)  # two workers lack a class
    assert few.where("metric = 'train_loss'").count() == 3
    gap = 1 + x[:, :1] - z[:, 0][None]
    assert L.all_pairs_hinge(x[:, 0], z[:, 0]) == pytest.approx(np.maximum(0, gap).mean())


def test_binned_area_brackets_the_exact_one(spark):
    rng = np.random.default_rng(4)
    rows = [(float(v), bool(b)) for v, b in zip(rng.normal(size=300), rng.random(300) < 0.3)]
    df = spark.createDataFrame(rows, "s double, y boolean")
    exact, b = metrics.auc(df, F.col("s"), F.col("y")).first(), metrics.auc_binned(df, F.col("s"), F.col("y"), -3, 3, 40).first()
    assert b.low <= exact.auc_half <= b.high and abs(b.auc - exact.auc_half) < 0.02


def test_relational_helpers(spark):
    a = spark.createDataFrame([(1, 0.0), (2, 10.0), (3, 10.4)], "k int, v double")
    b = spark.createDataFrame([(7, 0.3), (8, 9.9), (9, -0.99)], "j int, w double")
    got = {(r.k, r.j) for r in relops.range_join(a, b, "v", "w", 1.0).collect()}
    assert got == {(1, 7), (1, 9), (2, 8), (3, 8)}
    t = relops.ordered_tuples(spark.createDataFrame([("g", 1), ("g", 2), ("g", 3), ("h", 1)], "g string, o int"), ["g"], "o", 3)
    assert [tuple(r) for r in t.collect()] == [("g", 1, 2, 3)]
    grid = spark.createDataFrame([(1,), (2,)], "k int")
    assert relops.complete_grid(a.where("k = 1"), ["k"], grid, {"v": -1.0}).where("k = 2").first().v == -1.0


def test_schema_check(spark):
    df = spark.createDataFrame([(0, 0, "a", 1.0)], schema.SAMPLE)
    assert schema.require(df, schema.SAMPLE) is df
    with pytest.raises(ValueError, match="score is missing"):
        schema.require(df.drop("score"), schema.SAMPLE)
    with pytest.raises(ValueError, match="key is"):
        schema.require(df.withColumn("key", F.lit(1)), schema.SAMPLE)


def test_sources(spark, tmp_path):
    synthetic.register(spark)
    df = spark.read.format("tuplestat_synthetic").options(law="gaussian", n="40", m="10", shift="2", seed="3").load()
    assert df.count() == 50 and df.where("sample = 0").agg(F.avg("score")).first()[0] > 1
    with pytest.raises(ValueError):
        catalog.read_any(spark, "x", "csv")
    assert catalog.cut(df.select("sample")).count() == 50
    assert df.schema == T.StructType.fromDDL("sample int, idx bigint, key string, score double")


def test_group_functions(spark):
    rng = np.random.default_rng(1)
    x, y = rng.integers(0, 8, 80).astype(float), rng.integers(0, 8, 80).astype(float)
    want = sum((x[i] - x[j]) * (y[i] - y[j]) > 0 for i in range(80) for j in range(i))
    assert sqlfns.concordant_pairs(x, y) == want


def test_stream_equals_batch(spark):
    e = catalog.load(spark, SF, "events").where("value IS NOT NULL")
    y = F.col("event_type") == "error"
    batch = windows.window_counts(e, "ts", F.col("value"), y, "1 day")
    s = catalog.stream_table(spark, SF, "events").where("value IS NOT NULL").withColumn("ts", F.col("ts").cast("timestamp"))
    live = windows.run_to_end(windows.window_counts(s, "ts", F.col("value"), y, "1 day", watermark="1 day"))
    key = lambda df: sorted((str(r.start), r.score, r.pos, r.neg) for r in df.collect())
    assert key(batch) == key(live)


def test_place_rows_keeps_workers_together(spark):
    df = spark.range(200).withColumn("worker", (F.col("id") % 7).cast("int"))
    parts = schemes.place_rows(df, 3).withColumn("p", F.spark_partition_id()).groupBy("worker").agg(F.countDistinct("p").alias("k")).collect()
    assert all(r.k == 1 for r in parts)


def test_late_rows(spark):
    rows = [(1, "2024-01-01 00:00", "2024-01-01 01:00"), (2, "2024-01-05 00:00", "2024-01-05 00:00"), (3, "2024-01-01 02:00", "2024-01-05 03:00")]
    df = spark.createDataFrame(rows, "k int, t string, a string").select("k", F.to_timestamp("t").alias("t"), F.to_timestamp("a").alias("a"))
    assert {r.k: r.late for r in windows.split_late(df, "t", "a", "2 days").collect()} == {1: False, 2: False, 3: True}


def test_shuffles_raise_the_median_and_narrow_the_band(spark):
    """With two or three rows of a class on a worker, a worker's fixed pairs are a small part of all
    pairs: without shuffles models differ by the cut they got, with shuffles they agree and are better."""
    rng = np.random.default_rng(2)
    w = rng.normal(size=9)

    def rows(k, high):
        f = rng.normal(size=(k * 30, 9))
        f = f[np.argsort(f @ w + rng.normal(size=k * 30))]
        return f[-k * 6 :][rng.permutation(k * 6)[:k]] if high else f[: k * 24][rng.permutation(k * 24)[:k]]

    x, z, test_x, test_z = rows(60, False), rows(40, True), rows(500, False), rows(500, True)
    t = L.simulate(spark, x, z, test_x, test_z, 40, 300, 20, 20, (1, 25, None), 3, eval_every=300, monitor_pairs=20_000)
    last = t.where("iteration = 300").collect()
    for metric, sign in (("test_auc", 1), ("test_loss", -1), ("train_loss", -1)):
        value = {e: np.array([sign * r.value for r in last if r.shuffle_every == e and r.metric == metric]) for e in (1, 25, 0)}
        median = [np.median(value[e]) for e in (1, 25, 0)]
        band = [np.ptp(np.quantile(value[e], [0.05, 0.95])) for e in (1, 25, 0)]
        assert median[0] > median[1] > median[2] and band[0] < band[1] < band[2], metric


def test_two_point_runs_have_the_law_of_single_runs(spark):
    from tuplestat.plans import montecarlo as MC

    rng = np.random.default_rng(1)
    fast = MC.two_point_runs(rng, 4000, 0.2, 60, 12, 4, 3, 10)
    slow = {}
    for _ in range(4000):
        x, z = np.where(rng.random(60) < 0.2, 0.0, 2.0), np.where(rng.random(12) < 0.2, 1.0, -1.0)
        for k, v in MC.one_run(x, z, 4, 3, 10, "prop_swor", rng).items():
            slow.setdefault(k, []).append(v)
    for k, v in slow.items():
        assert np.mean(v) == pytest.approx(fast[k].mean(), abs=0.004), k
        assert np.var(v) == pytest.approx(np.var(fast[k]), rel=0.15), k
