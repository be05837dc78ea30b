"""Queries on larger or odder tables than the given ones, each against brute force or exact integers."""

import math
import os

import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from tuplestat.operators.samples import release

SF = "/root/testdata/sf0.001"


def rows(spark, name, d=SF):
    got = entry.queries()[name](spark, str(d)).collect()
    release()
    return got


def tables(spark, folder, *names, **changed):
    """A folder of the smallest tables, with some of them replaced."""
    for n in names:
        os.symlink(f"{SF}/{n}.parquet", folder / f"{n}.parquet")
    for n, df in changed.items():
        df.write.parquet(str(folder / f"{n}.parquet"))
    return folder


def numbers(spark, d, table, *columns):
    got = spark.read.parquet(f"{d}/{table}.parquet").select(*columns).collect()
    return [np.array([r[k] for r in got]) for k in range(len(columns))]


@pytest.fixture(scope="module")
def many_prices(spark, tmp_path_factory):
    """Two hundred thousand orders of large prices, whose double sum is not the sum of their cents."""
    o = spark.read.parquet(f"{SF}/orders.parquet")
    i = F.col("i")
    price = (F.lit(9_000_000_000) + i * 7919 % 999_983) + (i * 37 % 100) / 100
    many = spark.range(200_000).withColumnRenamed("id", "i").select(
        F.concat(F.lit("F")).alias("o_orderstatus"), F.when(i % 2 == 0, "1-URGENT").otherwise("5-LOW").alias("o_orderpriority"),
        i.alias("o_orderkey"), price.alias("o_totalprice"),
    )
    assert set(many.columns) <= set(o.columns)
    return tables(spark, tmp_path_factory.mktemp("prices"), orders=many)


@pytest.mark.parametrize("name", ["agg_cube", "agg_rollup", "agg_grouping_sets"])
def test_cents_are_exact(spark, many_prices, name):
    i = np.arange(200_000)
    cents = (9_000_000_000 + i * 7919 % 999_983) * 100 + i * 37 % 100
    got = {(r.o_orderstatus, r.o_orderpriority): r.cents for r in rows(spark, name, many_prices)}
    assert got[None, None] == int(cents.sum())
    if name != "agg_rollup":
        assert got[None, "1-URGENT"] == int(cents[::2].sum())


def test_binomials_beyond_64_bits(spark, tmp_path):
    o = spark.read.parquet(f"{SF}/orders.parquet").withColumn("o_orderkey", F.col("o_orderkey") + 8_000_000)
    got = rows(spark, "fn_math", tables(spark, tmp_path, orders=o))
    assert len(got) == o.count()
    for r in got:
        assert (int(r.pairs), int(r.triples)) == (math.comb(r.o_orderkey, 2), math.comb(r.o_orderkey, 3))
    assert dict(entry.queries()["fn_math"](spark, SF).dtypes)["triples"] == "bigint"


# ------------------------------------------------------------------ no pairs where a form needs none


@pytest.fixture
def no_tuples(monkeypatch):
    """An error where a query joins rows to tuples, or draws them."""
    from tuplestat.operators import estimators as E

    def never(*_, **__):
        raise AssertionError("tuples are formed")

    for name in ("tuples", "draws", "summed"):
        monkeypatch.setattr(E, name, never)


def thirds(spark):
    nation, v = numbers(spark, SF.replace("0.001", "0.01"), "supplier", "s_nationkey", "s_acctbal")
    return [v[nation % 3 == c] for c in range(3)]


def test_u_complete_k3(spark, no_tuples):
    a, b, c = thirds(spark)
    r = rows(spark, "u_complete_k3", SF.replace("0.001", "0.01"))[0]
    wins = ((a[None] < b[:, None]).sum(axis=1) * (b[:, None] < c[None]).sum(axis=1)).sum()
    assert (r.tuples, r.total) == (len(a) * len(b) * len(c), wins)


def rounded_half_up(v):
    return [int(math.floor(abs(x) + 0.5)) * (1 if x >= 0 else -1) for x in v]


def test_u_complete_d2(spark, no_tuples):
    v = rounded_half_up(numbers(spark, SF, "customer", "c_acctbal")[0])
    r = rows(spark, "u_complete_d2")[0]
    total = sum((a - b) ** 2 for i, a in enumerate(v) for b in v[:i])
    assert (r.tuples, r.total) == (math.comb(len(v), 2), total) and r.estimate == pytest.approx(total / r.tuples, abs=1e-3)


def test_u_complete_d3(spark, no_tuples):
    import itertools

    v = rounded_half_up(numbers(spark, SF.replace("0.001", "0.01"), "supplier", "s_acctbal")[0])
    r = rows(spark, "u_complete_d3", SF.replace("0.001", "0.01"))[0]
    assert (r.tuples, r.total) == (math.comb(len(v), 3), sum(t[2] - t[0] for t in itertools.combinations(sorted(v), 3)))


def wins(spark):
    (x,), (z,) = numbers(spark, SF, "customer", "c_acctbal"), numbers(spark, SF, "supplier", "s_acctbal")
    return len(x) * len(z), int((z[None] < x[:, None]).sum())


def test_u_incomplete_wor_all(spark, no_tuples):
    r = rows(spark, "u_incomplete_wor_all")[0]
    assert (r.tuples, r.total) == wins(spark)


def test_u_complete_tiled(spark, no_tuples):
    r = rows(spark, "u_complete_tiled")[0]
    assert (r.tuples, r.total) == wins(spark)


def parts(spark, samples, workers, rounds):
    from tuplestat.operators import schemes as S
    from tuplestat.workloads.base import SEED

    out = {}
    for r in S.hash_rank(samples, workers, rounds, SEED).collect():
        out.setdefault((r["round"], r.worker), []).append((r["sample"], r.score))
    return out


def test_u_repartitioned_d2(spark, no_tuples):
    from tuplestat.workloads.estimator_queries import _customers

    got = {(r["round"], r.worker): (r.tuples, r.wins) for r in rows(spark, "u_repartitioned_d2")}
    want = parts(spark, _customers(spark, SF), 5, 3)
    assert set(got) == set(want)
    for k, v in want.items():
        v = [int(x) for _, x in v]
        assert got[k] == (math.comb(len(v), 2), sum(abs(a - b) for i, a in enumerate(v) for b in v[:i]))


def test_u_repartitioned_k3(spark, no_tuples):
    from tuplestat.workloads.estimator_queries import _thirds

    d = SF.replace("0.001", "0.01")
    got = {(r["round"], r.worker): (r.tuples, r.wins) for r in rows(spark, "u_repartitioned_k3", d)}
    for k, v in parts(spark, _thirds(spark, d), 5, 2).items():
        a, b, c = (np.array([x for s, x in v if s == i]) for i in range(3))
        chains = ((a[None] < b[:, None]).sum(axis=1) * (b[:, None] < c[None]).sum(axis=1)).sum()
        assert got[k] == (len(a) * len(b) * len(c), chains)


def test_w4_degenerate(spark, no_tuples):
    r = rows(spark, "w4_degenerate")[0]
    assert r.tuples == wins(spark)[0] and r.estimate == 0


def test_topk_hard_pairs(spark, monkeypatch):
    from tuplestat.operators import metrics as M

    kept = M.hardest_pairs

    def few(pairs, *rest):
        assert pairs.count() <= 400
        return kept(pairs, *rest)

    monkeypatch.setattr(M, "hardest_pairs", few)
    d = SF.replace("0.001", "0.01")
    (xk, x), (zk, z) = numbers(spark, d, "customer", "c_custkey", "c_acctbal"), numbers(spark, d, "supplier", "s_suppkey", "s_acctbal")
    cents = np.round(z * 100)[None] - np.round(x * 100)[:, None]
    want = sorted((int(cents[i, j]), str(xk[i]), str(zk[j])) for i, j in zip(*np.nonzero(cents <= np.partition(cents.ravel(), 40)[40])))
    assert [(r.cents, r.xk, r.zk) for r in rows(spark, "topk_hard_pairs", d)] == want[:20]


@pytest.mark.parametrize("name", ["kernel_vus3", "vus_exact"])
def test_volumes_beyond_64_bits(spark, tmp_path, name):
    """Three million rows a class: their product has 65 bits."""
    i = F.col("id")
    o = spark.range(9_000_000).select(F.element_at(F.array(*map(F.lit, "FOP")), (i % 3 + 1).cast("int")).alias("o_orderstatus"), F.floor(i / 900_000).cast("double").alias("o_totalprice"))
    r = rows(spark, name, tables(spark, tmp_path, orders=o))[0]
    assert (int(r.tuples), int(r.chains)) == (3_000_000**3, math.comb(10, 3) * 300_000**3)


# ------------------------------------------------------------------ block against block


@pytest.fixture
def no_column_pairs(monkeypatch, no_tuples):
    from tuplestat.operators import kernels as K
    from tuplestat.plans import variance as V

    def never(*_, **__):
        raise AssertionError("pairs of rows are formed")

    monkeypatch.setattr(V, "pair_components", never)
    monkeypatch.setattr(K, "metric_pair", never)


def anova(h):
    n, m = h.shape
    u, r, c = h.mean(), h.mean(axis=1), h.mean(axis=0)
    v0 = ((h - r[:, None] - c[None] + u) ** 2).sum() / ((n - 1) * (m - 1))
    return u, v0, (m * ((r - u) ** 2).sum() / (n - 1) - v0) / m, (n * ((c - u) ** 2).sum() / (m - 1) - v0) / n


def test_blocks_of_scores(spark, no_column_pairs):
    d = SF.replace("0.001", "0.01")
    (x,), (z,) = numbers(spark, d, "customer", "c_acctbal"), numbers(spark, d, "supplier", "s_acctbal")
    r = rows(spark, "kernel_logistic", d)[0]
    assert r.tuples == len(x) * len(z) and r.estimate == pytest.approx(np.logaddexp(0, (x[:, None] - z[None]) / 1000).mean(), abs=1e-8)
    r = rows(spark, "variance_components_pairs", d)[0]
    assert (r.u, r.v0, r.v1, r.v2) == pytest.approx(anova((z[None] < x[:, None]).astype(float)), abs=1e-7)
    r = rows(spark, "degenerate_kernel", d)[0]
    h = (x - x.mean())[:, None] * (z - z.mean())[None] / 1e6
    assert r.degenerate and r.v0 == pytest.approx(anova(h)[1], abs=1e-5)


def test_blocks_of_vectors(spark, no_column_pairs, tmp_path):
    """Null labels differ from every label; vectors with a null have no distance and no loss."""
    data = [(k, None if k == 3 else k % 2, [float((k * j) % 5) / 2 if (k, j) != (4, 1) else None for j in range(1, 4)] if k != 6 else None) for k in range(9)]
    e = spark.createDataFrame(data, "vec_id long, label int, embedding array<float>")
    r = rows(spark, "kernel_metric", tables(spark, tmp_path, embeddings=e))[0]
    total = 0.0
    for i, (_, ya, a) in enumerate(data):
        for _, yb, b in data[:i]:
            if a and b and None not in a and None not in b:
                gap = sum((p - q) ** 2 for p, q in zip(a, b)) - 2
                total += max(0, 1 + (gap if ya is not None and ya == yb else -gap))
    assert r.pairs == 36 and r.estimate == pytest.approx(total / 36, abs=1e-7)


def test_stream_dedup_keeps_rows_off_the_driver(spark, monkeypatch):
    from tuplestat.streaming import windows as W

    def never(*_, **__):
        raise AssertionError("the driver holds the stream's rows")

    monkeypatch.setattr(W, "run_to_end", never)
    assert rows(spark, "stream_dedup")[0].events == spark.read.parquet(f"{SF}/events.parquet").count()


# ------------------------------------------------------------------ learning on stored rows


def learnt(t):
    return {(r.run, r.shuffle_every, r.iteration, r.metric): r.value for r in t.collect()}


@pytest.mark.parametrize("sorted_test", [False, True])
def test_stored_runs_measure_what_shipped_runs_do(spark, monkeypatch, sorted_test):
    """Both forms start from the same models, on the same held-out rows; later values follow the law only."""
    from tuplestat.plans import learning as L
    from tuplestat.workloads import learning_queries as W

    d = SF.replace("0.001", "0.01") if not sorted_test else SF
    data = W.planted(spark, d, hard=False).cache()
    plan = (2, 12, 5, 20, (1, None)) if not sorted_test else (1, 2, 5, 20, (None,))
    shipped = learnt(W.curves(spark, data, *plan))
    monkeypatch.setattr(L, "BROADCAST_ROWS", 1000)
    if sorted_test:
        monkeypatch.setattr(L, "BROADCAST_TEST", 10)
    stored = learnt(W.curves(spark, data, *plan))
    release()
    assert set(stored) == set(shipped)
    for k, v in shipped.items():
        if k[3].startswith("test") and k[2] == 0:
            assert stored[k] == pytest.approx(v, abs=1e-9)
        else:
            assert stored[k] == pytest.approx(v, abs=0.05)


def test_planted_lines_are_joined_once_and_broadcast_nothing_that_grows(spark):
    from tuplestat.workloads import learning_queries as W

    plan = W.planted(spark, SF, hard=False)._jdf.queryExecution().executedPlan().toString()
    release()
    assert "InMemoryTableScan" in plan and "SortMergeJoin" in plan and "BroadcastHashJoin" not in plan


def test_cuts_hold_out_the_same_rows(spark):
    from tuplestat.functions.keyed import keyed_u64
    from tuplestat.plans import learning as L

    s = spark.range(1003).select((F.col("id") % 7 == 0).cast("int").alias("cls"), F.col("id").cast("string").alias("key"))
    want = {r.key for r in L.stratified_holdout(s, 0.2, 7).where("held_out").collect()}
    release()
    h = s.withColumn("h", keyed_u64(7, "holdout", F.col("key")))
    cuts = L.held_out_cuts(h, 0.2)
    assert {r.key for r in h.collect() if r.h <= cuts[r.cls]} == want


# ------------------------------------------------------------------ jobs on given tables


@pytest.mark.parametrize("name", [
    "discrete_law", "equal_budget", "fn_permute", "mc_rates", "mc_relative_variance", "plan_budget", "plan_diagnose", "rate_table", "source_synthetic",
    "swor_bias", "swor_empty_probability", "swor_variance",
])
def test_results_follow_the_table(spark, name):
    """Two tables have two results, and each is what the SQL makes of it."""
    import duckdb

    small = sorted(map(tuple, rows(spark, name)))
    d = SF.replace("0.001", "0.01")
    large = sorted(map(tuple, rows(spark, name, d)))
    assert small != large
    if name.startswith("mc_"):
        return
    con = duckdb.connect()
    for t in ("customer", "supplier", "lineitem"):
        con.execute(f"create view {t} as select * from '{d}/{t}.parquet'")
    cur = con.execute(entry.oracle_sql()[name])
    order = [c[0] for c in cur.description]
    want = sorted(cur.fetchall())
    columns = entry.queries()[name](spark, d).columns
    release()
    got = sorted(tuple(r[columns.index(c)] for c in order) for r in large)
    assert len(got) == len(want)
    for g, w in zip(got, want):
        assert all(a == b or a == pytest.approx(b, abs=1e-6) for a, b in zip(g, w))
