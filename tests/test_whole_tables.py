"""Whole-table queries against brute force over every row of the smallest tables."""

import itertools

import numpy as np
import pytest

import __spark_entry__ as entry
from tuplestat.operators import schemes as S
from tuplestat.workloads.base import SEED

SF = "/root/testdata/sf0.001"


def rows(spark, name):
    return entry.queries()[name](spark, SF).collect()


def column(spark, table, *names):
    got = spark.read.parquet(f"{SF}/{table}.parquet").select(*names).collect()
    return [np.array([r[k] for r in got]) for k in range(len(names))]


def mean_gap(v, f=np.abs):
    i, j = np.triu_indices(len(v), 1)
    return f(v[i] - v[j]).mean()


def test_one_sample_forms(spark):
    (v,) = column(spark, "events", "value")
    v = np.array([x for x in v if x is not None], dtype=float)
    g = rows(spark, "kernel_gini")[0]
    assert g.n == len(v) and g.estimate == pytest.approx(mean_gap(v), rel=1e-7)
    (p,) = column(spark, "orders", "o_totalprice")
    d2 = rows(spark, "u_complete_d2_whole")[0]
    assert d2.n == len(p) and d2.estimate == pytest.approx(mean_gap(np.round(p), np.square), rel=1e-6)
    (size,) = column(spark, "part", "p_size")
    t = np.array([max(x) - min(x) for x in itertools.combinations(size.tolist(), 3)])
    d3 = rows(spark, "u_complete_d3_whole")[0]
    assert (d3.tuples, d3.total) == (len(t), t.sum()) and d3.estimate == pytest.approx(t.mean())


def test_concordance_and_chains(spark):
    x, y = column(spark, "lineitem", "l_quantity", "l_extendedprice")
    want = sum(int((((x[i] - x[i + 1 :]) * (y[i] - y[i + 1 :])) > 0).sum()) for i in range(len(x)))
    k = rows(spark, "kernel_kendall")[0]
    assert (k.pairs, k.concordant) == (len(x) * (len(x) - 1) // 2, want)
    p, c = column(spark, "orders", "o_totalprice", "o_orderpriority")
    c = np.array([int(s[0]) for s in c])
    ways = np.ones((c == 1).sum())
    for b in range(2, 6):
        ways = (p[c == b - 1][None] < p[c == b][:, None]) @ ways
    v = rows(spark, "kernel_vus5")[0]
    assert v.chains == pytest.approx(ways.sum()) and v.tuples == pytest.approx(np.prod([(c == b).sum() for b in range(1, 6)], dtype=float))
    loss = {r.pair: r.loss for r in rows(spark, "multipartite_loss")}
    for b in range(1, 5):
        gap = 1 + p[c == b][:, None] / 1e5 - p[c == b + 1][None] / 1e5
        assert loss[b] == pytest.approx(np.maximum(0, gap).mean(), abs=1e-6)


def test_vectors(spark):
    e, y = spark.read.parquet(f"{SF}/embeddings.parquet").select("embedding", "label").toPandas().to_numpy().T
    e, y = np.array(e.tolist(), dtype=float), y.astype(int)
    i, j = np.triu_indices(len(y), 1)
    far, same = np.square(e[i] - e[j]).sum(axis=1), y[i] == y[j]
    c, m = rows(spark, "kernel_cluster")[0], rows(spark, "kernel_metric")[0]
    assert (c.pairs, c.inside, m.pairs) == (len(i), same.sum(), len(i))
    assert c.estimate == pytest.approx(np.where(same, far, 0).mean(), abs=1e-6)
    assert m.estimate == pytest.approx(np.maximum(0, 1 + np.where(same, 1, -1) * (far - 2)).mean(), abs=1e-6)


def test_within_workers(spark):
    from pyspark.sql import functions as F

    o = spark.read.parquet(f"{SF}/orders.parquet")
    key = F.lpad(F.col("o_orderkey").cast("string"), 12, "0").alias("key")
    sets = {}
    one = o.select(F.lit(0).alias("sample"), key, F.round("o_totalprice").alias("score"))
    for r in S.hash_rank(one, 5, 3, SEED).collect():
        sets.setdefault((r["round"], r.worker), []).append(r.score)
    got = {(r["round"], r.worker): (r.tuples, r.value) for r in rows(spark, "u_repartitioned_d2_whole")}
    assert set(got) == set(sets) and sum(map(len, sets.values())) == 3 * o.count()
    for k, v in sets.items():
        assert got[k][0] == len(v) * (len(v) - 1) // 2 and got[k][1] == pytest.approx(mean_gap(np.array(v)), rel=1e-7)
    status = F.instr(F.lit("FOP"), F.col("o_orderstatus")) - 1
    three, parts = o.select(status.alias("sample"), key, F.col("o_totalprice").alias("score")), {}
    for r in S.hash_rank(three, 5, 2, SEED).collect():
        parts.setdefault((r["round"], r.worker), ([], [], []))[r["sample"]].append(r.score)
    got = {(r["round"], r.worker): (r.tuples, r.wins) for r in rows(spark, "u_repartitioned_k3_whole")}
    for k, (a, b, c) in parts.items():
        a, b, c = map(np.array, (a, b, c))
        wins = ((a[None] < b[:, None]).sum(axis=1) * (b[:, None] < c[None]).sum(axis=1)).sum()
        assert got[k] == (len(a) * len(b) * len(c), wins)


def test_learning_curves_use_every_row(spark, monkeypatch):
    from tuplestat.workloads import learning_queries as W

    seen = {}

    def simulate(spark, x, z, test_x, test_z, runs, iterations, workers, batch, *rest, **more):
        seen["rows"], seen["width"], seen["plan"] = sum(map(len, (x, z, test_x, test_z))), x.shape[1], (runs, workers, batch)
        return spark.createDataFrame([], "run int, shuffle_every int, iteration int, metric string, value double")

    monkeypatch.setattr(W.L, "simulate", simulate)
    sf = SF.replace("sf0.001", "sf0.01")
    lines = spark.read.parquet(f"{sf}/lineitem.parquet").count()
    for name in ("learning_curves", "learning_curves_planted"):
        entry.queries()[name](spark, sf)
        assert seen["rows"] == lines > 10_000
    entry.queries()["learning_curves_replica"](spark, sf)
    assert seen["rows"] == 49_000 and seen["plan"] == (100, 100, 100)
    entry.queries()["learning_curves_quality"](spark, sf)
    labels = spark.read.parquet(f"{sf}/labels.parquet").where("quality IN (0, 1)").count()
    assert (seen["rows"], seen["width"]) == (labels, 9)
