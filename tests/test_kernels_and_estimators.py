"""Hand-checked instances, identities between estimators, and sorted forms against brute force."""

import itertools

import numpy as np
import pytest
from pyspark.sql import functions as F

from tuplestat.functions.keyed import keyed_int, keyed_u64, permute, unpermute
from tuplestat.operators import concordance, estimators as E, kernels as K, schemes as S, sorted_forms as Q
from tuplestat.operators.samples import as_sample, number_rows, sizes

AUC = K.auc()


def frame(spark, x, z):
    rows = [(0, f"x{i:04}", float(v)) for i, v in enumerate(x)] + [(1, f"z{i:04}", float(v)) for i, v in enumerate(z)]
    return spark.createDataFrame(rows, "sample int, key string, score double")


def placed(spark, parts, round_=1):
    rows = []
    for w, (x, z) in enumerate(parts):
        rows += [(round_, w, 0, f"x{w}{i}", float(v)) for i, v in enumerate(x)] + [(round_, w, 1, f"z{w}{i}", float(v)) for i, v in enumerate(z)]
    return spark.createDataFrame(rows, "round int, worker int, sample int, key string, score double")


def test_hand_checked_areas(spark):
    s = frame(spark, [2, 2, 0, 2], [-1, 1, -1, 1])
    assert E.complete_u(s, AUC).first().estimate == 0.875
    one = placed(spark, [([2, 0], [-1, -1]), ([2, 2], [1, 1])])
    two = placed(spark, [([2, 2], [-1, -1]), ([0, 2], [1, 1])], 2)
    assert E.combine(E.local_estimates(one, AUC, 2, 1)).first().estimate == 1.0
    both = one.unionByName(two)
    r = E.combine(E.local_estimates(both, AUC, 2, 2)).first()
    assert (r.estimate, r.workers, r.rounds, r.tuples) == (0.875, 2, 2, 16)


def test_empty_worker_rules(spark):
    a = placed(spark, [([2, 2], [1]), ([2], [])])
    assert E.combine(E.local_estimates(a, AUC, 2, 1)).first().estimate == 0.5
    assert E.combine(E.local_estimates(a, AUC, 2, 1, "skip")).first().estimate == 1.0
    with pytest.raises(Exception, match="no tuples"):
        E.local_estimates(a, AUC, 2, 1, "error").collect()


def test_hand_checked_one_sample(spark):
    s = as_sample(spark.createDataFrame([(1, 1.0), (2, 3.0), (3, 6.0)], "k int, v double"), 0, F.col("k"), F.col("v"))
    assert E.complete_u(s, K.SQDIFF).first().estimate == pytest.approx(38 / 3)
    assert E.complete_u(s, K.HALF_SQDIFF).first().estimate == pytest.approx(19 / 3)
    assert E.complete_u(s, K.ABSDIFF).first().estimate == pytest.approx(10 / 3)
    assert Q.mean_absolute_difference(s, F.col("score")).first().estimate == pytest.approx(10 / 3)
    p = spark.createDataFrame([(1, 1), (2, 3), (3, 2)], "x int, y int")
    r = concordance.concordance_counts(p, "x", "y").first()
    assert (r.pairs, r.concordant) == (3, 2)


def test_ordered_chain(spark):
    rows = [(0, "a", 1.0), (0, "b", 2.0), (1, "a", 2.0), (1, "b", 3.0), (2, "a", 3.0), (2, "b", 4.0)]
    s = spark.createDataFrame(rows, "sample int, key string, score double")
    assert E.complete_u(s, K.chain(3)).first().total == 4
    r = Q.vus_counts(s, F.col("score"), F.col("sample") + 1, 3).first()
    assert (r.tuples, r.chains) == (8, 4)


def test_hinge_value(spark):
    r = Q.hinge_sums(frame(spark, [0, 2], [1, 2.5]), F.col("score"), F.col("sample") == 0).first()
    assert r.estimate == pytest.approx(0.625)


@pytest.mark.parametrize("seed", range(3))
def test_sorted_forms_against_brute_force(spark, seed):
    rng = np.random.default_rng(seed)
    x, z = rng.integers(0, 9, 60) / 2, rng.integers(0, 9, 25) / 2
    s = frame(spark, x, z)
    r = Q.auc_counts(s, F.col("score"), F.col("sample") == 0).first()
    assert (r.wins, r.ties) == ((z[None] < x[:, None]).sum(), (z[None] == x[:, None]).sum())
    h = Q.hinge_sums(s, F.col("score"), F.col("sample") == 0).first()
    assert h.total == pytest.approx(np.maximum(0, 1 + x[:, None] - z[None]).sum())
    v = as_sample(spark.createDataFrame([(i, float(a)) for i, a in enumerate(x)], "k int, v double"), 0, F.col("k"), F.col("v"))
    assert Q.mean_absolute_difference(v, F.col("score")).first().total == pytest.approx(np.abs(x[:, None] - x[None]).sum() / 2)
    y = rng.integers(0, 7, 60)
    p = spark.createDataFrame([(float(a), int(b)) for a, b in zip(x, y)], "x double, y int")
    want = sum((x[i] - x[j]) * (y[i] - y[j]) > 0 for i, j in itertools.combinations(range(60), 2))
    assert concordance.concordance_counts(p, "x", "y", 4).first().concordant == want
    a = S.hash_rank(s, 5, 2, seed)
    key = lambda df: sorted((q["round"], q.worker, q.tuples, q.total, round(q.value, 12)) for q in df.collect())
    assert key(Q.auc_by_worker(a)) == key(E.local_estimates(a, AUC, 5, 2).select("round", "worker", "tuples", "total", "value"))


def test_ordered_pairs_of_large_blocks():
    rng = np.random.default_rng(0)
    for span in (5, 400, 10**6):
        x, y = np.sort(rng.integers(0, span, 1500)), rng.integers(0, span, 1500)
        c = rng.integers(1, 4, 1500)
        want = int(c @ ((x[:, None] < x[None]) & (y[:, None] < y[None])) @ c)
        assert concordance.ordered_pairs(x, y, c) == want


def test_identities(spark):
    rng = np.random.default_rng(5)
    s = frame(spark, rng.normal(size=40), rng.normal(size=20))
    whole = E.complete_u(s, AUC).first()
    assert E.combine(E.repartitioned_u(s, AUC, 1, 1, 7)).first().estimate == pytest.approx(whole.estimate)
    fused = E.combine(E.repartitioned_u(s, AUC, 5, 3, 7)).first()
    assert E.combine(E.repartitioned_u(s, AUC, 5, 3, 7, execution="iterative")).first().estimate == pytest.approx(fused.estimate)
    by_round = [E.combine(E.repartitioned_u(s, AUC, 5, 3, 7).where(F.col("round") == t)).first().estimate for t in (1, 2, 3)]
    assert np.mean(by_round) == pytest.approx(fused.estimate)
    assert E.complete_tiled(s, AUC, (3, 2), 1).first().estimate == pytest.approx(whole.estimate)
    assert E.complete_auc_broadcast(s.repartition(5)).first().total == whole.total
    with pytest.raises(ValueError):
        E.complete_auc_broadcast(s, most_rows=3)


def test_inverse_permutation_gives_the_same_draws(spark):
    rng = np.random.default_rng(6)
    s = number_rows(frame(spark, rng.normal(size=53), rng.normal(size=21)))
    k = sizes(s)
    direct = E.local_incomplete(S.seeded(s, k, 4, 2, 3), AUC, 4, 2, 30, 3, k)
    inverse = E.local_incomplete_by_inverse(s, AUC, 4, 2, 30, 3, k)
    key = lambda df: sorted((r["round"], r.worker, r.tuples, r.total) for r in df.collect())
    assert key(direct) == key(inverse)


def test_mean_over_all_balanced_cuts_is_the_complete_statistic():
    rng = np.random.default_rng(8)
    x, z = rng.normal(size=4), rng.normal(size=4)
    h = (z[None] < x[:, None]).astype(float)
    values = []
    for a in itertools.combinations(range(4), 2):
        for b in itertools.combinations(range(4), 2):
            ra, rb = [i for i in range(4) if i not in a], [i for i in range(4) if i not in b]
            values.append((h[np.ix_(a, b)].mean() + h[np.ix_(ra, rb)].mean()) / 2)
    assert np.mean(values) == pytest.approx(h.mean())


def test_permutation_is_a_bijection_and_undone(spark):
    for n in (1, 2, 17, 256):
        r = spark.range(n).select("id", permute(F.col("id"), n, 9, 1, 0).alias("p")).withColumn("u", unpermute(F.col("p"), n, 9, 1, 0)).collect()
        assert sorted(q.p for q in r) == list(range(n)) and all(q.u == q.id for q in r)


def test_schemes_cover_and_balance(spark):
    s = number_rows(frame(spark, range(103), range(17)))
    k = sizes(s)
    for a in (S.hash_rank(s, 5, 2, 1), S.seeded(s, k, 5, 2, 1), S.stride(s, 5, 2)):
        parts = a.groupBy("round", "worker", "sample").count().collect()
        for sample, n in k.items():
            got = [r["count"] for r in parts if r["sample"] == sample]
            assert sum(got) == 2 * n and max(got) - min(got) <= 1
    swr = S.prop_swr(s, k, 5, 2, 1)
    assert swr.count() == 2 * 5 * (103 // 5 + 17 // 5)
    with pytest.raises(ValueError):
        S.prop_swr(s, k, 50, 1, 1)


def test_result_does_not_depend_on_partitioning(spark):
    rng = np.random.default_rng(11)
    s = frame(spark, rng.normal(size=50), rng.normal(size=20))
    a = E.combine(E.repartitioned_u(s, AUC, 5, 2, 7)).first().estimate
    b = E.combine(E.repartitioned_u(s.repartition(7), AUC, 5, 2, 7)).first().estimate
    assert a == pytest.approx(b)


def test_number_rows_is_dense(spark):
    s = number_rows(frame(spark, range(57), range(9)).repartition(5))
    for k, n in ((0, 57), (1, 9)):
        assert sorted(r.idx for r in s.where(F.col("sample") == k).collect()) == list(range(n))


def test_keyed_hash_on_driver_and_executors(spark):
    assert spark.range(1).select(keyed_u64(7, "a", 3).alias("h")).first().h == keyed_int(7, "a", 3)


def test_sampling_designs(spark):
    s = number_rows(frame(spark, range(30), range(20)))
    k = sizes(s)
    d = E.draws(spark, 600, 30, 20, 1, "without_replacement").collect()
    assert len({(r.i, r.j) for r in d}) == 600
    assert E.incomplete_u(s, AUC, 600, 1, k, "without_replacement").first().estimate == pytest.approx(E.complete_u(s, AUC).first().estimate)
    b = E.draws(spark, 300, 30, 20, 1, "bernoulli").collect()
    assert len({(r.i, r.j) for r in b}) == len(b) and 200 < len(b) < 400 and all(0 <= r.i < 30 and 0 <= r.j < 20 for r in b)


def test_nulls_and_nan_in_scores(spark):
    df = spark.createDataFrame([("a", 1.0), ("b", None), ("c", float("nan"))], "k string, v double")
    assert as_sample(df, 0, F.col("k"), F.col("v")).count() == 1
    with pytest.raises(Exception, match="null or NaN"):
        as_sample(df, 0, F.col("k"), F.col("v"), "error").collect()


def test_user_kernels(spark):
    s = frame(spark, [1, 2, 3], [2, 5])
    sql = K.Kernel.from_sql("CASE WHEN z < x THEN 1 ELSE 0 END", (1, 1))
    assert E.complete_u(s, sql).first().total == 1
    assert E.complete_u(s, K.Kernel.from_numpy(lambda x, z: (z < x).astype(float), (1, 1))).first().total == 1
    lop = K.Kernel("first", (2,), lambda a, b: a)
    one = as_sample(spark.createDataFrame([(1, 1.0), (2, 3.0)], "k int, v double"), 0, F.col("k"), F.col("v"))
    assert E.complete_u(one, lop.symmetrized()).first().estimate == 2.0


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_plans_scale(spark):
    s = frame(spark, range(20), range(10))
    a = S.hash_rank(s, 5, 2, 1)
    for df in (E.local_estimates(a, AUC, 5, 2), Q.auc_by_worker(a)):
        assert "CartesianProduct" not in plan(df) and "Exchange SinglePartition" not in plan(df)
    k = {0: 20, 1: 10}
    p = plan(S.seeded(number_rows(s), k, 5, 2, 1).select("round", "worker"))
    assert "ArrowEvalPython" not in p and "BatchEvalPython" not in p


def test_main_method_has_no_window_over_a_sample(spark, monkeypatch):
    s = number_rows(frame(spark, range(40), range(20)))
    assert "Window" not in plan(s).split("InMemoryTableScan")[0]
    s = spark.createDataFrame(s.collect(), s.schema)
    k = sizes(s)
    fused = E.repartitioned_u(s, AUC, 5, 3, 7, sizes=k)
    text = plan(fused)
    assert "Union" not in text and "row_number" not in text and text.count("Window") <= plan(Q.auc_by_worker(S.static(s, 5, 7))).count("Window")
    made = []
    monkeypatch.setattr(E, "seeded", lambda df, *a, **b: made.append(a[2]) or S.seeded(df, *a, **b))
    one_by_one = E.repartitioned_u(s, AUC, 5, 3, 7, sizes=k, execution="iterative")
    assert made == [1, 1, 1] and "Exchange" not in plan(one_by_one)  # three jobs of one round; their short rows are folded
    key = lambda df: sorted((r["round"], r.worker, r.tuples, r.total) for r in df.collect())
    assert key(one_by_one) == key(fused)
    drawn = [key(E.repartitioned_u(s, AUC, 5, 3, 7, 6, k, execution=x)) for x in ("inverse", "fused", "iterative")]
    assert drawn[0] == drawn[1] == drawn[2]


def test_prefix_sums_within_groups_over_many_tasks(spark):
    rng = np.random.default_rng(3)
    rows = [("big" if i % 3 else f"g{i % 40}", float(v), int(c)) for i, (v, c) in enumerate(zip(rng.permutation(4000), rng.integers(1, 9, 4000)))]
    df = spark.createDataFrame(rows, "g string, o double, v long").repartition(7)
    got = {(r.g, r.o): r.before_v for r in Q.prefix_sums(df, "o", ("v",), ("g",)).collect()}
    assert got == {(r.g, r.o): r.before_v for r in Q.prefix_sums(df, "o", ("v",), ("g",), local=True).collect()}
    assert len(got) == 4000
