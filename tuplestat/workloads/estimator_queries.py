"""Estimators and assignment schemes."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import estimators as E
from ..operators import kernels as K
from ..operators import schemes as S
from ..operators import sorted_forms
from ..operators.samples import as_sample, number_rows, sizes
from ..sources.catalog import load
from .base import (
    BATCH,
    COMBINED,
    LOCAL_AUC,
    NUMBERED,
    ROUNDS,
    SEED,
    TWO,
    WORKERS,
    balances,
    ku,
    local_rows,
    numbered_balances,
    query,
    ranked_sql,
    rounded,
    seeded_sql,
)

AUC = K.auc()

PAIRS = "FROM s x JOIN s z ON x.sample = 0 AND z.sample = 1"
COMPLETE = f"""WITH {TWO}
SELECT count(*) AS tuples, CAST(sum(CASE WHEN z.score < x.score THEN 1 ELSE 0 END) AS BIGINT) AS total,
       round(avg(CASE WHEN z.score < x.score THEN 1.0 ELSE 0.0 END), 9) AS estimate {PAIRS}"""


def _whole(df):
    return df.select("tuples", F.col("total").cast("long").alias("total"), F.round("estimate", 9).alias("estimate"))


@query(COMPLETE)
def u_complete_pair(spark, d):
    return _whole(E.complete_u(balances(spark, d), AUC))


@query(COMPLETE)
def u_complete_auc(spark, d):
    """The same number without pairs."""
    r = sorted_forms.auc_counts(balances(spark, d), F.col("score"), F.col("sample") == 0)
    return r.select((F.col("n") * F.col("m")).alias("tuples"), F.col("wins").alias("total"), F.round("auc", 9).alias("estimate"))


@query(
    COMPLETE.replace(
        "SELECT count(*) AS tuples",
        "SELECT (SELECT CAST(sum(CASE WHEN sample = 0 THEN 5 ELSE 3 END) AS BIGINT) FROM s) AS moved_rows, count(*) AS tuples",
    )
)
def u_complete_tiled(spark, d):
    return E.complete_tiled(balances(spark, d), AUC, (3, 5), SEED).select(
        "moved_rows", "tuples", F.col("total").cast("long").alias("total"), F.round("estimate", 9).alias("estimate")
    )


@query(COMPLETE)
def u_complete_broadcast(spark, d):
    """Small second sample: sorted, broadcast, searched; no shuffle of rows."""
    return _whole(E.complete_auc_broadcast(balances(spark, d)))


def _thirds(spark, d):
    """All suppliers in three classes."""
    s = load(spark, d, "supplier").where("s_acctbal IS NOT NULL")
    key = F.lpad(F.col("s_suppkey").cast("string"), 12, "0")
    return s.select(F.pmod("s_nationkey", F.lit(3)).cast("int").alias("sample"), key.alias("key"), F.col("s_acctbal").alias("score"))


THIRDS = """s AS (
  SELECT CAST(s_nationkey % 3 AS INTEGER) AS sample, lpad(CAST(s_suppkey AS VARCHAR), 12, '0') AS key, s_acctbal AS score FROM supplier WHERE s_acctbal IS NOT NULL
)"""


def _customers(spark, d):
    c = load(spark, d, "customer").where("c_acctbal IS NOT NULL")
    return as_sample(c, 0, F.lpad(F.col("c_custkey").cast("string"), 12, "0"), F.round("c_acctbal"))


CUSTOMERS = "s AS (SELECT 0 AS sample, lpad(CAST(c_custkey AS VARCHAR), 12, '0') AS key, CAST(round(c_acctbal) AS BIGINT) AS score FROM customer WHERE c_acctbal IS NOT NULL)"


@query(
    f"""WITH {THIRDS}
SELECT count(*) AS tuples, CAST(sum(CASE WHEN a.score < b.score AND b.score < c.score THEN 1 ELSE 0 END) AS BIGINT) AS total,
       round(avg(CASE WHEN a.score < b.score AND b.score < c.score THEN 1.0 ELSE 0.0 END), 9) AS estimate
FROM s a, s b, s c WHERE a.sample = 0 AND b.sample = 1 AND c.sample = 2"""
)
def u_complete_k3(spark, d):
    """Chains of three without triples."""
    r = E.complete_sorted(_thirds(spark, d), K.chain(3))
    return _whole(r.withColumn("tuples", F.col("tuples").cast("long")))


@query(
    f"""WITH {CUSTOMERS}
SELECT count(*) AS tuples, CAST(sum((a.score - b.score) * (a.score - b.score)) AS DOUBLE) AS total, round(avg((a.score - b.score) * (a.score - b.score)), 3) AS estimate
FROM s a JOIN s b ON a.key < b.key"""
)
def u_complete_d2(spark, d):
    """Exact from the sum of the balances and of their squares."""
    r = E.complete_sorted(_customers(spark, d), K.SQDIFF)
    return rounded(r.withColumn("total", F.col("total").cast("double")), 3, "estimate")


@query(
    f"""WITH {THIRDS}, v AS (SELECT key, CAST(round(score) AS BIGINT) AS v FROM s)
SELECT count(*) AS tuples, CAST(sum(greatest(a.v, b.v, c.v) - least(a.v, b.v, c.v)) AS BIGINT) AS total,
       round(avg(greatest(a.v, b.v, c.v) - least(a.v, b.v, c.v)), 9) AS estimate
FROM v a JOIN v b ON a.key < b.key JOIN v c ON b.key < c.key"""
)
def u_complete_d3(spark, d):
    """Mean range of three suppliers' balances: one sample, degree three, from ranks."""
    s = as_sample(_thirds(spark, d), 0, F.col("key"), F.round("score"))
    k = K.Kernel("range3", (3,), lambda a, b, c: F.greatest(a, b, c) - F.least(a, b, c))
    return _whole(E.complete_sorted(s, k).withColumn("tuples", F.col("tuples").cast("long")))


DRAWN = f"""WITH {NUMBERED}, c AS (
  SELECT count(*) FILTER (sample = 0) AS n, count(*) FILTER (sample = 1) AS m FROM s
), p AS (
  SELECT b, {ku(str(SEED), "'pair'", '0', 'b')} % n AS i, {ku(str(SEED), "'pair'", '1', 'b')} % m AS j
  FROM (SELECT unnest(range(2000)) AS b), c
)
SELECT count(*) AS tuples, CAST(sum(CASE WHEN z.score < x.score THEN 1 ELSE 0 END) AS BIGINT) AS total,
       round(avg(CASE WHEN z.score < x.score THEN 1.0 ELSE 0.0 END), 9) AS estimate
FROM p JOIN n x ON x.sample = 0 AND x.idx = p.i JOIN n z ON z.sample = 1 AND z.idx = p.j"""


@query(DRAWN)
def u_incomplete(spark, d):
    s = numbered_balances(spark, d)
    return _whole(E.incomplete_u(s, AUC, 2000, SEED, sizes(s)))


@query()
def u_incomplete_wor(spark, d):
    s = numbered_balances(spark, d)
    return _whole(E.incomplete_u(s, AUC, 2000, SEED, sizes(s), "without_replacement"))


@query(
    f"""WITH {NUMBERED}, c AS (SELECT count(*) FILTER (sample = 0) AS n, count(*) FILTER (sample = 1) AS m FROM s)
SELECT count(*) AS tuples, CAST(sum(CASE WHEN z.score < x.score THEN 1 ELSE 0 END) AS BIGINT) AS total,
       round(avg(CASE WHEN z.score < x.score THEN 1.0 ELSE 0.0 END), 9) AS estimate {PAIRS}"""
)
def u_incomplete_wor_all(spark, d):
    """As many draws without replacement as there are pairs: the complete statistic."""
    s = numbered_balances(spark, d)
    size = sizes(s)
    return _whole(E.incomplete_u(s, AUC, size[0] * size[1], SEED, size, "without_replacement"))


@query()
def u_incomplete_bernoulli(spark, d):
    s = numbered_balances(spark, d)
    return _whole(E.incomplete_u(s, AUC, 2000, SEED, sizes(s), "bernoulli"))


@query(
    f"""WITH {TWO}, k AS (
  SELECT *, row_number() OVER (PARTITION BY sample ORDER BY {ku(str(SEED), "'rows'", "concat_ws('|', sample, key)")}, concat_ws('|', sample, key)) AS r FROM s
)
SELECT count(*) AS tuples, CAST(sum(CASE WHEN z.score < x.score THEN 1 ELSE 0 END) AS BIGINT) AS total,
       round(avg(CASE WHEN z.score < x.score THEN 1.0 ELSE 0.0 END), 9) AS estimate
FROM k x JOIN k z ON x.sample = 0 AND z.sample = 1 AND x.r <= 100 AND z.r <= 20"""
)
def u_subsample(spark, d):
    return _whole(E.subsample_u(balances(spark, d), AUC, {0: 100, 1: 20}, SEED))


def _seeded(rounds=ROUNDS, workers=WORKERS):
    return f"WITH {NUMBERED}, {seeded_sql(workers, rounds)}, {LOCAL_AUC.format(rounds=rounds, workers=workers)}"


LOCAL = " SELECT CAST(round AS INTEGER) AS round, CAST(worker AS INTEGER) AS worker, tuples, wins, round(value, 9) AS value FROM g"
MOVED = COMBINED.format(source="g").replace("round(avg(value), 9) AS estimate", f"round(avg(value), 9) AS estimate, (SELECT {ROUNDS} * count(*) FROM s) AS moved_rows")


def _shuffled(rounds=ROUNDS, workers=WORKERS):
    return f"WITH {TWO}, {ranked_sql('s', workers, rounds)}, {LOCAL_AUC.format(rounds=rounds, workers=workers)}"


@query(_shuffled(1) + " SELECT CAST(round AS INTEGER) AS round, CAST(worker AS INTEGER) AS worker, tuples, wins, round(value, 9) AS value FROM g")
def u_local(spark, d):
    return local_rows(E.local_estimates(S.hash_rank(balances(spark, d), WORKERS, 1, SEED), AUC, WORKERS, 1))


@query(_seeded() + LOCAL)
def u_repartitioned(spark, d):
    """The main method: one row per round and worker, workers by the seeded permutation, evaluated
    without pairs."""
    return local_rows(E.repartitioned_u(balances(spark, d), AUC, WORKERS, ROUNDS, SEED, hashed="md5"))


@query(_shuffled() + LOCAL)
def u_repartitioned_ranked(spark, d):
    """The same law from ranked hashes, which coordinate through a sort."""
    return local_rows(E.repartitioned_u(balances(spark, d), AUC, WORKERS, ROUNDS, SEED, permutation="hash_rank", execution="fused"))


@query(_seeded() + MOVED)
def u_repartitioned_estimate(spark, d):
    s = numbered_balances(spark, d)
    size = sizes(s)
    local = E.repartitioned_u(s, AUC, WORKERS, ROUNDS, SEED, sizes=size, hashed="md5")
    return rounded(E.combine(local, moved_rows=E.shipped_rows(size, ROUNDS)), 9, "estimate")


@query(_seeded() + COMBINED.format(source="g"))
def u_repartitioned_iterative(spark, d):
    """A job per round; one copy of the data in shuffle storage at a time."""
    local = E.repartitioned_u(balances(spark, d), AUC, WORKERS, ROUNDS, SEED, execution="iterative", hashed="md5")
    return rounded(E.combine(local), 9, "estimate")


@query(_seeded() + COMBINED.format(source="g"))
def u_repartitioned_pairs(spark, d):
    """The same number from pairs that meet in an equi-join, as kernels without a sorted form do."""
    s = numbered_balances(spark, d)
    a = S.seeded(s, sizes(s), WORKERS, ROUNDS, SEED, hashed="md5")
    return rounded(E.combine(E.local_estimates(a, AUC, WORKERS, ROUNDS)), 9, "estimate")


def _local_draws(rounds, seeded=False):
    c = "(SELECT count(*) FROM s WHERE sample = {k})"
    part = lambda k: f"({c.format(k=k)} // {WORKERS} + CASE WHEN k.worker < {c.format(k=k)} % {WORKERS} THEN 1 ELSE 0 END)"
    key = lambda k: ku(str(SEED), "'local'", "t.round", "k.worker", str(k), "b")
    rows = f"{NUMBERED}, {seeded_sql(WORKERS, rounds)}" if seeded else f"{TWO}, {ranked_sql('s', WORKERS, rounds)}"
    return f"""WITH {rows}, p AS (
  SELECT t.round, k.worker, b, {key(0)} % {part(0)} AS i, {key(1)} % {part(1)} AS j
  FROM (SELECT unnest(range(1, {rounds + 1})) AS round) t, (SELECT unnest(range({WORKERS})) AS worker) k, (SELECT unnest(range({BATCH})) AS b)
), g AS (
  SELECT p.round, p.worker, count(*) AS tuples, CAST(sum(CASE WHEN z.score < x.score THEN 1 ELSE 0 END) AS BIGINT) AS wins,
         avg(CASE WHEN z.score < x.score THEN 1.0 ELSE 0.0 END) AS value
  FROM p JOIN w x ON x.sample = 0 AND x.round = p.round AND x.worker = p.worker AND x.slot = p.i
         JOIN w z ON z.sample = 1 AND z.round = p.round AND z.worker = p.worker AND z.slot = p.j
  GROUP BY 1, 2
)"""


@query(_local_draws(1) + " SELECT CAST(round AS INTEGER) AS round, CAST(worker AS INTEGER) AS worker, tuples, wins, round(value, 9) AS value FROM g")
def u_local_incomplete(spark, d):
    s = balances(spark, d)
    a = S.hash_rank(s, WORKERS, 1, SEED)
    return local_rows(E.local_incomplete(a, AUC, WORKERS, 1, BATCH, SEED, sizes(s)))


@query(_local_draws(ROUNDS) + COMBINED.format(source="g"))
def u_repartitioned_incomplete(spark, d):
    s = balances(spark, d)
    local = E.repartitioned_u(s, AUC, WORKERS, ROUNDS, SEED, BATCH, sizes(s), "hash_rank", "fused")
    return rounded(E.combine(local), 9, "estimate")


@query(_local_draws(ROUNDS, True) + LOCAL)
def u_repartitioned_incomplete_inverse(spark, d):
    """Seeded permutation, drawn rows looked up through its inverse: no repartition at all."""
    return local_rows(E.repartitioned_u(balances(spark, d), AUC, WORKERS, ROUNDS, SEED, BATCH, hashed="md5"))


@query(_local_draws(ROUNDS, True) + COMBINED.format(source="g"))
def u_repartitioned_incomplete_iterative(spark, d):
    """The same draws after a true repartition, a job per round."""
    local = E.repartitioned_u(balances(spark, d), AUC, WORKERS, ROUNDS, SEED, BATCH, execution="iterative", hashed="md5")
    return rounded(E.combine(local), 9, "estimate")


@query(_seeded() + LOCAL)
def u_repartitioned_seeded(spark, d):
    """The scheme and the sorted form by themselves."""
    s = numbered_balances(spark, d)
    return local_rows(sorted_forms.auc_by_worker(S.seeded(s, sizes(s), WORKERS, ROUNDS, SEED, hashed="md5")))


@query(f"SELECT {ROUNDS} AS rounds, {ROUNDS * WORKERS} AS parts, (SELECT count(*) FROM customer WHERE c_acctbal IS NOT NULL) // {WORKERS} * (SELECT count(*) FROM supplier WHERE s_acctbal IS NOT NULL) // {WORKERS} AS pairs_each")
def u_repartitioned_fast(spark, d):
    """The default (64-bit) hash: rounds, parts and pairs of a part; its values are held to those of the
    md5 form by law, not by number."""
    local = E.repartitioned_u(balances(spark, d), AUC, WORKERS, ROUNDS, SEED)
    return local.agg(F.countDistinct("round").cast("int").alias("rounds"), F.count("*").cast("int").alias("parts"), F.min("tuples").alias("pairs_each"))


GRID = f"""{_local_draws(ROUNDS)}, l AS (
  SELECT x.round, x.worker, avg(CASE WHEN z.score < x.score THEN 1.0 ELSE 0.0 END) AS value, count(*) AS tuples
  FROM w x JOIN w z ON x.round = z.round AND x.worker = z.worker AND x.sample = 0 AND z.sample = 1 GROUP BY 1, 2
)
SELECT 'complete' AS estimator, count(*) AS tuples, round(avg(CASE WHEN z.score < x.score THEN 1.0 ELSE 0.0 END), 9) AS estimate {PAIRS}
UNION ALL SELECT 'local', CAST(sum(tuples) AS BIGINT), round(avg(value), 9) FROM l WHERE round = 1
UNION ALL SELECT 'local_incomplete', CAST(sum(tuples) AS BIGINT), round(avg(value), 9) FROM g WHERE round = 1
UNION ALL SELECT 'repartitioned', CAST(sum(tuples) AS BIGINT), round(avg(value), 9) FROM l
UNION ALL SELECT 'repartitioned_incomplete', CAST(sum(tuples) AS BIGINT), round(avg(value), 9) FROM g"""


@query(GRID)
def estimator_grid(spark, d):
    """Shuffled or not, all pairs or drawn ones, beside the complete statistic."""
    s = balances(spark, d)
    size = sizes(s)
    a = S.hash_rank(s, WORKERS, ROUNDS, SEED)
    full = E.local_estimates(a, AUC, WORKERS, ROUNDS)
    drawn = E.local_incomplete(a, AUC, WORKERS, ROUNDS, BATCH, SEED, size)

    def one(name, local):
        c = E.combine(local)
        return c.select(F.lit(name).alias("estimator"), "tuples", F.round("estimate", 9).alias("estimate"))

    out = E.complete_u(s, AUC).select(F.lit("complete").alias("estimator"), "tuples", F.round("estimate", 9).alias("estimate"))
    for name, local in (
        ("local", full.where("round = 1")),
        ("local_incomplete", drawn.where("round = 1")),
        ("repartitioned", full),
        ("repartitioned_incomplete", drawn),
    ):
        out = out.unionByName(one(name, local))
    return out


@query(
    f"""WITH {THIRDS}, {ranked_sql('s', 5, 2)}
SELECT CAST(a.round AS INTEGER) AS round, CAST(a.worker AS INTEGER) AS worker, count(*) AS tuples,
       CAST(sum(CASE WHEN a.score < b.score AND b.score < c.score THEN 1 ELSE 0 END) AS BIGINT) AS wins,
       round(avg(CASE WHEN a.score < b.score AND b.score < c.score THEN 1.0 ELSE 0.0 END), 9) AS value
FROM w a JOIN w b ON a.round = b.round AND a.worker = b.worker AND a.sample = 0 AND b.sample = 1
JOIN w c ON a.round = c.round AND a.worker = c.worker AND c.sample = 2 GROUP BY 1, 2"""
)
def u_repartitioned_k3(spark, d):
    return local_rows(E.local_sorted(S.hash_rank(_thirds(spark, d), 5, 2, SEED), K.chain(3), 5, 2))


@query(
    f"""WITH {CUSTOMERS},
{ranked_sql('s', 5, 3)}
SELECT CAST(a.round AS INTEGER) AS round, CAST(a.worker AS INTEGER) AS worker, count(*) AS tuples,
       CAST(sum(abs(a.score - b.score)) AS BIGINT) AS wins, round(avg(abs(a.score - b.score)), 6) AS value
FROM w a JOIN w b ON a.round = b.round AND a.worker = b.worker AND a.key < b.key GROUP BY 1, 2"""
)
def u_repartitioned_d2(spark, d):
    s = _customers(spark, d)
    return local_rows(E.local_sorted(S.hash_rank(s, 5, 3, SEED), K.ABSDIFF, 5, 3)).withColumn("value", F.round("value", 6))


@query(
    f"""{_seeded(12)}, v AS (SELECT round, avg(value) AS value FROM g GROUP BY round),
e AS (SELECT round, value, avg(value) OVER a AS estimate, stddev_samp(value) OVER a / sqrt(round) AS std_error FROM v WINDOW a AS (ORDER BY round ROWS UNBOUNDED PRECEDING)),
o AS (SELECT coalesce(min(round), 12) AS last FROM e WHERE round >= 3 AND std_error <= 0.002)
SELECT CAST(round AS INTEGER) AS round, round(value, 9) AS value, round(estimate, 9) AS estimate, round(std_error, 9) AS std_error FROM e, o WHERE round <= last"""
)
def u_early_stop(spark, d):
    return rounded(E.early_stopped(balances(spark, d), AUC, WORKERS, SEED, 0.002, 12, hashed="md5"), 9, "value", "estimate", "std_error")


# ------------------------------------------------------------------ schemes

ASSIGNED = "SELECT CAST(round AS INTEGER) AS round, CAST(sample AS INTEGER) AS sample, key, CAST(worker AS INTEGER) AS worker"


def _assigned(df, *more):
    return df.select(F.col("round").cast("int").alias("round"), "sample", "key", "worker", *more)


@query(f"WITH {TWO}, {ranked_sql('s', WORKERS, 2)} {ASSIGNED}, CAST(slot AS BIGINT) AS slot FROM w")
def assign_hash_rank(spark, d):
    return _assigned(S.hash_rank(balances(spark, d), WORKERS, 2, SEED), "slot")


@query(
    f"""WITH {TWO}, {ranked_sql('s', WORKERS, ROUNDS)}
SELECT CAST(round AS INTEGER) AS round, CAST(worker AS INTEGER) AS worker, count(*) FILTER (sample = 0) AS n, count(*) FILTER (sample = 1) AS m FROM w GROUP BY 1, 2"""
)
def assign_prop_swor(spark, d):
    """Exact proportions on every worker, from the coordination-free permutation."""
    s = numbered_balances(spark, d)
    a = S.seeded(s, sizes(s), WORKERS, ROUNDS, SEED)
    return a.groupBy("round", "worker").agg(
        F.sum((F.col("sample") == 0).cast("long")).alias("n"), F.sum((F.col("sample") == 1).cast("long")).alias("m")
    )


@query(f"WITH {NUMBERED}, {seeded_sql(WORKERS, 2)} {ASSIGNED}, CAST(slot AS BIGINT) AS slot FROM w")
def assign_seeded(spark, d):
    s = numbered_balances(spark, d)
    return _assigned(S.seeded(s, sizes(s), WORKERS, 2, SEED, hashed="md5"), "slot")


@query(f"WITH {TWO}, {ranked_sql('s', WORKERS, 2, 't.round')} {ASSIGNED} FROM w")
def assign_swor(spark, d):
    return _assigned(S.hash_rank(balances(spark, d), WORKERS, 2, SEED, by_sample=False))


@query(
    f"""WITH {TWO} SELECT CAST(t.round AS INTEGER) AS round, CAST(sample AS INTEGER) AS sample, key,
CAST({ku(str(SEED), "'iid'", 't.round', 'sample', 'key')} % {WORKERS} AS INTEGER) AS worker FROM s, (SELECT unnest(range(1, 3)) AS round) t"""
)
def assign_swor_iid(spark, d):
    return _assigned(S.swor_iid(balances(spark, d), WORKERS, 2, SEED))


@query(
    f"""WITH {NUMBERED}, c AS (SELECT sample, count(*) AS k FROM s GROUP BY sample), p AS (
  SELECT t.round, c.sample, w.worker, u.slot, {ku(str(SEED), "'swr'", 't.round', 'c.sample', 'w.worker', 'u.slot')} % k AS idx
  FROM c, (SELECT unnest(range(1, 3)) AS round) t, (SELECT unnest(range({WORKERS})) AS worker) w, (SELECT unnest(range(100000)) AS slot) u
  WHERE u.slot < k // {WORKERS}
) SELECT CAST(p.round AS INTEGER) AS round, CAST(p.sample AS INTEGER) AS sample, n.key, CAST(p.worker AS INTEGER) AS worker, CAST(p.slot AS BIGINT) AS slot
FROM p JOIN n ON n.sample = p.sample AND n.idx = p.idx"""
)
def assign_prop_swr(spark, d):
    s = numbered_balances(spark, d)
    return _assigned(S.prop_swr(s, sizes(s), WORKERS, 2, SEED), "slot")


@query(
    f"""WITH {NUMBERED} SELECT CAST(t.round AS INTEGER) AS round, CAST(sample AS INTEGER) AS sample, key,
CAST((idx + (idx // {WORKERS}) * t.round) % {WORKERS} AS INTEGER) AS worker FROM n, (SELECT unnest(range(1, 4)) AS round) t"""
)
def assign_stride(spark, d):
    return _assigned(S.stride(numbered_balances(spark, d), WORKERS, 3))


@query(
    f"""WITH {TWO} SELECT 1 AS round, CAST(sample AS INTEGER) AS sample, key,
CAST({ku(str(SEED), "'static'", 'sample', 'key')} % {WORKERS} AS INTEGER) AS worker FROM s"""
)
def assign_static(spark, d):
    return _assigned(S.static(balances(spark, d), WORKERS, SEED))


@query(f"WITH {TWO} SELECT {WORKERS} AS workers, count(*) AS rows, true AS even FROM s")
def assign_round_robin(spark, d):
    """The engine's own size-preserving shuffle: parts differ by one row per input task at most."""
    s = balances(spark, d)
    tasks = s.rdd.getNumPartitions()
    parts = s.repartition(WORKERS).groupBy(F.spark_partition_id().alias("worker")).agg(F.count("*").alias("rows"))
    even = (F.max("rows") - F.min("rows") <= tasks).alias("even")
    return parts.agg(F.count("*").cast("int").alias("workers"), F.sum("rows").alias("rows"), even)


@query(
    f"""WITH {TWO}, {ranked_sql('s', WORKERS, 3)}, q AS (SELECT round, worker, sample, count(*) AS k FROM w GROUP BY 1, 2, 3),
m AS (SELECT round, CAST(sum(CASE WHEN was <> worker THEN 1 ELSE 0 END) AS BIGINT) AS moved_rows
      FROM (SELECT *, lag(worker) OVER (PARTITION BY sample, key ORDER BY round) AS was FROM w) GROUP BY 1)
SELECT CAST(q.round AS INTEGER) AS round, min(k) FILTER (sample = 0) AS least_0, max(k) FILTER (sample = 0) AS most_0,
       min(k) FILTER (sample = 1) AS least_1, max(k) FILTER (sample = 1) AS most_1, CAST(0 AS BIGINT) AS empty_parts, any_value(m.moved_rows) AS moved_rows
FROM q JOIN m ON m.round = q.round GROUP BY 1"""
)
def assignment_stats(spark, d):
    r = S.assignment_stats(S.hash_rank(balances(spark, d), WORKERS, 3, SEED), WORKERS)
    return r.withColumn("round", F.col("round").cast("int"))


@query(f"WITH {NUMBERED} SELECT CAST(sample AS INTEGER) AS sample, key, CAST(idx AS BIGINT) AS idx FROM n")
def number_rows_dense(spark, d):
    return number_rows(balances(spark, d)).select("sample", "key", "idx")
