"""The experiments as workloads over the given tables."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import estimators as E
from ..operators import kernels as K
from ..operators import schemes as S
from ..operators import sorted_forms as Q
from ..operators.concordance import concordance_counts
from ..operators.samples import number_rows, sizes
from ..plans import montecarlo as MC
from ..plans import variance as V
from ..sources.catalog import load
from .base import SEED, WORKERS, balances, query, ranked_sql, rounded
from .kernel_queries import CONCORDANCE

#: Lines as the two-point law: informative pairs are rare. The modulus suits every table size.
LINES = """s AS (
  SELECT CASE l_returnflag WHEN 'R' THEN 0 ELSE 1 END AS sample,
         concat_ws('|', l_orderkey, l_linenumber, l_partkey, l_suppkey, CAST(round(l_extendedprice * 100) AS BIGINT)) AS key,
         CASE WHEN l_returnflag = 'R' THEN CASE WHEN l_partkey % 200 < 20 THEN 0.0 ELSE 2.0 END ELSE CASE WHEN l_partkey % 200 < 20 THEN 1.0 ELSE -1.0 END END AS score
  FROM lineitem WHERE l_returnflag IN ('R', 'A')
)"""


def hard_lines(spark, d, eps: float = 0.1):
    li = load(spark, d, "lineitem").where("l_returnflag IN ('R', 'A')")
    low = F.col("l_partkey") % 200 < int(round(200 * eps))
    x = F.when(low, 0.0).otherwise(2.0)
    z = F.when(low, 1.0).otherwise(-1.0)
    key = F.concat_ws("|", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", F.round(F.col("l_extendedprice") * 100).cast("long"))
    first = F.col("l_returnflag") == "R"
    return li.select((~first).cast("int").alias("sample"), key.alias("key"), F.when(first, x).otherwise(z).alias("score"))


@query(
    f"""WITH {LINES}, {ranked_sql('s', WORKERS, 2)}, c AS (SELECT round, worker, sample, score, count(*) AS k FROM w GROUP BY 1, 2, 3, 4)
SELECT CAST(x.round AS INTEGER) AS round, CAST(x.worker AS INTEGER) AS worker, CAST(sum(x.k * z.k) AS BIGINT) AS tuples,
CAST(sum(CASE WHEN z.score < x.score THEN x.k * z.k ELSE 0 END) AS BIGINT) AS wins, round(sum(CASE WHEN z.score < x.score THEN x.k * z.k ELSE 0 END) / sum(x.k * z.k), 9) AS value
FROM c x JOIN c z ON x.round = z.round AND x.worker = z.worker AND x.sample = 0 AND z.sample = 1 GROUP BY 1, 2"""
)
def w2_hard_lines(spark, d):
    """The repartitioned statistic of the rare-pair law on all lines."""
    a = S.hash_rank(hard_lines(spark, d), WORKERS, 2, SEED)
    r = Q.auc_by_worker(a)
    return r.select("round", "worker", "tuples", F.col("total").cast("long").alias("wins"), F.round("value", 9).alias("value"))


PRICES = """s AS (
  SELECT CASE l_returnflag WHEN 'R' THEN 0 ELSE 1 END AS sample,
         concat_ws('|', l_orderkey, l_linenumber, l_partkey, l_suppkey, CAST(round(l_extendedprice * 100) AS BIGINT)) AS key, l_extendedprice AS score
  FROM lineitem WHERE l_returnflag IN ('R', 'A')
)"""


def priced_lines(spark, d):
    """Price of returned (first) and accepted lines."""
    key = F.concat_ws("|", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", F.round(F.col("l_extendedprice") * 100).cast("long"))
    li = load(spark, d, "lineitem").where("l_returnflag IN ('R', 'A')")
    return li.select((F.col("l_returnflag") != "R").cast("int").alias("sample"), key.alias("key"), F.col("l_extendedprice").alias("score"))


@query(
    f"""WITH {PRICES}, {ranked_sql('s', 100, 4)}, c AS (SELECT round, worker, score, count(*) FILTER (sample = 0) AS pos, count(*) FILTER (sample = 1) AS neg FROM w GROUP BY 1, 2, 3),
b AS (SELECT *, coalesce(sum(neg) OVER (PARTITION BY round, worker ORDER BY score ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS below FROM c)
SELECT CAST(round AS INTEGER) AS round, CAST(worker AS INTEGER) AS worker, CAST(sum(pos) * sum(neg) AS BIGINT) AS tuples, CAST(sum(pos * below) AS BIGINT) AS wins,
round(sum(pos * below) / (CAST(sum(pos) AS DOUBLE) * sum(neg)), 9) AS value FROM b GROUP BY 1, 2"""
)
def lines_repartitioned(spark, d):
    """A hundred workers, four rounds, all lines, without pairs."""
    r = Q.auc_by_worker(S.hash_rank(priced_lines(spark, d), 100, 4, SEED))
    return r.select("round", "worker", "tuples", F.col("total").cast("long").alias("wins"), F.round("value", 9).alias("value"))


@query(
    f"""WITH {PRICES}, k AS (SELECT sample, count(*) AS n FROM s GROUP BY sample), w AS (SELECT unnest(range(100)) AS worker),
p AS (SELECT worker, max(n // 100 + CASE WHEN worker < n % 100 THEN 1 ELSE 0 END) FILTER (sample = 0) AS a, max(n // 100 + CASE WHEN worker < n % 100 THEN 1 ELSE 0 END) FILTER (sample = 1) AS b FROM k, w GROUP BY worker)
SELECT CAST(t AS INTEGER) AS round, CAST(worker AS INTEGER) AS worker, CAST(a * b AS BIGINT) AS tuples, true AS plausible FROM p, (SELECT unnest(range(1, 5)) AS t)"""
)
def lines_seeded(spark, d):
    """The default path on all lines: the fast hash's permutation, no sort of a sample. Its values follow
    the law only (plausible: within six standard errors of one half), its parts are exact."""
    s = number_rows(priced_lines(spark, d))
    local = E.repartitioned_u(s, K.auc(), 100, 4, SEED, sizes=sizes(s))
    error = F.sqrt(F.lit(1 / 12) * (F.lit(2.0) / F.sqrt(F.col("tuples").cast("double"))))
    return local.select("round", "worker", "tuples", (F.abs(F.col("value") - 0.5) < 6 * error).alias("plausible"))


@query()
def lines_drawn(spark, d):
    """A hundred workers, sixteen rounds, a hundred drawn pairs each, by inverse permutation."""
    s = number_rows(priced_lines(spark, d))
    local = E.local_incomplete_by_inverse(s, K.auc(), 100, 16, 100, SEED, sizes(s))
    return E.combine(local)


@query()
def w2_lines_relative_variance(spark, d, runs: int = 300):
    """Shuffles of one keyed draw of 5,000 and 50 lines: excess variance falls as 1/T."""
    from ..functions.keyed import sample_rows

    s = hard_lines(spark, d, 0.05)
    part = sample_rows(s.where("sample = 0"), F.col("key"), 5000, SEED).unionByName(sample_rows(s.where("sample = 1"), F.col("key"), 50, SEED))
    c = V.auc_components(part, F.col("score"), F.col("sample") == 0).first()
    out = None
    for t in (1, 2, 4):
        r = MC.table_runs(part, runs, 10, t, 100, "prop_swor", SEED).where("estimator = 'repartitioned'")
        one = MC.mc_summary(r, ("estimator",)).select(F.lit(t).alias("rounds"), "runs", "mean", "variance", F.lit(V.conditional_variance(c.v0, c.n, c.m, 10, t)).alias("exact"))
        out = one if out is None else out.unionByName(one)
    return out


@query(
    """WITH x AS (SELECT c_acctbal - (SELECT avg(c_acctbal) FROM customer) AS v FROM customer), z AS (SELECT s_acctbal - (SELECT avg(s_acctbal) FROM supplier) AS v FROM supplier)
SELECT count(*) AS tuples, round(avg(x.v / 1000 * z.v / 1000), 6) AS estimate FROM x, z"""
)
def w4_degenerate(spark, d):
    s = balances(spark, d)
    c = s.join(F.broadcast(s.groupBy("sample").agg(F.avg("score").alias("_m"))), "sample").withColumn("score", (F.col("score") - F.col("_m")) / 1000)
    r = E.complete_sorted(c.drop("_m"), K.PRODUCT).select("tuples", "estimate")
    return r.select("tuples", (F.round("estimate", 6) + 0.0).alias("estimate"))


@query(
    """WITH c AS (SELECT l_extendedprice AS v, count(*) FILTER (l_quantity = 50 AND l_discount = 0.1) AS pos, count(*) FILTER (NOT (l_quantity = 50 AND l_discount = 0.1)) AS neg FROM lineitem GROUP BY 1),
b AS (SELECT *, coalesce(sum(neg) OVER (ORDER BY v ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS below FROM c)
SELECT CAST(sum(pos) AS BIGINT) AS n, CAST(sum(neg) AS BIGINT) AS m, CAST(sum(pos * below) AS BIGINT) AS wins FROM b"""
)
def w5_imbalance(spark, d):
    """A tenth of a percent of the lines against the rest."""
    rare = (F.col("l_quantity") == 50) & (F.col("l_discount") == 0.1)
    return Q.auc_counts(load(spark, d, "lineitem"), F.col("l_extendedprice"), rare).select("n", "m", "wins")


@query(
    """SELECT count(*) AS n, round(sum((2 * r - n - 1) * v) / (n * (n - 1) / 2.0), 6) AS estimate
FROM (SELECT value AS v, row_number() OVER (ORDER BY value) AS r, count(*) OVER () AS n FROM events WHERE value IS NOT NULL) GROUP BY n"""
)
def w6_mean_difference(spark, d):
    r = Q.mean_absolute_difference(load(spark, d, "events").where("value IS NOT NULL"), F.col("value"))
    return rounded(r.select("n", "estimate"), 6, "estimate")


@query(CONCORDANCE)
def w6_concordance(spark, d):
    """Quantity against price over all lines: half the untied pairs, as they are independent."""
    return rounded(concordance_counts(load(spark, d, "lineitem"), "l_quantity", "l_extendedprice"), 9, "estimate")


def _chain_sql(k: int) -> str:
    """Chains that end in each class, class after class, from prefix sums over the scores."""
    out = "c1 AS (SELECT *, n1 AS e1 FROM c)"
    for i in range(2, k + 1):
        out += f""", c{i} AS (SELECT *, n{i} * coalesce(sum(e{i - 1}) OVER (ORDER BY v ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS e{i} FROM c{i - 1})"""
    return out


COUNTS5 = ", ".join(f"CAST(count(*) FILTER (substr(o_orderpriority, 1, 1) = '{i}') AS DOUBLE) AS n{i}" for i in range(1, 6))


@query(
    f"""WITH c AS (SELECT o_totalprice AS v, {COUNTS5} FROM orders GROUP BY 1), {_chain_sql(5)}
SELECT {" * ".join(f"sum(n{i})" for i in range(1, 6))} AS tuples, sum(e5) AS chains, round(sum(e5) / ({" * ".join(f"sum(n{i})" for i in range(1, 6))}), 12) AS estimate FROM c5"""
)
def w7_multipartite(spark, d):
    """Five ordered classes, all orders: near 1/120."""
    r = Q.vus_counts(load(spark, d, "orders"), F.col("o_totalprice"), F.substring("o_orderpriority", 1, 1), 5)
    return rounded(r.select("tuples", "chains", "estimate"), 12, "estimate")


@query(
    f"""WITH s AS (SELECT 0 AS sample, CAST(c_custkey AS VARCHAR) AS key, c_acctbal AS score, c_nationkey AS nation FROM customer UNION ALL SELECT 1, CAST(s_suppkey AS VARCHAR), s_acctbal, s_nationkey FROM supplier),
l AS (SELECT x.nation % 5 AS worker, avg(CASE WHEN z.score < x.score THEN 1.0 ELSE 0.0 END) AS value, count(*) AS tuples FROM s x JOIN s z ON x.nation % 5 = z.nation % 5 AND x.sample = 0 AND z.sample = 1 GROUP BY 1)
SELECT CAST(worker AS INTEGER) AS worker, tuples, round(value, 9) AS value FROM l"""
)
def w10_stored_by_nation(spark, d):
    """Rows left where a table stored by nation has them: the static placement."""
    c, s = load(spark, d, "customer"), load(spark, d, "supplier")
    rows = c.select(F.lit(0).alias("sample"), F.col("c_custkey").cast("string").alias("key"), F.col("c_acctbal").alias("score"), F.col("c_nationkey").alias("nation")).unionByName(
        s.select(F.lit(1).alias("sample"), F.col("s_suppkey").cast("string").alias("key"), F.col("s_acctbal").alias("score"), F.col("s_nationkey").alias("nation"))
    )
    a = S.static(rows, 5, SEED, by=F.col("nation"))
    r = E.local_estimates(a, K.auc(), 5, 1)
    return r.select("worker", "tuples", F.round("value", 9).alias("value"))
