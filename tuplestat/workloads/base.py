"""Registration of queries, and the SQL that their oracles share."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.samples import number_rows, two_sample
from ..sources.catalog import load

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}

SEED, WORKERS, ROUNDS, BATCH = 7, 10, 4, 50


def query(sql: str | None = None):
    """Register a function under its name, with SQL where the result can be had from SQL."""

    def keep(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            ORACLES[f.__name__] = sql
        return f

    return keep


def ku(*parts: str) -> str:
    """SQL of functions.keyed.keyed_u64."""
    return f"CAST(concat('0x', substr(md5(concat_ws('|', {', '.join(parts)})), 1, 15)) AS BIGINT)"


# Customers' balances against suppliers': two separate samples, 15 to 1.
TWO = """s AS (
  SELECT 0 AS sample, CAST(c_custkey AS VARCHAR) AS key, c_acctbal AS score FROM customer WHERE c_acctbal IS NOT NULL
  UNION ALL SELECT 1, CAST(s_suppkey AS VARCHAR), s_acctbal FROM supplier WHERE s_acctbal IS NOT NULL
)"""
#: The same with dense row numbers in key order.
NUMBERED = TWO + """, n AS (
  SELECT *, row_number() OVER (PARTITION BY sample ORDER BY key) - 1 AS idx FROM s
)"""


def ranked_sql(source: str, workers: int, rounds: int, keys: str = "t.round, s.sample", seed: int = SEED) -> str:
    """CTEs a (ranks) and w (worker, slot) of the hash-rank scheme over `source`."""
    return f"""a AS (
  SELECT t.round, s.*, row_number() OVER (PARTITION BY {keys} ORDER BY {ku(str(seed), 't.round', 's.sample', 's.key')}, s.sample, s.key) - 1 AS rk
  FROM {source} s, (SELECT unnest(range(1, {rounds + 1})) AS round) t
), w AS (SELECT *, rk % {workers} AS worker, rk // {workers} AS slot FROM a)"""


def seeded_sql(workers: int, rounds: int, seed: int = SEED) -> str:
    """CTEs c (sizes), y (places) and w (worker, slot) of the seeded permutation, hashed by md5, over the
    numbered rows n. Layer j pairs x with k - x modulo m and swaps by a bit of the larger one's hash."""
    k = f"({ku(str(seed), 'r', 'sample', 'j')} % m)"
    partner = f"(({k} + m - x) % m)"
    layer = f"CASE WHEN {ku(str(seed + 1), 'r', 'sample', 'j', f'greatest(x, {partner})')} % 2 = 1 THEN {partner} ELSE x END"
    return f"""c AS (SELECT sample, count(*) AS m FROM n GROUP BY sample), y AS (
  SELECT r AS round, n.*, list_reduce(list_prepend(CAST(idx AS BIGINT), range(1, CAST(greatest(24, 2 * ceil(log2(m))) AS BIGINT) + 1)), lambda x, j: {layer}) AS rk
  FROM n JOIN c USING (sample), (SELECT unnest(range(1, {rounds + 1})) AS r) t
), w AS (SELECT *, rk % {workers} AS worker, rk // {workers} AS slot FROM y)"""


#: Local strict AUC per (round, worker) of CTE w, empty workers as zero.
LOCAL_AUC = """l AS (
  SELECT x.round, x.worker, count(*) AS tuples, sum(CASE WHEN z.score < x.score THEN 1 ELSE 0 END) AS total
  FROM w x JOIN w z ON x.round = z.round AND x.worker = z.worker AND x.sample = 0 AND z.sample = 1
  GROUP BY 1, 2
), g AS (
  SELECT t.round, k.worker, CAST(coalesce(l.tuples, 0) AS BIGINT) AS tuples, CAST(coalesce(l.total, 0) AS BIGINT) AS wins,
         coalesce(l.total / l.tuples, 0) AS value
  FROM (SELECT unnest(range(1, {rounds} + 1)) AS round) t CROSS JOIN (SELECT unnest(range({workers})) AS worker) k
  LEFT JOIN l ON l.round = t.round AND l.worker = k.worker
)"""
COMBINED = """SELECT CAST(max(workers) AS BIGINT) AS workers, count(*) AS rounds, CAST(sum(tuples) AS BIGINT) AS tuples,
       round(avg(value), 9) AS estimate
FROM (SELECT round, count(*) AS workers, sum(tuples) AS tuples, avg(value) AS value FROM {source} GROUP BY round)"""


def balances(spark: SparkSession, sf_dir: str) -> DataFrame:
    return two_sample(
        load(spark, sf_dir, "customer"), load(spark, sf_dir, "supplier"), "c_custkey", "c_acctbal", "s_suppkey", "s_acctbal"
    )


def numbered_balances(spark: SparkSession, sf_dir: str) -> DataFrame:
    return number_rows(balances(spark, sf_dir))


def rounded(df: DataFrame, digits: int = 9, *names: str) -> DataFrame:
    for n in names:
        df = df.withColumn(n, F.round(n, digits))
    return df


def local_rows(local: DataFrame) -> DataFrame:
    """round, worker, tuples, wins, value of within-worker estimates of an indicator kernel."""
    return local.select("round", "worker", "tuples", F.col("total").cast("long").alias("wins"), F.round("value", 9).alias("value"))
