"""Scalar functions, UDFs, table functions, and the batch and stream forms of windows."""

from __future__ import annotations

import math

import pyarrow as pa
from pyspark.sql import functions as F

from ..functions import scalar
from ..functions import sqlfns as Q
from ..functions.keyed import keyed_u64, permute, unpermute
from ..operators import schemes as S
from ..operators.samples import number_rows, sizes
from ..sources.catalog import load, stream_table
from ..streaming import windows as W
from .base import SEED, TWO, WORKERS, balances, ku, local_rows, query, ranked_sql, rounded


@query(
    """SELECT o_orderkey, round(abs(o_totalprice - 150000), 2) AS away, CAST(sign(o_totalprice - 150000) AS INTEGER) AS side, round(ln(1 + o_totalprice), 9) AS log,
round(sqrt(o_totalprice), 9) AS root, CAST(o_orderkey % 7 AS BIGINT) AS m, CAST(floor(o_totalprice / 1000) AS BIGINT) AS thousands,
CAST(o_orderkey::HUGEINT * (o_orderkey - 1) // 2 AS BIGINT) AS pairs, CAST(o_orderkey::HUGEINT * (o_orderkey - 1) * (o_orderkey - 2) // 6 AS BIGINT) AS triples FROM orders"""
)
def fn_math(spark, d):
    """Pairs and triples are longs like in SQL; keys whose triples pass 64 bits (from 3.8 million on) make them
    decimal(38,0), where the SQL ends in an error."""
    p, o = F.col("o_totalprice"), load(spark, d, "orders")
    top = o.agg(F.max(F.abs("o_orderkey")).alias("k")).first().k or 0
    return o.select(
        "o_orderkey",
        F.round(F.abs(p - 150000), 2).alias("away"),
        F.signum(p - 150000).cast("int").alias("side"),
        F.round(F.log1p(p), 9).alias("log"),
        F.round(F.sqrt(p), 9).alias("root"),
        F.pmod("o_orderkey", F.lit(7)).cast("long").alias("m"),
        F.floor(p / 1000).alias("thousands"),
        *[
            scalar.binomial(F.col("o_orderkey"), k).cast(scalar.whole_type(math.comb(top + k, k))).alias(name)
            for k, name in ((2, "pairs"), (3, "triples"))
        ],
    )


@query(
    r"""WITH t AS (SELECT doc_id, text AS t, [w for w in regexp_split_to_array(text, '[ \t\n\x0B\f\r]+') if w <> ''] AS w, string_split(text, chr(10)) AS l FROM documents)
SELECT doc_id, round(ln(1 + length(t)), 8) AS f0, round(len(list_distinct(w)) / greatest(len(w), 1)::DOUBLE, 8) AS f1,
round(length(regexp_replace(t, '[^!-/:-@\[-`{-~]', '', 'g')) / greatest(length(t), 1)::DOUBLE, 8) AS f2, round(length(regexp_replace(t, '[^0-9]', '', 'g')) / greatest(length(t), 1)::DOUBLE, 8) AS f3,
round(coalesce(list_sum([length(x) for x in w]), 0) / greatest(len(w), 1)::DOUBLE, 8) AS f4, round(ln(1 + len(l)), 8) AS f5,
round(length(regexp_replace(t, '[^A-Z]', '', 'g')) / greatest(length(t), 1)::DOUBLE, 8) AS f6, round(ln(1 + coalesce(list_max([length(x) for x in w]), 0)), 8) AS f7,
round(1 - len(list_distinct(l)) / len(l)::DOUBLE, 8) AS f8 FROM t"""
)
def fn_doc_features(spark, d):
    f = scalar.doc_features(F.col("text"))
    t = load(spark, d, "documents").select("doc_id", f.alias("f"))
    return t.select("doc_id", *[F.round(F.get("f", F.lit(k)), 8).alias(f"f{k}") for k in range(9)])


@query(
    """SELECT o_orderkey, CAST(year(o_orderdate) AS INTEGER) AS y, CAST(CAST(date_trunc('month', o_orderdate) AS DATE) AS VARCHAR) AS month, CAST(date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS INTEGER) AS days FROM orders"""
)
def fn_dates(spark, d):
    o = F.col("o_orderdate")
    return load(spark, d, "orders").select(
        "o_orderkey",
        F.year(o).alias("y"),
        F.to_date(F.date_trunc("month", o)).cast("string").alias("month"),
        scalar.day_gap(F.to_date(o), F.lit("1992-01-01").cast("date")).alias("days"),
    )


@query(
    """SELECT vec_id, round(sqrt(list_sum([CAST(x AS DOUBLE) * x for x in embedding])), 6) AS norm, round(list_sum([CAST(p[1] AS DOUBLE) * p[2] for p in list_zip(embedding, list_reverse(embedding))]), 7) AS mirrored,
len(embedding) AS width, round(2 * CAST(embedding[1] AS DOUBLE) + embedding[64], 7) AS combined FROM embeddings"""
)
def fn_vectors(spark, d):
    e = F.col("embedding")
    return load(spark, d, "embeddings").select(
        "vec_id",
        F.round(scalar.norm2(e), 6).alias("norm"),
        F.round(scalar.dot(e, F.reverse(e)), 7).alias("mirrored"),
        F.size(e).cast("long").alias("width"),
        F.round(F.get(scalar.axpy(2.0, e, F.reverse(e)), F.lit(0)), 7).alias("combined"),
    )


@query("SELECT event_id, CAST(props->>'$.k' AS DOUBLE) AS k, round(CAST(props->>'$.k' AS DOUBLE) + value, 6) AS total FROM events")
def fn_json_map(spark, d):
    k = scalar.json_number(F.col("props"), "$.k")
    m = scalar.metrics_map({"k": k, "value": F.col("value")})
    e = load(spark, d, "events").select("event_id", m.alias("m"))
    return e.select("event_id", F.col("m")["k"].alias("k"), F.round(F.col("m")["k"] + F.col("m")["value"], 6).alias("total"))


@query(f"SELECT c_custkey, {ku('7', '3', 'c_custkey')} AS h FROM customer")
def fn_keyed_hash(spark, d):
    return load(spark, d, "customer").select("c_custkey", keyed_u64(7, 3, F.col("c_custkey")).alias("h"))


@query(
    f"""SELECT c_custkey, round(greatest(0, 1 + c_acctbal / 1000 - 5), 9) AS hinge, CASE WHEN 5000 < c_acctbal THEN 1 ELSE 0 END AS win,
CAST({ku('7', '2', 'c_custkey')} % 10 AS INTEGER) AS worker FROM customer"""
)
def sql_udf_surface(spark, d):
    Q.register_all(spark)
    load(spark, d, "customer").createOrReplaceTempView("tuplestat_customer")
    return spark.sql(
        "SELECT c_custkey, round(hinge_pair(c_acctbal / 1000, 5D), 9) AS hinge, auc_pair(c_acctbal, 5000D) AS win, "
        "keyed_worker(7, 2, cast(c_custkey AS STRING), 10) AS worker FROM tuplestat_customer"
    )


@query("SELECT count(*) AS n, count(*) AS places, CAST(0 AS BIGINT) AS least, count(*) - 1 AS most, count(*) AS undone FROM customer WHERE c_acctbal IS NOT NULL")
def fn_permute(spark, d):
    """The keyed permutation of the customers' row numbers is a bijection, and its inverse undoes it."""
    s = number_rows(balances(spark, d).where("sample = 0"))
    n = sizes(s).get(0, 0)
    p = s.select(F.col("idx").alias("id"), permute(F.col("idx"), n, SEED, 1, 0).alias("p"))
    u = p.withColumn("u", unpermute(F.col("p"), n, SEED, 1, 0))
    return u.agg(
        F.count("*").alias("n"), F.countDistinct("p").alias("places"), F.min("p").alias("least"), F.max("p").alias("most"),
        F.sum((F.col("u") == F.col("id")).cast("long")).alias("undone"),
    )


@query()
def udf_permute(spark, d):
    return spark.range(1000).select("id", permute(F.col("id"), 1000, SEED, 1, 0).alias("place"))


@query(
    """WITH r AS (SELECT c_nationkey, c_acctbal AS s, c_mktsegment = 'BUILDING' AS y FROM customer WHERE c_acctbal IS NOT NULL)
SELECT x.c_nationkey, round(avg(CASE WHEN z.s < x.s THEN 1.0 ELSE 0.0 END), 9) AS auc FROM r x JOIN r z ON x.c_nationkey = z.c_nationkey AND x.y AND NOT z.y GROUP BY 1"""
)
def udaf_auc(spark, d):
    """A Pandas aggregate, for groups that fit a task; `auc_grouped` has no such bound."""
    r = load(spark, d, "customer").where("c_acctbal IS NOT NULL")
    y = (F.col("c_mktsegment") == "BUILDING").cast("int")
    return rounded(r.groupBy("c_nationkey").agg(Q.auc_agg(F.col("c_acctbal"), y).alias("auc")), 9, "auc")


@query(
    """WITH o AS (SELECT c_custkey AS k, c_nationkey AS p, round(c_acctbal) AS v, CAST(c_custkey AS DOUBLE) AS c, c_custkey % 3 + 1 AS y FROM customer WHERE c_acctbal IS NOT NULL),
g AS (SELECT a.p, avg(abs(a.v - b.v)) AS gini, avg(CASE WHEN (a.v - b.v) * (a.c - b.c) > 0 THEN 1.0 ELSE 0.0 END) AS tau FROM o a JOIN o b ON a.p = b.p AND a.k < b.k GROUP BY 1),
v AS (SELECT a.p, avg(CASE WHEN a.v < b.v AND b.v < c.v THEN 1.0 ELSE 0.0 END) AS vus FROM o a JOIN o b ON a.p = b.p AND a.y = 1 AND b.y = 2 JOIN o c ON c.p = a.p AND c.y = 3 GROUP BY 1)
SELECT g.p AS nation, round(gini, 5) AS gini, round(tau, 9) AS concordance, round(vus, 9) AS vus FROM g JOIN v ON g.p = v.p"""
)
def udaf_family(spark, d):
    c = load(spark, d, "customer").where("c_acctbal IS NOT NULL")
    v = F.round("c_acctbal")
    y = (F.pmod("c_custkey", F.lit(3)) + 1).cast("int")
    g = c.groupBy(F.col("c_nationkey").alias("nation")).agg(
        Q.gini_agg(v).alias("gini"), Q.kendall_agg(v, F.col("c_custkey").cast("double")).alias("concordance"), Q.vus3_agg(v, y).alias("vus")
    )
    return rounded(rounded(g, 5, "gini"), 9, "concordance", "vus")


@query(f"SELECT CAST(b AS BIGINT) AS draw, {ku('7', chr(39) + 'pair' + chr(39), '0', 'b')} % 1500 AS i, {ku('7', chr(39) + 'pair' + chr(39), '1', 'b')} % 100 AS j FROM (SELECT unnest(range(300)) AS b)")
def udtf_pair_draws(spark, d):
    return Q.PairDraws(F.lit(1500), F.lit(100), F.lit(300), F.lit(7))


@query(
    f"""SELECT CAST(t AS INTEGER) AS round, CAST(i AS BIGINT) AS idx, CAST((i + {ku('7', chr(39) + 'stride' + chr(39), 't')} % 4 + (i // 4) * t) % 4 AS INTEGER) AS worker
FROM (SELECT unnest(range(1, 4)) AS t), (SELECT unnest(range(50)) AS i)"""
)
def udtf_assign_rounds(spark, d):
    Q.register_all(spark)
    return spark.sql("SELECT * FROM assign_rounds(50, 4, 3, 7)")


LOCAL = f"""WITH {TWO}, {ranked_sql('s', WORKERS, 2)}
SELECT CAST(x.round AS INTEGER) AS round, CAST(x.worker AS INTEGER) AS worker, count(*) AS tuples, CAST(sum(CASE WHEN z.score < x.score THEN 1 ELSE 0 END) AS BIGINT) AS wins,
round(avg(CASE WHEN z.score < x.score THEN 1.0 ELSE 0.0 END), 9) AS value FROM w x JOIN w z ON x.round = z.round AND x.worker = z.worker AND x.sample = 0 AND z.sample = 1 GROUP BY 1, 2"""
OUT = "round int, worker int, tuples long, total double, value double"


def _block(rnd, worker, x, z):
    import numpy as np

    n, wins = len(x) * len(z), int(np.searchsorted(np.sort(z), x, side="left").sum())
    return pa.table(
        {"round": pa.array([rnd], pa.int32()), "worker": pa.array([worker], pa.int32()), "tuples": [n], "total": [float(wins)], "value": [wins / n if n else 0.0]}
    )


@query(LOCAL)
def grouped_map_u(spark, d):
    """A kernel without a Column form: one Arrow call per (round, worker)."""

    def run(table: pa.Table) -> pa.Table:
        s, v = table.column("sample").to_numpy(), table.column("score").to_numpy()
        return _block(table.column("round")[0].as_py(), table.column("worker")[0].as_py(), v[s == 0], v[s == 1])

    a = S.hash_rank(balances(spark, d), WORKERS, 2, SEED).select("round", "worker", "sample", "score")
    return local_rows(a.groupBy("round", "worker").applyInArrow(run, OUT))


@query(LOCAL)
def cogroup_u(spark, d):
    """The two samples meet in cogroups; no pair exists outside NumPy."""

    def run(key, x: pa.Table, z: pa.Table) -> pa.Table:
        both = [t.column("score").to_numpy() if t.num_rows else [] for t in (x, z)]
        return _block(key[0].as_py(), key[1].as_py(), *both)

    a = S.hash_rank(balances(spark, d), WORKERS, 2, SEED).select("round", "worker", "sample", "score")
    # The sides come from one frame: the second one's columns get identities of their own.
    z = a.where("sample = 1").select(*[(F.col(c) + 0).alias(c) for c in ("round", "worker", "score")]).groupBy("round", "worker")
    x = a.where("sample = 0").select("round", "worker", "score").groupBy("round", "worker")
    return local_rows(x.cogroup(z).applyInArrow(run, OUT))


# ------------------------------------------------------------------ windows over time

WINDOWED = """SELECT {start} AS start, count(*) FILTER (event_type = 'error') AS n, count(*) FILTER (event_type <> 'error') AS m FROM {source} GROUP BY 1"""
TUMBLING = """WITH e AS (SELECT date_trunc('day', ts) AS start, value AS s, event_type = 'error' AS y FROM events WHERE value IS NOT NULL)
SELECT x.start, count(*) AS pairs, CAST(sum(CASE WHEN z.s < x.s THEN 1 ELSE 0 END) AS BIGINT) AS wins FROM e x JOIN e z ON x.start = z.start AND x.y AND NOT z.y GROUP BY 1"""


def _windowed(e, window, slide=None):
    counts = W.window_counts(e.where("value IS NOT NULL"), "ts", F.col("value"), F.col("event_type") == "error", window, slide)
    return _areas(counts)


def _areas(counts):
    r = W.auc_of_counts(counts)
    return r.select(F.col("start").cast("timestamp_ntz").alias("start"), (F.col("n") * F.col("m")).alias("pairs"), "wins").where("pairs > 0")


@query(TUMBLING)
def window_tumbling_auc(spark, d):
    return _windowed(load(spark, d, "events"), "1 day")


@query(
    """WITH e AS (SELECT date_trunc('day', ts) - to_days(CAST(k AS INTEGER)) AS start, value AS s, event_type = 'error' AS y FROM events, (SELECT unnest([0, 1]) AS k) WHERE value IS NOT NULL)
SELECT x.start, count(*) AS pairs, CAST(sum(CASE WHEN z.s < x.s THEN 1 ELSE 0 END) AS BIGINT) AS wins FROM e x JOIN e z ON x.start = z.start AND x.y AND NOT z.y GROUP BY 1"""
)
def window_sliding_auc(spark, d):
    return _windowed(load(spark, d, "events"), "2 days", "1 day")


@query(
    """WITH o AS (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM events),
s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS k FROM o)
SELECT user_id, min(ts) AS start, count(*) AS events FROM s GROUP BY user_id, k"""
)
def window_session_stats(spark, d):
    r = W.session_stats(load(spark, d, "events"), "user_id", "ts", "value", "6 hours")
    return r.select("user_id", F.col("start").cast("timestamp_ntz").alias("start"), "events")


@query(TUMBLING)
def stream_tumbling_auc(spark, d):
    """The same windows from a stream that is run to its end."""
    e = stream_table(spark, d, "events").where("value IS NOT NULL").withColumn("ts", F.col("ts").cast("timestamp"))
    counts = W.window_counts(e, "ts", F.col("value"), F.col("event_type") == "error", "1 day", watermark="2 days")
    return _areas(W.run_to_end(counts, "complete"))


@query()
def stream_local_auc(spark, d):
    e = stream_table(spark, d, "events").where("value IS NOT NULL").withColumn("error", F.col("event_type") == "error")
    out = W.run_to_end(W.local_auc_stream(e, "event_id", "value", "error", 4, 200, SEED), "update")
    return out.groupBy("worker").agg(*[F.max_by(c, "seen").alias(c) for c in ("pairs", "wins", "auc")], F.max("seen").alias("seen"))


@query("SELECT CAST(count(DISTINCT event_id) AS BIGINT) AS events FROM events")
def stream_dedup(spark, d):
    """Each event once within the watermark, from a stream that holds it twice. Rows go to files in the
    shared folder and the state to RocksDB: neither fits a driver's memory."""
    e = stream_table(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp")).select("event_id", "ts")
    twice = e.withColumn("copy", F.explode(F.array(F.lit(1), F.lit(2))))
    once = twice.withWatermark("ts", "40 days").dropDuplicatesWithinWatermark(["event_id"])
    return W.run_to_files(once.select("event_id")).agg(F.count("*").alias("events"))


@query(
    f"""WITH a AS (SELECT event_id, ts, ts + to_hours(CAST({ku('7', chr(39) + 'late' + chr(39), 'event_id')} % 72 AS INTEGER)) AS arrived FROM events),
o AS (SELECT *, max(ts) OVER (ORDER BY arrived, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS top FROM a)
SELECT event_id, coalesce(ts < top - INTERVAL 2 DAY, false) AS late FROM o"""
)
def stream_split_late(spark, d):
    """What a two-day watermark would drop, for keyed delays of up to three days. Arrivals are made
    distinct by the id, in microseconds."""
    h = F.pmod(keyed_u64(SEED, "late", F.col("event_id")), F.lit(72)).cast("int")
    e = load(spark, d, "events").select("event_id", "ts", (F.col("ts") + F.make_dt_interval(F.lit(0), h)).alias("arrived"))
    order = F.struct("arrived", "event_id")
    from pyspark.sql import Window

    day = Window.partitionBy("day").orderBy(order).rowsBetween(Window.unboundedPreceding, -1)
    tops = e.groupBy(F.to_date("arrived").alias("day")).agg(F.max("ts").alias("top"))
    earlier = Window.orderBy("day").rowsBetween(Window.unboundedPreceding, -1)  # one row a day
    tops = tops.withColumn("before", F.max("top").over(earlier)).drop("top")
    out = e.withColumn("day", F.to_date("arrived")).join(F.broadcast(tops), "day")
    top = F.greatest(F.max("ts").over(day), F.col("before"))
    return out.select("event_id", F.coalesce(F.col("ts") < top - F.expr("interval 2 days"), F.lit(False)).alias("late"))
