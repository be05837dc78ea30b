"""The relational surface: joins, groupings, windows, sets, sources and sinks."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.keyed import sample_fraction, sample_rows
from ..operators import estimators as E
from ..operators import kernels as K
from ..operators import relops as R
from ..operators import schemes as S
from ..operators.samples import number_rows, sizes
from ..sources import catalog, synthetic
from ..sources.catalog import load
from .base import LOCAL_AUC, NUMBERED, SEED, TWO, WORKERS, balances, ku, query, ranked_sql, rounded


def _scratch(spark, name):
    return f"{catalog.shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


@query("SELECT o_orderkey, o_totalprice FROM orders WHERE o_orderstatus = 'P' AND o_totalprice > 200000")
def scan_project_filter(spark, d):
    return load(spark, d, "orders").where("o_orderstatus = 'P' AND o_totalprice > 200000").select("o_orderkey", "o_totalprice")


@query(
    """SELECT c_custkey, CASE WHEN c_acctbal < 0 THEN 'debt' WHEN c_acctbal BETWEEN 0 AND 5000 THEN 'middle' ELSE 'rich' END AS band
FROM customer WHERE c_nationkey IN (1, 3, 5, 7) AND c_mktsegment LIKE '%U%' AND c_acctbal IS DISTINCT FROM NULL"""
)
def filter_predicates(spark, d):
    b = F.col("c_acctbal")
    band = F.when(b < 0, "debt").when(b.between(0, 5000), "middle").otherwise("rich")
    keep = F.col("c_nationkey").isin(1, 3, 5, 7) & F.col("c_mktsegment").like("%U%") & ~b.eqNullSafe(F.lit(None))
    return load(spark, d, "customer").where(keep).select("c_custkey", band.alias("band"))


BY_NATION = """SELECT n_name, count(*) AS customers, CAST(round(sum(c_acctbal) * 100) AS BIGINT) AS cents
FROM customer JOIN nation ON n_nationkey = c_nationkey GROUP BY n_name"""


def _by_nation(joined):
    return joined.groupBy("n_name").agg(F.count("*").alias("customers"), F.round(F.sum("c_acctbal") * 100).cast("long").alias("cents"))


@query(BY_NATION)
def join_broadcast(spark, d):
    c, n = load(spark, d, "customer"), load(spark, d, "nation")  # 25 rows, whatever the scale
    return _by_nation(c.join(F.broadcast(n), c.c_nationkey == n.n_nationkey))


@query(BY_NATION)
def join_sort_merge(spark, d):
    c, n = load(spark, d, "customer"), load(spark, d, "nation")
    return _by_nation(c.join(n.hint("merge"), c.c_nationkey == n.n_nationkey))


@query(BY_NATION)
def join_shuffle_hash(spark, d):
    c, n = load(spark, d, "customer"), load(spark, d, "nation")
    return _by_nation(c.join(n.hint("shuffle_hash"), c.c_nationkey == n.n_nationkey))


@query(
    """SELECT s_suppkey, count(*) AS above FROM supplier JOIN customer ON c_acctbal > s_acctbal AND c_nationkey = s_nationkey GROUP BY 1"""
)
def join_theta(spark, d):
    c, s = load(spark, d, "customer"), load(spark, d, "supplier")
    p = (F.col("c_acctbal") > F.col("s_acctbal")) & (F.col("c_nationkey") == F.col("s_nationkey"))
    return R.theta_join(s, c, p).groupBy("s_suppkey").agg(F.count("*").alias("above"))


@query("SELECT s_suppkey, c_custkey FROM supplier JOIN customer ON abs(s_acctbal - c_acctbal) < 25")
def join_range(spark, d):
    """Pairs of close balances (those that a margin keeps active), through buckets."""
    s = load(spark, d, "supplier").select("s_suppkey", "s_acctbal")
    c = load(spark, d, "customer").select("c_custkey", "c_acctbal")
    return R.range_join(s, c, "s_acctbal", "c_acctbal", 25.0).select("s_suppkey", "c_custkey")


@query(
    """SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id
AND b.ts BETWEEN a.ts - INTERVAL 1 HOUR AND a.ts + INTERVAL 2 HOUR WHERE a.event_type = 'error' AND b.event_type <> 'error'"""
)
def join_interval(spark, d):
    e = load(spark, d, "events")
    a = e.where("event_type = 'error'").select("user_id", F.col("event_id").alias("a"), F.col("ts").alias("ta"))
    b = e.where("event_type <> 'error'").select("user_id", F.col("event_id").alias("b"), F.col("ts").alias("tb"))
    return R.interval_join(a, b, ["user_id"], "ta", "tb", "1 hour", "2 hours").select("a", "b")


@query(
    """SELECT a.event_id, arg_max(b.event_id, (b.ts, b.event_id)) AS last_event FROM events a LEFT JOIN events b
ON a.user_id = b.user_id AND b.event_type = 'click' AND b.ts <= a.ts WHERE a.event_type = 'error' GROUP BY 1"""
)
def join_asof(spark, d):
    e = load(spark, d, "events")
    left = e.where("event_type = 'error'").select("user_id", "event_id", "ts")
    right = e.where("event_type = 'click'").groupBy("user_id", "ts").agg(F.max("event_id").alias("event"))
    return R.asof_join(left, right, ["user_id"], "ts", "ts", ["event"]).select("event_id", "last_event")


@query(
    """SELECT (SELECT count(*) FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)) AS labelled,
(SELECT count(*) FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)) AS unlabelled"""
)
def join_semi_anti(spark, d):
    docs, labels = load(spark, d, "documents").select("doc_id"), load(spark, d, "labels").select("doc_id")
    yes = R.keep_matching(docs, labels, ["doc_id"]).agg(F.count("*").alias("labelled"))
    no = R.drop_matching(docs, labels, ["doc_id"]).agg(F.count("*").alias("unlabelled"))
    return yes.join(F.broadcast(no))  # one row each


@query(
    f"""WITH {TWO}, w AS (SELECT 1 AS round, s.*, {ku(str(SEED), "'iid'", '1', 'sample', 'key')} % 120 AS worker FROM s), {LOCAL_AUC.format(rounds=1, workers=120)}
SELECT CAST(worker AS INTEGER) AS worker, tuples, wins, round(value, 9) AS value FROM g"""
)
def join_outer_workers(spark, d):
    """More workers than suppliers, rows thrown at random: workers without pairs are kept, as 0."""
    a = S.swor_iid(balances(spark, d), 120, 1, SEED)
    r = E.local_estimates(a, K.auc(), 120, 1)
    return r.select("worker", "tuples", F.col("total").cast("long").alias("wins"), F.round("value", 9).alias("value"))


ORDERS_AGG = "count(*) AS n, CAST(round(sum(o_totalprice) * 100) AS BIGINT) AS cents"


def _aggs():
    """Prices are added as decimals: a sum of millions of doubles is off by some cents, by a different number
    in every order of addition."""
    total = F.sum(F.col("o_totalprice").cast("decimal(28,10)"))
    return [F.count("*").alias("n"), F.round(total * 100).cast("long").alias("cents")]


@query(f"SELECT o_orderstatus, {ORDERS_AGG} FROM orders GROUP BY 1")
def agg_partial_final(spark, d):
    return R.grouped(load(spark, d, "orders"), ["o_orderstatus"], _aggs())


@query("SELECT c_nationkey, string_agg(c_custkey::VARCHAR, ',' ORDER BY c_custkey) AS keys FROM customer GROUP BY 1")
def agg_collect(spark, d):
    keys = F.transform(F.array_sort(F.collect_list("c_custkey")), lambda k: k.cast("string"))
    return load(spark, d, "customer").groupBy("c_nationkey").agg(F.array_join(keys, ",").alias("keys"))


@query("SELECT l_returnflag, count(DISTINCT l_quantity) AS quantities, count(DISTINCT l_partkey) AS parts FROM lineitem GROUP BY 1")
def agg_distinct(spark, d):
    return load(spark, d, "lineitem").groupBy("l_returnflag").agg(
        F.countDistinct("l_quantity").alias("quantities"), F.countDistinct("l_partkey").alias("parts")
    )


@query(f"SELECT o_orderstatus, o_orderpriority, {ORDERS_AGG} FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)")
def agg_cube(spark, d):
    return R.grouped(load(spark, d, "orders"), ["o_orderstatus", "o_orderpriority"], _aggs(), "cube")


@query(f"SELECT o_orderstatus, o_orderpriority, {ORDERS_AGG} FROM orders GROUP BY ROLLUP (o_orderstatus, o_orderpriority)")
def agg_rollup(spark, d):
    return R.grouped(load(spark, d, "orders"), ["o_orderstatus", "o_orderpriority"], _aggs(), "rollup")


@query(f"SELECT o_orderstatus, o_orderpriority, {ORDERS_AGG} FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())")
def agg_grouping_sets(spark, d):
    return load(spark, d, "orders").groupingSets(
        [["o_orderstatus"], ["o_orderpriority"], []], "o_orderstatus", "o_orderpriority"
    ).agg(*_aggs())


@query(
    """SELECT c_custkey, row_number() OVER w AS row_number, rank() OVER w AS rank, dense_rank() OVER w AS dense_rank, round(percent_rank() OVER w, 9) AS percent_rank,
ntile(4) OVER w AS quartile FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_acctbal, c_custkey)"""
)
def window_rank(spark, d):
    kinds = ("row_number", "rank", "dense_rank", "percent_rank", "quartile")
    r = R.ranked(load(spark, d, "customer"), ["c_nationkey"], [F.col("c_acctbal"), F.col("c_custkey")], kinds)
    return rounded(r.select("c_custkey", *kinds), 9, "percent_rank")


@query(
    """SELECT event_id, lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS previous, lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS following,
count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 3 PRECEDING AND CURRENT ROW) AS recent,
min(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 3 PRECEDING AND CURRENT ROW) AS least FROM events"""
)
def window_frames(spark, d):
    e = load(spark, d, "events")
    r = R.framed(e, ["user_id"], ["ts", "event_id"], (-3, 0), {"recent": F.count("*"), "least": F.min("event_id")})
    from pyspark.sql import Window

    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return r.select("event_id", F.lag("event_id").over(w).alias("previous"), F.lead("event_id").over(w).alias("following"), "recent", "least")


@query(
    """WITH r AS (SELECT c_custkey, c_nationkey, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) AS r FROM customer)
SELECT c_nationkey, c_custkey FROM r WHERE r <= 3"""
)
def topk_grouped(spark, d):
    c = load(spark, d, "customer").select("c_nationkey", "c_custkey", "c_acctbal")
    return R.top_k(c, [F.desc("c_acctbal"), F.col("c_custkey")], 3, ["c_nationkey"]).drop("c_acctbal")


@query(
    """WITH a AS (SELECT c_nationkey AS k FROM customer WHERE c_acctbal > 9000), b AS (SELECT s_nationkey AS k FROM supplier)
SELECT 'union' AS op, k FROM (SELECT k FROM a UNION SELECT k FROM b) UNION ALL SELECT 'intersect', k FROM (SELECT k FROM a INTERSECT SELECT k FROM b)
UNION ALL SELECT 'except', k FROM (SELECT k FROM a EXCEPT SELECT k FROM b) UNION ALL SELECT 'except_all', k FROM (SELECT k FROM a EXCEPT ALL SELECT k FROM b)"""
)
def set_ops(spark, d):
    a = load(spark, d, "customer").where("c_acctbal > 9000").select(F.col("c_nationkey").alias("k"))
    b = load(spark, d, "supplier").select(F.col("s_nationkey").alias("k"))
    named = {"union": a.union(b).distinct(), "intersect": a.intersect(b), "except": a.subtract(b), "except_all": a.exceptAll(b)}
    out = None
    for op, df in named.items():
        one = df.select(F.lit(op).alias("op"), "k")
        out = one if out is None else out.unionByName(one)
    return out


@query(
    f"""WITH {TWO}, {ranked_sql('s', WORKERS, 3)}, {LOCAL_AUC.format(rounds=3, workers=WORKERS)}
SELECT CAST(worker AS INTEGER) AS worker, CAST(max(wins) FILTER (round = 1) AS BIGINT) AS r1, CAST(max(wins) FILTER (round = 2) AS BIGINT) AS r2, CAST(max(wins) FILTER (round = 3) AS BIGINT) AS r3 FROM g GROUP BY 1"""
)
def pivot_grid(spark, d):
    local = E.local_estimates(S.hash_rank(balances(spark, d), WORKERS, 3, SEED), K.auc(), WORKERS, 3)
    wide = R.to_wide(local, ["worker"], "round", [1, 2, 3], F.max("total"))
    return wide.select("worker", *[F.col(str(k)).cast("long").alias(f"r{k}") for k in (1, 2, 3)])


@query(
    """SELECT c_custkey, 'nation' AS name, CAST(c_nationkey AS BIGINT) AS value FROM customer
UNION ALL SELECT c_custkey, 'cents', CAST(round(c_acctbal * 100) AS BIGINT) FROM customer"""
)
def unpivot_long(spark, d):
    c = load(spark, d, "customer").select(
        "c_custkey", F.col("c_nationkey").cast("long").alias("nation"), F.round(F.col("c_acctbal") * 100).cast("long").alias("cents")
    )
    return R.to_long(c, ["c_custkey"], ["nation", "cents"])


@query(
    f"""SELECT c_custkey, 'tenth' AS kind FROM customer WHERE {ku(str(SEED), "'bernoulli'", 'c_custkey')} < CAST(floor(0.1 * 1152921504606846976) AS BIGINT)
UNION ALL SELECT c_custkey, 'fixed' FROM (SELECT c_custkey, row_number() OVER (ORDER BY {ku(str(SEED), "'rows'", 'c_custkey')}, c_custkey) AS r FROM customer) WHERE r <= 25"""
)
def sample_keyed(spark, d):
    c = load(spark, d, "customer").select("c_custkey")
    tenth = sample_fraction(c, F.col("c_custkey"), 0.1, SEED).withColumn("kind", F.lit("tenth"))
    return tenth.unionByName(sample_rows(c, F.col("c_custkey"), 25, SEED).withColumn("kind", F.lit("fixed")))


# ------------------------------------------------------------------ sources and sinks

CUSTOMERS = "SELECT c_custkey, c_nationkey, c_acctbal, c_mktsegment FROM customer"


def _customers(spark, d):
    return load(spark, d, "customer").select("c_custkey", "c_nationkey", "c_acctbal", "c_mktsegment")


@query(CUSTOMERS)
def source_csv_roundtrip(spark, d):
    c = _customers(spark, d)
    path = catalog.save(c, _scratch(spark, "csv"), "csv", header=True)
    return catalog.read_any(spark, path, "csv", c.schema, header=True)


@query(CUSTOMERS)
def source_json_roundtrip(spark, d):
    c = _customers(spark, d)
    return catalog.read_any(spark, catalog.save(c, _scratch(spark, "json"), "json"), "json", c.schema)


@query(CUSTOMERS)
def source_orc_roundtrip(spark, d):
    return catalog.read_any(spark, catalog.save(_customers(spark, d), _scratch(spark, "orc"), "orc"), "orc")


@query("SELECT CAST(c_custkey AS VARCHAR) AS value FROM customer")
def source_text_roundtrip(spark, d):
    t = load(spark, d, "customer").select(F.col("c_custkey").cast("string").alias("value"))
    return catalog.read_any(spark, catalog.save(t, _scratch(spark, "text"), "text"), "text")


@query(CUSTOMERS + " WHERE c_nationkey = 3")
def sink_roundtrip(spark, d):
    """A sink partitioned by nation; reading one nation opens only its folder."""
    path = catalog.save(_customers(spark, d), _scratch(spark, "parts"), "parquet", ("c_nationkey",))
    return catalog.read_any(spark, path, "parquet").where("c_nationkey = 3").select("c_custkey", "c_nationkey", "c_acctbal", "c_mktsegment")


@query(
    f"""WITH {NUMBERED}, v AS (SELECT sample, key, idx AS i, ({ku('7', 'sample', 'idx')} // 1073741824) / 1073741824.0::DOUBLE AS u FROM n)
SELECT sample, CAST(i AS BIGINT) AS idx, key, CASE WHEN sample = 0 THEN CASE WHEN u < 0.1 THEN 0.0::DOUBLE ELSE 2.0 END ELSE CASE WHEN u < 0.1 THEN 1.0 ELSE -1.0 END END AS score FROM v"""
)
def source_synthetic(spark, d):
    """Scores of the two-point law for every customer and supplier, by their row numbers."""
    synthetic.register(spark)
    s = number_rows(balances(spark, d))
    k = sizes(s)
    drawn = spark.read.format("tuplestat_synthetic").options(law="hard_pairs", n=str(k.get(0, 0)), m=str(k.get(1, 0)), eps="0.1", seed="7").load()
    return s.select("sample", "idx", "key").join(drawn.select("sample", "idx", "score"), ["sample", "idx"])


@query("SELECT CAST(count(*) AS BIGINT) AS n, CAST(sum(c_custkey) AS BIGINT) AS total FROM customer")
def checkpoint_cut(spark, d):
    return catalog.cut(_customers(spark, d)).agg(F.count("*").alias("n"), F.sum("c_custkey").alias("total"))
