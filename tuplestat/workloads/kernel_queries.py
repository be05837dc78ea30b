"""Kernels and evaluation measures."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions.scalar import whole_type
from ..operators import blocks as B
from ..operators import estimators as E
from ..operators import kernels as K
from ..operators import metrics as M
from ..operators import sorted_forms as Q
from ..operators.concordance import concordance_counts
from ..operators.samples import kept, sizes
from ..sources.catalog import load
from .base import NUMBERED, SEED, TWO, balances, ku, numbered_balances, query, rounded

# The scorer of the hinge queries: balances in thousands.
SCALE = 1000.0


@query(
    f"""WITH {TWO} SELECT count(*) FILTER (1 = 1) AS tuples,
CAST(sum(CASE WHEN z.score < x.score THEN 1 ELSE 0 END) AS BIGINT) AS wins, CAST(sum(CASE WHEN z.score = x.score THEN 1 ELSE 0 END) AS BIGINT) AS ties,
round(avg(CASE WHEN z.score < x.score THEN 1.0 WHEN z.score = x.score THEN 0.5 ELSE 0.0 END), 9) AS auc_half
FROM s x JOIN s z ON x.sample = 0 AND z.sample = 1"""
)
def kernel_auc(spark, d):
    """Strict wins and ties at once; scores rounded to hundreds would only add ties."""
    r = Q.auc_counts(balances(spark, d), F.col("score"), F.col("sample") == 0)
    return r.select((F.col("n") * F.col("m")).alias("tuples"), "wins", "ties", F.round("auc_half", 9).alias("auc_half"))


def _vus_sql(k, label, whole="DOUBLE"):
    """Rising chains class by class: rows of a class times the chains that end below them."""
    counts = ", ".join(f"CAST(count(*) FILTER (y = {c}) AS DOUBLE) AS n{c}" for c in range(1, k + 1))
    steps = ", ".join(
        f"h{c} AS (SELECT * REPLACE (n{c} * coalesce(sum(h) OVER (ORDER BY v ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS h) FROM h{c - 1})"
        for c in range(2, k + 1)
    )
    product = " * ".join(f"sum(n{c})" for c in range(1, k + 1))
    return f"""WITH c AS (SELECT v, {counts} FROM (SELECT {label} AS y, o_totalprice AS v FROM orders) GROUP BY v), h1 AS (SELECT *, n1 AS h FROM c), {steps}
SELECT CAST({product} AS {whole}) AS tuples, CAST(sum(h) AS {whole}) AS chains, round(sum(h) / ({product}), 9) AS estimate FROM h{k}"""


def _vus(df, label, k):
    """Counts are exact; those beyond 64 bits (from some two million rows a class on) are decimal(38,0),
    where the SQL ends in an error."""
    r = kept(Q.vus_counts(df, F.col("o_totalprice"), label, k, Q.WHOLE))
    top = r.first()
    counts = [F.col(c).cast(whole_type(top[c])).alias(c) for c in ("tuples", "chains")]
    return r.select(*counts, F.round("estimate", 9).alias("estimate"))


def _status_label():
    return F.array_position(F.array(*map(F.lit, "FOP")), F.col("o_orderstatus"))


def _priority_label():
    return F.substring("o_orderpriority", 1, 1).cast("int")


@query(_vus_sql(3, "strpos('FOP', o_orderstatus)", "BIGINT"))
def kernel_vus3(spark, d):
    return _vus(load(spark, d, "orders"), _status_label(), 3)


@query(_vus_sql(5, "CAST(substr(o_orderpriority, 1, 1) AS INTEGER)"))
def kernel_vus5(spark, d):
    r = Q.vus_counts(load(spark, d, "orders"), F.col("o_totalprice"), _priority_label(), 5)
    return rounded(r.select("tuples", "chains", "estimate"), 9, "estimate")


@query(
    """SELECT count(*) AS n, round(2 * var_samp(o_totalprice), 0) AS sqdiff, round(var_samp(o_totalprice), 0) AS half_sqdiff FROM orders"""
)
def kernel_variance(spark, d):
    r = Q.squared_difference(load(spark, d, "orders"), F.col("o_totalprice"))
    return r.select("n", F.round("estimate", 0).alias("sqdiff"), F.round(F.col("estimate") / 2, 0).alias("half_sqdiff"))


@query(
    """WITH c AS (SELECT value AS v, CAST(count(*) AS DOUBLE) AS c FROM events WHERE value IS NOT NULL GROUP BY 1),
b AS (SELECT *, coalesce(sum(c) OVER w, 0) AS bc, coalesce(sum(c * v) OVER w, 0) AS bw FROM c WINDOW w AS (ORDER BY v ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING))
SELECT CAST(sum(c) AS BIGINT) AS n, round(sum(c * (v * bc - bw)) / (sum(c) * (sum(c) - 1) / 2), 6) AS estimate FROM b"""
)
def kernel_gini(spark, d):
    r = Q.mean_absolute_difference(load(spark, d, "events").where("value IS NOT NULL"), F.col("value"))
    return rounded(r.select("n", "estimate"), 6, "estimate")


#: Concordant pairs of quantity and price over all lines: for each of the few quantities, its lines against
#: the lines of a smaller quantity and a smaller price.
CONCORDANCE = """WITH p AS (SELECT l_quantity AS x, l_extendedprice AS y, count(*) AS c FROM lineitem WHERE l_quantity IS NOT NULL AND l_extendedprice IS NOT NULL GROUP BY 1, 2),
q AS (SELECT DISTINCT x AS level FROM p), t AS (SELECT sum(c) AS n FROM p),
b AS (SELECT level, x, c, coalesce(sum(CASE WHEN x < level THEN c ELSE 0 END) OVER (PARTITION BY level ORDER BY y RANGE BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW EXCLUDE GROUP), 0) AS below FROM p, q),
k AS (SELECT sum(c * below) AS k FROM b WHERE x = level)
SELECT CAST(n * (n - 1) // 2 AS BIGINT) AS pairs, CAST(k AS BIGINT) AS concordant, round(CAST(k AS DOUBLE) / (CAST(n AS DOUBLE) * (n - 1) / 2), 9) AS estimate FROM k, t"""


@query(CONCORDANCE)
def kernel_kendall(spark, d):
    """Concordance of quantity and price without a pair (see operators.concordance)."""
    return rounded(concordance_counts(load(spark, d, "lineitem"), "l_quantity", "l_extendedprice"), 9, "estimate")


@query(
    """SELECT (SELECT count(*) FROM customer) AS n, (SELECT count(*) FROM supplier) AS m,
round((SELECT avg(c_acctbal) FROM customer) * (SELECT avg(s_acctbal) FROM supplier), 2) AS estimate"""
)
def kernel_product(spark, d):
    return rounded(Q.product_mean(balances(spark, d), F.col("score"), F.col("sample") == 0), 2, "estimate")


HINGE = f"""WITH {TWO} SELECT count(*) AS pairs, CAST(sum(CASE WHEN 1 + x.score / 1000 - z.score / 1000 > 0 THEN 1 ELSE 0 END) AS BIGINT) AS active,
round(avg(greatest(0, 1 + x.score / 1000 - z.score / 1000)), 7) AS estimate FROM s x JOIN s z ON x.sample = 0 AND z.sample = 1"""


@query(HINGE)
def kernel_hinge(spark, d):
    r = Q.hinge_sums(balances(spark, d), F.col("score") / SCALE, F.col("sample") == 0)
    return r.select((F.col("n") * F.col("m")).alias("pairs"), "active", F.round("estimate", 7).alias("estimate"))


@query(
    f"""WITH {TWO} SELECT count(*) AS pairs, round(avg(greatest(0, 1 + (0.4 * x.score - 0.4 * z.score) / 1000)), 7) AS loss,
round(avg(CASE WHEN 1 + (0.4 * x.score - 0.4 * z.score) / 1000 > 0 THEN (x.score - z.score) / 1000 ELSE 0 END), 7) AS gradient
FROM s x JOIN s z ON x.sample = 0 AND z.sample = 1"""
)
def kernel_hinge_grad(spark, d):
    """The kernel's gradient in the scorer's one weight, from counts of active pairs."""
    from ..plans.learning import full_gradient

    train = balances(spark, d).select(F.col("sample").alias("cls"), F.array(F.col("score") / SCALE).alias("features"))
    g = full_gradient(train, [0.4])
    return g.select("pairs", F.round("loss", 7).alias("loss"), F.round("g0", 7).alias("gradient"))


@query(
    f"""WITH {TWO}, p AS (SELECT (x.score - z.score) / 1000 AS v FROM s x JOIN s z ON x.sample = 0 AND z.sample = 1)
SELECT count(*) AS tuples, round(avg(greatest(v, 0) + ln(1 + exp(-abs(v)))), 8) AS estimate FROM p"""
)
def kernel_logistic(spark, d):
    """All pairs of distinct balances, block against block."""
    s = balances(spark, d).withColumn("score", F.col("score") / SCALE)
    return rounded(B.complete_blocks(s, K.logistic_rank()).select("tuples", "estimate"), 8, "estimate")


VECTORS = "SELECT vec_id AS k, label AS y, embedding AS e FROM embeddings"
DISTANCE = "list_sum([(CAST(p[1] AS DOUBLE) - p[2]) * (CAST(p[1] AS DOUBLE) - p[2]) for p in list_zip(a.e, b.e)])"


@query(
    f"""WITH s AS ({VECTORS}) SELECT count(*) AS pairs, count(*) FILTER (a.y = b.y) AS inside,
round(avg(CASE WHEN a.y = b.y THEN {DISTANCE} ELSE 0 END), 8) AS estimate FROM s a JOIN s b ON a.k < b.k"""
)
def kernel_cluster(spark, d):
    """Squared distances inside a label sum to its size times its squares less the square of its sum."""
    v = load(spark, d, "embeddings").select("label", F.posexplode("embedding").alias("k", "e"))
    v = v.select("label", "k", F.col("e").cast("double").alias("e"))
    by = v.groupBy("label", "k").agg(F.count("*").alias("n"), F.sum("e").alias("s"), F.sum(F.col("e") * F.col("e")).alias("q"))
    inside = by.agg(F.sum(F.col("n") * F.col("q") - F.col("s") * F.col("s")).alias("total"))
    sizes = load(spark, d, "embeddings").groupBy("label").agg(F.count("*").alias("c")).agg(
        F.sum("c").alias("n"), F.sum(F.col("c") * (F.col("c") - 1) / 2).cast("long").alias("inside")
    )
    pairs = (F.col("n") * (F.col("n") - 1) / 2).cast("long")
    return sizes.join(F.broadcast(inside)).select(pairs.alias("pairs"), "inside", F.round(F.col("total") / pairs, 8).alias("estimate"))


@query(
    f"""WITH s AS ({VECTORS}) SELECT count(*) AS pairs,
round(avg(greatest(0, 1 + (CASE WHEN a.y = b.y THEN 1 ELSE -1 END) * ({DISTANCE} - 2))), 8) AS estimate FROM s a JOIN s b ON a.k < b.k"""
)
def kernel_metric(spark, d):
    """All pairs of vectors, block against block: the work is quadratic in the table."""
    v = load(spark, d, "embeddings").select(F.col("vec_id").alias("key"), "label", F.col("embedding").alias("vector"))
    return rounded(B.metric_pairs(v, 2.0), 8, "estimate")


@query(
    f"""WITH {TWO} SELECT count(*) AS tuples, round(avg(CASE WHEN abs(x.score - z.score) < 500 THEN 1.0 ELSE 0.0 END), 9) AS estimate
FROM s x JOIN s z ON x.sample = 0 AND z.sample = 1"""
)
def kernel_user_sql(spark, d):
    k = K.Kernel.from_sql("CASE WHEN abs(x - z) < 500 THEN 1 ELSE 0 END", (1, 1))
    return rounded(E.complete_u(balances(spark, d), k).select("tuples", "estimate"), 9, "estimate")


# ------------------------------------------------------------------ measures


def _returns(spark, d):
    """Price of returned against accepted lines: independent, so the area is near a half."""
    return load(spark, d, "lineitem").where("l_returnflag IN ('R', 'A')").select(
        F.col("l_extendedprice").alias("score"), (F.col("l_returnflag") == "R").alias("y"), "l_linestatus", "l_orderkey"
    )


RETURNS = "r AS (SELECT l_extendedprice AS score, l_returnflag = 'R' AS y, l_linestatus, l_orderkey FROM lineitem WHERE l_returnflag IN ('R', 'A'))"
#: Exact wins by rank sums, which is feasible for all rows where pairs are not.
RANKED = """c AS (SELECT {by} score, count(*) FILTER (y) AS pos, count(*) FILTER (NOT y) AS neg FROM r GROUP BY {by} score),
b AS (SELECT *, coalesce(sum(neg) OVER ({part} ORDER BY score ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS below FROM c)"""


@query(
    f"""WITH {RETURNS}, {RANKED.format(by='', part='')} SELECT CAST(sum(pos) AS BIGINT) AS n, CAST(sum(neg) AS BIGINT) AS m,
CAST(sum(pos * below) AS BIGINT) AS wins, CAST(sum(pos * neg) AS BIGINT) AS ties, round(sum(pos * below) / (CAST(sum(pos) AS DOUBLE) * sum(neg)), 9) AS auc FROM b"""
)
def auc_exact(spark, d):
    return rounded(M.auc(_returns(spark, d), F.col("score"), F.col("y")).drop("auc_half"), 9, "auc")


@query(
    f"""WITH {RETURNS}, k AS (SELECT least(49, greatest(0, CAST(floor((score - 900) / 2000.0) AS INTEGER))) AS score, y FROM r),
{RANKED.format(by='', part='').replace('FROM r', 'FROM k')}
SELECT CAST(sum(pos) AS BIGINT) AS n, CAST(sum(neg) AS BIGINT) AS m, round(sum(pos * below) / (CAST(sum(pos) AS DOUBLE) * sum(neg)), 9) AS low,
round((sum(pos * below) + sum(pos * neg) / 2) / (CAST(sum(pos) AS DOUBLE) * sum(neg)), 9) AS auc,
round((sum(pos * below) + sum(pos * neg)) / (CAST(sum(pos) AS DOUBLE) * sum(neg)), 9) AS high FROM b"""
)
def auc_binned(spark, d):
    return rounded(M.auc_binned(_returns(spark, d), F.col("score"), F.col("y"), 900.0, 100900.0, 50), 9, "low", "auc", "high")


@query(
    f"""WITH {RETURNS}, {RANKED.format(by='l_linestatus,', part='PARTITION BY l_linestatus')} SELECT l_linestatus, CAST(sum(pos) AS BIGINT) AS n,
CAST(sum(neg) AS BIGINT) AS m, CAST(sum(pos * below) AS BIGINT) AS wins, round(sum(pos * below) / (CAST(sum(pos) AS DOUBLE) * sum(neg)), 9) AS auc FROM b GROUP BY 1"""
)
def auc_grouped(spark, d):
    r = M.auc_by(_returns(spark, d), F.col("score"), F.col("y"), ("l_linestatus",))
    return rounded(r.select("l_linestatus", "n", "m", "wins", "auc"), 9, "auc")


@query(
    """WITH c AS (SELECT o_totalprice AS v, count(*) FILTER (o_orderstatus = 'F') AS f, count(*) FILTER (o_orderstatus = 'O') AS o, count(*) FILTER (o_orderstatus = 'P') AS p
  FROM orders GROUP BY 1),
w AS (SELECT *, coalesce(sum(f) OVER (ORDER BY v ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS bf,
              coalesce(sum(p) OVER (ORDER BY v DESC ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS ap FROM c)
SELECT CAST(CAST(sum(f) AS DOUBLE) * sum(o) * sum(p) AS BIGINT) AS tuples, CAST(sum(CAST(bf AS DOUBLE) * o * ap) AS BIGINT) AS chains,
       round(sum(CAST(bf AS DOUBLE) * o * ap) / (CAST(sum(f) AS DOUBLE) * sum(o) * sum(p)), 9) AS estimate FROM w"""
)
def vus_exact(spark, d):
    """All orders; scores are independent of the class, so the estimate is near one sixth."""
    return _vus(load(spark, d, "orders"), _status_label(), 3)


FIXED = f"""WITH {NUMBERED}, c AS (SELECT count(*) FILTER (sample = 0) AS n, count(*) FILTER (sample = 1) AS m FROM s),
p AS (SELECT b, {ku(str(SEED), "'monitor'", '0', 'b')} % n AS i, {ku(str(SEED), "'monitor'", '1', 'b')} % m AS j FROM (SELECT unnest(range(5000)) AS b), c),
f AS (SELECT b, x.score / 1000 AS x, z.score / 1000 AS z FROM p JOIN n x ON x.sample = 0 AND x.idx = i JOIN n z ON z.sample = 1 AND z.idx = j)"""


def _fixed(spark, d):
    s = numbered_balances(spark, d).withColumn("score", F.col("score") / SCALE)
    return M.fixed_pairs(s, sizes(s), 5000, SEED)


@query(FIXED + " SELECT count(*) AS pairs, round(avg(greatest(0, 1 + x - z)), 8) AS loss FROM f")
def pair_loss_fixed(spark, d):
    return rounded(M.pair_loss(_fixed(spark, d)).drop("accuracy"), 8, "loss")


@query(FIXED + " SELECT count(*) AS pairs, round(avg(CASE WHEN x < z THEN 1.0 ELSE 0.0 END), 9) AS accuracy FROM f")
def pair_accuracy(spark, d):
    return rounded(M.pair_loss(_fixed(spark, d)).drop("loss"), 9, "accuracy")


@query(
    f"""WITH {TWO}, p AS (SELECT x.key AS xk, z.key AS zk, round((z.score - x.score) * 100) AS margin FROM s x JOIN s z ON x.sample = 0 AND z.sample = 1)
SELECT xk, zk, CAST(margin AS BIGINT) AS cents FROM p ORDER BY margin, xk, zk LIMIT 20"""
)
def topk_hard_pairs(spark, d):
    """The twenty pairs ranked wrong by most. A row behind twenty of its own sample (ties by key) is behind
    twenty pairs with every partner, so the first twenty of each sample hold them all."""
    s = balances(spark, d)
    x = s.where("sample = 0").select(F.col("key").alias("xk"), F.round(F.col("score") * 100).alias("x"))
    z = s.where("sample = 1").select(F.col("key").alias("zk"), F.round(F.col("score") * 100).alias("z"))
    x, z = x.orderBy(F.col("x").desc(), "xk").limit(20), z.orderBy("z", "zk").limit(20)
    top = M.hardest_pairs(x.crossJoin(z), 20, ("xk", "zk"))
    return top.select("xk", "zk", F.col("margin").cast("long").alias("cents"))
