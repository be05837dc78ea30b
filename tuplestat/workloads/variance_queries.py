"""Variance theory, planning, and the theoretical experiments."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import kernels as K
from ..plans import montecarlo as MC
from ..plans import planner as P
from ..plans import variance as V
from ..sources.catalog import load
from .base import ROUNDS, SEED, TWO, WORKERS, balances, query, rounded

# Sizes of the two configurations that the experiments use, and component presets.
LARGE, SMALL = (100_000, 200, 100), (5000, 50, 10)
PRESETS = {"small_v2": V.Components(0.1, 0.001, 1.0), "large_v2": V.Components(0.1, 0.1, 1.0)}
EPS = (0.5, 0.2, 0.1, 0.05, 0.02, 0.01)


def line_shares(spark, d, eps):
    """{eps: (share of returned lines, of accepted lines)} that can lose a pair in the law of `hard_lines`."""
    lines = load(spark, d, "lineitem").where("l_returnflag IN ('R', 'A')")
    count = lambda flag, low: F.sum(((F.col("l_returnflag") == flag) & low).cast("long"))
    low = {e: F.col("l_partkey") % 200 < int(round(200 * e)) for e in eps}
    got = lines.agg(*[count(f, c) for f in "RA" for c in (F.lit(True), *low.values())]).first()
    k = len(eps) + 1
    return {e: (got[1 + i] / got[0], got[k + 1 + i] / got[k]) for i, e in enumerate(eps)}


#: Most pairs and most moved rows.
BUDGET = (10**6 + 1, 5 * (100_000 + 200) + 1)
GRID_T, GRID_B = (1, 2, 5, 10, 25, 100), (20, 100, 500)


def _grid(spark):
    n, m, w = LARGE
    rows = [(k, c.v1, c.v2, c.v0, n, m, w, t, b) for k, c in PRESETS.items() for t in GRID_T for b in GRID_B]
    return spark.createDataFrame(rows, "preset string, v1 double, v2 double, v0 double, n long, m long, w long, t long, b long")


GRID = f"""WITH p AS (SELECT * FROM (VALUES ('small_v2', 0.1::DOUBLE, 0.001::DOUBLE, 1.0::DOUBLE), ('large_v2', 0.1, 0.1, 1.0)) x(preset, v1, v2, v0)),
g AS (SELECT p.*, t, b, 100000.0::DOUBLE AS n, 200.0::DOUBLE AS m, 100.0::DOUBLE AS w FROM p, (SELECT unnest([{', '.join(map(str, GRID_T))}]) AS t), (SELECT unnest([{', '.join(map(str, GRID_B))}]) AS b)),
h AS (SELECT *, v0 + v1 + v2 AS v, v1 / n + v2 / m + v0 / (n * m) AS vn FROM g)"""


@query(
    GRID
    + """ SELECT preset, CAST(t AS BIGINT) AS rounds, CAST(b AS BIGINT) AS batch, round(vn * 1e6, 6) AS complete, round(((1 - 1.0::DOUBLE / b) * vn + v / b) * 1e6, 6) AS incomplete,
round((vn + (w - 1) * v0 / (n * m)) * 1e6, 6) AS local, round(((1 - 1.0::DOUBLE / b) * (vn + (w - 1) * v0 / (n * m)) + v / (w * b)) * 1e6, 6) AS local_incomplete,
round((vn + (w - 1) * v0 / (n * m * t)) * 1e6, 6) AS repartitioned,
round((vn + (w - 1) * v0 / (n * m * t) - (vn + (w - 1) * v0 / (n * m)) / (t * b) + v / (w * t * b)) * 1e6, 6) AS repartitioned_incomplete FROM h"""
)
def theory_variance(spark, d):
    """All six variances (in millionths) on a grid of shuffles and drawn pairs."""

    class C:
        v1, v2, v0 = F.col("v1"), F.col("v2"), F.col("v0")
        v = F.col("v0") + F.col("v1") + F.col("v2")

    n, m, w, t, b = (F.col(x).cast("double") for x in "nmwtb")
    made = {
        "complete": V.var_complete(C, n, m),
        "incomplete": V.var_incomplete(C, n, m, b),
        "local": V.var_local(C, n, m, w),
        "local_incomplete": V.var_local_incomplete(C, n, m, w, b),
        "repartitioned": V.var_repartitioned(C, n, m, w, t),
        "repartitioned_incomplete": V.var_repartitioned_incomplete(C, n, m, w, t, b),
    }
    return _grid(spark).select(
        "preset", F.col("t").alias("rounds"), F.col("b").alias("batch"), *[F.round(e * 1e6, 6).alias(k) for k, e in made.items()]
    )


@query(
    GRID
    + """ SELECT DISTINCT preset, CAST(t AS BIGINT) AS rounds, round((vn + ((1 - 1 / n) * (v1 / n + v0 / (n * m)) + (1 - 1 / m) * (v2 / m + v0 / (n * m))
 + w * (1 - 1 / n) * (1 - 1 / m) * v0 / (n * m)) / t) * 1e6, 6) AS prop_swr FROM h"""
)
def theory_variance_swr(spark, d):
    class C:
        v1, v2, v0 = F.col("v1"), F.col("v2"), F.col("v0")
        v = F.col("v0") + F.col("v1") + F.col("v2")

    n, m, w, t = (F.col(x).cast("double") for x in "nmwt")
    return _grid(spark).select("preset", F.col("t").alias("rounds"), F.round(V.var_prop_swr(C, n, m, w, t) * 1e6, 6).alias("prop_swr")).distinct()


PAIR = f"""WITH {TWO}, p AS (SELECT x.key AS x, z.key AS z, CASE WHEN z.score < x.score THEN 1.0::DOUBLE ELSE 0.0 END AS h FROM s x JOIN s z ON x.sample = 0 AND z.sample = 1),
u AS (SELECT avg(h) AS u, sum(h * h) AS hh, count(*) AS nm FROM p), r AS (SELECT x, avg(h) AS r FROM p GROUP BY x), c AS (SELECT z, avg(h) AS c FROM p GROUP BY z),
q AS (SELECT (SELECT count(*) FROM r) AS n, (SELECT count(*) FROM c) AS m, u.u, hh, nm,
  (SELECT sum((r - u.u) * (r - u.u)) FROM r) AS rr, (SELECT sum((c - u.u) * (c - u.u)) FROM c) AS cc FROM u),
k AS (SELECT n, m, u, m * rr AS sx, n * cc AS sz, (hh - nm * u * u - m * rr - n * cc) / ((n - 1.0::DOUBLE) * (m - 1)) AS ms0 FROM q)"""


#: Sizes, area and components of the balances from ranks (h), with the complete variance (g).
MEASURED = f"""WITH {TWO}, d AS (SELECT score, count(*) FILTER (sample = 0) AS pos, count(*) FILTER (sample = 1) AS neg FROM s GROUP BY 1),
b AS (SELECT *, coalesce(sum(neg) OVER w, 0) AS bn, coalesce(sum(pos) OVER w, 0) AS bp, sum(pos) OVER () AS n, sum(neg) OVER () AS m FROM d WINDOW w AS (ORDER BY score ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
q AS (SELECT CAST(max(n) AS DOUBLE) AS n, CAST(max(m) AS DOUBLE) AS m, sum(pos * (bn / m)) / max(n) AS u, sum(pos * (bn / m) * (bn / m)) AS rr,
  sum(neg * ((n - bp - pos) / n) * ((n - bp - pos) / n)) AS cc FROM b),
k AS (SELECT n, m, u, m * (rr - n * u * u) AS sx, n * (cc - m * u * u) AS sz, (n * m * u * (1 - u) - m * (rr - n * u * u) - n * (cc - m * u * u)) / ((n - 1) * (m - 1)) AS ms0 FROM q),
h AS (SELECT n, m, {WORKERS}.0::DOUBLE AS w, u, ms0 AS v0, (sx / (n - 1) - ms0) / m AS v1, (sz / (m - 1) - ms0) / n AS v2 FROM k),
g AS (SELECT *, v0 + v1 + v2 AS v, v1 / n + v2 / m + v0 / (n * m) AS vn FROM h)"""


def measured(spark, d):
    """Components, both sizes and the area of the balances."""
    c = V.auc_components(balances(spark, d), F.col("score"), F.col("sample") == 0).first()
    return V.Components(c.v1, c.v2, c.v0), c.n, c.m, c.u


def dealt_to(m):
    """Workers that leave five or two rows of the minority on each."""
    return max(1, m // 5), max(1, m // 2)


@query(
    PAIR
    + " SELECT CAST(n AS BIGINT) AS n, CAST(m AS BIGINT) AS m, round(u, 9) AS u, round(ms0, 8) AS v0, round((sx / (n - 1) - ms0) / m, 8) AS v1, round((sz / (m - 1) - ms0) / n, 8) AS v2 FROM k"
)
def variance_components(spark, d):
    """Unbiased components of the area between balances, from ranks alone."""
    r = V.auc_components(balances(spark, d), F.col("score"), F.col("sample") == 0)
    return rounded(rounded(r, 9, "u"), 8, "v0", "v1", "v2")


@query(
    PAIR
    + " SELECT CAST(n AS BIGINT) AS n, CAST(m AS BIGINT) AS m, round(u, 9) AS u, round(ms0, 8) AS v0, round((sx / (n - 1) - ms0) / m, 8) AS v1, round((sz / (m - 1) - ms0) / n, 8) AS v2 FROM k"
)
def variance_components_pairs(spark, d):
    """The same by pairs (of distinct balances, block against block), which serves any kernel."""
    r = V.block_components(balances(spark, d), K.auc())
    return rounded(rounded(r, 9, "u"), 8, "v0", "v1", "v2")


@query(
    PAIR
    + f""", j AS (SELECT 0 AS sample, x AS key, r - u AS effect FROM r, u UNION ALL SELECT 1, z, c - u FROM c, u)
SELECT sample, key, round(effect, 9) AS effect FROM j"""
)
def hoeffding_scores(spark, d):
    """Row effects of both samples: how far a row's mean kernel value is from the average."""
    s = balances(spark, d)
    e = V.auc_effects(s, F.col("score"), F.col("sample") == 0)
    u = e.agg((F.sum(F.col("pos") * F.col("r")) / F.sum("pos")).alias("u"))
    placed = s.join(e.select("score", "r", "c"), "score").join(F.broadcast(u))
    return placed.select("sample", "key", F.round(F.when(F.col("sample") == 0, F.col("r")).otherwise(F.col("c")) - F.col("u"), 9).alias("effect"))


@query(PAIR + f" SELECT CAST(t AS INTEGER) AS rounds, round({WORKERS - 1} * ms0 / (n * m * t) * 1e6, 6) AS millionths FROM k, (SELECT unnest([1, 2, 4, 8]) AS t)")
def conditional_variance(spark, d):
    """Variance over shuffles of this one table."""
    c = V.auc_components(balances(spark, d), F.col("score"), F.col("sample") == 0)
    t = c.withColumn("rounds", F.explode(F.array(*map(F.lit, (1, 2, 4, 8)))))
    v = V.conditional_variance(F.col("v0"), F.col("n").cast("double"), F.col("m"), WORKERS, F.col("rounds"))
    return t.select("rounds", F.round(v * 1e6, 6).alias("millionths"))


@query(
    PAIR
    + """ SELECT round(u, 9) AS estimate, round(((sx / (n - 1) - ms0) / m / n + (sz / (m - 1) - ms0) / n / m + ms0 / (n * m)) * 1e6, 4) AS millionths,
round(u - 1.959963984540054 * sqrt((sx / (n - 1) - ms0) / m / n + (sz / (m - 1) - ms0) / n / m + ms0 / (n * m)), 7) AS low,
round(u + 1.959963984540054 * sqrt((sx / (n - 1) - ms0) / m / n + (sz / (m - 1) - ms0) / n / m + ms0 / (n * m)), 7) AS high FROM k"""
)
def estimate_ci(spark, d):
    c = V.auc_components(balances(spark, d), F.col("score"), F.col("sample") == 0)
    var = F.col("v1") / F.col("n") + F.col("v2") / F.col("m") + F.col("v0") / (F.col("n").cast("double") * F.col("m"))
    lo, hi = V.confidence_interval(F.col("u"), var)
    return c.select(F.round("u", 9).alias("estimate"), F.round(var * 1e6, 4).alias("millionths"), F.round(lo, 7).alias("low"), F.round(hi, 7).alias("high"))


@query(
    f"""WITH e AS (SELECT unnest([{', '.join(f'{x}::DOUBLE' for x in EPS)}]) AS eps), 
k AS (SELECT eps, count(*) FILTER (l_returnflag = 'A' AND low) / count(*) FILTER (l_returnflag = 'A') AS p, 1 - count(*) FILTER (l_returnflag = 'R' AND low) / count(*) FILTER (l_returnflag = 'R') AS q
  FROM (SELECT eps, l_returnflag, l_partkey % 200 < CAST(round(200 * eps) AS INTEGER) AS low FROM lineitem, e WHERE l_returnflag IN ('R', 'A')) GROUP BY eps),
o AS (SELECT eps, a.v AS x, a.w AS wx, b.v AS z, b.w AS wz FROM k,
  LATERAL (SELECT 2.0::DOUBLE AS v, q AS w UNION ALL SELECT 0.0, 1 - q) a, LATERAL (SELECT 1.0::DOUBLE AS v, p AS w UNION ALL SELECT -1.0, 1 - p) b),
u AS (SELECT eps, sum(wx * wz * (z < x)::INT) AS u FROM o GROUP BY eps),
r AS (SELECT eps, sum(wx * r * r) AS rr FROM (SELECT eps, x, wx, sum(wz * (z < x)::INT) AS r FROM o GROUP BY eps, x, wx) GROUP BY eps),
c AS (SELECT eps, sum(wz * c * c) AS cc FROM (SELECT eps, z, wz, sum(wx * (z < x)::INT) AS c FROM o GROUP BY eps, z, wz) GROUP BY eps)
SELECT eps, round(u, 9) AS auc, round(rr - u * u, 12) AS v1, round(cc - u * u, 12) AS v2, round(u - rr - cc + u * u, 12) AS v0 FROM u JOIN r USING (eps) JOIN c USING (eps)"""
)
def discrete_law(spark, d):
    """Closed forms of the lines' two-point laws against enumeration of the four outcomes."""
    rows = [(e, 1 - a * b, c.v1, c.v2, c.v0) for e, (a, b) in line_shares(spark, d, EPS).items() for c in [V.discrete_law(b, 1 - a)]]
    df = spark.createDataFrame(rows, "eps double, auc double, v1 double, v2 double, v0 double")
    return rounded(rounded(df, 9, "auc"), 12, "v1", "v2", "v0")


@query(
    MEASURED + """, p AS (SELECT CAST(n AS BIGINT) AS n, CAST(m AS BIGINT) AS m, u, unnest([greatest(1, CAST(m AS BIGINT) // 5), greatest(1, CAST(m AS BIGINT) // 2)]) AS w FROM h),
f AS (SELECT n, m, u, w, unnest(range((n + m) // w)) AS i FROM p)
SELECT n, m, w AS workers, round(exp(sum(ln((n - i)::DOUBLE) - ln((n + m - i)::DOUBLE))), 8) AS fixed_size,
round(pow(1 - 1.0::DOUBLE / w, m), 8) AS independent FROM f GROUP BY n, m, u, w"""
)
def swor_empty_probability(spark, d):
    """Chance of a worker without a supplier when customers and suppliers are dealt alike."""
    _, n, m, _ = measured(spark, d)
    rows = [(n, m, w, V.swor_empty_probability(n, m, w), V.swor_empty_probability(n, m, w, False)) for w in dealt_to(m)]
    df = spark.createDataFrame(rows, "n long, m long, workers long, fixed_size double, independent double")
    return rounded(df, 8, "fixed_size", "independent")


@query(
    MEASURED + f""", e AS (SELECT g.*, b, n * m * 2 / w / (w * b) AS tt FROM g, (SELECT unnest([{', '.join(map(str, GRID_B))}]) AS b))
SELECT CAST(b AS BIGINT) AS batch, round(tt, 6) AS rounds, round(((vn + (w - 1) * v0 / (n * m * tt) - (vn + (w - 1) * v0 / (n * m)) / (tt * b) + v / (w * tt * b))
 - (vn + (w - 1) * v0 / (n * m * 2))) * 1e6, 6) AS gap FROM e"""
)
def equal_budget(spark, d):
    """At equal pairs of the balances, drawn pairs over more shuffles never beat all local pairs over fewer."""
    c, n, m, _ = measured(spark, d)
    rows = [(b, V.equal_budget(n, m, WORKERS, 2, b), V.dominance_gap(c, n, m, WORKERS, 2, b) * 1e6) for b in GRID_B]
    return rounded(spark.createDataFrame(rows, "batch long, rounds double, gap double"), 6, "rounds", "gap")


@query(
    """WITH x AS (SELECT c_acctbal - avg(c_acctbal) OVER () AS v FROM customer), z AS (SELECT s_acctbal - avg(s_acctbal) OVER () AS v FROM supplier)
SELECT (SELECT count(*) FROM x) AS n, (SELECT count(*) FROM z) AS m, true AS degenerate, round((SELECT var_samp(v) FROM x) / 1e6 * ((SELECT var_samp(v) FROM z) / 1e6), 5) AS v0"""
)
def degenerate_kernel(spark, d):
    """The product of centred balances has no row effects: all its variance is in the pairs."""
    s = balances(spark, d)
    means = s.groupBy("sample").agg(F.avg("score").alias("_m"))
    c = s.join(F.broadcast(means), "sample").withColumn("score", F.col("score") - F.col("_m"))
    r = V.block_components(c.select("sample", (F.col("score") / 1000).alias("score")), K.PRODUCT)
    return r.select("n", "m", (F.greatest(F.lit(0.0), F.col("v1") + F.col("v2")) <= 0.05 * F.col("v0")).alias("degenerate"), F.round("v0", 5).alias("v0"))


@query(
    """SELECT l_returnflag, CAST(n AS BIGINT) AS n, CAST(k AS INTEGER) AS degree, round(sqrt(ln(n) / n), 9) AS sampled_tuples, round(sqrt(ln(n) / pow(n, 1.0::DOUBLE / k)), 9) AS subsampled_rows
FROM (SELECT l_returnflag, count(l_extendedprice) AS n FROM lineitem GROUP BY 1), (SELECT unnest([2, 3]) AS k)"""
)
def rate_table(spark, d):
    """Rates at the sizes of the lines' three groups."""
    rows = []
    for flag, n in load(spark, d, "lineitem").groupBy("l_returnflag").agg(F.count("l_extendedprice")).collect():  # a row per flag
        for k in (2, 3):
            r = V.rate_table(n, (k,))
            rows.append((flag, n, k, r["sampled_tuples"], r["subsampled_rows"]))
    df = spark.createDataFrame(rows, "l_returnflag string, n long, degree int, sampled_tuples double, subsampled_rows double")
    return rounded(df, 9, "sampled_tuples", "subsampled_rows")


# ------------------------------------------------------------------ planning


@query(
    PAIR
    + f""", e AS (SELECT *, {WORKERS - 1} * ms0 / (n * m) / ((sx / (n - 1) - ms0) / m / n + (sz / (m - 1) - ms0) / n / m + ms0 / (n * m)) AS excess FROM k)
SELECT round(ratio, 3) AS ratio, CAST(greatest(1, ceil(excess / (ratio - 1) - 1e-12)) AS INTEGER) AS rounds FROM e, (SELECT unnest([1.001::DOUBLE, 1.01, 1.1]) AS ratio)"""
)
def plan_rounds(spark, d):
    """Fewest shuffles for a wanted relative variance, from measured components."""
    c = V.auc_components(balances(spark, d), F.col("score"), F.col("sample") == 0).first()
    k = V.Components(c.v1, c.v2, c.v0)
    rows = [(r, P.rounds_for(k, c.n, c.m, WORKERS, r)) for r in (1.001, 1.01, 1.1)]
    return spark.createDataFrame(rows, "ratio double, rounds int")


@query(
    GRID
    + """ SELECT preset, 'repartitioned' AS estimator, CAST(t AS INTEGER) AS rounds, 0 AS batch, CAST(n * m * t / w AS BIGINT) AS pairs, round((vn + (w - 1) * v0 / (n * m * t)) * 1e6, 6) AS millionths FROM h WHERE b = 20
UNION ALL SELECT preset, 'repartitioned_incomplete', CAST(t AS INTEGER), CAST(b AS INTEGER), CAST(w * b * t AS BIGINT),
round((vn + (w - 1) * v0 / (n * m * t) - (vn + (w - 1) * v0 / (n * m)) / (t * b) + v / (w * t * b)) * 1e6, 6) FROM h
UNION ALL SELECT preset, 'incomplete', 0, 0, CAST(n * m * t / w AS BIGINT), round(((1 - w / (n * m * t)) * vn + v * w / (n * m * t)) * 1e6, 6) FROM h WHERE b = 20
UNION ALL SELECT preset, 'complete', 0, 0, CAST(n * m AS BIGINT), round(vn * 1e6, 6) FROM h WHERE b = 20 AND t = 1"""
)
def variance_frontier(spark, d):
    """Variance against evaluated pairs in the large configuration."""
    n, m, w = LARGE
    rows = [(k, *r[:4], r[4] * 1e6) for k, c in PRESETS.items() for r in P.frontier(c, n, m, w, GRID_T, GRID_B)]
    return rounded(spark.createDataFrame(rows, "preset string, estimator string, rounds int, batch int, pairs long, millionths double"), 6, "millionths")


@query(
    PAIR
    + f""", vc AS (SELECT *, (sx / (n - 1) - ms0) / m AS v1, (sz / (m - 1) - ms0) / n AS v2 FROM k), t AS (SELECT unnest([1, 2, 5, 10]) AS t),
e AS (SELECT t, n, m, ms0, v1 / n + v2 / m + ms0 / (n * m) AS vn, v1 + v2 + ms0 AS v FROM vc, t)
SELECT 'repartitioned' AS estimator, CAST(t AS INTEGER) AS rounds, CAST(n * m * t // {WORKERS} AS BIGINT) AS pairs, round((vn + {WORKERS - 1} * ms0 / (n * m * t)) / vn, 8) AS relative FROM e
UNION ALL SELECT 'incomplete', 0, CAST(n * m * t // {WORKERS} AS BIGINT), round(((1 - 1.0::DOUBLE / (n * m * t // {WORKERS})) * vn + v / (n * m * t // {WORKERS})) / vn, 8) FROM e
UNION ALL SELECT 'complete', 0, CAST(n * m AS BIGINT), 1.0 FROM e WHERE t = 1"""
)
def variance_frontier_measured(spark, d):
    """The same curves, relative to the complete statistic, from components measured on the balances."""
    c = V.auc_components(balances(spark, d), F.col("score"), F.col("sample") == 0).first()
    k = V.Components(c.v1, c.v2, c.v0)
    vn = V.var_complete(k, c.n, c.m)
    rows = [(r[0], r[1], r[3], r[4] / vn) for r in P.frontier(k, c.n, c.m, WORKERS, (1, 2, 5, 10), ())]
    return rounded(spark.createDataFrame(rows, "estimator string, rounds int, pairs long, relative double"), 8, "relative")


@query(
    MEASURED + """, p AS (SELECT CAST(n AS BIGINT) AS n, CAST(m AS BIGINT) AS m, u, unnest([greatest(1, CAST(m AS BIGINT) // 5), greatest(1, CAST(m AS BIGINT) // 2)]) AS w FROM h),
f AS (SELECT n, m, u, w, unnest(range((n + m) // w)) AS i FROM p)
SELECT n, m, w AS workers, round(-u * exp(sum(ln((n - i)::DOUBLE) - ln((n + m - i)::DOUBLE))), 8) AS fixed_size,
round(-u * pow(1 - 1.0::DOUBLE / w, m), 8) AS independent FROM f GROUP BY n, m, u, w"""
)
def swor_bias(spark, d):
    """Bias of the zero rule when rows are dealt without regard to sample, at the balances' own area."""
    _, n, m, u = measured(spark, d)
    rows = [(n, m, w, V.swor_bias(u, n, m, w), V.swor_bias(u, n, m, w, False)) for w in dealt_to(m)]
    return rounded(spark.createDataFrame(rows, "n long, m long, workers long, fixed_size double, independent double"), 8, "fixed_size", "independent")


@query(
    MEASURED + """, c AS (SELECT n, m, v0, v1, v2, unnest([greatest(1, CAST(m AS BIGINT) // 5), greatest(1, CAST(m AS BIGINT) // 2)]) AS w FROM h),
p AS (SELECT n, m, w, k, exp(lgamma(m + 1) - lgamma(k + 1) - lgamma(m - k + 1) + k * ln(1.0::DOUBLE / w) + (m - k) * ln(1 - 1.0::DOUBLE / w)) AS chance,
  v1 * w / n + v2 / k + v0 * w / (n * k) AS var FROM (SELECT *, unnest(range(1, CAST(m AS BIGINT) + 1)) AS k FROM c))
SELECT CAST(n AS BIGINT) AS n, CAST(m AS BIGINT) AS m, w AS workers, round(sum(chance * var) / sum(chance) / w * 1e6, 4) AS millionths FROM p GROUP BY n, m, w"""
)
def swor_variance(spark, d):
    """One round of independently thrown rows, empty workers skipped: a mixture over minority sizes, with the
    balances' components."""
    c, n, m, _ = measured(spark, d)
    rows = [(n, m, w, V.swor_numeric(c, n, m, w) * 1e6) for w in dealt_to(m)]
    return rounded(spark.createDataFrame(rows, "n long, m long, workers long, millionths double"), 4, "millionths")


@query(
    MEASURED + """, e AS (SELECT (w - 1) * v0 / (n * m) / vn AS excess FROM g)
SELECT CASE WHEN excess > 0.05 THEN 'shuffle' ELSE 'minority_limited' END AS advice, round(excess, 6) AS excess FROM e"""
)
def plan_diagnose(spark, d):
    c, n, m, _ = measured(spark, d)
    return rounded(spark.createDataFrame([P.diagnose(c, n, m, WORKERS)], "advice string, excess double"), 6, "excess")


@query(
    MEASURED + f""", r AS (SELECT g.*, unnest(range(1, 6)) AS k FROM g),
o AS (SELECT k, 0 AS batch, vn + (w - 1) * v0 / (n * m * k) AS var FROM r WHERE floor(n * m / w) * k <= {BUDGET[0]}
  UNION ALL SELECT k, batch, vn + (w - 1) * v0 / (n * m * k) - (vn + (w - 1) * v0 / (n * m)) / (k * batch) + v / (w * k * batch)
  FROM (SELECT *, CAST(floor({BUDGET[0]} / (w * k)) AS BIGINT) AS batch FROM r))
SELECT CAST(k AS INTEGER) AS rounds, CAST(batch AS INTEGER) AS batch, round(var * 1e6, 6) AS millionths FROM o ORDER BY var, batch, k LIMIT 1"""
)
def plan_budget(spark, d):
    """A million pairs and five moves of all rows, for the balances: drawn pairs where one round has more."""
    c, n, m, _ = measured(spark, d)
    t, b, v = P.best_under_budget(c, n, m, WORKERS, BUDGET[0], 5 * (n + m) + 1)
    return rounded(spark.createDataFrame([(t, b, v * 1e6)], "rounds int, batch int, millionths double"), 6, "millionths")


# ------------------------------------------------------------------ Monte-Carlo experiments


@query()
def mc_relative_variance(spark, d, runs: int = 5000):
    """Fresh samples of the lines' two-point laws: each estimator's variance over the complete one's closed
    form, beside the theory."""
    n, m, w = SMALL
    shares = line_shares(spark, d, EPS)
    runs_df = MC.law_runs(spark, runs, n, m, EPS, w, ROUNDS, 100, "prop_swor", SEED, shares)
    s = MC.mc_summary(runs_df, ("eps", "estimator"), {e: 1 - a * b for e, (a, b) in shares.items()})
    rows = []
    for e, (a, b) in shares.items():
        c = V.discrete_law(b, 1 - a)
        vn = V.var_complete(c, n, m)
        for name, v in (
            ("complete", vn),
            ("incomplete", V.var_incomplete(c, n, m, w * 100)),
            ("local", V.var_local(c, n, m, w)),
            ("local_incomplete", V.var_local_incomplete(c, n, m, w, 100)),
            ("repartitioned", V.var_repartitioned(c, n, m, w, ROUNDS)),
            ("repartitioned_incomplete", V.var_repartitioned_incomplete(c, n, m, w, ROUNDS, 100)),
        ):
            rows.append((e, name, v / vn, vn))
    theory = spark.createDataFrame(rows, "eps double, estimator string, theory double, vn double")
    return s.join(F.broadcast(theory), ["eps", "estimator"]).select(
        "eps", "estimator", "runs", "mean", "bias", (F.col("variance") / F.col("vn")).alias("relative_variance"), "theory"
    )


@query()
def mc_schemes(spark, d, runs: int = 300):
    """Schemes side by side on one table: mean and variance over shuffles."""
    out = None
    for scheme in MC.SCHEMES:
        r = MC.table_runs(balances(spark, d), runs, WORKERS, ROUNDS, 50, scheme, SEED)
        one = MC.mc_summary(r, ("estimator",)).withColumn("scheme", F.lit(scheme))
        out = one if out is None else out.unionByName(one)
    return out


@query()
def mc_summary(spark, d, runs: int = 300):
    """Shuffles of one table against the exact conditional variance."""
    s = balances(spark, d)
    c = V.auc_components(s, F.col("score"), F.col("sample") == 0).first()
    r = MC.mc_summary(MC.table_runs(s, runs, WORKERS, ROUNDS, 50, "prop_swor", SEED), ("estimator",))
    exact = {"local": 1, "repartitioned": ROUNDS}
    rows = [(k, V.conditional_variance(c.v0, c.n, c.m, WORKERS, t)) for k, t in exact.items()]
    return r.join(F.broadcast(spark.createDataFrame(rows, "estimator string, exact double")), "estimator")


@query()
def mc_rates(spark, d, runs: int = 300):
    """Drawn pairs against subsampled rows at equal pairs: the former vary less."""
    n, m, w = SMALL
    r = MC.law_runs(spark, runs, n, m, (0.1,), w, 1, 100, "prop_swor", SEED, line_shares(spark, d, (0.1,)))
    return MC.mc_summary(r.where("estimator IN ('incomplete', 'subsample', 'complete')"), ("estimator",))
