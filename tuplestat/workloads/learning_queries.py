"""Learning from pairs on the given tables."""

from __future__ import annotations

import numpy as np
from pyspark import StorageLevel
from pyspark.sql import functions as F

from ..functions.keyed import keyed_u64
from ..operators import schemes as S
from ..operators.estimators import draws
from ..operators.samples import kept, number_rows, release, sizes
from ..plans import learning as L
from ..plans.montecarlo import trace_bands as bands
from ..sources.catalog import load
from .base import BATCH, SEED, ku, query, ranked_sql, rounded

W = [0.3, -0.2]
FEATURES = ("(length(text) / 1000.0)", "(n_words / 100.0)")

#: Labelled documents, quality 0 being the lower class: length in thousands, words in hundreds.
DOCS = """s AS (
  SELECT CAST(quality AS INTEGER) AS sample, lpad(CAST(d.doc_id AS VARCHAR), 12, '0') AS key,
         CAST(length(text) AS DOUBLE) / 1000 AS f0, CAST(len(string_split(text, ' ')) AS DOUBLE) / 100 AS f1
  FROM documents d JOIN labels l ON l.doc_id = d.doc_id WHERE quality IN (0, 1)
)"""


def quality_rows(spark, d):
    docs = load(spark, d, "documents").select("doc_id", "text")
    labels = load(spark, d, "labels").where("quality IN (0, 1)").select("doc_id", F.col("quality").alias("cls"))
    return docs.join(labels, "doc_id").select(
        "cls",
        F.lpad(F.col("doc_id").cast("string"), 12, "0").alias("key"),
        F.array(F.char_length("text").cast("double") / 1000, F.size(F.split("text", " ", -1)).cast("double") / 100).alias("features"),
    )


GAP = "1 + (0.3 * x.f0 - 0.2 * x.f1) - (0.3 * z.f0 - 0.2 * z.f1)"


def _grad_sql(source, count="count(*)"):
    return f"""SELECT {count} AS pairs, round(avg(greatest(0, {GAP})), 7) AS loss,
round(avg(CASE WHEN {GAP} > 0 THEN x.f0 - z.f0 ELSE 0 END), 7) AS g0, round(avg(CASE WHEN {GAP} > 0 THEN x.f1 - z.f1 ELSE 0 END), 7) AS g1 FROM {source}"""


@query(f"WITH {DOCS} " + _grad_sql("s x JOIN s z ON x.sample = 0 AND z.sample = 1"))
def gd_step(spark, d):
    """The complete gradient, without pairs."""
    return rounded(L.full_gradient(quality_rows(spark, d), W), 7, "loss", "g0", "g1")


def _numbered(spark, d):
    return number_rows(quality_rows(spark, d).withColumnRenamed("cls", "sample"))


def _lookup(drawn, s):
    x = s.where("sample = 0").select(F.col("idx").alias("i"), F.col("features").alias("fx"))
    z = s.where("sample = 1").select(F.col("idx").alias("j"), F.col("features").alias("fz"))
    return drawn.join(x, "i").join(z, "j")


@query(
    f"""WITH {DOCS}, n AS (SELECT *, row_number() OVER (PARTITION BY sample ORDER BY key) - 1 AS idx FROM s),
c AS (SELECT count(*) FILTER (sample = 0) AS n, count(*) FILTER (sample = 1) AS m FROM s),
p AS (SELECT b, {ku(str(SEED), "'pair'", '0', 'b')} % n AS i, {ku(str(SEED), "'pair'", '1', 'b')} % m AS j FROM (SELECT unnest(range(500)) AS b), c) """
    + _grad_sql("p JOIN n x ON x.sample = 0 AND x.idx = i JOIN n z ON z.sample = 1 AND z.idx = j")
)
def sgd_central_step(spark, d):
    s = _numbered(spark, d)
    k = sizes(s)
    return rounded(L.hinge_pairs_gradient(_lookup(draws(spark, 500, k[0], k[1], SEED), s), W), 7, "loss", "g0", "g1")


@query(
    f"""WITH {DOCS}, k AS (SELECT *, row_number() OVER (PARTITION BY sample ORDER BY {ku(str(SEED), "'rows'", "concat_ws('|', sample, key)")}, key) AS r FROM s) """
    + _grad_sql("k x JOIN k z ON x.sample = 0 AND z.sample = 1 AND x.r <= 20 AND z.r <= 30")
)
def sgd_subsample_step(spark, d):
    from ..functions.keyed import sample_rows

    s = quality_rows(spark, d)
    parts = {c: sample_rows(s.where(F.col("cls") == c), F.concat_ws("|", F.lit(str(c)), F.col("key")), n, SEED) for c, n in ((0, 20), (1, 30))}
    pairs = parts[0].select(F.col("features").alias("fx")).crossJoin(parts[1].select(F.col("features").alias("fz")))
    return rounded(L.hinge_pairs_gradient(pairs, W), 7, "loss", "g0", "g1")


def _part(k):
    c = f"(SELECT count(*) FROM s WHERE sample = {k})"
    return f"({c} // 5 + CASE WHEN k.worker < {c} % 5 THEN 1 ELSE 0 END)"


@query(
    f"""WITH {DOCS}, {ranked_sql('s', 5, 1)}, p AS (
  SELECT k.worker, b, {ku(str(SEED), "'step'", 'k.worker', '0', 'b')} % {_part(0)} AS i, {ku(str(SEED), "'step'", 'k.worker', '1', 'b')} % {_part(1)} AS j
  FROM (SELECT unnest(range(5)) AS worker) k, (SELECT unnest(range({BATCH})) AS b)
), g AS (SELECT x.worker, """
    + _grad_sql("p JOIN w x ON x.sample = 0 AND x.worker = p.worker AND x.slot = i JOIN w z ON z.sample = 1 AND z.worker = p.worker AND z.slot = j").removeprefix("SELECT ").replace(", 7)", ", 12)")
    + """ GROUP BY x.worker)
SELECT round(0.3 - 0.01 * (avg(g0) + 2 * 0.05 * 0.3), 9) AS w0, round(-0.2 - 0.01 * (avg(g1) + 2 * 0.05 * -0.2), 9) AS w1, count(*) AS workers FROM g"""
)
def sgd_distributed_step(spark, d):
    """One step of distributed SGD: drawn pairs inside five workers, mean of their gradients,
    momentum from rest, L2."""
    s = quality_rows(spark, d).withColumnRenamed("cls", "sample")
    a = S.hash_rank(s, 5, 1, SEED)
    size = sizes(s)
    part = lambda k: F.lit(size[k] // 5) + F.when(F.col("worker") < size[k] % 5, 1).otherwise(0)
    p = spark.range(5).select(F.col("id").cast("int").alias("worker")).withColumn("b", F.explode(F.sequence(F.lit(0), F.lit(BATCH - 1))))
    p = p.select("worker", *[F.pmod(keyed_u64(SEED, "step", F.col("worker"), k, F.col("b")), part(k)).alias("ij"[k]) for k in (0, 1)])
    x = a.where("sample = 0").select("worker", F.col("slot").alias("i"), F.col("features").alias("fx"))
    z = a.where("sample = 1").select("worker", F.col("slot").alias("j"), F.col("features").alias("fz"))
    g = L.hinge_pairs_gradient(p.join(x, ["worker", "i"]).join(z, ["worker", "j"]), W, ("worker",))
    m = g.agg(F.avg("g0").alias("g0"), F.avg("g1").alias("g1"), F.count("*").alias("workers"))
    step = lambda w, c: F.round(F.lit(w) - 0.01 * (F.col(c) + 2 * 0.05 * w), 9)
    return m.select(step(W[0], "g0").alias("w0"), step(W[1], "g1").alias("w1"), "workers")


def _fit(spark, d, every, mode="lookup", iterations=6):
    train = L.standardized_features(quality_rows(spark, d), 2)
    w, trace = L.fit_sgd(train, [0.0, 0.0], iterations, 5, BATCH, every, SEED, mode)
    rows = [(0, it, rnd, "norm", v) for it, rnd, v in trace] + [(0, iterations, 0, f"w{k}", float(v)) for k, v in enumerate(w)]
    return spark.createDataFrame(rows, "run int, iteration int, round int, metric string, value double")


@query()
def sgd_static(spark, d):
    return _fit(spark, d, None)


@query()
def sgd_repartitioned(spark, d):
    return _fit(spark, d, 3)


@query()
def sgd_every_iteration(spark, d):
    return _fit(spark, d, 1, iterations=4)


@query()
def sgd_placed(spark, d):
    """The same run as sgd_repartitioned with rows placed on their workers, a job per iteration."""
    return _fit(spark, d, 3, "driver_sync")


@query()
def sgd_barrier(spark, d):
    """The same run as sgd_repartitioned, a barrier job per round."""
    return _fit(spark, d, 3, "barrier")


@query(
    """WITH k AS (SELECT count(*) AS rows FROM documents d JOIN labels l ON l.doc_id = d.doc_id WHERE quality IN (0, 1)), e AS (SELECT unnest([1, 25, 100, 0]) AS every)
SELECT CAST(every AS INTEGER) AS shuffle_every, CAST(CASE WHEN every = 0 THEN 1 ELSE ceil(200.0 / every) END AS BIGINT) AS shuffles,
CAST(rows * CASE WHEN every = 0 THEN 1 ELSE ceil(200.0 / every) END AS BIGINT) AS moved_rows, CAST(200 * 100 * 9 AS BIGINT) AS gradient_numbers, CAST(200 * 100 * 9 AS BIGINT) AS model_numbers FROM k, e"""
)
def sgd_communication(spark, d):
    """What 200 iterations of SGD over a hundred workers send, by the iterations between shuffles."""
    rows = quality_rows(spark, d).count()
    out = [(e or 0, *L.communication(rows, 200, e, 100, 9).values()) for e in (1, 25, 100, None)]
    return spark.createDataFrame(out, "shuffle_every int, shuffles long, moved_rows long, gradient_numbers long, model_numbers long")


def _loss_sql(c):
    a, b = c
    gap = f"1 + ({a} * x.f0 + {b} * x.f1) - ({a} * z.f0 + {b} * z.f1)"
    return f"(SELECT avg(greatest(0, {gap})) FROM s x JOIN s z ON x.sample = 0 AND z.sample = 1)"


CANDIDATES = [[0.3, -0.2], [0.0, 0.1], [-0.1, 0.0], [0.5, -2.0]]


@query(
    f"""WITH {DOCS}, c AS ({" UNION ALL ".join(f"SELECT {i} AS candidate, {_loss_sql(c)} AS loss" for i, c in enumerate(CANDIDATES))})
SELECT candidate, round(loss, 7) AS loss, loss = (SELECT min(loss) FROM c) AS best FROM c"""
)
def erm_select(spark, d):
    return rounded(L.erm_select(quality_rows(spark, d), CANDIDATES), 7, "loss")


@query(
    """WITH s AS (SELECT CAST(substr(o_orderpriority, 1, 1) AS INTEGER) AS y, o_totalprice / 100000 AS v FROM orders),
u AS (SELECT y AS pair, v + 1 AS t, 1 AS f, v FROM s WHERE y < 5 UNION ALL SELECT y - 1, v, 0, v FROM s WHERE y > 1),
c AS (SELECT pair, t, sum(f) AS nx, sum(1 - f) AS nz, sum((1 - f) * v) AS sz FROM u GROUP BY 1, 2),
b AS (SELECT *, coalesce(sum(nz) OVER w, 0) AS bn, coalesce(sum(sz) OVER w, 0) AS bs FROM c
  WINDOW w AS (PARTITION BY pair ORDER BY t ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING))
SELECT pair, round(sum(nx * (t * bn - bs)) / (CAST(sum(nx) AS DOUBLE) * sum(nz)), 7) AS loss FROM b GROUP BY 1"""
)
def multipartite_loss(spark, d):
    r = L.multipartite_loss(load(spark, d, "orders"), F.col("o_totalprice") / 100000, F.substring("o_orderpriority", 1, 1), 5)
    return rounded(r, 7, "loss")


@query(f"WITH {DOCS} SELECT key, round(0.3 * f0 - 0.2 * f1 + 0.5, 9) AS score FROM s")
def linear_score(spark, d):
    return quality_rows(spark, d).select("key", F.round(L.linear_score(F.col("features"), W, 0.5), 9).alias("score"))


@query(
    f"""WITH {DOCS}, r AS (SELECT *, row_number() OVER (PARTITION BY sample ORDER BY {ku(str(SEED), "'holdout'", 'key')}, key) AS r, count(*) OVER (PARTITION BY sample) AS n FROM s)
SELECT key, sample AS cls, r <= floor(n * 0.2) AS held_out FROM r"""
)
def holdout_split(spark, d):
    return L.stratified_holdout(quality_rows(spark, d), 0.2, SEED).select("key", "cls", "held_out")


@query(
    """SELECT p_partkey, round((p_size - avg(p_size) OVER ()) / stddev_samp(p_size) OVER (), 8) AS p_size,
round((p_retailprice - avg(p_retailprice) OVER ()) / stddev_samp(p_retailprice) OVER (), 8) AS p_retailprice FROM part"""
)
def standardize(spark, d):
    p = load(spark, d, "part").select("p_partkey", F.col("p_size").cast("double").alias("p_size"), "p_retailprice")
    return rounded(L.standardize(p, ["p_size", "p_retailprice"]), 8, "p_size", "p_retailprice")


# ------------------------------------------------------------------ learning curves


def planted(spark, d, hard: bool = True, share: float = 0.07):
    """Lines with nine standardised numbers; a hidden linear rule with keyed noise names the top
    `share` anomalies; in the hard variant a keyed 3 % of rows are flipped and blown up. The lines are joined
    once and kept on disk; neither orders nor parts are broadcast, since both grow with the lines."""
    li, o, p = (load(spark, d, t) for t in ("lineitem", "orders", "part"))
    rows = li.join(o.select(F.col("o_orderkey").alias("l_orderkey"), "o_totalprice", "o_orderdate").hint("merge"), "l_orderkey").join(
        p.select(F.col("p_partkey").alias("l_partkey"), "p_size", "p_retailprice").hint("merge"), "l_partkey"
    )
    cols = {
        "f0": F.col("l_quantity"), "f1": F.col("l_extendedprice"), "f2": F.col("l_discount"), "f3": F.col("l_tax"), "f4": F.col("l_linenumber"),
        "f5": F.datediff("l_shipdate", "o_orderdate"), "f6": F.col("o_totalprice"), "f7": F.col("p_size"), "f8": F.col("p_retailprice"),
    }
    key = F.concat_ws("|", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", F.round(F.col("l_extendedprice") * 100).cast("long"))
    df = kept(rows.select(key.alias("key"), *[v.cast("double").alias(k) for k, v in cols.items()]), StorageLevel.DISK_ONLY)
    df = L.standardize(df, list(cols), keep=True)
    hidden = [0.9, -0.7, 0.5, 0.3, -0.2, 0.6, -0.4, 0.8, 0.1]
    noise = (F.shiftright(keyed_u64(SEED, "noise", F.col("key")), 30) / float(1 << 30) - 0.5) * 0.8
    df = df.withColumn("rule", sum((F.col(f"f{k}") * h for k, h in enumerate(hidden)), noise))
    cut = df.approxQuantile("rule", [1 - share], 0.001)[0]
    factor = F.when(keyed_u64(SEED, "hard", F.col("key")) % 100 < 3, -30.0).otherwise(1.0) if hard else F.lit(1.0)
    return df.select((F.col("rule") > cut).cast("int").alias("cls"), "key", F.array(*[F.col(f"f{k}") * factor for k in range(9)]).alias("features"))


def curves(spark, rows, runs: int, iterations: int, workers: int, batch: int, every: tuple, limit: int | None = None):
    """Learning curves on all rows, or on a keyed subset of `limit`, a fifth held out. The runs
    share one copy of up to 256 MB of rows; more are stored, and runs look up the rows that they draw."""
    points = max(1, iterations // 6)
    if limit is None and rows.count() * len(rows.select("features").first().features) * 8 > L.BROADCAST_ROWS:
        out = L.simulate_stored(rows, 0.2, runs, iterations, workers, batch, every, SEED, eval_every=points)
        release()
        return out
    sub = rows if limit is None else rows.orderBy(keyed_u64(SEED, "subset", F.col("key")), "key").limit(limit)
    data = L.stratified_holdout(sub, 0.2, SEED).orderBy("key").select("cls", "held_out", "features").toArrow()
    features = data.column("features").combine_chunks()
    features = features.flatten().to_numpy().reshape(len(features), -1)
    cls, held = data.column("cls").to_numpy(), data.column("held_out").to_numpy()
    pick = lambda c, h: features[(cls == c) & (held == h)]
    release()
    return L.simulate(spark, pick(0, False), pick(1, False), pick(0, True), pick(1, True), runs, iterations, workers, batch, every, SEED, eval_every=points)


@query()
def learning_curves(spark, d, runs: int = 6, iterations: int = 60):
    """Median and band over runs, shuffling every 1, 25 or no iterations, hard planted rows, all lines."""
    t = curves(spark, planted(spark, d), runs, iterations, 20, 50, (1, 25, None))
    return bands(t, ("shuffle_every", "iteration", "metric"))


@query()
def learning_curves_replica(spark, d, runs: int = 100, iterations: int = 200):
    """The experiment's size: 49,000 rows, 100 workers, 100 pairs a worker, 100 runs, shuffles every
    1, 5, 25, 100 or no iterations."""
    t = curves(spark, planted(spark, d), runs, iterations, 100, 100, (1, 5, 25, 100, None), 49_000)
    return bands(t, ("shuffle_every", "iteration", "metric"))


@query()
def learning_curves_small_parts(spark, d, runs: int = 40, iterations: int = 300):
    """The regime where shuffles matter most: 20 workers with a few rows of each class, so that fixed
    parts hold a small part of all pairs. Bands narrow and medians improve with more shuffles."""
    rows = planted(spark, d, hard=False, share=0.4)
    t = curves(spark, rows, runs, iterations, 20, 20, (1, 25, None), 125)
    return bands(t, ("shuffle_every", "iteration", "metric"))


def quality_features(spark, d):
    """Labelled documents with the nine features of FIXTURES F6, standardised."""
    from .function_queries import fn_doc_features

    rows = quality_rows(spark, d).select("cls", "key", F.col("key").cast("long").alias("doc_id"))
    nine = fn_doc_features(spark, d).select("doc_id", F.array(*[f"f{k}" for k in range(9)]).alias("features"))
    return L.standardized_features(rows.join(nine, "doc_id"), 9)


@query()
def learning_curves_quality(spark, d, runs: int = 6, iterations: int = 60):
    t = curves(spark, quality_features(spark, d), runs, iterations, 5, 20, (1, 25, None))
    return bands(t, ("shuffle_every", "iteration", "metric"))


@query()
def learning_curves_planted(spark, d, runs: int = 6, iterations: int = 60):
    """The planted rule without hard rows."""
    t = curves(spark, planted(spark, d, hard=False), runs, iterations, 20, 50, (1, 25, None))
    return bands(t, ("shuffle_every", "iteration", "metric"))


@query()
def learning_curves_null(spark, d, runs: int = 6, iterations: int = 60):
    """Null control: one label of the embeddings, which nothing predicts; areas stay near a half."""
    e = load(spark, d, "embeddings")
    rows = e.select(
        (F.col("label") == 0).cast("int").alias("cls"),
        F.lpad(F.col("vec_id").cast("string"), 12, "0").alias("key"),
        F.transform(F.slice("embedding", 1, 9), lambda x: x.cast("double") * 8).alias("features"),
    )
    t = curves(spark, rows, runs, iterations, 5, 20, (1, 25, None))
    return bands(t, ("shuffle_every", "iteration", "metric"))


@query(
    """SELECT CAST(it AS INTEGER) AS iteration, count(*) AS runs, round(quantile_cont(v, 0.05), 9) AS low, round(median(v), 9) AS median, round(quantile_cont(v, 0.95), 9) AS high
FROM (SELECT run, it, sin(run + it / 7.0) AS v FROM (SELECT unnest(range(40)) AS run), (SELECT unnest(range(5)) AS it)) GROUP BY it"""
)
def trace_bands(spark, d):
    """Bands over forty runs of a known curve."""
    rows = [(run, it, float(np.sin(run + it / 7))) for run in range(40) for it in range(5)]
    t = spark.createDataFrame(rows, "run int, iteration int, value double")
    return rounded(bands(t, ("iteration",)), 9, "low", "median", "high")
