"""Pair-free forms over all orders and parts of the queries that join pairs of a smaller table.

They have no SQL: tests compare them with brute force on the smallest tables. Counts that grow with a
power of the rows are doubles."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import schemes as S
from ..operators import sorted_forms as Q
from ..operators.samples import as_sample
from ..sources.catalog import load
from .base import SEED, query, rounded
from .kernel_queries import _status_label


@query()
def u_complete_d2_whole(spark, d):
    return rounded(Q.squared_difference(load(spark, d, "orders"), F.round("o_totalprice")), 3, "estimate")


@query()
def u_complete_d3_whole(spark, d):
    """Mean range of three sizes, from the number of triples whose largest (smallest) is each value."""
    sizes = load(spark, d, "part").where("p_size IS NOT NULL").groupBy(F.col("p_size").alias("v")).agg(F.count("*").cast("double").alias("c"))
    three = lambda n: n * (n - 1) * (n - 2) / 6
    ranked = Q.prefix_sums(sizes, "v", ("c",)).join(F.broadcast(sizes.agg(F.sum("c").alias("n"))))
    below, to = F.col("before_c"), F.col("before_c") + F.col("c")
    largest = three(to) - three(below)
    smallest = three(F.col("n") - below) - three(F.col("n") - to)
    r = ranked.agg(F.max(three(F.col("n"))).alias("tuples"), F.sum(F.col("v") * (largest - smallest)).alias("total"))
    return r.select("tuples", "total", F.round(F.col("total") / F.col("tuples"), 9).alias("estimate"))


@query()
def u_repartitioned_k3_whole(spark, d):
    """Rising chains of three inside workers: two prefix sums in each worker."""
    o = load(spark, d, "orders").withColumn("y", _status_label().cast("int") - 1).where("y >= 0 AND o_totalprice IS NOT NULL")
    s = o.select(F.col("y").alias("sample"), F.lpad(F.col("o_orderkey").cast("string"), 12, "0").alias("key"), F.col("o_totalprice").alias("score"))
    by = ("round", "worker")
    cur = S.hash_rank(s, 5, 2, SEED).groupBy(*by, "score").agg(
        *[F.sum((F.col("sample") == c).cast("double")).alias(f"n{c}") for c in range(3)]
    )
    cur = Q.prefix_sums(cur, "score", ("n0",), by, local=True).withColumn("two", F.col("n1") * F.col("before_n0"))
    cur = Q.prefix_sums(cur, "score", ("two",), by, local=True)
    r = cur.groupBy(*by).agg(
        (F.sum("n0") * F.sum("n1") * F.sum("n2")).alias("tuples"), F.sum(F.col("n2") * F.col("before_two")).alias("wins")
    )
    return r.withColumn("value", F.round(F.when(F.col("tuples") > 0, F.col("wins") / F.col("tuples")).otherwise(0.0), 9))


@query()
def u_repartitioned_d2_whole(spark, d):
    """Mean absolute difference inside workers, from ordered weights."""
    key = F.lpad(F.col("o_orderkey").cast("string"), 12, "0")
    s = as_sample(load(spark, d, "orders"), 0, key, F.round("o_totalprice"))
    by, c, v = ("round", "worker"), F.col("c"), F.col("score")
    cur = S.hash_rank(s, 5, 3, SEED).groupBy(*by, "score").agg(F.count("*").cast("double").alias("c"))
    cur = Q.prefix_sums(cur.withColumn("w", c * v), "score", ("c", "w"), by, local=True)
    r = cur.groupBy(*by).agg(
        (F.sum("c") * (F.sum("c") - 1) / 2).cast("long").alias("tuples"), F.sum(c * (v * F.col("before_c") - F.col("before_w"))).alias("total")
    )
    return r.withColumn("value", F.round(F.when(F.col("tuples") > 0, F.col("total") / F.col("tuples")).otherwise(0.0), 6))
