"""Connected components of an edge table, distributed, for graphs made of stars and short chains.

Alternates two steps until nothing changes: every node hooks its larger neighbours to the
smallest node it sees, then its smaller neighbours. Both are an aggregate with a map-side part
and a join; the number of rounds grows with the logarithm of the longest chain. Only counts come
to the driver. Each round is written to the shared folder, so a lost executor costs one round.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import discard, staged


#: A node with more edges than this, and than a thousandth of all, is a hub.
HUB_EDGES = 64


def _hook(edges: DataFrame, total: int, larger: bool) -> DataFrame:
    """Edges (u, v), u > v, after one step; `larger`: hook larger neighbours, else the smaller.

    Edges find their node's least neighbour by a join on the node. Hubs (at most 2,048 of them,
    each having more than a thousandth of `total` edges) are broadcast, so that the edges of a
    giant component's centre stay where they are."""
    seen = edges.select("u", "v")
    if larger:
        seen = seen.union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = seen.groupBy("u").agg(F.min("v").alias("m"), F.count("*").alias("k")).select("u", F.least("u", "m").alias("m"), "k")
    most = max(HUB_EDGES, total // 1024)
    hubs = least.where(F.col("k") > most).select("u", F.col("m").alias("hub_m"))
    rest = least.where(F.col("k") <= most).select("u", "m")
    marked = seen.join(F.broadcast(hubs), "u", "left")
    joined = marked.where("hub_m IS NOT NULL").select("u", "v", F.col("hub_m").alias("m")).union(
        marked.where("hub_m IS NULL").select("u", "v").join(rest, "u").select("u", "v", "m")
    )
    if larger:
        out = joined.where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
    else:
        out = joined.select(F.col("v").alias("u"), F.col("m").alias("v")).union(
            least.select("u", F.col("m").alias("v"))
        )
    return out.where("u <> v").distinct()


def connected(edges: DataFrame) -> DataFrame:
    """id, component for every node of `edges` (a, b: long), component being its smallest node.

    Nulls and self-loops are ignored; repeated and reversed edges are one; no edges, no rows.
    """
    now = staged(
        edges.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct(),
        "edges",
    )
    mark, total = None, now.count()
    while True:
        half = staged(_hook(now, total, True), "edges")
        nxt = staged(_hook(half, total, False), "edges")
        discard(half)
        # Stars only: every node has one edge, and no node is both a centre and a leaf.
        row = nxt.agg(
            F.count("*").alias("n"),
            F.countDistinct("u").alias("leaves"),
            F.expr("bit_xor(xxhash64(u, v))").alias("x"),
        ).first()
        discard(now)
        now = nxt
        if row.n == row.leaves and (row.n, row.x) == mark:
            break
        mark, total = (row.n, row.x), row.n
    return now.select(F.col("u").alias("id"), F.col("v").alias("component")).union(
        now.select("v", "v").distinct()
    )
