"""Statistics over streams of scored events: windowed areas, sessions, and a running
within-worker average over reservoirs."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..functions.keyed import keyed_u64


def window_counts(df: DataFrame, time: str, score: Column, positive: Column, window: str, slide: str | None = None, watermark: str | None = None) -> DataFrame:
    """start, score, pos, neg per window and distinct score: works on streams and tables alike.
    State per open window is its distinct scores."""
    if watermark:
        df = df.withWatermark(time, watermark)
    w = F.window(time, window, slide) if slide else F.window(time, window)
    return (
        df.select(w.alias("w"), score.alias("score"), positive.cast("long").alias("y"))
        .groupBy("w", "score")
        .agg(F.sum("y").alias("pos"), F.sum(1 - F.col("y")).alias("neg"))
        .select(F.col("w.start").alias("start"), "score", "pos", "neg")
    )


def auc_of_counts(counts: DataFrame) -> DataFrame:
    """start, n, m, wins, auc per window from its counts (a table)."""
    before = Window.partitionBy("start").orderBy("score").rowsBetween(Window.unboundedPreceding, -1)
    ranked = counts.withColumn("b", F.coalesce(F.sum("neg").over(before), F.lit(0)))
    nm = F.col("n").cast("double") * F.col("m")
    return (
        ranked.groupBy("start")
        .agg(F.sum("pos").alias("n"), F.sum("neg").alias("m"), F.sum(F.col("pos") * F.col("b")).alias("wins"))
        .withColumn("auc", F.when(nm > 0, F.col("wins") / nm))
    )


def session_stats(df: DataFrame, key: str, time: str, value: str, gap: str, watermark: str | None = None) -> DataFrame:
    """key, start, events, total per session that `gap` closes."""
    if watermark:
        df = df.withWatermark(time, watermark)
    return (
        df.groupBy(key, F.session_window(time, gap).alias("w"))
        .agg(F.count("*").alias("events"), F.sum(value).alias("total"))
        .select(key, F.col("w.start").alias("start"), "events", "total")
    )


def split_late(df: DataFrame, time: str, arrival: str, delay: str) -> DataFrame:
    """`df` with late: behind the largest time that has arrived before it by more than `delay`
    (what a watermark would drop), for a table with arrival order in days."""
    day = F.to_date(arrival)
    per_day = Window.partitionBy("_day").orderBy(arrival).rowsBetween(Window.unboundedPreceding, -1)
    by_day = df.groupBy(day.alias("_day")).agg(F.max(time).alias("_top"))
    earlier = Window.orderBy("_day").rowsBetween(Window.unboundedPreceding, -1)  # one row per day
    tops = by_day.withColumn("_before", F.max("_top").over(earlier)).drop("_top")
    top = F.greatest(F.max(time).over(per_day), F.col("_before"))
    out = df.withColumn("_day", day).join(F.broadcast(tops), "_day")
    return out.withColumn("late", F.coalesce(F.col(time) < top - F.expr(f"interval {delay}"), F.lit(False))).drop("_day", "_before")


def local_auc_stream(stream: DataFrame, key: str, score: str, positive: str, workers: int, reservoir: int, seed: int) -> DataFrame:
    """worker, seen, pairs, wins, auc: every logical worker keeps two bounded reservoirs and the
    win count of arrivals against the other class's reservoir. State is workers * 2 * reservoir
    scores; an arrival costs one search."""
    rows = stream.select(
        F.pmod(keyed_u64(seed, "stream", F.col(key)), F.lit(workers)).cast("int").alias("worker"),
        F.col(key).cast("string").alias("k"),
        F.col(score).cast("double").alias("s"),
        F.col(positive).cast("boolean").alias("y"),
    )

    def update(worker: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        seen, pairs, wins, pos, neg = state.get if state.exists else (0, 0, 0, [], [])
        pos, neg = list(pos), list(neg)
        for f in frames:
            for k, s, y in f.sort_values("k")[["k", "s", "y"]].itertuples(index=False):
                other = np.asarray(neg if y else pos)
                pairs += len(other)
                wins += int((other < s).sum() if y else (other > s).sum())
                mine = pos if y else neg
                seen += 1
                if len(mine) < reservoir:
                    mine.append(s)
                else:
                    at = hash((seed, seen, k)) % seen
                    if at < reservoir:
                        mine[at] = s
        state.update((seen, pairs, wins, pos, neg))
        yield pd.DataFrame({"worker": [worker[0]], "seen": [seen], "pairs": [pairs], "wins": [wins], "auc": [wins / pairs if pairs else float("nan")]})

    return rows.groupBy("worker").applyInPandasWithState(
        update,
        "worker int, seen long, pairs long, wins long, auc double",
        "seen long, pairs long, wins long, pos array<double>, neg array<double>",
        "update",
        GroupStateTimeout.NoTimeout,
    )


ROCKS = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"


def run_to_files(stream: DataFrame) -> DataFrame:
    """All of a bounded stream through a file sink in the shared folder, keyed state on disk; the result as
    a table of those files."""
    from ..sources.catalog import shared_dir

    spark = stream.sparkSession
    path, name = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}", "spark.sql.streaming.stateStore.providerClass"
    before = spark.conf.get(name)
    spark.conf.set(name, ROCKS)
    try:
        query = stream.writeStream.format("parquet").option("path", f"{path}/rows").option("checkpointLocation", f"{path}/state")
        query.outputMode("append").trigger(availableNow=True).start().awaitTermination()
    finally:
        spark.conf.set(name, before)
    return spark.read.schema(stream.schema).parquet(f"{path}/rows")


def run_to_end(stream: DataFrame, mode: str = "complete") -> DataFrame:
    """All of a bounded stream through the memory sink; the result as a table."""
    name = f"stream_{uuid.uuid4().hex}"
    query = stream.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    query.awaitTermination()
    return stream.sparkSession.table(name)
