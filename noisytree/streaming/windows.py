"""Releases over windows of a stream of points.

Windows are disjoint, so each may spend the whole budget (event level); a sliding window's event is in
several, which share it. Only append output can be released: a window is final once the watermark has
passed it, late rows are dropped by then, and noise is keyed by window, level and node, so a replayed batch
releases what it released before.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from noisytree.functions.cells import enumerate_nodes, leaf_of
from noisytree.functions.noise import DEFAULT, Noise
from noisytree.operators.counts import level_value
from noisytree.plans.domain import Domain


def tumbling_leaves(points: DataFrame, domain: Domain, h: int, ts: str = "ts", length: str = "1 day", late: str | None = "1 hour") -> DataFrame:
    """win_start, node_id, c: works on batches and streams alike."""
    p = points.withWatermark(ts, late) if late and points.isStreaming else points
    return leaf_of(p, domain, h).groupBy(F.window(ts, length).alias("w"), "node_id").agg(F.count("*").alias("c")).select(F.col("w.start").alias("win_start"), "node_id", "c")


def window_trees(leaves: DataFrame, h: int, bits: int, eps_levels: list[float], tree: str = "win", noise: Noise = DEFAULT) -> DataFrame:
    """win_start, level, node_id, y: the complete noisy tree of each window in leaves."""
    up = leaves.withColumn("level", F.explode(F.sequence(F.lit(0), F.lit(h))))
    got = up.groupBy("win_start", "level", F.expr(f"shiftright(node_id, {bits} * level)").alias("node_id")).agg(F.sum("c").alias("c"))
    windows = leaves.select("win_start").distinct()
    every = windows.crossJoin(F.broadcast(enumerate_nodes(leaves.sparkSession, h, 1 << bits)))
    full = every.join(got, ["win_start", "level", "node_id"], "left").withColumn("c", F.coalesce("c", F.lit(0).cast("long")))
    eps = level_value(eps_levels)
    return full.select("win_start", "level", "node_id", (F.col("c") + noise.laplace(1 / eps, "cnt", tree, F.col("level"), F.col("node_id"), epoch(F.col("win_start")))).alias("y"))


def epoch(ts: Column) -> Column:
    """Seconds since 1970 of a wall clock."""
    day = F.datediff(ts.cast("date"), F.lit("1970-01-01").cast("date")).cast("long")
    return day * 86_400 + F.hour(ts) * 3600 + F.minute(ts) * 60 + F.second(ts)


def release_stream(points: DataFrame, domain: Domain, h: int, eps_levels: list[float], sink, checkpoint: str, ts: str = "ts", length: str = "1 day", late: str = "1 hour", noise: Noise = DEFAULT):
    """A started query that hands each final window's noisy tree to sink(batch, batch_id)."""
    if not points.isStreaming:
        raise ValueError("points must be a stream; use window_trees on batches")

    def each(batch: DataFrame, batch_id: int) -> None:
        sink(window_trees(batch, h, domain.d, eps_levels, "win", noise), batch_id)

    leaves = tumbling_leaves(points, domain, h, ts, length, late)
    return leaves.writeStream.outputMode("append").option("checkpointLocation", checkpoint).foreachBatch(each).trigger(availableNow=True).start()


def sliding_counts(points: DataFrame, ts: str = "ts", length: str = "1 day", slide: str = "6 hours") -> DataFrame:
    return points.groupBy(F.window(ts, length, slide).alias("w")).agg(F.count("*").alias("c")).select(F.col("w.start").alias("win_start"), "c")


def sliding_share(eps: float, length_hours: float, slide_hours: float) -> float:
    """Budget of one window: an event is in so many of them."""
    import math

    return eps / math.ceil(length_hours / slide_hours)


def session_counts(points: DataFrame, user: str = "user_id", ts: str = "ts", gap: str = "30 minutes") -> DataFrame:
    """user, start, c by session: bounds follow the data, so these are not for release."""
    return points.groupBy(user, F.session_window(ts, gap).alias("w")).agg(F.count("*").alias("c")).select(user, F.col("w.start").alias("start"), "c")


def bounded(points: DataFrame, k: int, user: str = "user_id", order: str = "event_id") -> DataFrame:
    """At most k rows a user, the first by order: a user then spends k times a row's budget."""
    w = Window.partitionBy(user).orderBy(order)
    return points.withColumn("_k", F.row_number().over(w)).where(F.col("_k") <= k).drop("_k")
