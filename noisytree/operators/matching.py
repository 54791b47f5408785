"""Private blocking for record matching between two parties.

One party releases a tree whose whole count budget is in the leaves. Pairs whose leaves, grown by the
distance threshold, do not meet can be left out of the secure computation. The protocol around it is
not described by the reference; assumed here: only leaves with a positive noisy count take part, each as
many times as its noisy count, rounded up.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from noisytree.plans.domain import Domain


def near_boxes(domain: Domain, theta: tuple[float, ...]):
    """The point of b lies within the threshold of the leaf's box."""
    parts = [(F.col(f"b_{a.name}") >= F.col(f"{a.name}0") - t) & (F.col(f"b_{a.name}") <= F.col(f"{a.name}1") + t) for a, t in zip(domain.axes, theta, strict=True)]
    return reduce(lambda p, q: p & q, parts)


def blocked(leaves: DataFrame, b: DataFrame, domain: Domain, theta: tuple[float, ...]) -> DataFrame:
    """node_id, y, n_b: of each leaf that takes part, how many points of b it has to be compared with."""
    live = leaves.where("y > 0").select("node_id", "y", *domain.box)
    other = b.select(*[F.col(n).alias(f"b_{n}") for n in domain.names])
    # Leaves are few against points: the released side is broadcast.
    return other.join(F.broadcast(live), near_boxes(domain, theta)).groupBy("node_id", "y").agg(F.count("*").alias("n_b"))


def reduction_ratio(leaves: DataFrame, a: DataFrame, b: DataFrame, domain: Domain, theta: tuple[float, ...]) -> DataFrame:
    """ratio: one less the share of all pairs that is left."""
    left = blocked(leaves, b, domain, theta).agg(F.coalesce(F.sum(F.ceil("y") * F.col("n_b")), F.lit(0)).alias("left"))
    sizes = a.agg(F.count("*").alias("na")).join(b.agg(F.count("*").alias("nb")))
    return left.join(sizes).select(F.greatest(F.lit(0.0), 1 - F.col("left") / (F.col("na") * F.col("nb"))).alias("ratio"))


def matching_recall(leaves: DataFrame, a_leaf: DataFrame, b: DataFrame, domain: Domain, theta: tuple[float, ...]) -> DataFrame:
    """recall: true matches of a and b (all axes within theta) whose leaf takes part. a_leaf: points of a, node_id."""
    other = b.select(*[F.col(n).alias(f"b_{n}") for n in domain.names])
    close = reduce(lambda p, q: p & q, [F.abs(F.col(n) - F.col(f"b_{n}")) <= t for n, t in zip(domain.names, theta, strict=True)])
    # An equi-join on cells as wide as the threshold where it has a width, else on the value itself.
    keys_a, keys_b = [], []
    for n, t in zip(domain.names, theta, strict=True):
        cell = lambda c, t=t: F.floor(c / t) if t > 0 else c
        keys_a.append(F.array(*[cell(F.col(n)) + k for k in (-1, 0, 1)]) if t > 0 else F.array(F.col(n)))
        keys_b.append(cell(F.col(f"b_{n}")))
    for i, k in enumerate(keys_a):
        a_leaf = a_leaf.withColumn(f"_k{i}", F.explode(k))
        other = other.withColumn(f"_k{i}", keys_b[i])
    pairs = a_leaf.join(other, [f"_k{i}" for i in range(len(keys_a))]).where(close)
    live = leaves.where("y > 0").select("node_id", F.lit(1).alias("live"))
    return pairs.join(F.broadcast(live), "node_id", "left").agg(F.coalesce(F.avg(F.coalesce("live", F.lit(0)).cast("double")), F.lit(1.0)).alias("recall"))
