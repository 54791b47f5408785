"""Pruning by released counts: what lies beneath a node with fewer than m is dropped. True counts are out of reach here."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def by_noisy_count(nodes: DataFrame, m: float | None, h: int, bits: int = 2, value: str = "beta") -> DataFrame:
    """nodes that stay, with is_leaf. m None: all stay."""
    if m is None:
        return nodes.withColumn("is_leaf", F.col("level") == 0)
    low = nodes.where(F.col(value) < m).select(F.col("level").alias("up"), F.col("node_id").alias("anc"))
    # A node goes if any strict ancestor is low: one join of (level, ancestor) pairs, whatever the height.
    up = nodes.where(F.col("level") < h).select("level", "node_id", F.explode(F.sequence(F.col("level") + 1, F.lit(h))).alias("up"))
    gone = up.withColumn("anc", F.expr(f"shiftright(node_id, {bits} * (up - level))")).join(low, ["up", "anc"], "left_semi").select("level", "node_id").distinct()
    return nodes.join(gone, ["level", "node_id"], "left_anti").withColumn("is_leaf", (F.col("level") == 0) | (F.col(value) < m))


def by_area(nodes: DataFrame, least: float, names: list[str]) -> DataFrame:
    """Nodes whose parents are no smaller than ``least``; a node smaller than it is a leaf. Boxes are public, so this
    rule may be applied to any release (parents' boxes as p...; null at the root)."""
    from functools import reduce

    area = lambda p: reduce(lambda a, b: a * b, [F.col(f"{p}{n}1") - F.col(f"{p}{n}0") for n in names])
    root = F.col(f"p{names[0]}0").isNull()
    return nodes.where(root | (area("p") >= least)).withColumn("is_leaf", F.col("is_leaf") | (area("") < least))
