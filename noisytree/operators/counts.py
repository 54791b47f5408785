"""Exact counts of nodes, and noisy ones.

One scan counts the leaves (partial sums in each task, so skew does no harm); all upper levels come from
leaf counts. True counts live in private frames only: add_noise drops them.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from noisytree.functions.cells import enumerate_nodes, leaf_of
from noisytree.functions.noise import DEFAULT, Noise
from noisytree.plans.domain import Domain


def leaf_counts(points: DataFrame, domain: Domain, h: int) -> DataFrame:
    """node_id, c of the leaves of a midpoint tree that hold points."""
    return leaf_of(points, domain, h).groupBy("node_id").agg(F.count("*").alias("c"))


def all_levels(leaves: DataFrame, h: int, bits: int) -> DataFrame:
    """level, node_id, c of all nodes that hold points. bits: of a child's digit."""
    up = leaves.select(F.explode(F.sequence(F.lit(0), F.lit(h))).alias("level"), "node_id", "c")
    return up.groupBy("level", F.expr(f"shiftright(node_id, {bits} * level)").alias("node_id")).agg(F.sum("c").alias("c"))


def complete(counts: DataFrame, h: int, f: int) -> DataFrame:
    """counts with the nodes that hold no point."""
    nodes = enumerate_nodes(counts.sparkSession, h, f)
    return nodes.join(counts, ["level", "node_id"], "left").withColumn("c", F.coalesce("c", F.lit(0).cast("long")))


def tree_counts(points: DataFrame, domain: Domain, h: int) -> DataFrame:
    """level, node_id, c of the complete midpoint tree."""
    return complete(all_levels(leaf_counts(points, domain, h), h, domain.d), h, 1 << domain.d)


def by_rollup(points: DataFrame, domain: Domain, h: int) -> DataFrame:
    """d1 (digit below the root), ..., dh, gid, c: the tree's paths as a rollup of digits."""
    digit = lambda k: F.shiftright("node_id", domain.d * (h - k)).bitwiseAND(F.lit((1 << domain.d) - 1).cast("long")).alias(f"d{k}")
    leaves = leaf_counts(points, domain, h).select(*[digit(k) for k in range(1, h + 1)], "c")
    return leaves.rollup(*[f"d{k}" for k in range(1, h + 1)]).agg(F.grouping_id().cast("long").alias("gid"), F.sum("c").alias("c"))


def level_value(values: list[float]) -> Column:
    """The entry of the row's level."""
    return F.element_at(F.array(*[F.lit(float(v)) for v in values]), F.col("level") + 1)


def add_noise(counts: DataFrame, eps_levels: list[float], tree: str, noise: Noise = DEFAULT, integer: bool = False) -> DataFrame:
    """counts with eps_count and y, without c. Levels without budget release no count (y is null)."""
    funded = [i for i, e in enumerate(eps_levels) if e > 0]
    eps = level_value(eps_levels)
    key = ("cnt", tree, F.col("level"), F.col("node_id"))
    noisy = F.col("c") + (noise.two_sided_geometric(eps, *key) if integer else noise.laplace(1 / eps, *key))
    return counts.withColumn("eps_count", eps).withColumn("y", F.when(F.col("level").isin(funded), noisy.cast("double"))).drop("c")


def grid_counts(points: DataFrame, domain: Domain, shape: tuple[int, ...]) -> DataFrame:
    """cell_id, c of a flat grid, empty cells included; the last axis varies fastest."""
    from noisytree.functions.cells import axis_cell, valid

    cell = reduce(lambda acc, p: acc * p[1] + p[0], [(axis_cell(F.col(a.name), a, n), n) for a, n in zip(domain.axes, shape, strict=True)], F.lit(0).cast("long"))
    total = reduce(lambda a, b: a * b, shape)
    counts = valid(points, domain).groupBy(cell.alias("cell_id")).agg(F.count("*").alias("c"))
    cells = points.sparkSession.range(total).select(F.col("id").alias("cell_id"))
    return cells.join(counts, "cell_id", "left").withColumn("c", F.coalesce("c", F.lit(0).cast("long")))


def grid_noisy(points: DataFrame, domain: Domain, shape: tuple[int, ...], eps: float, tree: str = "grid", noise: Noise = DEFAULT) -> DataFrame:
    counts = grid_counts(points, domain, shape)
    return counts.select("cell_id", (F.col("c") + noise.laplace(1 / eps, "cell", tree, F.col("cell_id"))).alias("y"))
