"""Least-squares counts of a noisy tree: consistent sums, least variance among linear unbiased ones.

For levels with budgets e_l (leaf: 0) let w_l = e_l**2 and E_l = sum over i <= l of f**i w_i. Two passes:
up, S of a node is f**l w_l y plus its children's S; down, the node's value is (S + f**l D) / E_l, where D
sums w (y - value) over its strict ancestors.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from noisytree.operators.durable import BROADCAST_NODES, durable


def prefix_weights(eps_levels: list[float], f: int) -> list[float]:
    if eps_levels[0] <= 0:
        raise ValueError("the leaves must be funded; cut the tree at its lowest funded level instead")
    return list(np.cumsum([f**i * e**2 for i, e in enumerate(eps_levels)]))


def ols(nodes: DataFrame, eps_levels: list[float], f: int = 4, engine: str = "levels", cut: int | None = None) -> DataFrame:
    """nodes (level, node_id, y, ...) with beta. engine: ``levels`` joins level by level; ``blocks`` solves
    whole subtrees of height ``cut`` in tasks, with one exchange and a top tree on the driver."""
    if engine == "blocks":
        return by_blocks(nodes, eps_levels, f, cut)
    h, bits = len(eps_levels) - 1, f.bit_length() - 1
    big_e = prefix_weights(eps_levels, f)
    w = [e * e for e in eps_levels]
    level_w = F.element_at(F.array(*[F.lit(float(f**i * w[i])) for i in range(h + 1)]), F.col("level") + 1)
    own = nodes.select("level", "node_id", (level_w * F.coalesce("y", F.lit(0.0))).alias("wy"))
    # Up: one aggregation in place of a round a level.
    up = own.select("node_id", "wy", "level", F.explode(F.sequence(F.col("level"), F.lit(h))).alias("at"))
    s = up.groupBy(F.col("at").alias("level"), F.expr(f"shiftright(node_id, {bits} * (at - level))").alias("node_id")).agg(F.sum("wy").alias("s"))
    base = durable(nodes.select("level", "node_id", F.coalesce("y", F.lit(0.0)).alias("y")).join(s, ["level", "node_id"]))
    # Down: a level at a time, the parents' side broadcast while it is small.
    above, done = None, []
    for level in range(h, -1, -1):
        here = base.where(F.col("level") == level)
        if above is None:
            here = here.withColumn("d", F.lit(0.0))
        else:
            side = above.select(F.col("node_id").alias("parent"), F.col("dd").alias("d"))
            side = F.broadcast(side) if f ** (h - level - 1) <= BROADCAST_NODES else side
            here = here.withColumn("parent", F.shiftright("node_id", bits)).join(side, "parent").drop("parent")
        here = here.withColumn("beta", (F.col("s") + float(f**level) * F.col("d")) / big_e[level])
        here = here.withColumn("dd", F.col("d") + w[level] * (F.col("y") - F.col("beta")))
        done.append(here.select("level", "node_id", "beta"))
        above = here
        if (h - level) % 3 == 2:
            above = durable(above)
    every = done[0]
    for x in done[1:]:
        every = every.unionByName(x)
    return nodes.join(every, ["level", "node_id"])


def _subtree(y: list[np.ndarray], w: list[float], big_e: list[float], f: int, d: float) -> list[np.ndarray]:
    """Values of a complete subtree given as arrays by level (leaves first) and D at its root."""
    top = len(y) - 1
    s = [None] * (top + 1)
    for level in range(top + 1):
        s[level] = f**level * w[level] * y[level]
        if level:
            s[level] = s[level] + s[level - 1].reshape(-1, f).sum(1)
    beta, dd = [None] * (top + 1), np.array([d])
    for level in range(top, -1, -1):
        beta[level] = (s[level] + f**level * dd) / big_e[level]
        dd = np.repeat(dd + w[level] * (y[level] - beta[level]), f) if level else dd
    return beta


def by_blocks(nodes: DataFrame, eps_levels: list[float], f: int = 4, cut: int | None = None) -> DataFrame:
    h, bits = len(eps_levels) - 1, f.bit_length() - 1
    cut = min(h, 6) if cut is None else cut
    if f ** (h - cut) > 4_000_000:
        raise ValueError(f"a top tree of {f ** (h - cut)} leaves is too large for the driver; take a larger cut")
    big_e, w = prefix_weights(eps_levels, f), [e * e for e in eps_levels]
    low = nodes.where(F.col("level") <= cut).select("level", "node_id", F.coalesce("y", F.lit(0.0)).alias("y"))
    low = low.withColumn("block", F.expr(f"shiftright(node_id, {bits} * ({cut} - level))"))
    weight = F.element_at(F.array(*[F.lit(float(f**i * w[i])) for i in range(cut + 1)]), F.col("level") + 1)
    sums = low.groupBy("block").agg(F.sum(weight * F.col("y")).alias("s"))
    # f ** (h - cut) rows, a bound that is checked above.
    s = np.zeros(f ** (h - cut))
    for r in sums.collect():
        s[r["block"]] = r["s"]
    top_y: dict[int, dict[int, float]] = {}
    for r in nodes.where(F.col("level") > cut).select("level", "node_id", F.coalesce("y", F.lit(0.0)).alias("y")).collect():
        top_y.setdefault(r["level"], {})[r["node_id"]] = r["y"]
    up = {cut: s}
    for level in range(cut + 1, h + 1):
        y = np.array([top_y[level][i] for i in range(f ** (h - level))])
        up[level] = f**level * w[level] * y + up[level - 1].reshape(-1, f).sum(1)
    dd, top = np.zeros(1), []
    for level in range(h, cut, -1):
        y = np.array([top_y[level][i] for i in range(f ** (h - level))])
        beta = (up[level] + f**level * dd) / big_e[level]
        top += [(level, i, float(b)) for i, b in enumerate(beta)]
        dd = np.repeat(dd + w[level] * (y - beta), f)
    spark = nodes.sparkSession
    roots = spark.createDataFrame([(i, float(x)) for i, x in enumerate(dd)], "block long, d double")
    roots = F.broadcast(roots) if len(dd) <= BROADCAST_NODES else roots

    def solve(pdf):
        import pandas as pd

        block, d = int(pdf["block"].iloc[0]), float(pdf["d"].iloc[0])
        y = []
        for level in range(cut + 1):
            part = np.zeros(f ** (cut - level))
            rows = pdf[pdf["level"] == level]
            part[rows["node_id"].to_numpy() - block * f ** (cut - level)] = rows["y"].to_numpy()
            y.append(part)
        beta = _subtree(y, w, big_e, f, d)
        return pd.concat([pd.DataFrame({"level": level, "node_id": block * f ** (cut - level) + np.arange(len(b)), "beta": b}) for level, b in enumerate(beta)])

    below = low.join(roots, "block").groupBy("block").applyInPandas(solve, "level int, node_id long, beta double")
    above = spark.createDataFrame(top, "level int, node_id long, beta double")
    return nodes.join(below.unionByName(above), ["level", "node_id"])


def dense_ols(y: list[np.ndarray], eps_levels: list[float], f: int) -> list[np.ndarray]:
    """The definition, by a dense solver: levels of y with the leaves first. For tests."""
    leaves = len(y[0])
    rows, values = [], []
    for level, part in enumerate(y):
        for i, v in enumerate(part):
            row = np.zeros(leaves)
            row[i * f**level : (i + 1) * f**level] = eps_levels[level]
            rows.append(row)
            values.append(eps_levels[level] * v)
    x = np.linalg.lstsq(np.array(rows), np.array(values), rcond=None)[0]
    return [x.reshape(-1, f**level).sum(1) for level in range(len(y))]


def combine_root(eps_root: float, eps_leaf: float, f: int = 4) -> tuple[float, float]:
    """Weight of the root's own noisy count against the sum of its leaves', and the variance left."""
    weight = f * eps_root**2 / (f * eps_root**2 + eps_leaf**2)
    return weight, 2 * f / (f * eps_root**2 + eps_leaf**2)


def check(nodes: DataFrame, f: int = 4, value: str = "beta") -> DataFrame:
    """level, node_id, gap: a node's value less its children's sum, of all inner nodes."""
    bits = f.bit_length() - 1
    sums = nodes.where("level is not null").groupBy((F.col("level") + 1).alias("level"), F.shiftright("node_id", bits).alias("node_id")).agg(F.sum(value).alias("s"))
    return nodes.join(sums, ["level", "node_id"]).select("level", "node_id", (F.col(value) - F.col("s")).alias("gap"))


def weighted_tree(nodes: DataFrame, h: int) -> DataFrame:
    """Least squares with a budget of its own for each node, of trees of any fanout, by inverse variances.

    nodes: level, node_id, parent_id, y, eps (0: no count of its own). Up: a node's best estimate from its subtree
    weighs its count and its children's sum; down: a discrepancy is shared by the children's variances.
    """
    rows = nodes.withColumn("own_var", F.when(F.col("eps") > 0, 2 / (F.col("eps") * F.col("eps"))))
    up, levels = None, []
    for level in range(h + 1):
        here = rows.where(F.col("level") == level)
        if up is None:
            here = here.withColumn("z", F.col("y")).withColumn("var", F.col("own_var")).withColumn("cs", F.lit(None).cast("double")).withColumn("cv", F.lit(None).cast("double"))
        else:
            kids = up.groupBy(F.col("parent_id").alias("node_id")).agg(F.sum("z").alias("cs"), F.sum("var").alias("cv"))
            here = here.join(kids, "node_id", "left")
            both = 1 / (1 / F.col("own_var") + 1 / F.col("cv"))
            z = (F.col("y") / F.col("own_var") + F.col("cs") / F.col("cv")) * both
            here = here.withColumn("z", F.when(F.col("cv").isNull(), F.col("y")).when(F.col("own_var").isNull(), F.col("cs")).otherwise(z)).withColumn("var", F.when(F.col("cv").isNull(), F.col("own_var")).when(F.col("own_var").isNull(), F.col("cv")).otherwise(both))
        up = durable(here)
        levels.append(up)
    top = levels[h].withColumn("beta", F.col("z"))
    done = [top]
    for level in range(h - 1, -1, -1):
        parent = top.select(F.col("node_id").alias("parent_id"), F.col("beta").alias("pb"), F.col("cs").alias("pcs"), F.col("cv").alias("pcv"))
        top = levels[level].join(parent, "parent_id").withColumn("beta", F.col("z") + (F.col("pb") - F.col("pcs")) * F.col("var") / F.col("pcv")).drop("pb", "pcs", "pcv")
        done.append(top)
    out = done[0].select("level", "node_id", "beta")
    for x in done[1:]:
        out = out.unionByName(x.select("level", "node_id", "beta"))
    return nodes.join(out, ["level", "node_id"])
