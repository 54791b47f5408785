"""Shares of a privacy budget over the levels of a tree (leaf: level 0, root: level h).

All strategies return one value a level that sum to the whole: a root-to-leaf path meets each level once.
"""

from __future__ import annotations

import math
from collections.abc import Iterable, Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def _shares(weights: Sequence[float], eps: float) -> list[float]:
    """Weights scaled to sum to eps; normalised by their sum, not by a closed form."""
    if eps <= 0 or any(w < 0 for w in weights) or weights[0] <= 0:
        raise ValueError("the budget and the leaves' share must be positive, no share negative")
    total = sum(weights)
    return [eps * w / total for w in weights]


def uniform(eps: float, h: int) -> list[float]:
    return _shares([1.0] * (h + 1), eps)


def growth(f: int = 4, d: int = 2) -> float:
    """Ratio of a level's share to that of the level above: the cube root of the growth of touched nodes."""
    return (f ** (1 - 1 / d)) ** (1 / 3)


def geometric(eps: float, h: int, f: int = 4, d: int = 2) -> list[float]:
    g = growth(f, d)
    return _shares([g ** (h - i) for i in range(h + 1)], eps)


def leaf_only(eps: float, h: int) -> list[float]:
    return _shares([1.0] + [0.0] * h, eps)


def skip(eps: float, h: int, keep: Iterable[int], base=geometric) -> list[float]:
    """Levels outside keep release no count."""
    keep = set(keep)
    if 0 not in keep:
        raise ValueError("the leaves must be funded; cut the tree at its lowest funded level instead")
    return _shares([w if i in keep else 0.0 for i, w in enumerate(base(eps, h))], eps)


def for_workload_levels(touched: Sequence[float], eps: float) -> list[float]:
    """Least total variance where a workload touches so many nodes a level: cube-root shares."""
    return _shares([max(n, 1e-9) ** (1 / 3) for n in touched], eps)


def custom(values: Sequence[float]) -> list[float]:
    return _shares(values, sum(values))


def split(eps: float, count_share: float = 0.7) -> tuple[float, float]:
    """(for counts, for medians)."""
    if not 0 < count_share <= 1:
        raise ValueError("the counts' share must be within (0, 1]")
    return eps * count_share, eps - eps * count_share


def median_uniform(eps: float, binary_levels: int) -> list[float]:
    return [eps / binary_levels] * binary_levels


def median_hybrid(eps: float, h: int, switch: int) -> list[float]:
    """By binary depth: the first ``switch`` levels of fanout 4 are split by data, the rest at midpoints."""
    return [eps / (2 * switch)] * (2 * switch) + [0.0] * (2 * (h - switch)) if switch else [0.0] * (2 * h)


def for_workload_nodes(nodes: DataFrame, h: int, eps: float, d: int = 2, floor: float = 1e-3) -> DataFrame:
    """level, node_id, eps: shares by node that sum to eps along each path. nodes: level, node_id, w
    (how often the workload adds the node's count).

    A subtree costs 2 c / eps**2, where the cube root of c is that of the node's own weight plus that of
    its children's sum; a node takes the share of its own cube root in what its ancestors left.
    """
    cost = nodes.select("level", "node_id", F.greatest("w", F.lit(floor)).alias("w"))
    up = cost.where("level = 0").withColumn("c", F.col("w"))
    every = up
    for level in range(1, h + 1):
        below = up.groupBy(F.shiftright("node_id", d).alias("node_id")).agg(F.sum("c").alias("s"))
        up = cost.where(F.col("level") == level).join(below, "node_id")
        up = up.select("level", "node_id", "w", F.pow(F.cbrt("w") + F.cbrt("s"), F.lit(3.0)).alias("c"))
        every = every.unionByName(up)
    every = every.withColumn("share", F.cbrt("w") / F.cbrt("c"))
    # What is left at a node: the product over its strict ancestors, as a sum of logarithms.
    if not h:
        return every.select("level", "node_id", F.lit(eps).alias("eps"))
    path = every.where(F.col("level") < h).select("level", "node_id", F.explode(F.sequence(F.col("level") + 1, F.lit(h))).alias("up"))
    path = path.withColumn("anc", F.expr(f"shiftright(node_id, {d} * (up - level))"))
    anc = every.select(F.col("level").alias("up"), F.col("node_id").alias("anc"), (1 - F.col("share")).alias("rest"))
    rest = path.join(anc, ["up", "anc"]).groupBy("level", "node_id").agg(F.sum(F.log("rest")).alias("lr"))
    out = every.join(rest, ["level", "node_id"], "left")
    # A leaf spends all that is left.
    mine = F.when(F.col("level") == 0, F.lit(1.0)).otherwise(F.col("share"))
    return out.select("level", "node_id", (F.lit(eps) * F.exp(F.coalesce("lr", F.lit(0.0))) * mine).alias("eps"))


def total_error(eps_levels: Sequence[float], f: int = 4, d: int = 2) -> float:
    """Worst-case variance of a range count: 8 f**(i-like growth) nodes a level, each 2 / eps**2."""
    h = len(eps_levels) - 1
    per_level = f ** (1 - 1 / d)
    return sum(8 * per_level ** (h - i) * 2 / e**2 for i, e in enumerate(eps_levels) if e > 0)


def touch_bound(h: int, f: int, d: int, level: int | None = None) -> float:
    """Nodes of a level (or of all) that a box's boundary can add: min of faces and all nodes."""
    one = lambda i: min(2 * d * 2 * (f ** (1 - 1 / d)) ** (h - i), f ** (h - i))
    return one(level) if level is not None else sum(one(i) for i in range(h + 1))


def advise_height(n_noisy: float, eps: float, max_h: int = 12, f: int = 4, d: int = 2) -> int:
    """Height with the least noise deviation plus uniformity error, for a public or noisy size."""
    return min(range(1, max_h + 1), key=lambda h: n_noisy / 2**h + math.sqrt(total_error(geometric(eps, h, f, d), f, d)))


def worst_case(h: Column) -> tuple[Column, Column]:
    """Curves of the worst case of uniform and geometric budgets, in units of 16 / eps**2."""
    g = 2 ** (1 / 3)
    unif = (h + 1) * (h + 1) * (F.pow(F.lit(2.0), h + 1) - 1)
    return unif, F.pow((F.pow(F.lit(g), h + 1) - 1) / (g - 1), F.lit(3.0))
