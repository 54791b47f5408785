"""One entry for all trees: what to build, and the steps from points to consistent, pruned nodes."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from noisytree.functions.cells import with_boxes
from noisytree.functions.noise import DEFAULT, Noise
from noisytree.operators import answer, consistency, counts, prune, sampling, trees
from noisytree.operators.durable import durable
from noisytree.plans import budget
from noisytree.plans.domain import Domain


@dataclass(frozen=True)
class TreeSpec:
    """kind: quad, grid is in counts; kd (split: exact, exponential, smooth, noisy_mean, cell), hybrid, hilbert."""

    kind: str = "quad"
    h: int = 4
    eps: float = 1.0
    split: str = "exponential"
    count_budget: str = "geometric"
    count_share: float = 0.7
    exact_counts: bool = False
    post: bool = True
    prune_at: float | None = None
    switch: int = 2
    order: int = 18
    cells: tuple[int, int] = (256, 256)
    sample: float | None = None
    delta: float = 1e-4
    tree: str = "t"
    noise: Noise = DEFAULT

    def but(self, **changes) -> TreeSpec:
        return replace(self, **changes)


BUDGETS = {"uniform": budget.uniform, "geometric": budget.geometric, "leaf_only": budget.leaf_only}


def split_budgets(spec: TreeSpec) -> tuple[list[float], list[float]]:
    """(by level for counts, by binary depth for medians; what a sampled median may use, not what it spends)."""
    own = spec.kind in ("kd", "hybrid", "hilbert") and spec.split != "exact"
    for_counts, for_medians = budget.split(spec.eps, spec.count_share) if own else (spec.eps, 0.0)
    level = BUDGETS[spec.count_budget](for_counts, spec.h)
    if not own:
        return level, []
    depth = 2 * (spec.switch if spec.kind == "hybrid" else spec.h)
    each = [for_medians / max(1, depth)] * depth
    return level, [sampling.required_eps(e, spec.sample) for e in each] if spec.sample else each


def private_counts(points: DataFrame, domain: Domain, spec: TreeSpec) -> DataFrame:
    """level, node_id, box, c: private, the splits already released."""
    _, medians = split_budgets(spec)
    if spec.kind == "quad":
        return with_boxes(counts.tree_counts(points, domain, spec.h), domain, spec.h)
    if spec.kind == "kd" and spec.split == "cell":
        return trees.counted(trees.cell_tree(points, domain, 2 * spec.h, spec.cells, sum(medians), spec.tree, spec.noise))
    if spec.kind == "kd":
        return trees.counted(trees.grow(points, domain, 2 * spec.h, spec.split, medians, spec.tree, spec.delta, spec.noise, spec.sample))
    if spec.kind == "hybrid":
        return trees.hybrid(points, domain, spec.h, spec.switch, medians, spec.tree, spec.split, spec.noise, spec.sample)
    if spec.kind == "hilbert":
        nodes = trees.hilbert_tree(points, domain, spec.h, medians, spec.order, spec.tree, spec.split, spec.noise, spec.sample)
        return trees.node_boxes(nodes, domain, spec.order)
    raise ValueError(f"no kind {spec.kind}")


def build(points: DataFrame, domain: Domain, spec: TreeSpec) -> DataFrame:
    """Released nodes: level, node_id, box, eps_count, y, beta, is_leaf, and the parent's box as p...

    beta is the consistent count, or y itself without post-processing.
    """
    level, _ = split_budgets(spec)
    c = private_counts(points, domain, spec)
    if spec.exact_counts:
        noisy = c.withColumn("eps_count", F.lit(None).cast("double")).withColumn("y", F.col("c").cast("double")).drop("c")
    else:
        noisy = counts.add_noise(c, level, spec.tree, spec.noise)
    noisy = durable(noisy)
    if spec.post and not spec.exact_counts:
        beta = consistency.ols(noisy.select("level", "node_id", "y"), level, 1 << domain.d).select("level", "node_id", "beta")
        noisy = noisy.join(beta, ["level", "node_id"])
    else:
        noisy = noisy.withColumn("beta", F.col("y"))
    nodes = prune.by_noisy_count(noisy, spec.prune_at, spec.h, domain.d)
    return durable(answer.with_parent_boxes(nodes, domain, spec.h, domain.d, "beta"))
