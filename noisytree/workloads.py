"""The experiments as parameter sweeps. Each returns a frame of figures and runs on any points; heights are
those of the given tables' sizes (see FIXTURES.md), not the publication's."""

from __future__ import annotations

import time
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from noisytree.operators import answer, matching, measures, medians, sampling
from noisytree.operators.durable import durable
from noisytree.plans.build import TreeSpec, build
from noisytree.plans.domain import UNI, Domain
from noisytree.sources import workloads as made


def errors(points: DataFrame, domain: Domain, specs: dict[str, TreeSpec], queries: DataFrame) -> DataFrame:
    """method, shape, med_rel_err over the boxes that hold a point."""
    truth, out = durable(answer.exact(points, queries, domain)), []
    for name, spec in specs.items():
        got = answer.canonical(build(points, domain, spec), queries, domain)
        out.append(measures.median_relative_error(got, truth, queries).select(F.lit(name).alias("method"), "shape", "med_rel_err"))
    return reduce(DataFrame.unionByName, out)


def non_empty_boxes(spark: SparkSession, points: DataFrame, domain: Domain, count: int, shapes=made.REPORTED) -> DataFrame:
    """``count`` boxes a shape that hold a point, from three times as many drawn."""
    q = made.boxes(spark, domain, 3 * count, shapes)
    return durable(made.non_empty(q, answer.exact(points, q, domain), count))


def quadtree_options(points: DataFrame, domain: Domain, queries: DataFrame, h: int, budgets=(0.1, 0.5, 1.0)) -> DataFrame:
    """Budget strategy by post-processing, for each budget."""
    specs = {f"{b}{'_ols' if post else '_raw'}@{e}": TreeSpec("quad", h, e, count_budget=b, post=post) for e in budgets for b in ("uniform", "geometric") for post in (False, True)}
    return errors(points, domain, specs, queries)


def kd_variants(points: DataFrame, domain: Domain, queries: DataFrame, h: int, budgets=(0.1, 0.5, 1.0), cells=(256, 256), switch: int | None = None) -> DataFrame:
    """Exact tree, exact splits with noisy counts, and the private kd-trees."""
    base, specs = TreeSpec("kd", h, prune_at=32), {}
    for e in budgets:
        specs |= {f"true@{e}": base.but(eps=e, split="exact", exact_counts=True), f"medians@{e}": base.but(eps=e, split="exact"), f"standard@{e}": base.but(eps=e), f"hybrid@{e}": base.but(eps=e, kind="hybrid", switch=switch or max(1, h // 2)), f"cell@{e}": base.but(eps=e, split="cell", cells=cells), f"mean@{e}": base.but(eps=e, split="noisy_mean")}
    return errors(points, domain, specs, queries)


def families(points: DataFrame, domain: Domain, queries: DataFrame, heights=(4, 5, 6), eps: float = 0.5, cells=(256, 256)) -> DataFrame:
    """The best of each family by height."""
    specs = {}
    for h in heights:
        base = TreeSpec("quad", h, eps, prune_at=32)
        specs |= {f"quad-h{h}": base, f"kd-hybrid-h{h}": base.but(kind="hybrid", switch=max(1, h // 2)), f"kd-cell-h{h}": base.but(kind="kd", split="cell", cells=cells), f"hilbert-h{h}": base.but(kind="hilbert")}
    return errors(points, domain, specs, queries)


def shares(points, domain, queries, h: int, eps: float = 0.5, values=(0.1, 0.3, 0.5, 0.7, 0.9)) -> DataFrame:
    """Counts' share of the budget."""
    return errors(points, domain, {f"share-{s}": TreeSpec("kd", h, eps, count_share=s) for s in values}, queries)


def switches(points, domain, queries, h: int, eps: float = 0.5) -> DataFrame:
    """Level at which a hybrid turns to midpoints."""
    return errors(points, domain, {f"switch-{s}": TreeSpec("hybrid", h, eps, switch=s) for s in range(h + 1)}, queries)


def orders(points, domain, queries, h: int, eps: float = 0.5, values=(12, 16, 18, 20, 24)) -> DataFrame:
    """Order of the Hilbert curve."""
    return errors(points, domain, {f"order-{o}": TreeSpec("hilbert", h, eps, order=o) for o in values}, queries)


def count_budgets(points, domain, queries, h: int, eps: float = 0.5) -> DataFrame:
    """Uniform against geometric on trees other than the quadtree."""
    return errors(points, domain, {f"{k}-{b}": TreeSpec(k, h, eps, count_budget=b, switch=max(1, h // 2)) for k in ("kd", "hybrid", "hilbert") for b in ("uniform", "geometric")}, queries)


def pruning(points, domain, queries, h: int, eps: float = 0.5, values=(None, 8, 32, 64)) -> DataFrame:
    return errors(points, domain, {f"prune-{m}": TreeSpec("quad", h, eps, prune_at=m) for m in values}, queries)


MEDIANS = ("exponential", "smooth", "noisy_mean")


def median_quality(values: DataFrame, domain: Domain = UNI, depth: int = 6, eps: float = 0.01, delta: float = 1e-4, rate: float = 0.01, cells: int = 1024) -> DataFrame:
    """method, depth, rank_err (mean over nodes), seconds: exact splits above, each method at every depth.

    values: pid, x. Sampled runs (suffix _s) use the budget that the sample allows.
    """
    from noisytree.operators.trees import grow

    grown = grow(values, domain, depth, "exact", [], "exact")
    out = []
    for b in range(depth):
        at = durable(descend_to(values, grown, b))
        bounds = durable(grown.boxes[b].select("node_id", F.col("x0").alias("lo"), F.col("x1").alias("hi")))
        for method in (*MEDIANS, "exponential_s", "smooth_s", "cell"):
            start = time.time()
            if method == "cell":
                width = (domain.axes[0].hi - domain.axes[0].lo) / cells
                got = cell_medians(at, bounds, width, eps, domain)
            else:
                sampled = method.endswith("_s")
                v = sampling.bernoulli(at, rate, str(b)) if sampled else at
                got = medians.split(v.select("node_id", "v"), bounds, method.removesuffix("_s"), sampling.required_eps(eps, rate) if sampled else eps, delta, depth=b)
            err = measures.rank_error(durable(got.select("node_id", "split")), at).agg(F.avg("rank_err")).first()[0]
            out.append((method, b, float(err) if err is not None else None, time.time() - start))
    return values.sparkSession.createDataFrame(out, "method string, depth int, rank_err double, seconds double")


def descend_to(values: DataFrame, grown, depth: int) -> DataFrame:
    """pid, node_id, v at a binary depth."""
    from noisytree.operators.trees import clamped, descend

    p = clamped(values, grown.domain).withColumn("node_id", F.lit(0).cast("long"))
    for b in range(depth):
        p = descend(p, grown.splits[b], "x", 1 << b)
    return p.select("pid", "node_id", F.col("x").alias("v"))


def cell_medians(values: DataFrame, bounds: DataFrame, width: float, eps: float, domain: Domain) -> DataFrame:
    """node_id, split from noisy counts of cells of one width over the whole domain."""
    from noisytree.functions.noise import DEFAULT

    lo = domain.axes[0].lo
    every = bounds.select("node_id", F.explode(F.sequence(F.floor((F.col("lo") - lo) / width), F.greatest(F.floor((F.col("lo") - lo) / width), F.ceil((F.col("hi") - lo) / width) - 1))).alias("i"))
    c = values.groupBy("node_id", F.floor((F.col("v") - lo) / width).alias("i")).agg(F.count("*").alias("c"))
    w = every.join(c, ["node_id", "i"], "left").select("node_id", "i", (F.coalesce("c", F.lit(0)) + DEFAULT.laplace(1 / eps, "cell", "q", F.col("node_id"), F.col("i"))).alias("w"))
    ends = every.groupBy("node_id").agg(F.min("i").alias("i0"), (F.max("i") + 1).alias("i1"))
    got = medians.cell_split(w, ends)
    return got.join(bounds, "node_id").select("node_id", F.least(F.greatest(F.lit(lo) + F.col("line") * width, F.col("lo")), F.col("hi")).alias("split"))


def build_times(points: DataFrame, domain: Domain, specs: dict[str, TreeSpec]) -> DataFrame:
    """tree, seconds, nodes."""
    out = []
    for name, spec in specs.items():
        start = time.time()
        n = build(points, domain, spec).count()
        out.append((name, time.time() - start, n))
    return points.sparkSession.createDataFrame(out, "tree string, seconds double, nodes long")


def record_matching(a: DataFrame, b: DataFrame, domain: Domain, theta: tuple[float, ...], h: int = 2, budgets=(0.1, 0.5, 1.0)) -> DataFrame:
    """method, eps, ratio: all of the counts' budget in the leaves."""
    out = []
    for e in budgets:
        for name, spec in {"quad": TreeSpec("quad", h, e), "mean": TreeSpec("kd", h, e, split="noisy_mean"), "exponential": TreeSpec("kd", h, e)}.items():
            leaves = build(a, domain, spec.but(count_budget="leaf_only", post=False)).where("level = 0")
            out.append(matching.reduction_ratio(leaves, a, b, domain, theta).select(F.lit(name).alias("method"), F.lit(e).alias("eps"), "ratio"))
    return reduce(DataFrame.unionByName, out)
