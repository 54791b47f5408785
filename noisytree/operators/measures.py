"""Accuracy and cost measures of answers, splits and matchings."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from noisytree.functions.noise import Noise
from noisytree.operators import answer
from noisytree.operators.counts import add_noise, level_value
from noisytree.plans.domain import Domain


def noise_variance(nodes: DataFrame, queries: DataFrame, domain: Domain, eps_levels: list[float], strategy: str = "nested") -> DataFrame:
    """qid, err: variance of an answer from raw counts, two over the square of the budget a node."""
    t = answer.touched(nodes, queries, domain, "level", strategy)
    eps = level_value(eps_levels)
    got = t.groupBy("qid").agg(F.sum(2 * F.col("part") * F.col("part") / (eps * eps)).alias("err"))
    return queries.select("qid", "shape").join(got, "qid", "left").na.fill(0, ["err"])


def workload_error(variances: DataFrame) -> DataFrame:
    return variances.groupBy("shape").agg(F.avg("err").alias("err"))


def relative_error(answers: DataFrame, exact: DataFrame, queries: DataFrame) -> DataFrame:
    """qid, shape, rel_err of the boxes that hold a point."""
    j = answers.join(exact, "qid").join(queries.select("qid", "shape"), "qid").where("true_count > 0")
    return j.select("qid", "shape", (F.abs(F.col("estimate") - F.col("true_count")) / F.col("true_count")).alias("rel_err"))


def median_relative_error(answers: DataFrame, exact: DataFrame, queries: DataFrame) -> DataFrame:
    return relative_error(answers, exact, queries).groupBy("shape").agg(F.percentile("rel_err", F.lit(0.5)).alias("med_rel_err"))


def absolute_error(answers: DataFrame, exact: DataFrame) -> DataFrame:
    return answers.join(exact, "qid").select("qid", F.abs(F.col("estimate") - F.col("true_count")).alias("abs_err"))


def replicate(counts: DataFrame, queries: DataFrame, domain: Domain, eps_levels: list[float], boxed, seeds: list[str], tree: str = "r") -> DataFrame:
    """qid, mean, var of raw answers over draws of the noise. boxed: adds boxes to noisy nodes."""
    runs = []
    for s in seeds:
        nodes = boxed(add_noise(counts, eps_levels, tree, Noise(s)))
        runs.append(answer.canonical(nodes, queries, domain, "y").select("qid", "estimate"))
    return reduce(DataFrame.unionByName, runs).groupBy("qid").agg(F.avg("estimate").alias("mean"), F.var_samp("estimate").alias("var"))


def rank_error(splits: DataFrame, values: DataFrame) -> DataFrame:
    """node_id, rank_err: distance of the split's rank from the median's over n / 2, 1 at most: exactly 1
    at either end of the data."""
    j = values.join(F.broadcast(splits.select("node_id", "split")), "node_id")
    r = j.groupBy("node_id").agg(F.count("*").alias("n"), F.sum((F.col("v") < F.col("split")).cast("long")).alias("below"))
    # The split stands after ``below`` values; the median after half of them.
    return r.select("node_id", F.least(F.lit(1.0), F.abs(F.col("below") - F.col("n") / 2) / (F.col("n") / 2)).alias("rank_err"))


def balance(splits: DataFrame, values: DataFrame) -> DataFrame:
    """node_id, left_share: of the points of a node, those left of its split."""
    j = values.join(F.broadcast(splits.select("node_id", "split")), "node_id")
    return j.groupBy("node_id").agg(F.avg((F.col("v") < F.col("split")).cast("double")).alias("left_share"))


def leaf_load(leaves: DataFrame) -> DataFrame:
    """Largest and mean number of points of a leaf: of private counts, for layout only."""
    return leaves.agg(F.max("c").alias("largest"), F.avg("c").alias("mean"))


def confidence_half_width(variances: DataFrame, level: float = 0.95) -> DataFrame:
    """qid, half_width by a normal approximation of the answer's noise."""
    from statistics import NormalDist

    z = NormalDist().inv_cdf(0.5 + level / 2)
    return variances.select("qid", (F.lit(z) * F.sqrt("err")).alias("half_width"))
