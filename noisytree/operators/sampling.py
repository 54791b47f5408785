"""Bernoulli samples by hashed keys, and what sampling is worth in budget."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from noisytree.functions.noise import DEFAULT, Noise


def amplify(eps: float, p: float, rule: str = "tight") -> float:
    """Budget that an eps-private method spends when run on a sample of rate p."""
    if rule == "stated":
        return 2 * p * math.exp(eps)
    if rule == "tight":
        return math.log1p(p * math.expm1(eps))
    raise ValueError(f"no rule {rule}")


def required_eps(target: float, p: float, rule: str = "tight") -> float:
    """Budget that a method may use on the sample to spend ``target``."""
    if rule == "tight":
        return math.log1p(math.expm1(target) / p)
    if target <= 2 * p:
        raise ValueError(f"the stated rule spends {2 * p} at least at rate {p}")
    return math.log(target / (2 * p))


def rate_for(target: float) -> float:
    """A tenth of the target: then the method may use about 0.9 under the stated rule."""
    return target / 10


def bernoulli(points: DataFrame, p: float, scope: str = "0", noise: Noise = DEFAULT, key: str = "pid") -> DataFrame:
    """The same rows whatever the partitioning, unlike DataFrame.sample."""
    return points.where(noise.uniform("smp", scope, F.col(key)) < p)
