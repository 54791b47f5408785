"""What users ask of a release beyond one box; all of it is post-processing and costs no budget."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from noisytree.functions.noise import DEFAULT, Noise
from noisytree.operators.answer import canonical
from noisytree.plans.domain import Domain


def density(nodes: DataFrame, domain: Domain, level: int = 0, value: str = "beta") -> DataFrame:
    area = reduce(lambda a, b: a * b, [F.col(f"{n}1") - F.col(f"{n}0") for n in domain.names])
    return nodes.where(F.col("level") == level).select("node_id", *domain.box, (F.col(value) / area).alias("density"))


def busiest(nodes: DataFrame, domain: Domain, k: int = 10, level: int = 0) -> DataFrame:
    return density(nodes, domain, level).orderBy(F.col("density").desc(), "node_id").limit(k)


def marginal(nodes: DataFrame, domain: Domain, axis: str = "x", value: str = "beta") -> DataFrame:
    """bin (low end), n, cdf along an axis, from the leaves of a midpoint tree."""
    bins = nodes.where("level = 0").groupBy(F.col(f"{axis}0").alias("bin")).agg(F.sum(value).alias("n"))
    w = Window.orderBy("bin")  # 2**h rows
    return bins.withColumn("cum", F.sum("n").over(w)).withColumn("all", F.sum("n").over(Window.partitionBy())).select("bin", "n", (F.col("cum") / F.col("all")).alias("cdf"))


def quantile(nodes: DataFrame, domain: Domain, p: float, axis: str = "x") -> DataFrame:
    """The first bin whose cdf reaches p."""
    return marginal(nodes, domain, axis).where(F.col("cdf") >= p).agg(F.min("bin").alias("quantile"))


def regions(nodes: DataFrame, named: DataFrame, domain: Domain, value: str = "beta") -> DataFrame:
    """name, estimate, share of each named box. named: qid, name, qx0, ..."""
    got = canonical(nodes, named, domain, value).join(named.select("qid", "name"), "qid")
    total = nodes.groupBy().agg(F.max_by(value, "level").alias("total"))
    return got.join(F.broadcast(total)).select("name", "estimate", (F.col("estimate") / F.col("total")).alias("share"))


def difference(one: DataFrame, two: DataFrame, value: str = "beta") -> DataFrame:
    """level, node_id, delta of two releases over the same tree."""
    return one.select("level", "node_id", F.col(value).alias("_a")).join(two.select("level", "node_id", F.col(value).alias("_b")), ["level", "node_id"], "full").select("level", "node_id", (F.coalesce("_b", F.lit(0.0)) - F.coalesce("_a", F.lit(0.0))).alias("delta"))


def synthetic_points(nodes: DataFrame, domain: Domain, value: str = "beta", noise: Noise = DEFAULT) -> DataFrame:
    """Points spread evenly in each leaf, as many as its released count (negatives none)."""
    n = F.greatest(F.lit(0), F.round(value).cast("int"))
    rows = nodes.where("level = 0").withColumn("_n", n).where("_n > 0").withColumn("i", F.explode(F.sequence(F.lit(1), F.col("_n"))))
    at = {a: F.col(f"{a}0") + noise.uniform("syn", a, F.col("node_id"), F.col("i")) * (F.col(f"{a}1") - F.col(f"{a}0")) for a in domain.names}
    return rows.select("node_id", *[c.alias(a) for a, c in at.items()])
