"""Query boxes and synthetic point sets, all drawn from hashes of keys."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from noisytree.functions.noise import DEFAULT, Noise
from noisytree.plans.domain import Domain

#: Extents of a box as shares of each axis, by shape.
SHAPES = {"square_small": (0.0458, 0.0566), "square_mid": (0.229, 0.283), "square_large": (0.458, 0.566), "skinny": (0.687, 0.0113)}
REPORTED = ("square_small", "square_large", "skinny")


def boxes(spark: SparkSession, domain: Domain, count: int = 20, shapes=REPORTED, noise: Noise = DEFAULT) -> DataFrame:
    """qid, shape, qx0, qx1, ...: ``count`` boxes a shape, extents fixed, lower corners uniform."""
    frames = []
    for s, shape in enumerate(shapes):
        one = spark.range(count).select((F.lit(s * count) + F.col("id")).alias("qid"), F.lit(shape).alias("shape"), F.col("id").alias("i"))
        for a, axis in enumerate(domain.axes):
            extent = SHAPES[shape][a % 2] * axis.width
            corner = F.lit(axis.lo) + noise.uniform("box", shape, F.col("i"), a) * F.lit(axis.width - extent)
            one = one.withColumn(f"q{axis.name}0", corner).withColumn(f"q{axis.name}1", F.col(f"q{axis.name}0") + F.lit(extent))
        frames.append(one.drop("i"))
    return reduce(DataFrame.unionByName, frames)


def non_empty(boxes: DataFrame, exact: DataFrame, count: int) -> DataFrame:
    """The first ``count`` boxes of each shape, by qid, that hold a point; fewer where fewer do."""
    from pyspark.sql import Window

    hit = boxes.join(exact.where("true_count > 0").select("qid"), "qid", "left_semi")
    w = Window.partitionBy("shape").orderBy("qid")
    return hit.withColumn("_k", F.row_number().over(w)).where(F.col("_k") <= count).drop("_k")


def uniform_values(spark: SparkSession, n: int = 1 << 20, top: float = float(1 << 26), noise: Noise = DEFAULT) -> DataFrame:
    """pid, x: uniform in [0, top)."""
    return spark.range(n).select(F.col("id").cast("string").alias("pid"), (noise.uniform("val", F.col("id")) * top).alias("x"))


def synthetic(spark: SparkSession, kind: str, n: int, noise: Noise = DEFAULT) -> DataFrame:
    """pid, x, y in [0, 1)**2: ``uniform``, ``mixture`` of four Gaussians, or ``power`` law."""
    u = lambda name: noise.uniform(name, F.col("id"))
    if kind == "uniform":
        x, y = u("x"), u("y")
    elif kind == "power":
        x, y = F.pow(u("x"), F.lit(3.0)), F.pow(u("y"), F.lit(3.0))
    elif kind == "mixture":
        centre = F.floor(u("c") * 4)
        r, angle = F.sqrt(-2 * F.log(u("r"))) * 0.06, 2 * 3.141592653589793 * u("a")
        x = F.element_at(F.array(*[F.lit(v) for v in (0.2, 0.75, 0.4, 0.85)]), (centre + 1).cast("int")) + r * F.cos(angle)
        y = F.element_at(F.array(*[F.lit(v) for v in (0.3, 0.2, 0.7, 0.8)]), (centre + 1).cast("int")) + r * F.sin(angle)
        x, y = [F.greatest(F.lit(0.0), F.least(F.lit(0.999999), v)) for v in (x, y)]
    else:
        raise ValueError(f"no distribution {kind}")
    return spark.range(n).select(F.col("id").cast("string").alias("pid"), x.alias("x"), y.alias("y"))
