"""Median splits of many nodes at once: exact, noisy, by exponential mechanism, smooth sensitivity, noisy
mean, and over a noisy grid of cells.

Common contract: values (node_id, v) within their node's bounds (node_id, lo, hi); the result (node_id, split)
has a row for each of bounds, clamped to them. The median is the value of rank floor((n + 1) / 2).
Ranks are found without a window over a whole node: equal values collapse first, values are dealt to
buckets of their node, bucket totals are summed up, and ranks continue within each bucket.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from noisytree.functions.noise import DEFAULT, Noise

BUCKETS = 64


def clamp(c, lo="lo", hi="hi"):
    return F.least(F.greatest(c, F.col(lo)), F.col(hi))


def ranks(values: DataFrame, bounds: DataFrame, buckets: int = BUCKETS) -> tuple[DataFrame, DataFrame]:
    """(ranked: node_id, v, k, after, and totals: node_id, lo, hi, n, first). k points of the node are <= v;
    after is the next larger value, or hi."""
    b = values.where("v is not null and not isnan(v)").join(F.broadcast(bounds.select("node_id", "lo", "hi")), "node_id").withColumn("v", clamp(F.col("v")))
    at = F.floor((F.col("v") - F.col("lo")) / (F.col("hi") - F.col("lo")) * float(buckets))
    b = b.withColumn("bucket", F.when(F.col("hi") > F.col("lo"), F.least(F.lit(buckets - 1), at.cast("int"))).otherwise(F.lit(0)))
    each = b.groupBy("node_id", "bucket", "v").agg(F.count("*").alias("c"), F.first("hi").alias("hi"))
    by_bucket = each.groupBy("node_id", "bucket").agg(F.sum("c").alias("bc"), F.min("v").alias("least"))
    w = Window.partitionBy("node_id").orderBy("bucket")
    by_bucket = by_bucket.select("node_id", "bucket", F.coalesce(F.sum("bc").over(w.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0).cast("long")).alias("before"), F.lead("least").over(w).alias("next_least"), "bc", "least")
    inner = Window.partitionBy("node_id", "bucket").orderBy("v")
    out = each.join(by_bucket.select("node_id", "bucket", "before", "next_least"), ["node_id", "bucket"])
    out = out.select("node_id", "v", (F.col("before") + F.sum("c").over(inner.rowsBetween(Window.unboundedPreceding, 0))).alias("k"), F.coalesce(F.lead("v").over(inner), F.col("next_least"), F.col("hi")).alias("after"))
    totals = by_bucket.groupBy("node_id").agg(F.sum("bc").alias("n"), F.min("least").alias("first"))
    totals = bounds.select("node_id", "lo", "hi").join(totals, "node_id", "left").withColumn("n", F.coalesce("n", F.lit(0).cast("long"))).withColumn("first", F.coalesce("first", "hi"))
    return out, totals


def middle(n):
    return F.floor((n + 1) / 2)


def exact(values: DataFrame, bounds: DataFrame, buckets: int = BUCKETS) -> DataFrame:
    """node_id, split, n: the median itself; the midpoint of an empty node. Not private."""
    ranked, totals = ranks(values, bounds, buckets)
    hit = ranked.join(F.broadcast(totals.select("node_id", "n")), "node_id").where(F.col("k") >= middle(F.col("n"))).groupBy("node_id").agg(F.min("v").alias("split"))
    return totals.join(hit, "node_id", "left").select("node_id", F.coalesce("split", (F.col("lo") + F.col("hi")) / 2).alias("split"), "n")


def global_laplace(values: DataFrame, bounds: DataFrame, eps: float, noise: Noise = DEFAULT, key=("lap", 0)) -> DataFrame:
    """node_id, out (not clamped), split: noise to the width of the domain, so mostly out of range."""
    got = exact(values, bounds).join(bounds, "node_id")
    out = F.col("split") + noise.laplace((F.col("hi") - F.col("lo")) / eps, *key, F.col("node_id"))
    return got.select("node_id", out.alias("out"), F.least(F.greatest(out, F.col("lo")), F.col("hi")).alias("split"))


def gaps(values: DataFrame, bounds: DataFrame, buckets: int = BUCKETS) -> DataFrame:
    """node_id, n, k, left, right: the intervals between neighbouring values that have a width; k points lie
    at or before left."""
    ranked, totals = ranks(values, bounds, buckets)
    first = totals.select("node_id", "n", F.lit(0).cast("long").alias("k"), F.col("lo").alias("left"), F.col("first").alias("right"))
    rest = ranked.join(F.broadcast(totals.select("node_id", "n")), "node_id").select("node_id", "n", "k", F.col("v").alias("left"), F.col("after").alias("right"))
    return first.unionByName(rest).where("right > left")


def exponential(values: DataFrame, bounds: DataFrame, eps: float, noise: Noise = DEFAULT, tree: str = "t", depth: int = 0, buckets: int = BUCKETS) -> DataFrame:
    """The exponential mechanism over gaps, as the largest of Gumbel scores: one pass with partial maxima."""
    g = gaps(values, bounds, buckets)
    score = F.log(F.col("right") - F.col("left")) - F.lit(eps) * F.abs(F.col("k") - middle(F.col("n"))) / 2 + noise.gumbel("gum", tree, depth, F.col("node_id"), F.col("k"))
    best = g.withColumn("score", score).groupBy("node_id").agg(F.max_by("left", "score").alias("left"), F.max_by("right", "score").alias("right"))
    u = noise.uniform("uni", tree, depth, F.col("node_id"))
    out = bounds.select("node_id", "lo", "hi").join(best, "node_id", "left")
    return out.select("node_id", clamp(F.coalesce(F.col("left") + u * (F.col("right") - F.col("left")), F.col("lo"))).alias("split"))


def expmech_probabilities(values: DataFrame, bounds: DataFrame, eps: float) -> DataFrame:
    """node_id, k, p: the chance of each gap."""
    g = gaps(values, bounds).withColumn("logw", F.log(F.col("right") - F.col("left")) - F.lit(eps) * F.abs(F.col("k") - middle(F.col("n"))) / 2)
    top = g.groupBy("node_id").agg(F.max("logw").alias("top"))
    g = g.join(F.broadcast(top), "node_id").withColumn("w", F.exp(F.col("logw") - F.col("top")))
    total = g.groupBy("node_id").agg(F.sum("w").alias("total"))
    return g.join(F.broadcast(total), "node_id").select("node_id", "k", (F.col("w") / F.col("total")).alias("p"))


def noisy_mean(values: DataFrame, bounds: DataFrame, eps: float, noise: Noise = DEFAULT, tree: str = "t", depth: int = 0, sum_share: float = 0.5) -> DataFrame:
    """Noisy sum over noisy count; the midpoint where the noisy count is not positive."""
    v = values.where("v is not null and not isnan(v)").join(F.broadcast(bounds.select("node_id", "lo", "hi")), "node_id")
    # Decimal sums do not depend on the order of addition, so neither does the release.
    sums = v.groupBy("node_id").agg(F.sum((clamp(F.col("v")) - F.col("lo")).cast("decimal(28,6)")).cast("double").alias("s"), F.count("*").alias("n"))
    out = bounds.select("node_id", "lo", "hi").join(sums, "node_id", "left").na.fill(0, ["s", "n"])
    s = F.col("s") + noise.laplace((F.col("hi") - F.col("lo")) / (eps * sum_share), "sum", tree, depth, F.col("node_id"))
    n = F.col("n") + noise.laplace(1 / (eps * (1 - sum_share)), "num", tree, depth, F.col("node_id"))
    return out.select("node_id", clamp(F.when(n > 0, F.col("lo") + s / n).otherwise((F.col("lo") + F.col("hi")) / 2)).alias("split"))


def xi(eps: float, delta: float) -> float:
    return eps / (4 * (1 + math.log(2 / delta)))


def smooth_sigma(x: np.ndarray, m: int, lo: float, hi: float, decay: float) -> float:
    """max over a <= m <= b of exp(-(b - a - 1) decay) (x_b - x_a), ranks 1..n, lo before and hi after.

    The best b does not fall as a grows, so halves of the range of a share out the range of b.
    """
    n = len(x)
    padded = np.concatenate([[lo], x, [hi]])
    best = 0.0
    todo = [(0, m, m, n + 1)]
    while todo:
        a0, a1, b0, b1 = todo.pop()
        if a0 > a1:
            continue
        a = (a0 + a1) // 2
        b = np.arange(max(b0, a + 1), b1 + 1)
        if not len(b):
            continue
        value = np.exp(-(b - a - 1) * decay) * (padded[b] - padded[a])
        at = int(value.argmax())
        best = max(best, float(value[at]))
        todo += [(a0, a - 1, b0, int(b[at])), (a + 1, a1, int(b[at]), b1)]
    return best


def smooth(values: DataFrame, bounds: DataFrame, eps: float, delta: float = 1e-4, noise: Noise = DEFAULT, tree: str = "t", depth: int = 0) -> DataFrame:
    """node_id, sigma, split by smooth sensitivity. Only ranks near the median can matter (terms decay below
    1e-12 of the width), so a task holds a window of ranks, never a node."""
    decay = xi(eps, delta)
    reach = math.ceil(28 / decay)
    ranked, totals = ranks(values, bounds)
    near = ranked.join(F.broadcast(totals), "node_id")
    w = Window.partitionBy("node_id").orderBy("k")
    near = near.withColumn("from_k", F.coalesce(F.lag("k").over(w), F.lit(0).cast("long")) + 1)
    m = middle(F.col("n"))
    near = near.where((F.col("k") >= m - reach) & (F.col("from_k") <= m + reach)).select("node_id", "v", "from_k", "k", "n", "lo", "hi")

    def one(pdf):
        import pandas as pd

        pdf = pdf.sort_values("k")
        n, lo, hi = int(pdf["n"].iloc[0]), float(pdf["lo"].iloc[0]), float(pdf["hi"].iloc[0])
        mid = (n + 1) // 2
        first = max(int(pdf["from_k"].iloc[0]), mid - reach)
        last = min(int(pdf["k"].iloc[-1]), mid + reach)
        count = np.minimum(pdf["k"].to_numpy(), last) - np.maximum(pdf["from_k"].to_numpy(), first) + 1
        x = np.repeat(pdf["v"].to_numpy(), count)
        below = lo if first == 1 else float(x[0])
        above = hi if last == n else float(x[-1])
        sigma = smooth_sigma(x, mid - first + 1, below, above, decay)
        return pd.DataFrame({"node_id": [int(pdf["node_id"].iloc[0])], "sigma": [sigma], "median": [float(x[mid - first])]})

    got = near.groupBy("node_id").applyInPandas(one, "node_id long, sigma double, median double")
    out = bounds.select("node_id", "lo", "hi").join(got, "node_id", "left")
    shifted = F.col("median") + 2 * F.col("sigma") / eps * noise.laplace(1.0, "smo", tree, depth, F.col("node_id"))
    return out.select("node_id", "sigma", clamp(F.coalesce(shifted, (F.col("lo") + F.col("hi")) / 2)).alias("split"))


def cell_split(weights: DataFrame, bounds: DataFrame) -> DataFrame:
    """node_id, line: the grid line nearest to half of a node's noisy weight. weights: node_id, i, w (a
    cell's index and its noisy count, negatives taken as 0); bounds: node_id, i0, i1 (cells [i0, i1))."""
    per = weights.groupBy("node_id", "i").agg(F.sum(F.greatest("w", F.lit(0.0)).cast("decimal(28,9)")).cast("double").alias("w"))
    w = Window.partitionBy("node_id").orderBy("i")
    cum = per.withColumn("cum", F.sum("w").over(w.rowsBetween(Window.unboundedPreceding, 0)))
    total = per.groupBy("node_id").agg(F.sum("w").alias("total"))
    lines = cum.join(F.broadcast(bounds.select("node_id", "i1")), "node_id").join(F.broadcast(total), "node_id").where("i < i1 - 1")
    best = lines.groupBy("node_id").agg(F.min(F.struct(F.round(F.abs(F.col("cum") - F.col("total") / 2), 6).alias("off"), "i")).alias("b"))
    return bounds.join(best, "node_id", "left").select("node_id", F.coalesce(F.col("b.i") + 1, F.col("i1")).cast("long").alias("line"))


def split(values: DataFrame, bounds: DataFrame, method: str, eps: float = 0.0, delta: float = 1e-4, noise: Noise = DEFAULT, tree: str = "t", depth: int = 0, buckets: int = BUCKETS) -> DataFrame:
    if method == "exact":
        return exact(values, bounds, buckets).select("node_id", "split")
    if method == "exponential":
        return exponential(values, bounds, eps, noise, tree, depth, buckets)
    if method == "noisy_mean":
        return noisy_mean(values, bounds, eps, noise, tree, depth)
    if method == "smooth":
        return smooth(values, bounds, eps, delta, noise, tree, depth).select("node_id", "split")
    if method == "laplace":
        return global_laplace(values, bounds, eps, noise, ("lap", depth)).select("node_id", "split")
    raise ValueError(f"no method {method}")


def eighty_twenty(values: DataFrame) -> DataFrame:
    """ratio of the middle three fifths' spread to the observed range, and whether it is a fifth at least."""
    r = values.agg(F.expr("percentile_disc(0.2) within group (order by v)").alias("p20"), F.expr("percentile_disc(0.8) within group (order by v)").alias("p80"), F.min("v").alias("lo"), F.max("v").alias("hi"))
    ratio = (F.col("p80") - F.col("p20")) / (F.col("hi") - F.col("lo"))
    return r.select(ratio.alias("ratio"), (ratio >= 0.2).alias("ok"))


def em_hit_bound() -> float:
    """Under the eighty-twenty condition the exponential mechanism hits the middle three fifths this often."""
    return 1 / 6


def smooth_hit_bound(eps: float) -> float:
    """... and smooth sensitivity, if n xi is 4.03 or more."""
    return 0.5 * (1 - math.exp(-eps / 4))
