import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from noisytree.functions.noise import Noise
from noisytree.operators import measures, medians


def values(spark, v, node=0):
    return spark.createDataFrame([(node, float(x)) for x in v], "node_id long, v double")


def bounds(spark, lo, hi, nodes=(0,)):
    return spark.createDataFrame([(n, float(lo), float(hi)) for n in nodes], "node_id long, lo double, hi double")


def test_exponential_probabilities(spark):
    got = medians.expmech_probabilities(values(spark, [2, 4, 7]), bounds(spark, 0, 10), 2 * math.log(2)).orderBy("k").collect()
    assert np.allclose([r.p for r in got], [1 / 12, 1 / 6, 1 / 2, 1 / 4])


def test_exponential_draws_follow_the_probabilities(spark):
    v = spark.range(3000).select(F.col("id").alias("node_id"), F.explode(F.array(*[F.lit(float(x)) for x in (2, 4, 7)])).alias("v"))
    b = spark.range(3000).select(F.col("id").alias("node_id"), F.lit(0.0).alias("lo"), F.lit(10.0).alias("hi"))
    s = np.array([r.split for r in medians.exponential(v, b, 2 * math.log(2)).collect()])
    share = np.histogram(s, [0, 2, 4, 7, 10])[0] / len(s)
    chi = (3000 * (share - np.array([1 / 12, 1 / 6, 1 / 2, 1 / 4])) ** 2 / np.array([1 / 12, 1 / 6, 1 / 2, 1 / 4])).sum()
    assert chi < 16.3  # 0.999 of chi-square with 3 degrees


def test_smooth_sensitivity_toys():
    x = np.array([2.0, 4, 7])
    assert abs(medians.smooth_sigma(x, 2, 0, 10, math.log(2)) - 3) < 1e-12
    assert abs(medians.smooth_sigma(x, 2, 0, 10, 0.1) - 10 * math.exp(-0.3)) < 1e-9


def test_smooth_sensitivity_equals_brute_force():
    rng = np.random.default_rng(1)
    for _ in range(150):
        n = int(rng.integers(1, 30))
        x, xi = np.sort(rng.random(n) * 10), float(rng.random() * 0.5 + 0.001)
        m, p = (n + 1) // 2, np.concatenate([[0], x, [10]])
        brute = max(math.exp(-(b - a - 1) * xi) * (p[b] - p[a]) for a in range(m + 1) for b in range(max(m, a + 1), n + 2))
        assert abs(medians.smooth_sigma(x, m, 0, 10, xi) - brute) < 1e-9


def test_empty_ties_nulls_and_degenerate_nodes(spark):
    v = values(spark, [5, 5, 5, 9]).unionByName(spark.createDataFrame([(0, None), (0, float("nan"))], "node_id long, v double"))
    b = bounds(spark, 0, 10, (0, 1)).unionByName(spark.createDataFrame([(2, 3.0, 3.0)], "node_id long, lo double, hi double"))
    exact = {r.node_id: (r.split, r.n) for r in medians.exact(v, b).collect()}
    assert exact == {0: (5.0, 4), 1: (5.0, 0), 2: (3.0, 0)}
    for method in ("exponential", "noisy_mean", "smooth", "laplace"):
        got = {r.node_id: r.split for r in medians.split(v, b, method, 0.5).collect()}
        assert set(got) == {0, 1, 2} and got[2] == 3.0 and all(0 <= s <= 10 for s in got.values())
    gaps = medians.gaps(v, b).where("node_id = 0").orderBy("k").collect()
    assert [(r.k, r.left, r.right) for r in gaps] == [(0, 0, 5), (3, 5, 9), (4, 9, 10)]


@pytest.mark.parametrize("buckets", [1, 7, 64])
def test_ranks_do_not_depend_on_buckets(spark, buckets):
    rng = np.random.default_rng(4)
    x = np.round(rng.random(500) * 50)
    ranked, _ = medians.ranks(values(spark, x), bounds(spark, 0, 50), buckets)
    for r in ranked.collect():
        assert r.k == (x <= r.v).sum()
        later = x[x > r.v]
        assert r.after == (later.min() if len(later) else 50)


def test_hit_rates_on_even_data(spark):
    v = spark.range(200).crossJoin(spark.range(400).select(F.col("id").alias("n"))).select(F.col("n").alias("node_id"), (F.col("id") / 2).alias("v"))
    b = spark.range(400).select(F.col("id").alias("node_id"), F.lit(0.0).alias("lo"), F.lit(100.0).alias("hi"))
    s = np.array([r.split for r in medians.exponential(v, b, 0.1).collect()])
    assert ((s >= 20) & (s <= 80)).mean() >= medians.em_hit_bound()


def test_rank_error_bounds(spark):
    v = values(spark, range(100))
    err = lambda s: measures.rank_error(spark.createDataFrame([(0, float(s))], "node_id long, split double"), v).first().rank_err
    assert err(-5) == 1 and err(500) == 1 and err(50) == 0


def test_noise_moments_and_repeatability(spark):
    n = Noise("11")
    rows = spark.range(20000).select(n.laplace(1.0, "a", F.col("id")).alias("x"), n.two_sided_geometric(1.0, "b", F.col("id")).alias("g"))
    m = rows.agg(F.avg("x"), F.var_samp("x"), F.avg("g"), F.var_samp("g")).first()
    q = math.exp(-1)
    assert abs(m[0]) < 0.05 and abs(m[1] - 2) < 0.15 and abs(m[2]) < 0.05 and abs(m[3] - 2 * q / (1 - q) ** 2) < 0.15
    assert rows.repartition(7).agg(F.sum("x")).first()[0] == pytest.approx(rows.agg(F.sum("x")).first()[0])
    secure = Noise.fresh()
    assert secure.secure and len(secure.seed) == 64


def test_likelihood_ratio_of_neighbours(spark):
    n = Noise("5")
    rows = spark.range(20000).select(n.laplace(1.0, "x", F.col("id")).alias("x"))
    a = np.array([r.x for r in rows.collect()])
    one, two = np.histogram(a + 10, np.arange(7, 14))[0], np.histogram(a + 11, np.arange(7, 14))[0]
    assert (np.maximum(one / two, two / one) < math.e * 1.2).all()
