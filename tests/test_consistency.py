from fractions import Fraction

import numpy as np
import pytest
from pyspark.sql import functions as F

from noisytree.operators import consistency


def frame(spark, y):
    rows = [(level, i, float(v)) for level, part in enumerate(y) for i, v in enumerate(part)]
    return spark.createDataFrame(rows, "level int, node_id long, y double")


def values(df, y):
    got = {(r.level, r.node_id): r.beta for r in df.collect()}
    return [np.array([got[level, i] for i in range(len(part))]) for level, part in enumerate(y)]


@pytest.mark.parametrize(("f", "eps"), [(4, [0.5, 0.3, 0.2]), (2, [0.5, 0.0, 0.2, 0.1, 0.2]), (4, [0.25] * 3)])
@pytest.mark.parametrize("engine", ["levels", "blocks"])
def test_equals_dense_least_squares(spark, f, eps, engine):
    rng = np.random.default_rng(3)
    h = len(eps) - 1
    y = [rng.normal(20, 9, f ** (h - level)) for level in range(h + 1)]
    dense = consistency.dense_ols(y, eps, f)
    got = values(consistency.ols(frame(spark, y), eps, f, engine, 1), y)
    assert max(np.abs(a - b).max() for a, b in zip(dense, got, strict=True)) < 1e-9


def test_five_node_example(spark):
    y = [np.array([1.0, 2, 3, 2]), np.array([10.0])]
    got = values(consistency.ols(frame(spark, y), [0.5, 0.5]), y)
    assert np.allclose(got[0], [1.4, 2.4, 3.4, 2.4]) and np.allclose(got[1], [9.6])


def test_root_combination():
    weight, variance = consistency.combine_root(0.3, 0.7)
    assert abs(weight - 4 * 0.09 / (4 * 0.09 + 0.49)) < 1e-12 and abs(variance - 8 / (4 * 0.09 + 0.49)) < 1e-12
    # Equal budgets: the plain average of one's own count and four children's has 5/4, the best weights 4/5.
    average, best = Fraction(1, 4) * 1 + Fraction(1, 4) * 4, Fraction(16, 25) + Fraction(1, 25) * 4
    assert (average, best) == (Fraction(5, 4), Fraction(4, 5))


def test_zero_leaf_budget_is_refused(spark):
    with pytest.raises(ValueError):
        consistency.ols(frame(spark, [np.ones(4), np.ones(1)]), [0.0, 1.0])


def test_weighted_tree_equals_dense(spark):
    # Unequal fanouts: root 0, inner 0 and 1 with 3 and 2 leaves.
    leaf, inner = [5.0, 1.0, 2.0, 8.0, 4.0], [9.0, 10.0]
    eps = {0: [0.5, 0.4, 0.3, 0.6, 0.7], 1: [0.5, 0.2], 2: [0.3]}
    rows = [(0, i, 0 if i < 3 else 1, v, eps[0][i]) for i, v in enumerate(leaf)] + [(1, i, 0, v, eps[1][i]) for i, v in enumerate(inner)] + [(2, 0, None, 22.0, 0.3)]
    got = {(r.level, r.node_id): r.beta for r in consistency.weighted_tree(spark.createDataFrame(rows, "level int, node_id long, parent_id long, y double, eps double"), 2).collect()}
    a = np.vstack([np.diag(eps[0]), [[0.5, 0.5, 0.5, 0, 0]], [[0, 0, 0, 0.2, 0.2]], [[0.3] * 5]])
    b = np.array([e * v for e, v in zip(eps[0], leaf, strict=True)] + [0.5 * 9, 0.2 * 10, 0.3 * 22])
    x = np.linalg.lstsq(a, b, rcond=None)[0]
    assert np.allclose([got[0, i] for i in range(5)], x) and abs(got[2, 0] - x.sum()) < 1e-9


def test_gap_is_nil(spark):
    rng = np.random.default_rng(5)
    y = [rng.normal(3, 2, 4**k) for k in (3, 2, 1, 0)]
    fit = consistency.ols(frame(spark, y), [0.4, 0.3, 0.2, 0.1])
    assert consistency.check(fit).agg(F.max(F.abs("gap"))).first()[0] < 1e-9
