import math

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from noisytree.operators import sampling
from noisytree.plans import budget, ledger


@given(st.floats(0.01, 5), st.integers(0, 12))
@settings(max_examples=60, deadline=None)
def test_strategies_sum_to_the_whole(eps, h):
    for b in (budget.uniform(eps, h), budget.geometric(eps, h), budget.leaf_only(eps, h)):
        assert math.isclose(sum(b), eps, rel_tol=1e-12) and len(b) == h + 1


def test_geometric_ratio_and_values():
    leaf, root = budget.geometric(1.0, 1)
    assert math.isclose(leaf / root, 2 ** (1 / 3))
    assert round(leaf, 6) == 0.557507 and round(root, 6) == 0.442493
    assert math.isclose(budget.growth(2, 2), 2 ** (1 / 6)) and budget.growth(2, 1) == 1.0


@given(st.lists(st.floats(0.05, 1), min_size=5, max_size=5))
@settings(max_examples=60, deadline=None)
def test_geometric_is_the_optimum(weights):
    cost = lambda e: sum(2 ** (4 - i) / x**2 for i, x in enumerate(e))
    other = [w / sum(weights) for w in weights]
    assert cost(budget.geometric(1.0, 4)) <= cost(other) * (1 + 1e-9)


def test_workload_levels_contain_geometric():
    got = budget.for_workload_levels([2.0 ** (5 - i) for i in range(6)], 0.7)
    assert all(math.isclose(a, b) for a, b in zip(got, budget.geometric(0.7, 5)))


def test_bad_budgets_are_refused():
    for bad in (lambda: budget.custom([0, 1]), lambda: budget.skip(1, 3, {1, 2}), lambda: budget.custom([1, -1]), lambda: budget.split(1, 0)):
        with pytest.raises(ValueError):
            bad()


def test_skip_and_hybrid():
    b = budget.skip(1.0, 3, {0, 2, 3})
    assert b[1] == 0 and math.isclose(sum(b), 1)
    assert budget.median_hybrid(0.3, 4, 2) == [0.075] * 4 + [0.0] * 4


def test_worst_case_curves(spark):
    from pyspark.sql import functions as F

    unif, geom = budget.worst_case(F.col("id").cast("double"))
    rows = spark.range(5, 11).select(unif.alias("u"), geom.alias("g")).collect()
    assert [round(r.u) for r in rows] == [2268, 6223, 16320, 41391, 102300, 247687]
    assert [round(r.g, 1) for r in rows] == [1537.6, 3754.2, 8718.5, 19533.0, 42622.9, 91189.6]


def test_amplification():
    assert round(sampling.amplify(0.9, 0.01, "stated"), 4) == 0.0492
    assert round(sampling.required_eps(0.01, 0.01), 3) == 0.697 or abs(sampling.required_eps(0.01, 0.01) - math.log(1 + (math.exp(0.01) - 1) / 0.01)) < 1e-12
    assert math.isclose(sampling.amplify(sampling.required_eps(0.01, 0.01), 0.01), 0.01)
    with pytest.raises(ValueError):
        sampling.required_eps(0.01, 0.01, "stated")


def test_height_advice_grows_with_the_data():
    heights = [budget.advise_height(n, 0.5) for n in (1e2, 1e4, 1e6, 1e8)]
    assert heights == sorted(heights) and heights[0] < heights[-1]


def test_ledger(spark, tmp_path):
    book = ledger.Ledger(spark, str(tmp_path / "ledger"))
    assert book.spent("d") == (0.0, 0.0)
    book.append(ledger.Entry("d", "t1", 0.5, 1e-4, spec={"h": "3"}))
    book.append(ledger.Entry("d", "t2", 0.25))
    assert book.spent("d") == (0.75, 1e-4)
    with pytest.raises(ValueError):
        book.append(ledger.Entry("d", "t1", 0.1))
    assert ledger.compose_sequential([ledger.Entry("d", "a", 1), ledger.Entry("d", "b", 2)]) == (3, 0)
    assert ledger.compose_parallel([ledger.Entry("d", "a", 1), ledger.Entry("d", "b", 2)]) == (2, 0)
    assert ledger.sensitivity_of("sum", 10.0, "replace") == 20.0


def test_workload_nodes_sum_along_paths(spark):
    from noisytree.catalogue import queries
    from tests.conftest import TINY

    rows = queries()["budget_workload_nodes"](spark, TINY).collect()
    eps = {(r.level, r.node_id): r.eps for r in rows}
    for leaf in range(64):
        assert abs(sum(eps[level, leaf >> (2 * level)] for level in range(4)) - 1) < 1e-4
