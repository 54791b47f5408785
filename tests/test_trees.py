import numpy as np
import pytest
from pyspark.sql import functions as F

from noisytree.functions import hilbert
from noisytree.functions.cells import with_boxes
from noisytree.functions.noise import DEFAULT
from noisytree.operators import answer, counts, measures, prune, trees
from noisytree.plans import budget
from noisytree.plans.build import TreeSpec, build, split_budgets
from noisytree.plans.domain import EV, LI, plane
from noisytree.plans.ledger import Entry, Ledger
from noisytree.plans.schema import assert_released
from noisytree.sources import workloads
from noisytree.sources.points import points, read_points
from noisytree.sources.releases import publish, read_release, release, to_wkt
from tests.conftest import TINY

TOY = plane(0.0, 4.0, 0.0, 4.0)


def box(spark, *b):
    return spark.createDataFrame([(0, "s", *map(float, b))], "qid long, shape string, qx0 double, qx1 double, qy0 double, qy1 double")


def toy(spark):
    return spark.createDataFrame([(str(i), float(i % 4) + 0.5, float(i // 4) + 0.5) for i in range(16)], "pid string, x double, y double")


def test_canonical_nodes_of_the_toy(spark):
    nodes = answer.midpoint_nodes(counts.tree_counts(toy(spark), TOY, 2).withColumn("beta", F.col("c").cast("double")), TOY, 2)
    for b, levels, estimate, partial in (((0, 3, 0, 2), [0, 0, 1], 6, 0), ((0, 2.5, 0, 2), [0, 0, 1], 5, 2)):
        t = answer.touched(nodes, box(spark, *b), TOY, "beta")
        assert sorted(r.level for r in t.collect()) == levels
        for strategy in ("nested", "cells", "descent"):
            r = answer.canonical(nodes, box(spark, *b), TOY, strategy=strategy, h=2).first()
            assert (r.estimate, r.n_partial) == (estimate, partial)


def test_all_strategies_agree_and_stay_within_bounds(spark):
    p, q = points(spark, TINY, "EV"), workloads.boxes(spark, EV, 8, tuple(workloads.SHAPES))
    nodes = answer.midpoint_nodes(counts.tree_counts(p, EV, 5).withColumn("beta", F.col("c").cast("double")), EV, 5).cache()
    got = [{r.qid: round(r.estimate, 6) for r in answer.canonical(nodes, q, EV, strategy=s, h=5).collect()} for s in ("nested", "cells", "descent")]
    assert got[0] == got[1] == got[2]
    for r in answer.touch_profile(nodes, q, EV, "beta").collect():
        assert r.n_i <= budget.touch_bound(5, 4, 2, r.level)


def test_removing_a_row_moves_one_count_a_level(spark):
    p = points(spark, TINY, "LI")
    gone = p.orderBy("pid").limit(1).select("pid")
    full, less = counts.tree_counts(p, LI, 3), counts.tree_counts(p.join(gone, "pid", "left_anti"), LI, 3)
    d = full.join(less.withColumnRenamed("c", "c2"), ["level", "node_id"]).select((F.col("c") - F.col("c2")).alias("d"))
    assert sorted(r.d for r in d.collect())[-4:] == [1, 1, 1, 1] and d.agg(F.sum("d")).first()[0] == 4


def test_release_does_not_depend_on_partitions(spark):
    p = points(spark, TINY, "EV")
    run = lambda q: {(r.level, r.node_id): (r.y, r.beta) for r in build(q, EV, TreeSpec("kd", 1, split="noisy_mean", tree="x")).collect()}
    one, two = run(p), run(p.repartition(5))
    assert one.keys() == two.keys() and all(one[k][0] == two[k][0] and abs(one[k][1] - two[k][1]) < 1e-9 for k in one)


@pytest.mark.parametrize("spec", [TreeSpec("quad", 2), TreeSpec("kd", 1), TreeSpec("kd", 1, split="exact", exact_counts=True), TreeSpec("kd", 1, split="cell", cells=(16, 16)), TreeSpec("kd", 1, split="smooth"), TreeSpec("kd", 1, sample=0.5), TreeSpec("hybrid", 2, switch=1), TreeSpec("hilbert", 1, order=10)], ids=lambda s: f"{s.kind}-{s.split}")
def test_every_tree_counts_all_points_and_leaks_none(spark, spec):
    p = points(spark, TINY, "EV")
    nodes = build(p, EV, spec.but(eps=200.0))
    assert_released(nodes)
    level, _ = split_budgets(spec)
    assert abs(sum(level) - spec.eps * (1 if spec.kind == "quad" or spec.split == "exact" else spec.count_share)) < 1e-9
    n, root = p.count(), nodes.where(F.col("level") == spec.h).first()
    assert abs(root.beta - n) < 2 and nodes.count() == sum(4**k for k in range(spec.h + 1))
    leaves = nodes.where("level = 0").agg(F.sum("beta")).first()[0]
    assert abs(leaves - n) < 5
    whole = box(spark, EV.axes[0].lo, EV.axes[0].hi, EV.axes[1].lo, EV.axes[1].hi)
    assert abs(answer.canonical(nodes, whole, EV).first().estimate - n) < 5


def test_points_stand_in_their_boxes(spark):
    grown = trees.grow(points(spark, TINY, "EV"), EV, 4, "exponential", [0.2] * 4)
    j = grown.points.join(grown.boxes[-1], "node_id")
    assert j.where("x < x0 or x > x1 or y < y0 or y > y1").isEmpty() and j.count() == grown.points.count()
    area = grown.boxes[-1].agg(F.sum((F.col("x1") - F.col("x0")) * (F.col("y1") - F.col("y0")))).first()[0]
    assert abs(area - 30 * 640) < 1e-6


def test_empty_nodes_and_bad_points(spark):
    p = spark.createDataFrame([("a", 1.0, None), ("b", float("nan"), 1.0), ("c", -9.0, 99.0)], "pid string, x double, y double")
    got = {(r.level, r.node_id): r.c for r in counts.tree_counts(p, TOY, 1).collect()}
    assert got == {(0, 0): 0, (0, 1): 1, (0, 2): 0, (0, 3): 0, (1, 0): 1}  # outside points go to the outermost cell
    noisy = counts.add_noise(counts.tree_counts(p.limit(0), TOY, 1), [0.5, 0.5], "e")
    assert noisy.where("y is null").isEmpty() and noisy.where("y = 0").isEmpty()


def test_hilbert_curve(spark):
    assert [hilbert.point(v, 1) for v in range(4)] == [(0, 0), (0, 1), (1, 1), (1, 0)]
    for order in (1, 2, 3, 5):
        cells = [hilbert.point(v, order) for v in range(4**order)]
        assert len(set(cells)) == 4**order
        assert all(abs(a - c) + abs(b - d) == 1 for (a, b), (c, d) in zip(cells, cells[1:], strict=False))
        rows = spark.createDataFrame([(x, y, v) for v, (x, y) in enumerate(cells)], "x long, y long, v long")
        assert rows.where(hilbert.encode(F.col("x"), F.col("y"), order) != F.col("v")).isEmpty()


def test_interval_boxes():
    for lo, hi in ((0, 64), (3, 17), (5, 6), (10, 40)):
        cells = [hilbert.point(v, 3) for v in range(lo, hi)]
        xs, ys = [c[0] for c in cells], [c[1] for c in cells]
        assert hilbert.interval_box(lo, hi, 3) == (min(xs), max(xs) + 1, min(ys), max(ys) + 1)
    assert hilbert.interval_box(5, 5, 3) is None


def test_pruning_reads_released_counts_only(spark):
    nodes = with_boxes(counts.add_noise(counts.tree_counts(points(spark, TINY, "EV"), EV, 3), budget.geometric(1.0, 3), "p").withColumn("beta", F.col("y")), EV, 3)
    kept = prune.by_noisy_count(nodes, 50, 3)
    low = {(r.level, r.node_id) for r in nodes.where("beta < 50").collect()}
    got = {(r.level, r.node_id) for r in kept.collect()}
    want = {(r.level, r.node_id) for r in nodes.collect() if not any((u, r.node_id >> (2 * (u - r.level))) in low for u in range(r.level + 1, 4))}
    assert got == want and prune.by_noisy_count(nodes, None, 3).count() == nodes.count()


def test_variance_is_that_of_replicas(spark):
    p, q, eps = points(spark, TINY, "EV"), box(spark, 3, 17, 10, 300), budget.geometric(1.0, 2)
    c = counts.tree_counts(p, EV, 2).cache()
    boxed = lambda n: answer.midpoint_nodes(n, EV, 2)
    want = measures.noise_variance(boxed(counts.add_noise(c, eps, "v")), q, EV, eps).first().err
    one = boxed(counts.add_noise(c, eps, "v").withColumn("y", F.lit(0.0)))
    used = answer.touched(one, q, EV, "y").cache()
    # Many draws of the same nodes' noise in one frame.
    from noisytree.functions.noise import Noise

    draws = used.withColumn("s", F.explode(F.sequence(F.lit(1), F.lit(600)))).withColumn("n", Noise("1").laplace(1 / counts.level_value(eps), F.col("s"), F.col("level"), F.col("node_id")) * F.col("part"))
    got = draws.groupBy("s").agg(F.sum("n").alias("n")).agg(F.var_samp("n")).first()[0]
    assert abs(got / want - 1) < 0.25
    few = measures.replicate(c, q, EV, eps, boxed, ["1", "2", "3"]).first()
    assert few["var"] > 0


def test_sinks(spark, tmp_path):
    book = Ledger(spark, str(tmp_path / "ledger"))
    p = points(spark, TINY, "EV")
    nodes = build(p, EV, TreeSpec("quad", 2))
    with pytest.raises(ValueError):
        release(counts.tree_counts(p, EV, 2), str(tmp_path / "r"), Entry("EV", "bad", 1.0), book, DEFAULT, 2, testing=True)
    release(nodes, str(tmp_path / "r"), Entry("EV", "t", 1.0), book, DEFAULT, 2, testing=True)
    assert read_release(spark, str(tmp_path / "r"), "t").count() == 21
    with pytest.raises(ValueError):
        release(nodes, str(tmp_path / "r"), Entry("EV", "t", 1.0), book, DEFAULT, 2, testing=True)
    p.select("pid", "x", "y").write.option("header", True).csv(str(tmp_path / "csv"))
    again = read_points(spark, "csv", str(tmp_path / "csv"), {"pid": "pid", "x": "x", "y": "y"}, EV, schema="pid string, x double, y double", header=True)
    assert again.count() == p.count()
    assert nodes.select(to_wkt()).first()[0].startswith("POLYGON((")


def test_synthetic_points(spark):
    for kind in ("uniform", "mixture", "power"):
        r = workloads.synthetic(spark, kind, 500).agg(F.count("*"), F.min("x"), F.max("x"), F.min("y"), F.max("y")).first()
        assert r[0] == 500 and min(r[1], r[3]) >= 0 and max(r[2], r[4]) < 1
    assert np.isclose(workloads.uniform_values(spark, 2000).agg(F.avg("x")).first()[0], 2**25, rtol=0.05)


def test_optimised_quadtree_beats_the_plain_one(spark):
    p, q = points(spark, TINY, "LI"), workloads.boxes(spark, LI, 20)
    truth = answer.exact(p, q, LI).cache()
    err = {}
    for name, spec in {"plain": TreeSpec("quad", 5, 0.1, count_budget="uniform", post=False), "best": TreeSpec("quad", 5, 0.1)}.items():
        got = answer.canonical(build(p, LI, spec), q, LI)
        err[name] = measures.relative_error(got, truth, q).where("shape = 'square_large'").agg(F.percentile("rel_err", F.lit(0.5))).first()[0]
    assert err["best"] < err["plain"]


def test_a_release_is_private_by_default(spark, tmp_path):
    p = points(spark, TINY, "EV")
    book, path = Ledger(spark, str(tmp_path / "ledger")), str(tmp_path / "r")
    spec = TreeSpec("quad", 2, 1.0)
    nodes = build(p, EV, spec)
    with pytest.raises(ValueError, match="public seed"):
        release(nodes, path, Entry("EV", "open", 1.0), book, DEFAULT, 2)
    with pytest.raises(ValueError, match="spends"):
        release(nodes, path, Entry("EV", "dear", 0.5), book, DEFAULT, 2, testing=True)
    with pytest.raises(ValueError, match="no release"):
        publish(p, EV, spec.but(exact_counts=True), path, "EV", "exact", book)
    assert book.entries().count() == 0
    publish(p, EV, spec, path, "EV", "one", book)
    publish(p, EV, spec, path, "EV", "two", book, neighbor="replace")
    one, two = ({(r.level, r.node_id): r for r in read_release(spark, path, t).collect()} for t in ("one", "two"))
    assert one.keys() == two.keys() and not {r.y for r in one.values()} & {r.y for r in two.values()}
    assert all(abs(two[k].eps_count - one[k].eps_count / 2) < 1e-12 for k in one)
    assert book.spent("EV") == (2.0, 0.0)
