import pytest
from pyspark.sql import functions as F

from noisytree import workloads as runs
from noisytree.functions import hilbert, sqlfuncs, udfs
from noisytree.functions.noise import DEFAULT
from noisytree.operators import answer, medians, prune, sampling, uses
from noisytree.plans.build import TreeSpec, build
from noisytree.plans.domain import CUST, EV, LI, Axis, Domain
from noisytree.sources import workloads
from noisytree.sources.points import points, table
from tests.conftest import TINY


def test_sql_surface(spark):
    sqlfuncs.register(spark)
    assert spark.sql("SELECT box_fraction(0D, 4D, 1D, 3D) AS f, cell_id(7D, 0D, 8D, 4L) AS c").first()[:] == (0.5, 3)
    want = spark.range(5).select(DEFAULT.laplace(2.0, "k", F.col("id")).alias("x")).collect()
    got = spark.sql("SELECT laplace_at(concat('k:', id), 2D) AS x FROM range(5)").collect()
    assert [round(r.x, 9) for r in got] == [round(r.x, 9) for r in want]
    assert sorted(r[:] for r in spark.sql("SELECT * FROM hilbert_blocks(3, 17)").collect()) == sorted((s, 1 << k) for s, k in hilbert.blocks(3, 17))


def test_range_count_in_sql(spark):
    nodes = build(points(spark, TINY, "EV"), EV, TreeSpec("quad", 3))
    sqlfuncs.register_tree(spark, nodes, "ev_tree")
    q = workloads.boxes(spark, EV, 3)
    want = {r.qid: r.estimate for r in answer.canonical(nodes, q, EV).collect()}
    for r in q.collect():
        got = spark.sql(f"SELECT * FROM ev_tree_count({r.qx0}D, {r.qx1}D, {r.qy0}D, {r.qy1}D)").first().estimate
        assert abs(got - want[r.qid]) < 1e-6


def test_arrow_functions_equal_columns(spark):
    cells = spark.range(1024).select((F.col("id") % 32).alias("x"), F.floor(F.col("id") / 32).alias("y"))
    assert cells.where(udfs.hilbert_encode_arrow(5)("x", "y") != hilbert.encode(F.col("x"), F.col("y"), 5)).isEmpty()
    v = table(spark, TINY, "customer").select(F.col("c_nationkey").cast("long").alias("node_id"), F.col("c_acctbal").alias("v"))
    b = v.select("node_id").distinct().select("node_id", F.lit(-1000.0).alias("lo"), F.lit(10000.0).alias("hi"))
    xi = medians.xi(1.0, 1e-4)
    one = {r.node_id: round(r.s, 6) for r in v.groupBy("node_id").agg(udfs.smooth_sens_agg(-1000.0, 10000.0, xi)("v").alias("s")).collect()}
    assert one == {r.node_id: round(r.sigma, 6) for r in medians.smooth(v, b, 1.0, 1e-4).collect()}


def test_uses_of_a_release(spark):
    nodes = build(points(spark, TINY, "LI"), LI, TreeSpec("quad", 3, 5.0))
    n = points(spark, TINY, "LI").count()
    cdf = [r.cdf for r in uses.marginal(nodes, LI).orderBy("bin").collect()]
    assert len(cdf) == 8 and abs(cdf[-1] - 1) < 1e-9
    assert 0 < uses.quantile(nodes, LI, 0.5).first()[0] < 105_000
    assert uses.density(nodes, LI, 1).count() == 16 and uses.busiest(nodes, LI, 5).count() == 5
    assert abs(uses.synthetic_points(nodes, LI).count() - n) < 60
    small = prune.by_area(nodes, 105_000 * 2560 / 16, ["x", "y"])
    assert small.groupBy("level").count().count() == 4 and small.where("level = 1 and is_leaf").isEmpty()
    less = prune.by_area(nodes, 105_000 * 2560 / 8, ["x", "y"])
    assert less.where("level = 0").isEmpty() and less.where("level = 1 and is_leaf").count() == 16


def test_sweeps_run(spark):
    p = points(spark, TINY, "EV")
    q = runs.non_empty_boxes(spark, p, EV, 4, ("square_large",))
    assert q.count() == 4
    assert runs.quadtree_options(p, EV, q, 3, (1.0,)).count() == 4
    assert runs.pruning(p, EV, q, 3, values=(None, 32)).count() == 2
    assert runs.switches(p, EV, q, 1).count() == 2
    assert runs.orders(p, EV, q, 1, values=(12,)).count() == 1
    assert runs.build_times(p, EV, {"quad": TreeSpec("quad", 2)}).first().nodes == 21
    ratio = runs.record_matching(points(spark, TINY, "CUST"), points(spark, TINY, "SUPP"), CUST, (50.0, 0.0), 1, (1.0,)).collect()
    assert len(ratio) == 3 and all(0 <= r.ratio <= 1 for r in ratio)


def test_median_quality_ranks_the_methods(spark):
    v = workloads.uniform_values(spark, 1 << 12)
    got = runs.median_quality(v, depth=1, eps=0.5, rate=0.2).collect()
    err = {r.method: r.rank_err for r in got}
    assert set(err) == {"exponential", "smooth", "noisy_mean", "exponential_s", "smooth_s", "cell"}
    assert err["exponential"] <= 0.05 and all(0 <= e <= 1 for e in err.values())


def test_samples_are_the_same_in_any_layout(spark):
    p = points(spark, TINY, "LI")
    one = {r.pid for r in sampling.bernoulli(p, 0.1).collect()}
    assert one == {r.pid for r in sampling.bernoulli(p.repartition(3), 0.1).collect()} and 400 < len(one) < 800
    assert sampling.rate_for(0.1) == pytest.approx(0.01)


def test_bad_domains_are_refused():
    with pytest.raises(ValueError):
        Axis("x", 1.0, 1.0)
    assert Domain((Axis("x", 0.0, 1.0),)).box == ["x0", "x1"]
