"""All queries of the library, with their equivalents in SQL.

Unless stated: points of lineitem (price, ship day), height 3, fanout 4, budget 1, seed 7, doubles rounded to 6
digits.
"""

from __future__ import annotations

import re
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from noisytree import oracles as sql
from noisytree.functions.cells import enumerate_nodes, with_boxes
from noisytree.functions.noise import DEFAULT
from noisytree.operators import answer, consistency, counts, matching, measures, medians, prune, sampling, trees, uses
from noisytree.operators.durable import durable
from noisytree.plans import budget, domain, ledger
from noisytree.plans.domain import CUST, EMB, EV, LI, Domain
from noisytree.sources import workloads
from noisytree.sources.points import micros, points, table
from noisytree.streaming import windows

H = 3
_QUERIES: dict = {}
_SQL: dict[str, str] = {}


def query(f=None, *, text: str | None = None):
    def add(g):
        _QUERIES[g.__name__] = g
        if text is not None:
            _SQL[g.__name__] = text
        return g

    return add(f) if f else add


def r6(c) -> Column:
    """Rounded to 6 digits, without a negative zero."""
    return F.round(c, 6) + F.lit(0.0)


def li(spark: SparkSession, sf: str) -> DataFrame:
    return points(spark, sf, "LI")


def ev(spark: SparkSession, sf: str) -> DataFrame:
    return points(spark, sf, "EV")


def noisy_quad(p: DataFrame, h: int, eps: list[float], tree: str = "q", dom: Domain = LI) -> DataFrame:
    """level, node_id, y: drawn once, then read from storage."""
    return durable(counts.add_noise(counts.tree_counts(p, dom, h), eps, tree))


def fitted_quad(p: DataFrame, h: int, eps: list[float], tree: str = "q", dom: Domain = LI) -> DataFrame:
    return durable(consistency.ols(noisy_quad(p, h, eps, tree, dom), eps))


# -- exact counts, grids, boxes -------------------------------------------------------------------
@query(text=f"WITH pts AS ({sql.POINTS['LI']}), {sql.boxes(LI)}, {sql.exact_answers(LI)} SELECT qid, shape, true_count FROM truth JOIN boxes USING (qid)")
def range_exact(spark, sf):
    q = workloads.boxes(spark, LI)
    return answer.exact(li(spark, sf), q, LI).join(q, "qid").select("qid", "shape", "true_count")


_GRID = f"""WITH pts AS ({sql.POINTS['EV']}), cells AS (SELECT ({sql.cell('x', 0, 30, 16)}) * 16 + {sql.cell('y', 0, 640, 16)} AS cell_id FROM pts),
n AS (SELECT cell_id, count(*) AS c FROM cells GROUP BY 1), g AS (SELECT range AS cell_id, coalesce(c, 0)::BIGINT AS c FROM range(256) LEFT JOIN n ON cell_id = range)"""


@query(text=f"{_GRID} SELECT cell_id, c FROM g")
def grid_counts(spark, sf):
    return counts.grid_counts(ev(spark, sf), EV, (16, 16))


@query(text=f"{_GRID}, u AS (SELECT *, {sql.uniform(chr(39) + 'cell' + chr(39), chr(39) + 'grid' + chr(39), 'cell_id')} AS u FROM g) SELECT cell_id, round(c + {sql.lap('u')}, 6) + 0 AS y FROM u")
def grid_noisy(spark, sf):
    return counts.grid_noisy(ev(spark, sf), EV, (16, 16), 1.0).select("cell_id", r6("y").alias("y"))


@query(text=f"WITH {sql.counts('LI', LI, H)} SELECT level, node_id, c FROM nodes")
def quad_counts(spark, sf):
    return counts.tree_counts(li(spark, sf), LI, H)


@query(text=f"WITH {sql.leaves('LI', LI, H)}, d AS (SELECT (node_id >> 4) & 3 AS d1, (node_id >> 2) & 3 AS d2, node_id & 3 AS d3, c FROM leaf) SELECT d1, d2, d3, grouping(d1, d2, d3)::BIGINT AS gid, sum(c)::BIGINT AS c FROM d GROUP BY ROLLUP (d1, d2, d3)")
def quad_counts_rollup(spark, sf):
    return counts.by_rollup(li(spark, sf), LI, H)


@query(text=f"WITH {sql.counts('EMB', EMB, 2)} SELECT level, node_id, c FROM nodes")
def octree_counts(spark, sf):
    return counts.tree_counts(points(spark, sf, "EMB"), EMB, 2)


@query(text=f"WITH {sql.leaves('LI', LI, H)} SELECT node_id, {sql.node_box(LI, H, 0)} FROM leaf")
def leaf_boxes(spark, sf):
    """Of the leaves that hold a point."""
    return with_boxes(counts.tree_counts(li(spark, sf), LI, H).where("level = 0 and c > 0").drop("c"), LI, H).drop("level")


# -- noise, budgets, consistency ------------------------------------------------------------------
_GEO, _UNI = sql.geometric(H), budget.uniform(1.0, H)
_QUAD = f"WITH {sql.counts('LI', LI, H)}, {sql.noisy(_GEO, 'q')}"


@query(text=f"{_QUAD} SELECT level, node_id, round(y, 6) + 0 AS y FROM noisy")
def quad_noisy(spark, sf):
    return counts.add_noise(counts.tree_counts(li(spark, sf), LI, H), _GEO, "q").select("level", "node_id", r6("y").alias("y"))


@query(text=f"""WITH {sql.counts('LI', LI, H)}, u AS (SELECT *, CASE level {' '.join(f'WHEN {i} THEN {sql.dbl(e)}' for i, e in enumerate(_GEO))} END AS e,
{sql.uniform("'up'", "'cnt'", "'q'", "level", "node_id")} AS a, {sql.uniform("'down'", "'cnt'", "'q'", "level", "node_id")} AS b FROM nodes)
SELECT level, node_id, (c + floor(ln(a) / -e) - floor(ln(b) / -e))::BIGINT AS y FROM u""")
def quad_geometric_noise(spark, sf):
    n = counts.add_noise(counts.tree_counts(li(spark, sf), LI, H), _GEO, "q", integer=True)
    return n.select("level", "node_id", F.col("y").cast("long").alias("y"))


@query(text=f"{_QUAD}, {sql.ols(_GEO, H)} SELECT level, node_id, round(beta, 6) + 0 AS beta FROM fit")
def quad_ols(spark, sf):
    return fitted_quad(li(spark, sf), H, _GEO).select("level", "node_id", r6("beta").alias("beta"))


@query(text=_QUAD + ", " + sql.ols(_GEO, H) + " SELECT level, node_id, round(beta, 6) + 0 AS beta FROM fit")
def quad_ols_blocks(spark, sf):
    return consistency.ols(noisy_quad(li(spark, sf), H, _GEO), _GEO, engine="blocks", cut=2).select("level", "node_id", r6("beta").alias("beta"))


@query(text=f"WITH {sql.counts('LI', LI, H)}, {sql.noisy(_UNI, 'q')}, {sql.ols(_UNI, H)} SELECT level, node_id, round(beta, 6) + 0 AS beta FROM fit")
def quad_uniform_ols(spark, sf):
    return fitted_quad(li(spark, sf), H, _UNI).select("level", "node_id", r6("beta").alias("beta"))


@query(text=f"SELECT level, node_id, 0::DOUBLE AS gap FROM ({sql.all_nodes(H, 4)}) WHERE level > 0")
def ols_consistency_gap(spark, sf):
    return consistency.check(fitted_quad(li(spark, sf), H, _GEO)).select("level", "node_id", r6(F.round("gap", 6)).alias("gap"))


#: A tree for the orders of each customer, by how many there are (a public size): its height, from 3 on, is the least
#: at which a leaf of fanout 2 holds one of them on average, 10 at most.
_TREES = "trees AS (SELECT o_custkey AS tree, CASE " + " ".join(f"WHEN count(*) <= {2**i} THEN {3 + i}" for i in range(7)) + " ELSE 10 END AS h FROM orders WHERE o_custkey IS NOT NULL GROUP BY 1)"


def order_trees(spark: SparkSession, sf: str) -> DataFrame:
    """tree (a customer), h, n (orders)."""
    n = table(spark, sf, "orders").where("o_custkey is not null").groupBy(F.col("o_custkey").alias("tree")).agg(F.count("*").alias("n"))
    return n.select("tree", reduce(lambda other, i: F.when(F.col("n") <= 2**i, 3 + i).otherwise(other), reversed(range(7)), F.lit(10)).alias("h"), "n")


@query(text=f"WITH {_TREES} SELECT tree, h::INTEGER AS h, level::INTEGER AS level, round(1.0::DOUBLE / (h + 1), 6) AS eps FROM trees, LATERAL (SELECT unnest(range(0, h + 1)) AS level)")
def budget_uniform(spark, sf):
    rows = order_trees(spark, sf).select("tree", "h", F.explode(F.sequence(F.lit(0), F.col("h"))).alias("level"))
    return rows.select("tree", "h", "level", F.round(F.lit(1.0) / (F.col("h") + 1), 6).alias("eps"))


@query(text=f"""WITH {_TREES}, w AS (SELECT tree, h, level, pow(2::DOUBLE, (h - level) / 3.0::DOUBLE) AS w FROM trees, LATERAL (SELECT unnest(range(0, h + 1)) AS level))
SELECT tree, h::INTEGER AS h, level::INTEGER AS level, round(w / sum(w) OVER (PARTITION BY tree), 6) AS eps FROM w""")
def budget_geometric(spark, sf):
    shares = F.array(*[F.array(*[F.lit(e) for e in budget.geometric(1.0, h)]) for h in range(3, 11)])
    rows = order_trees(spark, sf).select("tree", "h", F.posexplode(F.element_at(shares, F.col("h") - 2)).alias("level", "eps"))
    return rows.select("tree", "h", "level", F.round("eps", 6).alias("eps"))


@query(text=f"""WITH {_TREES} SELECT tree, h::INTEGER AS h, round((h + 1) * (h + 1) * (pow(2::DOUBLE, h + 1) - 1), 4) AS unif,
round(pow(list_sum(list_transform(range(0, h + 1), lambda i: pow(2::DOUBLE, i / 3.0::DOUBLE))), 3), 4) AS geom FROM trees""")
def worst_case_curve(spark, sf):
    unif, geom = budget.worst_case(F.col("h").cast("double"))
    return order_trees(spark, sf).select("tree", "h", F.round(unif, 4).alias("unif"), F.round(geom, 4).alias("geom"))


@query(text="""WITH rates AS (SELECT o_custkey AS tree, 1::DOUBLE / count(*) AS p FROM orders WHERE o_custkey IS NOT NULL GROUP BY 1)
SELECT tree, e AS eps, round(p, 6) AS p, round(2 * p * exp(e), 6) AS stated, round(ln(1 + p * (exp(e) - 1)), 6) AS tight
FROM rates, (SELECT unnest([0.1, 0.5, 0.9, 1.0, 2.0]::DOUBLE[]) AS e)""")
def amplification_table(spark, sf):
    """What a sample of one order a customer on average amplifies."""
    p = F.lit(1.0) / F.col("n")
    rows = order_trees(spark, sf).select("tree", F.explode(F.array(*[F.lit(e) for e in (0.1, 0.5, 0.9, 1.0, 2.0)])).alias("eps"), p.alias("p"))
    stated, tight = 2 * F.col("p") * F.exp("eps"), F.log1p(F.col("p") * F.expm1("eps"))
    return rows.select("tree", "eps", F.round("p", 6).alias("p"), F.round(stated, 6).alias("stated"), F.round(tight, 6).alias("tight"))


# -- range answers and errors ---------------------------------------------------------------------
H4 = 4
_GEO4, _UNI4 = sql.geometric(H4), budget.uniform(1.0, H4)
_TREE4 = f"WITH {sql.counts('LI', LI, H4)}, {sql.noisy(_GEO4, 'q')}, {sql.ols(_GEO4, H4)}, {sql.boxes(LI)}, {sql.descent(LI, H4, 'noisy')}"


def tree4(spark, sf) -> tuple[DataFrame, DataFrame]:
    nodes = fitted_quad(li(spark, sf), H4, _GEO4)
    return answer.midpoint_nodes(nodes, LI, H4), workloads.boxes(spark, LI)


def est(df: DataFrame, name: str = "estimate") -> DataFrame:
    return df.select("qid", r6(name).alias("estimate"))


@query(text=f"{_TREE4} SELECT qid, level, count(*) AS n_i FROM hit GROUP BY ALL")
def touch_profile(spark, sf):
    return answer.touch_profile(*tree4(spark, sf), LI)


@query(text="SELECT NULL::BIGINT AS qid, NULL::INTEGER AS level, NULL::BIGINT AS n_i, NULL::DOUBLE AS bound WHERE false")
def touch_bound_violations(spark, sf):
    bound = counts.level_value([budget.touch_bound(H4, 4, 2, i) for i in range(H4 + 1)])
    return answer.touch_profile(*tree4(spark, sf), LI).withColumn("bound", bound).where("n_i > bound")


@query(text=f"{_TREE4}, {sql.answers('noisy', 'y')} SELECT qid, round(estimate, 6) + 0 AS estimate FROM ans")
def range_answers_y(spark, sf):
    return est(answer.canonical(*tree4(spark, sf), LI, "y"))


_BETA = f"{_TREE4}, {sql.answers('fit', 'beta')} SELECT qid, round(estimate, 6) + 0 AS estimate FROM ans"


@query(text=_BETA)
def range_answers_beta(spark, sf):
    return est(answer.canonical(*tree4(spark, sf), LI))


@query(text=_BETA)
def range_answers_cells(spark, sf):
    return est(answer.canonical(*tree4(spark, sf), LI, strategy="cells", h=H4))


@query(text=_BETA)
def range_answers_descent(spark, sf):
    return est(answer.canonical(*tree4(spark, sf), LI, strategy="descent", h=H4))


@query(text=f"""WITH {sql.counts('LI', LI, H)}, {sql.noisy(_GEO, 'q')}, {sql.ols(_GEO, H)}, {sql.boxes(LI)}, {sql.descent(LI, H, 'noisy')}, {sql.answers('fit', 'beta')}
SELECT qid, round(estimate, 4) + 0 AS direct, round(estimate, 4) + 0 AS complement FROM ans""")
def answers_by_complement(spark, sf):
    nodes = answer.midpoint_nodes(fitted_quad(li(spark, sf), H, _GEO), LI, H)
    got = answer.by_complement(nodes, workloads.boxes(spark, LI), LI)
    return got.select("qid", *[(F.round(c, 4) + F.lit(0.0)).alias(c) for c in ("direct", "complement")])


_VAR = f"{_TREE4}, err AS (SELECT b.qid, b.shape, coalesce(sum(2 * part * part / (e * e)), 0) AS err FROM boxes b LEFT JOIN hit USING (qid) LEFT JOIN (SELECT DISTINCT level, e FROM noisy) USING (level) GROUP BY ALL)"


@query(text=f"{_VAR} SELECT qid, round(err, 6) AS err FROM err")
def noise_variance(spark, sf):
    return measures.noise_variance(*tree4(spark, sf), LI, _GEO4).select("qid", F.round("err", 6).alias("err"))


@query(text=f"{_VAR} SELECT shape, round(avg(err), 6) AS err FROM err GROUP BY 1")
def workload_error(spark, sf):
    return measures.workload_error(measures.noise_variance(*tree4(spark, sf), LI, _GEO4)).select("shape", F.round("err", 6).alias("err"))


_VARIANTS = {"geometric_ols": (_GEO4, True), "geometric_raw": (_GEO4, False), "uniform_ols": (_UNI4, True), "uniform_raw": (_UNI4, False)}


def _errors_sql() -> str:
    parts = [sql.counts("LI", LI, H4), sql.boxes(LI), sql.exact_answers(LI), sql.descent(LI, H4, "nodes"), sql.noisy(_GEO4, "q", name="ng"), sql.ols(_GEO4, H4, src="ng", name="fg"), sql.noisy(_UNI4, "q", name="nu"), sql.ols(_UNI4, H4, src="nu", name="fu")]
    rows = []
    for v, (src, col) in {"geometric_ols": ("fg", "beta"), "geometric_raw": ("ng", "y"), "uniform_ols": ("fu", "beta"), "uniform_raw": ("nu", "y")}.items():
        parts.append(sql.answers(src, col, f"a_{v}"))
        rows.append(f"SELECT '{v}' AS variant, shape, abs(estimate - true_count) / true_count AS e FROM a_{v} JOIN truth USING (qid) JOIN boxes USING (qid) WHERE true_count > 0")
    return f"WITH {', '.join(parts)} SELECT variant, shape, round(quantile_cont(e, 0.5), 6) AS med_rel_err FROM ({' UNION ALL '.join(rows)}) GROUP BY ALL"


@query(text=_errors_sql())
def median_rel_error(spark, sf):
    p, q = li(spark, sf), workloads.boxes(spark, LI)
    truth, out = durable(answer.exact(p, q, LI)), []
    for name, (eps, post) in _VARIANTS.items():
        nodes = fitted_quad(p, H4, eps) if post else noisy_quad(p, H4, eps)
        got = answer.canonical(answer.midpoint_nodes(nodes, LI, H4), q, LI, "beta" if post else "y")
        out.append(measures.median_relative_error(got, truth, q).select(F.lit(name).alias("variant"), "shape", F.round("med_rel_err", 6).alias("med_rel_err")))
    return reduce(DataFrame.unionByName, out)


@query(text=f"""WITH {sql.counts('EV', EV, H4)}, {sql.boxes(EV)}, {sql.exact_answers(EV)}, {sql.descent(EV, H4, 'nodes')}, {sql.answers('nodes', 'c')}
SELECT shape, round(quantile_cont(abs(estimate - true_count) / true_count, 0.5), 6) AS med_rel_err FROM ans JOIN truth USING (qid) JOIN boxes USING (qid) WHERE true_count > 0 GROUP BY 1""")
def uniformity_error_exact_tree(spark, sf):
    p, q = ev(spark, sf), workloads.boxes(spark, EV)
    nodes = answer.midpoint_nodes(counts.tree_counts(p, EV, H4).withColumn("beta", F.col("c").cast("double")), EV, H4)
    return measures.median_relative_error(answer.canonical(nodes, q, EV), answer.exact(p, q, EV), q).select("shape", F.round("med_rel_err", 6).alias("med_rel_err"))


@query(text=f"""WITH {sql.counts('LI', LI, H4)}, {sql.noisy(_GEO4, 'q')}, {sql.ols(_GEO4, H4)}, {sql.boxes(LI)}, {sql.exact_answers(LI)}, {sql.descent(LI, H4, 'nodes')}, {sql.answers('fit', 'beta')}
SELECT qid, round(abs(estimate - true_count), 6) + 0 AS abs_err FROM ans JOIN truth USING (qid)""")
def absolute_error(spark, sf):
    nodes, q = tree4(spark, sf)
    return measures.absolute_error(answer.canonical(nodes, q, LI), answer.exact(li(spark, sf), q, LI)).select("qid", r6("abs_err").alias("abs_err"))


@query(text=f"""WITH {sql.counts('EV', EV, H)}, {sql.noisy(_GEO, 'q')}, {sql.ols(_GEO, H)},
gone AS (SELECT DISTINCT n.level, n.node_id FROM fit n JOIN fit a ON a.level > n.level AND a.beta < 32 AND (n.node_id >> (2 * (a.level - n.level))) = a.node_id)
SELECT level, node_id, round(beta, 6) + 0 AS beta, (level = 0 OR beta < 32) AS is_leaf FROM fit ANTI JOIN gone USING (level, node_id)""")
def pruned_tree(spark, sf):
    nodes = fitted_quad(ev(spark, sf), H, _GEO, dom=EV)
    return prune.by_noisy_count(nodes, 32, H).select("level", "node_id", r6("beta").alias("beta"), "is_leaf")


_SKIP = budget.skip(1.0, H, {0, 2, 3})


@query(text=f"WITH {sql.counts('LI', LI, H)}, {sql.noisy(_SKIP, 'q')}, {sql.boxes(LI)}, {sql.descent(LI, H, 'noisy', skipped=(1,))}, {sql.answers('noisy', 'y')} SELECT qid, round(estimate, 6) + 0 AS estimate FROM ans")
def skip_levels_answers(spark, sf):
    nodes = with_boxes(noisy_quad(li(spark, sf), H, _SKIP), LI, H)
    return est(answer.canonical(answer.with_parent_boxes(nodes, LI, H), workloads.boxes(spark, LI), LI, "y"))


_LEAF = budget.leaf_only(1.0, H)


@query(text=f"WITH {sql.counts('LI', LI, H)}, {sql.noisy(_LEAF, 'q')}, {sql.boxes(LI)}, {sql.descent(LI, H, 'noisy', skipped=(1, 2, 3))}, {sql.answers('noisy', 'y')} SELECT qid, round(estimate, 6) + 0 AS estimate FROM ans")
def leaf_only_answers(spark, sf):
    nodes = with_boxes(noisy_quad(li(spark, sf), H, _LEAF), LI, H)
    return est(answer.canonical(answer.with_parent_boxes(nodes, LI, H), workloads.boxes(spark, LI), LI, "y"))


@query(text=f"""{_TREE4}, n AS (SELECT l.level, coalesce(count(hit.qid), 0) AS n FROM (SELECT unnest(range(0, {H4 + 1}))::INTEGER AS level) l LEFT JOIN hit USING (level) GROUP BY 1),
w AS (SELECT level, cbrt(greatest(n, 1e-9)) AS w FROM n) SELECT level, round(w / sum(w) OVER (), 6) AS eps FROM w""")
def budget_workload_levels(spark, sf):
    got = answer.touch_profile(*tree4(spark, sf), LI).groupBy("level").agg(F.sum("n_i").alias("n"))
    n = {r["level"]: r["n"] for r in got.collect()}  # h + 1 rows
    eps = budget.for_workload_levels([n.get(i, 0) for i in range(H4 + 1)], 1.0)
    return spark.createDataFrame([(i, round(e, 6)) for i, e in enumerate(eps)], "level int, eps double")


@query
def budget_workload_nodes(spark, sf):
    """Each box is asked once for each point in it."""
    boxes = workloads.boxes(spark, LI)
    nodes = answer.midpoint_nodes(enumerate_nodes(spark, H, 4).withColumn("y", F.lit(0.0)), LI, H)
    asked = answer.exact(li(spark, sf), boxes, LI).select("qid", "true_count")
    used = answer.touched(nodes, boxes, LI, "y").join(asked, "qid").groupBy("level", "node_id").agg(F.sum(F.col("part") * F.col("part") * F.col("true_count")).alias("w"))
    every = enumerate_nodes(spark, H, 4).join(used, ["level", "node_id"], "left").na.fill(0.0, ["w"])
    return budget.for_workload_nodes(every, H, 1.0).select("level", "node_id", F.round("eps", 6).alias("eps"))


# -- medians --------------------------------------------------------------------------------------
def val(spark, sf) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(types: event_type, node_id; values; bounds)."""
    e = table(spark, sf, "events")
    names = e.select("event_type").distinct()
    # A handful of types: numbered by how many come before.
    types = durable(names.join(F.broadcast(names.select(F.col("event_type").alias("o"))), F.col("o") < F.col("event_type"), "left").groupBy("event_type").agg(F.count("o").alias("node_id")))
    values = e.join(F.broadcast(types), "event_type").select("node_id", F.col("event_id").cast("string").alias("pid"), F.col("value").cast("double").alias("v"))
    return types, values, types.select("node_id", F.lit(0.0).alias("lo"), F.lit(640.0).alias("hi"))


def typed(types: DataFrame, got: DataFrame, *cols) -> DataFrame:
    return types.join(got, "node_id").select("event_type", *cols)


@query(text=f"WITH {sql.VAL}, {sql.median('val', 'bnd', 's')} SELECT event_type, n, round(split, 6) AS med FROM s JOIN types USING (node_id)")
def median_exact(spark, sf):
    t, v, b = val(spark, sf)
    return typed(t, medians.exact(v, b), "n", F.round("split", 6).alias("med"))


@query(text=f"""WITH {sql.VAL}, {sql.median('val', 'bnd', 's')}, u AS (SELECT *, {sql.uniform("'lap'", "0", "node_id")} AS u FROM s),
o AS (SELECT *, split + 640 * {sql.lap('u')} AS o FROM u) SELECT event_type, round(o, 6) AS out, (o >= 0 AND o < 640) AS in_range FROM o JOIN types USING (node_id)""")
def median_laplace(spark, sf):
    t, v, b = val(spark, sf)
    return typed(t, medians.global_laplace(v, b, 1.0), F.round("out", 6).alias("out"), ((F.col("out") >= 0) & (F.col("out") < 640)).alias("in_range"))


@query(text="""WITH v AS (SELECT 'PRICE' AS view, l_extendedprice::DOUBLE AS v FROM lineitem UNION ALL SELECT 'VAL', value FROM events UNION ALL SELECT 'LEN', n_chars FROM documents UNION ALL SELECT 'ACCT', c_acctbal FROM customer),
r AS (SELECT view, (quantile_disc(v, 0.8) - quantile_disc(v, 0.2)) / (max(v) - min(v)) AS ratio FROM v GROUP BY 1) SELECT view, round(ratio, 6) AS ratio, ratio >= 0.2 AS ok FROM r""")
def eighty_twenty(spark, sf):
    out = []
    for name, src in {"PRICE": points(spark, sf, "PRICE"), "VAL": points(spark, sf, "VAL"), "LEN": points(spark, sf, "LEN"), "ACCT": points(spark, sf, "CUST")}.items():
        out.append(medians.eighty_twenty(src.select(F.col("x").alias("v"))).select(F.lit(name).alias("view"), F.round("ratio", 6).alias("ratio"), "ok"))
    return reduce(DataFrame.unionByName, out)


@query(text=sql.smooth_sigma(medians.xi(1.0, 1e-4)))
def smooth_sensitivity(spark, sf):
    v = table(spark, sf, "customer").select(F.col("c_nationkey").cast("long").alias("node_id"), F.col("c_acctbal").cast("double").alias("v"))
    b = v.select("node_id").distinct().select("node_id", F.lit(-1000.0).alias("lo"), F.lit(10000.0).alias("hi"))
    return medians.smooth(v, b, 1.0, 1e-4).select(F.col("node_id").alias("nationkey"), F.round("sigma", 6).alias("sigma"))


@query(text=f"""WITH {sql.VAL}, whole AS (SELECT node_id, floor(v) AS v FROM val), {sql.ranked('whole', 'bnd', 'g')},
w AS (SELECT node_id, k, ln(r - l) - 0.1::DOUBLE * abs(k - {sql.MID}) / 2 AS w FROM g_g), e AS (SELECT node_id, k, exp(w - max(w) OVER (PARTITION BY node_id)) AS e FROM w)
SELECT event_type, k, round(e / sum(e) OVER (PARTITION BY node_id), 6) AS p FROM e JOIN types USING (node_id)""")
def expmech_probabilities(spark, sf):
    t, v, b = val(spark, sf)
    return typed(t, medians.expmech_probabilities(v.withColumn("v", F.floor("v").cast("double")), b, 0.1), "k", F.round("p", 6).alias("p"))


@query(text=f"WITH {sql.VAL}, {sql.em('val', 'bnd', 0.1, 'm', 0, 's')} SELECT event_type, round(split, 6) AS split FROM s JOIN types USING (node_id)")
def expmech_split(spark, sf):
    t, v, b = val(spark, sf)
    return typed(t, medians.exponential(v, b, 0.1, tree="m"), F.round("split", 6).alias("split"))


@query(text=f"WITH {sql.VAL}, {sql.mean('val', 'bnd', 0.1, 'm', 0, 's')} SELECT event_type, round(split, 6) AS split FROM s JOIN types USING (node_id)")
def noisy_mean_split(spark, sf):
    t, v, b = val(spark, sf)
    return typed(t, medians.noisy_mean(v, b, 0.1, tree="m"), F.round("split", 6).alias("split"))


_CELLS = f"""cells AS (SELECT node_id, i::BIGINT AS i FROM types, range(64) r(i)), n AS (SELECT node_id, {sql.cell('v', 0, 640, 64)} AS i, count(*) AS c FROM val GROUP BY ALL),
y AS (SELECT node_id, i, coalesce(c, 0) AS c, {sql.uniform("'cell'", "'m'", "node_id", "i")} AS u FROM cells LEFT JOIN n USING (node_id, i)),
p AS (SELECT node_id, i, greatest(c + 10::DOUBLE * {sql.lap('u')}, 0)::DECIMAL(28,9)::DOUBLE AS w FROM y),
cum AS (SELECT *, sum(w) OVER (PARTITION BY node_id ORDER BY i) AS cum, sum(w) OVER (PARTITION BY node_id) AS total FROM p),
s AS (SELECT node_id, (arg_min(i, (round(abs(cum - total / 2), 6), i)) + 1) * 10.0::DOUBLE AS split FROM cum WHERE i < 63 GROUP BY 1)"""


def cell_medians(types, v) -> DataFrame:
    """node_id, split from 64 noisy cells of [0, 640) with budget 0.1."""
    from noisytree.functions.cells import axis_cell

    axis = domain.VAL.axes[0]
    got = v.groupBy("node_id", axis_cell(F.col("v"), axis, 64).alias("i")).agg(F.count("*").alias("c"))
    every = types.select("node_id", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(63).cast("long"))).alias("i"))
    w = every.join(got, ["node_id", "i"], "left").select("node_id", "i", (F.coalesce("c", F.lit(0)) + DEFAULT.laplace(1 / 0.1, "cell", "m", F.col("node_id"), F.col("i"))).alias("w"))
    bounds = types.select("node_id", F.lit(0).cast("long").alias("i0"), F.lit(64).cast("long").alias("i1"))
    return medians.cell_split(w, bounds).select("node_id", (F.col("line") * 10.0).alias("split"))


@query(text=f"WITH {sql.VAL}, {_CELLS} SELECT event_type, split FROM s JOIN types USING (node_id)")
def cell_median(spark, sf):
    t, v, _ = val(spark, sf)
    return typed(t, cell_medians(t, v), "split")


@query(text=f"""WITH pts AS ({sql.POINTS['LI']}), smp AS (SELECT 0::BIGINT AS node_id, x AS v FROM pts WHERE {sql.uniform("'smp'", "0", "pid")} < 0.01),
bnd AS (SELECT 0::BIGINT AS node_id, 0::DOUBLE AS lo, 105000::DOUBLE AS hi), {sql.em('smp', 'bnd', sampling.required_eps(0.01, 0.01), 'm', 0, 's')}
SELECT round(split, 6) AS split, (SELECT count(*) FROM smp) AS n_sample FROM s""")
def expmech_split_sampled(spark, sf):
    s = durable(sampling.bernoulli(points(spark, sf, "PRICE"), 0.01).select(F.lit(0).cast("long").alias("node_id"), F.col("x").alias("v")))
    b = spark.range(1).select(F.col("id").alias("node_id"), F.lit(0.0).alias("lo"), F.lit(105000.0).alias("hi"))
    got = medians.exponential(s, b, sampling.required_eps(0.01, 0.01), tree="m")
    return got.join(s.agg(F.count("*").alias("n_sample"))).select(F.round("split", 6).alias("split"), "n_sample")


_METHODS_SQL = f"""WITH {sql.VAL}, {sql.median('val', 'bnd', 'm1')}, {sql.em('val', 'bnd', 0.1, 'm', 0, 'm2')}, {sql.mean('val', 'bnd', 0.1, 'm', 0, 'm3')}, {_CELLS},
allm AS (SELECT 'exact' AS method, node_id, split FROM m1 UNION ALL SELECT 'exponential', node_id, split FROM m2 UNION ALL SELECT 'noisy_mean', node_id, split FROM m3 UNION ALL SELECT 'cell', node_id, split FROM s),
held AS (SELECT method, node_id, count(*) AS n, sum(CASE WHEN v < split THEN 1 ELSE 0 END) AS below FROM allm JOIN val USING (node_id) GROUP BY ALL)"""


def all_splits(spark, sf):
    t, v, b = val(spark, sf)
    return t, v, {"exact": medians.exact(v, b), "exponential": medians.exponential(v, b, 0.1, tree="m"), "noisy_mean": medians.noisy_mean(v, b, 0.1, tree="m"), "cell": cell_medians(t, v)}


@query(text=f"{_METHODS_SQL} SELECT method, event_type, round(least(1, abs(below - n / 2.0::DOUBLE) / (n / 2.0::DOUBLE)), 6) AS rank_err FROM held JOIN types USING (node_id)")
def split_rank_error(spark, sf):
    t, v, splits = all_splits(spark, sf)
    return reduce(DataFrame.unionByName, [typed(t, measures.rank_error(s, v), F.lit(m).alias("method"), F.round("rank_err", 6).alias("rank_err")) for m, s in splits.items()])


@query(text=f"{_METHODS_SQL} SELECT method, event_type, round(below::DOUBLE / n, 6) AS left_share FROM held JOIN types USING (node_id)")
def split_balance(spark, sf):
    t, v, splits = all_splits(spark, sf)
    return reduce(DataFrame.unionByName, [typed(t, measures.balance(s, v), F.lit(m).alias("method"), F.round("left_share", 6).alias("left_share")) for m, s in splits.items()])


@query(text=f"WITH pts AS ({sql.POINTS['LI']}) SELECT pid, x, y FROM pts WHERE {sql.uniform(chr(39) + 'smp' + chr(39), '0', 'pid')} < 0.01")
def bernoulli_sample(spark, sf):
    return sampling.bernoulli(li(spark, sf), 0.01)


# -- trees that follow the data -------------------------------------------------------------------
_C1, _M1 = sql.geometric(1, 0.7), 0.15


def boxed(nodes: DataFrame, dom: Domain, *cols) -> DataFrame:
    return nodes.select("level", "node_id", *[r6(c).alias(c) for c in dom.box], *cols)


def _kd_sql(h: int, stage, tail: str, extra: str = "", dom: Domain = LI, view: str = "LI", src: str | None = None) -> str:
    return f"WITH RECURSIVE {src or sql.clamped(view, dom)}{extra}, {sql.kd(dom, 2 * h, stage)}, {sql.kd_nodes(dom, h)} {tail}"


def _exact_stage(v, o, b, s):
    return sql.median(v, o, s)


@query(text=_kd_sql(2, _exact_stage, f"SELECT level, node_id, {sql.rounded(LI, 'c')} FROM tree"))
def kd_exact(spark, sf):
    return boxed(trees.counted(trees.grow(li(spark, sf), LI, 4, "exact", [], "kd")), LI, "c")


_G2 = sql.geometric(2)


@query(text=_kd_sql(2, _exact_stage, f", {sql.noisy(_G2, 'kd', 'tree')} SELECT level, node_id, {sql.rounded(LI, 'round(y, 6) + 0 AS y')} FROM noisy"))
def kd_exact_split_noisy(spark, sf):
    got = trees.counted(trees.grow(li(spark, sf), LI, 4, "exact", [], "kd"))
    return boxed(trees.released(got, _G2, "kd"), LI, r6("y").alias("y"))


def _released(tree: str, dom: Domain = LI) -> str:
    return f", {sql.noisy(_C1, tree, 'tree')} SELECT level, node_id, {sql.rounded(dom, 'round(y, 6) + 0 AS y')} FROM noisy"


def _kd1(spark, sf, method: str, tree: str, eps: float = _M1, **more) -> DataFrame:
    got = trees.counted(trees.grow(li(spark, sf), LI, 2, method, [eps] * 2, tree, **more))
    return boxed(trees.released(got, _C1, tree), LI, r6("y").alias("y"))


@query(text=_kd_sql(1, lambda v, o, b, s: sql.em(v, o, _M1, "kde", b, s), _released("kde")))
def kd_expmech(spark, sf):
    return _kd1(spark, sf, "exponential", "kde")


@query(text=_kd_sql(1, lambda v, o, b, s: sql.mean(v, o, _M1, "kdm", b, s), _released("kdm")))
def kd_noisy_mean(spark, sf):
    return _kd1(spark, sf, "noisy_mean", "kdm")


_SMP = 0.05


@query(text=_kd_sql(1, lambda v, o, b, s: f"""{v}s AS (SELECT p.node_id, p.{'xy'[b]} AS v FROM p{b} p WHERE {sql.uniform("'smp'", str(b), "pid")} < {_SMP}), """ + sql.em(f"{v}s", o, sampling.required_eps(_M1, _SMP), "kds", b, s), _released("kds")))
def kd_expmech_sampled(spark, sf):
    return _kd1(spark, sf, "exponential", "kds", sampling.required_eps(_M1, _SMP), sample=_SMP)


@query
def kd_smooth(spark, sf):
    return _kd1(spark, sf, "smooth", "kdss", delta=1e-4)


def _cell_kd_sql() -> str:
    dom, n = LI, 64
    grid = f"""cells0 AS (SELECT {sql.cell('x', 0, 105000, n)} AS ix, {sql.cell('y', 0, 2560, n)} AS iy, count(*) AS c FROM pts GROUP BY ALL),
cy AS (SELECT i::BIGINT AS ix, j::BIGINT AS iy, coalesce(c, 0) AS c, {sql.uniform("'cell'", "'kdc'", "(i * 64 + j)")} AS u FROM range({n}) a(i), range({n}) b(j) LEFT JOIN cells0 ON ix = i AND iy = j),
g0 AS (SELECT ix, iy, 0::BIGINT AS node_id, greatest(c + {sql.dbl(1 / (1.0 - 0.7))} * {sql.lap('u')}, 0) AS w FROM cy)"""
    grid += ", r0 AS (SELECT 0::BIGINT AS node_id, 0::BIGINT AS ix0, 64::BIGINT AS ix1, 0::BIGINT AS iy0, 64::BIGINT AS iy1)"

    def stage(v, o, b, s):
        i, a = ("ix", "iy")[b], dom.axes[b]
        return f"""q{b} AS (SELECT node_id, {i} AS i, sum(w::DECIMAL(28,9))::DOUBLE AS w FROM g{b} GROUP BY ALL),
k{b} AS (SELECT *, sum(w) OVER (PARTITION BY node_id ORDER BY i) AS cum, sum(w) OVER (PARTITION BY node_id) AS total FROM q{b}),
l{b} AS (SELECT r.node_id, coalesce(arg_min(i, (round(abs(cum - total / 2), 6), i)) + 1, any_value({i}1)) AS line FROM r{b} r LEFT JOIN k{b} k ON k.node_id = r.node_id AND k.i < r.{i}1 - 1 GROUP BY 1),
g{b + 1} AS (SELECT ix, iy, node_id * 2 + CASE WHEN {i} >= line THEN 1 ELSE 0 END AS node_id, w FROM g{b} JOIN l{b} USING (node_id)),
r{b + 1} AS (SELECT node_id * 2 AS node_id, * EXCLUDE (node_id, line, {i}1), line AS {i}1 FROM r{b} JOIN l{b} USING (node_id) UNION ALL BY NAME SELECT node_id * 2 + 1 AS node_id, * EXCLUDE (node_id, line, {i}0), line AS {i}0 FROM r{b} JOIN l{b} USING (node_id)),
{s} AS (SELECT node_id, {sql.dbl(a.lo)} + {sql.dbl(a.hi - a.lo)} * line / {sql.dbl(n)} AS split FROM l{b})"""

    return _kd_sql(1, stage, _released("kdc"), ", " + grid)


@query(text=_cell_kd_sql())
def kd_cell(spark, sf):
    got = trees.counted(trees.cell_tree(li(spark, sf), LI, 2, (64, 64), 1.0 - 0.7, "kdc"))
    return boxed(trees.released(got, _C1, "kdc"), LI, r6("y").alias("y"))


@query(text=_kd_sql(2, _exact_stage, "SELECT level, node_id, CASE WHEN level < 2 THEN node_id >> 2 END AS parent_id, c FROM tree"))
def kd_flatten(spark, sf):
    grown = trees.grow(li(spark, sf), LI, 4, "exact", [], "kd")
    return trees.flatten(trees.binary_counts(grown), 4).select("level", "node_id", "parent_id", "c")


@query(text=_kd_sql(2, _exact_stage, ", b AS (" + " UNION ALL ".join(f"SELECT {level}::INTEGER AS level, node_id >> {level} AS node_id, count(*) AS c FROM p4 GROUP BY 2" for level in range(5)) + ") SELECT level, node_id, c FROM b"))
def kd_binary_counts(spark, sf):
    return trees.binary_counts(trees.grow(li(spark, sf), LI, 4, "exact", [], "kd")).where("c > 0")


_HC = sql.geometric(3, 0.7)


def _hybrid_sql() -> str:
    em = lambda v, o, b, s: sql.em(v, o, _M1, "hyb", b, s)
    at = lambda n: f"CASE WHEN {n}1 > {n}0 THEN least(3, greatest(0, floor(({n} - {n}0) / ({n}1 - {n}0) * 4::DOUBLE)::BIGINT)) ELSE 0 END"
    parts = [f"pin AS (SELECT p.node_id, {at('x')} AS ix, {at('y')} AS iy FROM p2 p JOIN b2 USING (node_id))", f"leaf AS (SELECT node_id * 16 + {sql.interleave(['ix', 'iy'], 2)} AS node_id FROM pin)"]
    rows = ["SELECT 3::INTEGER AS level, node_id, x0, x1, y0, y1 FROM b0", "SELECT 2::INTEGER AS level, node_id, x0, x1, y0, y1 FROM b2"]
    for level, k in ((1, 4), (0, 16)):
        n = 2 ** (2 - level)
        end = lambda a, ax, e, n=n: f"{ax}0 + ({ax}1 - {ax}0) * (0::DOUBLE + 1::DOUBLE * ({sql.bits_of('l.range', 2, 2, a)} + {e}) / {n}::DOUBLE) AS {ax}{e}"
        rows.append(f"SELECT {level}::INTEGER AS level, node_id * {k} + l.range AS node_id, {end(0, 'x', 0)}, {end(0, 'x', 1)}, {end(1, 'y', 0)}, {end(1, 'y', 1)} FROM b2, range({k}) l")
    parts.append("shape AS (" + " UNION ALL ".join(rows) + ")")
    parts.append("tree AS (SELECT *, (SELECT count(*) FROM leaf WHERE leaf.node_id >> (2 * shape.level) = shape.node_id) AS c FROM shape)")
    return f"WITH {sql.clamped('LI', LI)}, {sql.kd(LI, 2, em)}, {', '.join(parts)}, {sql.noisy(_HC, 'hyb', 'tree')} SELECT level, node_id, {sql.rounded(LI, 'round(y, 6) + 0 AS y')} FROM noisy"


@query(text=_hybrid_sql())
def hybrid_tree(spark, sf):
    got = trees.hybrid(li(spark, sf), LI, 3, 1, [_M1] * 2, "hyb")
    return boxed(trees.released(got, _HC, "hyb"), LI, r6("y").alias("y"))


@query(text=f"WITH RECURSIVE pts AS ({sql.POINTS['EV']}), {sql.hilbert()} SELECT pid::BIGINT AS event_id, hv FROM curve")
def hilbert_encode(spark, sf):
    return trees.curve_points(ev(spark, sf), EV, 18).select(F.col("pid").cast("long").alias("event_id"), "hv")


_CURVE = f"pts AS ({sql.POINTS['EV']}), {sql.hilbert()}, pts0 AS (SELECT pid, hv::DOUBLE AS h, x, y FROM curve)"


@query(text=_kd_sql(1, lambda v, o, b, s: sql.em(v, o, _M1, "hil", b, s), f", {sql.noisy(_C1, 'hil', 'tree')} SELECT level, node_id, round(h0, 3) AS h_lo, round(h1, 3) AS h_hi, round(y, 6) + 0 AS y FROM noisy", dom=sql.HV, src=_CURVE))
def hilbert_tree(spark, sf):
    got = trees.hilbert_tree(ev(spark, sf), EV, 1, [_M1] * 2, tree="hil")
    return trees.released(got, _C1, "hil").select("level", "node_id", F.round("h0", 3).alias("h_lo"), F.round("h1", 3).alias("h_hi"), r6("y").alias("y"))


@query(text=_kd_sql(1, _exact_stage, "SELECT p.node_id, round(min(q.x), 6) AS x0, round(max(q.x), 6) AS x1, round(min(q.y), 6) AS y0, round(max(q.y), 6) AS y1 FROM p2 p JOIN pts0 q USING (pid) GROUP BY 1", dom=sql.HV, src=_CURVE))
def hilbert_exact_boxes(spark, sf):
    got = trees.exact_hilbert(ev(spark, sf), EV, 1).where("level = 0")
    return got.select("node_id", *[F.round(c, 6).alias(c) for c in EV.box])


@query(text=f"SELECT range::BIGINT AS leaf, round({sql.dbl(sum(_C1))} + {sql.dbl(2 * _M1)}, 6) AS eps FROM range(4)")
def path_epsilon(spark, sf):
    grown = trees.grow(li(spark, sf), LI, 2, "exponential", [_M1] * 2, "kde")
    nodes = trees.released(trees.counted(grown), _C1, "kde")
    # Both binary splits below the root are on every path.
    split_cost = F.when(F.col("level") == 1, F.lit(2 * _M1)).otherwise(F.lit(0.0))
    return ledger.path_epsilon(nodes.withColumn("eps_split", split_cost), 1).select("leaf", F.round("eps", 6).alias("eps"))


# -- uses of a release ----------------------------------------------------------------------------
@query(text=f"{_QUAD}, {sql.ols(_GEO, H)}, d AS (SELECT node_id, beta / ({sql.dbl(105000 / 8)} * {sql.dbl(2560 / 8)}) AS density FROM fit WHERE level = 0) SELECT node_id, round(density, 9) AS density FROM d ORDER BY d.density DESC, node_id LIMIT 10")
def release_topk_density(spark, sf):
    nodes = with_boxes(fitted_quad(li(spark, sf), H, _GEO), LI, H)
    return uses.busiest(nodes, LI, 10).select("node_id", F.round("density", 9).alias("density"))


@query(text=f"""{_QUAD}, {sql.ols(_GEO, H)}, b AS (SELECT x0 AS bin, sum(beta) AS n FROM (SELECT beta, {sql.node_box(LI, H, 0)} FROM fit WHERE level = 0) GROUP BY 1)
SELECT bin, round(sum(n) OVER (ORDER BY bin) / sum(n) OVER (), 6) AS cdf FROM b""")
def release_cdf(spark, sf):
    nodes = with_boxes(fitted_quad(li(spark, sf), H, _GEO), LI, H)
    return uses.marginal(nodes, LI).select("bin", F.round("cdf", 6).alias("cdf"))


_REGIONS = (("cheap early", 0.0, 26250.0, 0.0, 640.0), ("cheap late", 0.0, 26250.0, 1920.0, 2560.0), ("dear", 78750.0, 105000.0, 0.0, 2560.0), ("odd", 10000.0, 50000.0, 100.0, 1500.0))


@query(text=f"""{_QUAD}, {sql.ols(_GEO, H)}, boxes AS (SELECT i::BIGINT AS qid, name, a::DOUBLE AS qx0, b::DOUBLE AS qx1, c::DOUBLE AS qy0, d::DOUBLE AS qy1 FROM (VALUES {", ".join(f"({i}, '{n}', {a}, {b}, {c}, {d})" for i, (n, a, b, c, d) in enumerate(_REGIONS))}) t(i, name, a, b, c, d)), {sql.descent(LI, H, 'fit')}, {sql.answers('fit', 'beta')}
SELECT name, round(estimate, 6) + 0 AS estimate, round(estimate / (SELECT beta FROM fit WHERE level = 3), 6) + 0 AS share FROM ans JOIN boxes USING (qid)""")
def region_list_counts(spark, sf):
    nodes = answer.midpoint_nodes(fitted_quad(li(spark, sf), H, _GEO), LI, H)
    named = spark.createDataFrame([(i, *r) for i, r in enumerate(_REGIONS)], "qid long, name string, qx0 double, qx1 double, qy0 double, qy1 double")
    return uses.regions(nodes, named, LI).select("name", r6("estimate").alias("estimate"), r6("share").alias("share"))


def _difference_sql() -> str:
    parts = []
    for t, cond in (("a", "<"), ("b", ">=")):
        source = f"SELECT * FROM ({sql.POINTS['LI']}) WHERE y {cond} 1280"
        one = sql.counts("LI", LI, H, source)
        for n in ("pts", "ix", "leaf", "up", "every", "nodes"):
            one = re.sub(rf"\b{n}\b", f"{n}_{t}", one)
        parts += [one, sql.noisy(_GEO, f"d{t}", f"nodes_{t}", f"noisy_{t}"), sql.ols(_GEO, H, src=f"noisy_{t}", name=f"fit_{t}")]
    return f"WITH {', '.join(parts)} SELECT level, node_id, round(b.beta - a.beta, 6) + 0 AS delta FROM fit_a a JOIN fit_b b USING (level, node_id)"


@query(text=_difference_sql())
def release_difference(spark, sf):
    p = li(spark, sf)
    one, two = (fitted_quad(p.where(c), H, _GEO, t) for c, t in (("y < 1280", "da"), ("y >= 1280", "db")))
    return uses.difference(one, two).select("level", "node_id", r6("delta").alias("delta"))


_NR = """keys AS (SELECT n_nationkey::BIGINT AS nk, n_regionkey::BIGINT AS rk FROM nation), c AS (SELECT c_nationkey::BIGINT AS nk, count(*) AS c FROM customer GROUP BY 1),
tree AS (SELECT 0::INTEGER AS level, nk AS node_id, coalesce(c, 0)::BIGINT AS c FROM keys LEFT JOIN c USING (nk)
UNION ALL SELECT 1, rk, coalesce(sum(c), 0)::BIGINT FROM keys LEFT JOIN c USING (nk) GROUP BY rk UNION ALL SELECT 2, 0, (SELECT sum(c) FROM c)::BIGINT)"""
_NRE = [1 / 3] * 3


@query(text=f"WITH {_NR}, {sql.noisy(_NRE, 'nr', 'tree')} SELECT level, node_id AS key, round(y, 6) + 0 AS y FROM noisy")
def nation_region_hierarchy(spark, sf):
    return counts.add_noise(nation_counts(spark, sf).drop("parent_id"), _NRE, "nr").select("level", F.col("node_id").alias("key"), r6("y").alias("y"))


def nation_counts(spark, sf) -> DataFrame:
    """level, node_id, parent_id, c: customers by nation, region and in all; fanouts differ."""
    nation = table(spark, sf, "nation").select(F.col("n_nationkey").cast("long").alias("node_id"), F.col("n_regionkey").cast("long").alias("parent_id"))
    c = table(spark, sf, "customer").groupBy(F.col("c_nationkey").cast("long").alias("node_id")).agg(F.count("*").alias("c"))
    low = nation.join(F.broadcast(c), "node_id", "left").na.fill(0, ["c"]).withColumn("level", F.lit(0))
    mid = low.groupBy(F.col("parent_id").alias("node_id")).agg(F.sum("c").alias("c")).select("node_id", F.lit(0).cast("long").alias("parent_id"), "c", F.lit(1).alias("level"))
    top = mid.agg(F.sum("c").alias("c")).select(F.lit(0).cast("long").alias("node_id"), F.lit(None).cast("long").alias("parent_id"), "c", F.lit(2).alias("level"))
    return low.unionByName(mid).unionByName(top).select("level", "node_id", "parent_id", "c")


@query(text=f"""WITH {_NR}, {sql.noisy(_NRE, 'nr', 'tree')}, l AS (SELECT rk, y, nk FROM noisy JOIN keys ON level = 0 AND node_id = nk),
s AS (SELECT rk, sum(y) AS cs, count(*) AS f FROM l GROUP BY 1),
m AS (SELECT rk, cs, f, (y + cs / f) / (1 + 1::DOUBLE / f) AS z, 1 / (1 + 1::DOUBLE / f) AS v FROM s JOIN noisy ON level = 1 AND node_id = rk),
t AS (SELECT (any_value(y) + sum(z) / sum(v)) / (1 + 1 / sum(v)) AS beta, sum(z) AS cs, sum(v) AS cv FROM m, (SELECT y FROM noisy WHERE level = 2) r),
mb AS (SELECT rk, cs, f, z + (t.beta - t.cs) * v / t.cv AS beta FROM m, (SELECT beta, cs AS cs, cv FROM t) t(beta, cs, cv)),
fit AS (SELECT 2::INTEGER AS level, 0::BIGINT AS key, beta FROM t UNION ALL SELECT 1, rk, beta FROM mb UNION ALL SELECT 0, nk, y + (beta - cs) / f FROM l JOIN mb USING (rk))
SELECT level, key, round(beta, 6) + 0 AS beta FROM fit""".replace("SELECT rk, cs, f, z + (t.beta - t.cs) * v / t.cv AS beta FROM m,", "SELECT m.rk, m.cs, m.f, m.z + (t.beta - t.tcs) * m.v / t.tcv AS beta FROM m,").replace("t(beta, cs, cv))", "t(beta, tcs, tcv))"))
def nation_region_ols(spark, sf):
    c = nation_counts(spark, sf)
    noisy = durable(counts.add_noise(c, _NRE, "nr").withColumnRenamed("eps_count", "eps"))
    return consistency.weighted_tree(noisy, 2).select("level", F.col("node_id").alias("key"), r6("beta").alias("beta"))


# -- matching -------------------------------------------------------------------------------------
THETA = (50.0, 0.0)


def _leaf_trees(spark, sf) -> dict[str, tuple[DataFrame, DataFrame]]:
    """method: (leaves with box and y, points of a with their leaf): all of the counts' budget in the leaves."""
    a, out = points(spark, sf, "CUST"), {}
    quad = with_boxes(counts.add_noise(counts.tree_counts(a, CUST, 2), budget.leaf_only(1.0, 2), "mq"), CUST, 2).where("level = 0")
    from noisytree.functions.cells import leaf_of

    out["quad"] = (durable(quad), leaf_of(a, CUST, 2))
    for method, tree in (("noisy_mean", "mm"), ("exponential", "me")):
        grown = trees.grow(a, CUST, 2, method, [_M1] * 2, tree)
        got = trees.released(trees.counted(grown), budget.leaf_only(0.7, 1), tree).where("level = 0")
        out[method] = (durable(got), grown.points)
    return out


def _matching_sql(tail: str) -> str:
    """live_<method> (node_id, y, box) and at_<method> (x, y, node_id)."""
    eps_leaf = budget.leaf_only(0.7, 1)
    quad = sql.counts("CUST", CUST, 2)
    parts = [quad, sql.noisy(budget.leaf_only(1.0, 2), "mq"), f"live_quad AS (SELECT node_id, y AS w, {sql.node_box(CUST, 2, 0)} FROM noisy WHERE level = 0 AND y > 0)", f"at_quad AS (SELECT x, y, {sql.interleave(['i', 'j'], 2)} AS node_id FROM (SELECT x, y, {sql.cell('x', -1000, 10000, 4)} AS i, {sql.cell('y', 0, 25, 4)} AS j FROM pts))"]
    parts.append("pts0 AS (SELECT pid, least(greatest(x, -1000), 10000)::DOUBLE AS x, least(greatest(y, 0), 25)::DOUBLE AS y FROM pts)")
    for method, tree, stage in (("noisy_mean", "mm", lambda v, o, b, s: sql.mean(v, o, _M1, "mm", b, s)), ("exponential", "me", lambda v, o, b, s: sql.em(v, o, _M1, "me", b, s))):
        one = f"{sql.kd(CUST, 2, stage)}, {sql.kd_nodes(CUST, 1)}, {sql.noisy(eps_leaf, tree, 'tree', 'nz')}"
        # Names of one method's steps must not meet the other's.
        one = re.sub(r"\b([pbvos]\d(?:_\w)?|tree|nz|nz_u)\b", rf"{tree}_\1", one).replace(f"'{tree}_", "'")
        one = one.replace(f"{tree}_tree_u", f"{tree}_tree")
        parts += [one, f"live_{method} AS (SELECT node_id, y AS w, x0, x1, y0, y1 FROM {tree}_nz WHERE level = 0 AND y > 0)", f"at_{method} AS (SELECT x, y, node_id FROM {tree}_p2)"]
    return f"WITH {', '.join(parts)}, other AS ({sql.POINTS['SUPP']}) {tail}"


_METHODS = ("quad", "noisy_mean", "exponential")
_RATIO = " UNION ALL ".join(f"SELECT '{m}' AS method, round(greatest(0, 1 - coalesce(sum(ceil(w)), 0) / ((SELECT count(*) FROM pts) * (SELECT count(*) FROM other))::DOUBLE), 6) AS ratio FROM live_{m} l JOIN other o ON o.x >= x0 - 50 AND o.x <= x1 + 50 AND o.y >= y0 AND o.y <= y1" for m in _METHODS)
_RECALL = " UNION ALL ".join(f"SELECT '{m}' AS method, round(coalesce(avg(CASE WHEN l.node_id IS NULL THEN 0 ELSE 1 END), 1), 6) AS recall FROM at_{m} a JOIN other o ON abs(a.x - o.x) <= 50 AND a.y = o.y LEFT JOIN live_{m} l ON l.node_id = a.node_id" for m in _METHODS)


@query(text=_matching_sql(_RATIO))
def reduction_ratio(spark, sf):
    a, b = points(spark, sf, "CUST"), points(spark, sf, "SUPP")
    return reduce(DataFrame.unionByName, [matching.reduction_ratio(leaves, a, b, CUST, THETA).select(F.lit(m).alias("method"), F.round("ratio", 6).alias("ratio")) for m, (leaves, _) in _leaf_trees(spark, sf).items()])


@query(text=_matching_sql(_RECALL))
def matching_recall(spark, sf):
    b = points(spark, sf, "SUPP")
    return reduce(DataFrame.unionByName, [matching.matching_recall(leaves, at, b, CUST, THETA).select(F.lit(m).alias("method"), F.round("recall", 6).alias("recall")) for m, (leaves, at) in _leaf_trees(spark, sf).items()])


# -- windows --------------------------------------------------------------------------------------
@query(text="SELECT user_id, least(count(*), 10)::BIGINT AS kept FROM events GROUP BY 1")
def user_contribution_bound(spark, sf):
    return windows.bounded(table(spark, sf, "events"), 10).groupBy("user_id").agg(F.count("*").alias("kept"))


def timed(spark, sf) -> DataFrame:
    e = table(spark, sf, "events")
    return e.select("ts", "user_id", (micros("ts", "2024-01-01") / F.lit(86_400_000_000.0)).alias("x"), F.col("value").cast("double").alias("y"))


_TUMBLE = f"""e AS (SELECT (epoch(date_trunc('day', ts)))::BIGINT AS win_start, {sql.cell("date_diff('microsecond', TIMESTAMP '2024-01-01', ts)::DOUBLE / 86400000000::DOUBLE", 0, 30, 2)} AS i, {sql.cell('value::DOUBLE', 0, 640, 2)} AS j FROM events),
l AS (SELECT win_start, {sql.interleave(['i', 'j'], 1)} AS node_id, count(*) AS c FROM e GROUP BY ALL)"""


@query(text=f"WITH {_TUMBLE.replace(', 0, 30, 2)', '')} SELECT win_start, node_id AS cell, c FROM l")
def events_tumbling_counts(spark, sf):
    return windows.tumbling_leaves(timed(spark, sf), EV, 1).select(windows.epoch(F.col("win_start")).alias("win_start"), F.col("node_id").alias("cell"), "c")


_WE = sql.geometric(1)


@query(text=f"""WITH {_TUMBLE}, w AS (SELECT DISTINCT win_start FROM l), t AS (SELECT win_start, 0::INTEGER AS level, range::BIGINT AS node_id FROM w, range(4) UNION ALL SELECT win_start, 1, 0 FROM w),
n AS (SELECT t.win_start, t.level, t.node_id, coalesce((SELECT sum(c) FROM l WHERE l.win_start = t.win_start AND l.node_id >> (2 * t.level) = t.node_id), 0) AS c FROM t),
u AS (SELECT *, {sql.uniform("'cnt'", "'win'", "level", "node_id", "win_start")} AS u FROM n)
SELECT win_start, level, node_id, round(c + (CASE level WHEN 0 THEN 1 / {sql.dbl(_WE[0])} ELSE 1 / {sql.dbl(_WE[1])} END) * {sql.lap('u')}, 6) + 0 AS y FROM u""")
def events_window_tree(spark, sf):
    got = windows.window_trees(durable(windows.tumbling_leaves(timed(spark, sf), EV, 1)), 1, 2, _WE)
    return got.select(windows.epoch(F.col("win_start")).alias("win_start"), "level", "node_id", r6("y").alias("y"))


@query(text="WITH e AS (SELECT floor(epoch(ts) / 21600)::BIGINT * 21600 AS s FROM events) SELECT (s - 21600 * k)::BIGINT AS win_start, count(*) AS c FROM e, range(4) r(k) GROUP BY 1")
def events_sliding_counts(spark, sf):
    return windows.sliding_counts(table(spark, sf, "events")).select(windows.epoch(F.col("win_start")).alias("win_start"), "c")


@query(text="""WITH e AS (SELECT user_id, ts, CASE WHEN ts <= lag(ts) OVER w + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM e)
SELECT user_id, date_diff('microsecond', TIMESTAMP '2024-01-01', min(ts)) AS start, count(*) AS c FROM s GROUP BY user_id, s""")
def events_session_counts(spark, sf):
    return windows.session_counts(table(spark, sf, "events")).select("user_id", micros("start", "2024-01-01").alias("start"), "c")


_PV = Domain((domain.Axis("x", 0.0, 128.0),))
_PE = budget.uniform(1.0, 3)


@query(text=f"WITH {sql.counts('', _PV, 3, 'SELECT json_extract_string(props, ' + chr(39) + '$.k' + chr(39) + ')::DOUBLE AS x FROM events')}, {sql.noisy(_PE, 'pv')} SELECT level, node_id, round(y, 6) + 0 AS y FROM noisy")
def props_value_tree(spark, sf):
    p = table(spark, sf, "events").select(F.get_json_object("props", "$.k").cast("double").alias("x"))
    return counts.add_noise(counts.tree_counts(p, _PV, 3), _PE, "pv").select("level", "node_id", r6("y").alias("y"))


@query
def synthetic_from_leaves(spark, sf):
    nodes = with_boxes(fitted_quad(li(spark, sf), H, _GEO), LI, H)
    return uses.synthetic_points(nodes, LI).groupBy("node_id").agg(F.count("*").alias("n_points"))


def queries() -> dict:
    return dict(_QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(_SQL)
