"""Range counts from released trees.

A box's answer adds the maximal nodes inside it and shares of the leaves that its border cuts. "Inside, but
its parent is not" finds the maximal nodes without recursion, as boxes nest.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from noisytree.functions.cells import fraction, inside, overlaps, with_boxes
from noisytree.plans.domain import Domain

#: Boxes up to which they are broadcast to the points or nodes.
BROADCAST_BOXES = 20_000
#: Products of nodes and boxes beyond which the cells of a box are enumerated instead.
NESTED_PAIRS = 1_000_000_000


def with_parent_boxes(nodes: DataFrame, domain: Domain, h: int, bits: int = 2, value: str = "y") -> DataFrame:
    """Released nodes (value not null) with is_leaf and the box of the nearest released ancestor, as p...

    Levels without budget thus drop out: a query goes down to the next released ones. A node with a
    released ancestor missing altogether has null in p..., like the root.
    """
    r = nodes.where(F.col(value).isNotNull())
    if "is_leaf" not in r.columns:
        r = r.withColumn("is_leaf", F.col("level") == 0)
    up = r.where(F.col("level") < h).select("level", "node_id", F.explode(F.sequence(F.col("level") + 1, F.lit(h))).alias("up"))
    up = up.withColumn("anc", F.expr(f"shiftright(node_id, {bits} * (up - level))"))
    boxes = r.select(F.col("level").alias("up"), F.col("node_id").alias("anc"), F.struct(*domain.box).alias("box"))
    nearest = up.join(boxes, ["up", "anc"]).groupBy("level", "node_id").agg(F.min_by("box", "up").alias("box"))
    out = r.join(nearest, ["level", "node_id"], "left")
    return out.select(*r.columns, *[F.col(f"box.{c}").alias(f"p{c}") for c in domain.box])


def midpoint_nodes(nodes: DataFrame, domain: Domain, h: int) -> DataFrame:
    """Boxes and parents' boxes of a midpoint tree, by arithmetic alone."""
    out = nodes if "is_leaf" in nodes.columns else nodes.withColumn("is_leaf", F.col("level") == 0)
    return with_boxes(out, domain, h, parents=True)


def _taken(domain: Domain) -> tuple[Column, Column]:
    """(the node is a maximal one inside the box, the node is a leaf that the border cuts)."""
    root = reduce(lambda a, b: a & b, [F.col(f"p{c}").isNull() for c in domain.box])
    maximal = inside(domain) & (root | ~inside(domain, "p"))
    return maximal, F.col("is_leaf") & overlaps(domain) & ~inside(domain)


def touched(nodes: DataFrame, queries: DataFrame, domain: Domain, value: str, strategy: str = "nested", h: int | None = None, bits: int = 2) -> DataFrame:
    """qid, level, node_id, value, part (1 for maximal nodes, else the share of a cut leaf)."""
    maximal, cut = _taken(domain)
    q = queries.select("qid", *[f"q{c}" for c in domain.box])
    if strategy == "auto":
        known = h is not None and domain.d == 2
        strategy = "cells" if known and (1 << domain.d) ** h * queries.count() > NESTED_PAIRS else "nested"
    if strategy == "nested":
        # One theta join; the boxes' number is checked before they are broadcast.
        few = q.limit(BROADCAST_BOXES + 1).count() <= BROADCAST_BOXES
        pairs = nodes.join(F.broadcast(q) if few else q, maximal | cut)
    elif strategy == "cells":
        keys = cell_keys(q, domain, h)
        pairs = nodes.join(keys, ["level", "node_id"]).where(maximal | cut)
    elif strategy == "descent":
        return by_descent(nodes, q, domain, value, h, bits)
    else:
        raise ValueError(f"no strategy {strategy}")
    return pairs.select("qid", "level", "node_id", F.col(value).alias("value"), F.when(maximal, F.lit(1.0)).otherwise(fraction(domain)).alias("part"))


def canonical(nodes: DataFrame, queries: DataFrame, domain: Domain, value: str = "beta", strategy: str = "nested", h: int | None = None, bits: int = 2, clip: bool = False) -> DataFrame:
    """qid, estimate, n_nodes, n_partial of every box, 0 where no node is touched."""
    t = touched(nodes, queries, domain, value, strategy, h, bits)
    got = t.groupBy("qid").agg(F.sum(F.col("value") * F.col("part")).alias("estimate"), F.count("*").alias("n_nodes"), F.sum(F.when(F.col("part") < 1, 1).otherwise(0)).alias("n_partial"))
    out = queries.select("qid").join(got, "qid", "left").na.fill(0, ["estimate", "n_nodes", "n_partial"])
    return out.withColumn("estimate", F.greatest("estimate", F.lit(0.0))) if clip else out


def cell_keys(queries: DataFrame, domain: Domain, h: int) -> DataFrame:
    """qid, box, level, node_id of the cells of a midpoint tree that a box may take: border cells of each level,
    as what lies in a parent inside the box is left out. For plane domains."""
    from noisytree.functions.cells import interleave

    x, y = domain.axes
    q = queries.withColumn("level", F.explode(F.sequence(F.lit(0), F.lit(h))))
    n = F.pow(F.lit(2.0), F.lit(h) - F.col("level"))

    def ends(a, lo: str, hi: str) -> tuple[Column, Column]:
        scaled = lambda c: (F.col(c) - F.lit(a.lo)) / F.lit(a.width) * n
        first = F.greatest(F.lit(0), F.floor(scaled(lo)).cast("long"))
        last = F.least((n - 1).cast("long"), F.ceil(scaled(hi)).cast("long") - 1)
        return first, last

    fx, lx = ends(x, "qx0", "qx1")
    fy, ly = ends(y, "qy0", "qy1")
    q = q.withColumns({"fx": fx, "lx": lx, "fy": fy, "ly": ly}).where("fx <= lx and fy <= ly")
    q = q.withColumn("ix", F.explode(F.sequence("fx", "lx")))
    # Three cells from either end lie at the border of their parents; rows further in have a parent
    # inside the box unless their column lies at the border.
    edge = (F.col("ix") < F.col("fx") + 3) | (F.col("ix") > F.col("lx") - 3)
    whole = F.sequence("fy", "ly")
    ends_only = F.array_distinct(F.concat(F.slice(whole, 1, 3), F.slice(whole, F.greatest(F.lit(1), F.size(whole) - 2), F.lit(3))))
    q = q.withColumn("iy", F.explode(F.when(edge, whole).otherwise(ends_only)))
    return q.withColumn("node_id", interleave([F.col("ix"), F.col("iy")], h)).drop("fx", "lx", "fy", "ly", "ix", "iy")


def by_descent(nodes: DataFrame, q: DataFrame, domain: Domain, value: str, h: int, bits: int) -> DataFrame:
    """Level by level from the root: boxes meet the children of nodes that their border cuts."""
    front, out = None, []
    for level in range(h, -1, -1):
        here = nodes.where(F.col("level") == level)
        met = here.join(q, overlaps(domain)) if front is None else here.withColumn("_up", F.shiftright("node_id", bits)).join(front, "_up")
        met = met.where(overlaps(domain))
        done = inside(domain) & F.col(value).isNotNull()
        leaf = F.col("is_leaf")
        out.append(met.where(done | leaf).select("qid", "level", "node_id", F.col(value).alias("value"), F.when(done, F.lit(1.0)).otherwise(fraction(domain)).alias("part")))
        front = met.where(~done & ~leaf).select(F.col("node_id").alias("_up"), "qid", *[f"q{c}" for c in domain.box])
    return reduce(DataFrame.unionByName, out)


def touch_profile(nodes: DataFrame, queries: DataFrame, domain: Domain, value: str = "y") -> DataFrame:
    """qid, level, n_i: how many nodes of each level a box adds."""
    return touched(nodes, queries, domain, value).groupBy("qid", "level").agg(F.count("*").alias("n_i"))


def exact(points: DataFrame, queries: DataFrame, domain: Domain, cells: int = 64) -> DataFrame:
    """qid, true_count of every box, from the points: private."""
    cond = reduce(lambda a, b: a & b, [(F.col(n) >= F.col(f"q{n}0")) & (F.col(n) < F.col(f"q{n}1")) for n in domain.names])
    q = queries.select("qid", *[f"q{c}" for c in domain.box])
    p = points.select(*domain.names)
    if q.limit(BROADCAST_BOXES + 1).count() <= BROADCAST_BOXES:
        hits = p.join(F.broadcast(q), cond)
    else:
        # Many boxes: an equi-join on coarse cells of the first axis, then the condition.
        from noisytree.functions.cells import axis_cell

        a = domain.axes[0]
        q = q.withColumn("_cell", F.explode(F.sequence(axis_cell(F.col(f"q{a.name}0"), a, cells), axis_cell(F.col(f"q{a.name}1"), a, cells))))
        hits = p.withColumn("_cell", axis_cell(F.col(a.name), a, cells)).join(q, "_cell").where(cond)
    got = hits.groupBy("qid").agg(F.count("*").alias("true_count"))
    return queries.select("qid").join(got, "qid", "left").withColumn("true_count", F.coalesce("true_count", F.lit(0).cast("long")))


def by_complement(nodes: DataFrame, queries: DataFrame, domain: Domain, value: str = "beta") -> DataFrame:
    """qid, direct, complement: a box's answer, and the root's value less the leaves' shares outside it."""
    direct = canonical(nodes, queries, domain, value).select("qid", F.col("estimate").alias("direct"))
    part = F.when(overlaps(domain), fraction(domain)).otherwise(F.lit(0.0))
    q = queries.select("qid", *[f"q{c}" for c in domain.box])
    leaves = nodes.where("is_leaf").join(F.broadcast(q))
    outside = leaves.groupBy("qid").agg(F.sum(F.col(value) * (1 - part)).alias("outside"))
    root = nodes.groupBy().agg(F.max_by(value, "level").alias("root"))
    return direct.join(outside, "qid").join(F.broadcast(root)).select("qid", "direct", (F.col("root") - F.col("outside")).alias("complement"))
