"""Trees with splits that follow the data: kd-trees of all split methods, hybrids, cell trees, Hilbert trees.

A tree of fanout 4 and height h takes 2 h binary splits a path; the inner binary level of each pair is
never counted. Points learn their node from released splits only, level by level, by broadcast joins of
tables with one row a node.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from noisytree.functions import hilbert
from noisytree.functions.cells import axis_cell, interleave, valid, with_boxes
from noisytree.functions.noise import DEFAULT, Noise
from noisytree.operators import counts, medians
from noisytree.operators.durable import BROADCAST_NODES, durable
from noisytree.operators.sampling import bernoulli
from noisytree.plans.domain import Axis, Domain


@dataclass
class Grown:
    """points with node_id at the last binary depth; splits by depth; boxes by depth."""

    domain: Domain
    points: DataFrame
    splits: list[DataFrame]
    boxes: list[DataFrame]

    @property
    def depth(self) -> int:
        return len(self.splits)

    def split_table(self) -> DataFrame:
        """depth, node_id, axis, split, eps."""
        return reduce(DataFrame.unionByName, self.splits)


def clamped(points: DataFrame, domain: Domain) -> DataFrame:
    return valid(points, domain).withColumns({a.name: F.least(F.greatest(F.col(a.name), F.lit(a.lo)), F.lit(a.hi)) for a in domain.axes})


def root_box(points: DataFrame, domain: Domain) -> DataFrame:
    ends = {f"{a.name}{e}": F.lit(float((a.lo, a.hi)[e])) for a in domain.axes for e in (0, 1)}
    return points.sparkSession.range(1).select(F.col("id").alias("node_id"), *[c.alias(n) for n, c in ends.items()])


def small(df: DataFrame, rows: int) -> DataFrame:
    return F.broadcast(df) if rows <= BROADCAST_NODES else df


def descend(points: DataFrame, splits: DataFrame, axis: str, rows: int) -> DataFrame:
    """The next binary level: left where the coordinate is less than the split."""
    s = small(splits.select("node_id", F.col("split").alias("_split")), rows)
    return points.join(s, "node_id").withColumn("node_id", F.col("node_id") * 2 + F.when(F.col(axis) >= F.col("_split"), F.lit(1).cast("long")).otherwise(F.lit(0).cast("long"))).drop("_split")


def child_boxes(boxes: DataFrame, splits: DataFrame, axis: str) -> DataFrame:
    b = boxes.join(splits.select("node_id", F.col("split").alias("_split")), "node_id")
    left = b.withColumn("node_id", F.col("node_id") * 2).withColumn(f"{axis}1", F.col("_split"))
    right = b.withColumn("node_id", F.col("node_id") * 2 + 1).withColumn(f"{axis}0", F.col("_split"))
    return left.unionByName(right).drop("_split")


def grow(points: DataFrame, domain: Domain, depth: int, method: str, eps: list[float], tree: str = "kd", delta: float = 1e-4, noise: Noise = DEFAULT, sample: float | None = None, scope: str = "per_level", first: int = 0) -> Grown:
    """``depth`` binary levels, axes in turn. eps: budget of each level's medians (on the sample, where one is
    taken: see sampling.required_eps). scope: a fresh sample each level, or one shared by all."""
    everyone = clamped(points, domain).withColumn("node_id", F.lit(0).cast("long"))
    picked = bernoulli(everyone, sample, "0", noise) if sample and scope == "shared" else everyone
    boxes, splits = [durable(root_box(points, domain))], []
    for b in range(depth):
        axis = domain.axes[(first + b) % domain.d].name
        mine = picked if not sample or scope == "shared" else bernoulli(picked, sample, str(b), noise)
        bounds = boxes[-1].select("node_id", F.col(f"{axis}0").alias("lo"), F.col(f"{axis}1").alias("hi"))
        buckets = max(1, 4096 >> b) if depth > 6 else medians.BUCKETS
        found = medians.split(mine.select("node_id", F.col(axis).alias("v")), bounds, method, eps[b] if eps else 0.0, delta, noise, tree, b, buckets)
        found = durable(found)
        splits.append(found.select(F.lit(b).alias("depth"), "node_id", F.lit(axis).alias("axis"), "split", F.lit(float(eps[b]) if eps else 0.0).alias("eps")))
        boxes.append(durable(child_boxes(boxes[-1], found, axis)))
        everyone = descend(everyone, found, axis, 1 << b)
        picked = descend(picked, found, axis, 1 << b) if sample else everyone
    return Grown(domain, everyone, splits, boxes)


def flat_levels(grown: Grown) -> DataFrame:
    """level, node_id, parent_id, box of the fanout-4 tree: every other binary level."""
    h = grown.depth // 2
    parts = [grown.boxes[2 * (h - level)].withColumn("level", F.lit(level)) for level in range(h, -1, -1)]
    every = reduce(DataFrame.unionByName, parts)
    return every.withColumn("parent_id", F.when(F.col("level") < h, F.shiftright("node_id", 2)))


def flatten(binary: DataFrame, depth: int) -> DataFrame:
    """A binary tree (level, node_id, ...) as one of fanout 4: odd levels go, grandchildren become children."""
    out = binary.where(F.col("level") % 2 == 0).withColumn("level", (F.col("level") / 2).cast("int"))
    return out.withColumn("parent_id", F.when(F.col("level") < depth // 2, F.shiftright("node_id", 2)))


def binary_counts(grown: Grown) -> DataFrame:
    """level, node_id, c of the unflattened tree."""
    leaves = grown.points.groupBy("node_id").agg(F.count("*").alias("c"))
    return counts.complete(counts.all_levels(leaves, grown.depth, 1), grown.depth, 2)


def counted(grown: Grown) -> DataFrame:
    """level, node_id, parent_id, box, c of the flattened tree."""
    h = grown.depth // 2
    leaves = grown.points.groupBy("node_id").agg(F.count("*").alias("c"))
    got = counts.all_levels(leaves, h, 2)
    return flat_levels(grown).join(got, ["level", "node_id"], "left").withColumn("c", F.coalesce("c", F.lit(0).cast("long")))


def released(tree_counts: DataFrame, eps_levels: list[float], tree: str, noise: Noise = DEFAULT) -> DataFrame:
    return counts.add_noise(tree_counts, eps_levels, tree, noise)


def cell_tree(points: DataFrame, domain: Domain, depth: int, shape: tuple[int, int], eps: float, tree: str = "cell", noise: Noise = DEFAULT) -> Grown:
    """All splits from one noisy grid, which pays its budget once; points are read again for counts only."""
    grid = counts.grid_noisy(points, domain, shape, eps, tree, noise)
    cells = grid.select(F.floor(F.col("cell_id") / shape[1]).alias("ix"), (F.col("cell_id") % shape[1]).alias("iy"), F.col("y").alias("w")).withColumn("node_id", F.lit(0).cast("long"))
    cells = durable(cells)
    everyone = clamped(points, domain).withColumn("node_id", F.lit(0).cast("long"))
    spark = points.sparkSession
    ranges = spark.range(1).select(F.col("id").alias("node_id"), F.lit(0).cast("long").alias("ix0"), F.lit(shape[0]).cast("long").alias("ix1"), F.lit(0).cast("long").alias("iy0"), F.lit(shape[1]).cast("long").alias("iy1"))
    boxes, splits = [root_box(points, domain)], []
    for b in range(depth):
        a = b % 2
        axis, n, i = domain.axes[a], shape[a], ("ix", "iy")[a]
        bounds = ranges.select("node_id", F.col(f"{i}0").alias("i0"), F.col(f"{i}1").alias("i1"))
        line = durable(medians.cell_split(cells.select("node_id", F.col(i).alias("i"), "w"), bounds))
        at = F.lit(axis.lo) + F.lit(axis.hi - axis.lo) * F.col("line") / F.lit(float(n))
        found = line.withColumn("split", at)
        cells = cells.join(small(line, 1 << b), "node_id").withColumn("node_id", F.col("node_id") * 2 + (F.col(i) >= F.col("line")).cast("long")).drop("line")
        kids = ranges.join(line, "node_id")
        left = kids.withColumn("node_id", F.col("node_id") * 2).withColumn(f"{i}1", F.col("line"))
        right = kids.withColumn("node_id", F.col("node_id") * 2 + 1).withColumn(f"{i}0", F.col("line"))
        ranges = durable(left.unionByName(right).drop("line"))
        boxes.append(durable(child_boxes(boxes[-1], found, axis.name)))
        splits.append(found.select(F.lit(b).alias("depth"), "node_id", F.lit(axis.name).alias("axis"), "split", F.lit(eps if b == 0 else 0.0).alias("eps")))
        everyone = descend(everyone, found, axis.name, 1 << b)
    return Grown(domain, everyone, splits, boxes)


def hybrid(points: DataFrame, domain: Domain, h: int, switch: int, eps: list[float], tree: str = "hybrid", method: str = "exponential", noise: Noise = DEFAULT, sample: float | None = None) -> DataFrame:
    """level, node_id, parent_id, box, c: ``switch`` levels split by data, the rest at midpoints."""
    top = grow(points, domain, 2 * switch, method, eps, tree, noise=noise, sample=sample)
    rest = h - switch
    joints = top.boxes[-1]
    p = top.points.join(small(joints, 4**switch), "node_id")
    cells = []
    for a in domain.axes:
        at = F.floor((F.col(a.name) - F.col(f"{a.name}0")) / (F.col(f"{a.name}1") - F.col(f"{a.name}0")) * float(1 << rest))
        at = F.when(F.col(f"{a.name}1") > F.col(f"{a.name}0"), F.least(F.lit((1 << rest) - 1).cast("long"), F.greatest(F.lit(0).cast("long"), at))).otherwise(F.lit(0).cast("long"))
        p = p.withColumn(f"_i{a.name}", at)
        cells.append(F.col(f"_i{a.name}"))
    leaves = p.select((F.col("node_id") * (4**rest) + interleave(cells, rest)).alias("node_id")).groupBy("node_id").agg(F.count("*").alias("c"))
    got = counts.all_levels(leaves, h, 2)
    # Boxes below the joints are those of a unit midpoint tree, scaled.
    unit = Domain(tuple(Axis(a.name, 0.0, 1.0) for a in domain.axes))
    spark = points.sparkSession
    frames = [top.boxes[2 * (h - level)].withColumn("level", F.lit(level)) for level in range(h, rest - 1, -1)]
    for level in range(rest - 1, -1, -1):
        local = with_boxes(spark.range(4 ** (rest - level)).select(F.col("id").alias("node_id"), F.lit(level).alias("level")), unit, rest)
        local = local.select(F.col("node_id").alias("_l"), *[F.col(c).alias(f"_{c}") for c in unit.box])
        # Every joint has the same cells below: a product of two enumerations.
        both = joints.crossJoin(small(local, 4 ** (rest - level)))
        ends = {f"{a.name}{e}": F.col(f"{a.name}0") + (F.col(f"{a.name}1") - F.col(f"{a.name}0")) * F.col(f"_{a.name}{e}") for a in domain.axes for e in (0, 1)}
        frames.append(both.select((F.col("node_id") * (4 ** (rest - level)) + F.col("_l")).alias("node_id"), *[c.alias(n) for n, c in ends.items()]).withColumn("level", F.lit(level)))
    every = reduce(DataFrame.unionByName, frames)
    every = every.withColumn("parent_id", F.when(F.col("level") < h, F.shiftright("node_id", 2)))
    return every.join(got, ["level", "node_id"], "left").withColumn("c", F.coalesce("c", F.lit(0).cast("long")))


def curve_points(points: DataFrame, domain: Domain, order: int) -> DataFrame:
    """points with hv, their position on the Hilbert curve."""
    x, y = domain.axes
    out = valid(points, domain).withColumn("_cx", axis_cell(F.col(x.name), x, 1 << order)).withColumn("_cy", axis_cell(F.col(y.name), y, 1 << order))
    return out.withColumn("hv", hilbert.encode(F.col("_cx"), F.col("_cy"), order)).drop("_cx", "_cy")


def hilbert_tree(points: DataFrame, domain: Domain, h: int, eps: list[float], order: int = 18, tree: str = "hilbert", method: str = "exponential", noise: Noise = DEFAULT, sample: float | None = None) -> DataFrame:
    """level, node_id, parent_id, h0, h1, c: a tree over curve positions (see node_boxes)."""
    line = Domain((Axis("h", 0.0, float(4**order)),))
    moved = curve_points(points, domain, order).withColumn("h", F.col("hv").cast("double"))
    return counted(grow(moved, line, 2 * h, method, eps, tree, noise=noise, sample=sample))


def node_boxes(nodes: DataFrame, domain: Domain, order: int) -> DataFrame:
    """nodes with the box of their curve interval, in the domain's units; intervals, not data, bound it."""
    fields = nodes.schema.fields + [T.StructField(n, T.DoubleType()) for n in domain.box]
    side = float(1 << order)

    def boxes(batches):
        import math

        from noisytree.functions.hilbert import interval_box

        for pdf in batches:
            got = [interval_box(math.ceil(a), math.ceil(b), order) or (0, 0, 0, 0) for a, b in zip(pdf["h0"], pdf["h1"], strict=True)]
            for k, a in enumerate(domain.axes):
                for e in (0, 1):
                    pdf[f"{a.name}{e}"] = [a.lo + (a.hi - a.lo) * g[2 * k + e] / side for g in got]
            yield pdf

    return nodes.mapInPandas(boxes, T.StructType(fields))


def exact_hilbert(points: DataFrame, domain: Domain, h: int, order: int = 18) -> DataFrame:
    """level, node_id, c and the bounding box of the data of each leaf level: not private."""
    line = Domain((Axis("h", 0.0, float(4**order)),))
    moved = curve_points(points, domain, order).withColumn("h", F.col("hv").cast("double"))
    grown = grow(moved, line, 2 * h, "exact", [], "hx")
    ends = [f(a.name).alias(f"{a.name}{e}") for a in domain.axes for e, f in ((0, F.min), (1, F.max))]
    up = grown.points.withColumn("level", F.explode(F.sequence(F.lit(0), F.lit(h)))).withColumn("node_id", F.expr("shiftright(node_id, 2 * level)"))
    return up.groupBy("level", "node_id").agg(F.count("*").alias("c"), *ends)
