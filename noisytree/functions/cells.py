"""Cell and node arithmetic of midpoint trees, in columns.

The digit of a child holds one bit an axis, the first axis highest; a node's id is its parent's
times the fanout plus its digit, so an ancestor is a shift.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from noisytree.plans.domain import Axis, Domain


def axis_cell(v: Column, axis: Axis, cells: int) -> Column:
    """Number of the cell of v among so many equal ones; values outside go to the outermost."""
    at = F.floor((v - F.lit(axis.lo)) / F.lit(axis.hi - axis.lo) * F.lit(float(cells)))
    return F.least(F.lit(cells - 1).cast("long"), F.greatest(F.lit(0).cast("long"), at.cast("long")))


def interleave(indices: list[Column], bits: int) -> Column:
    d = len(indices)
    parts = [F.shiftleft(F.shiftright(ix, k).bitwiseAND(F.lit(1).cast("long")), d * k + d - 1 - a) for k in range(bits) for a, ix in enumerate(indices)]
    return reduce(lambda p, q: p.bitwiseOR(q), parts) if parts else F.lit(0).cast("long")


def deinterleave(node: Column, bits: int, d: int, axis: int) -> Column:
    parts = [F.shiftleft(F.shiftright(node, d * k + d - 1 - axis).bitwiseAND(F.lit(1).cast("long")), k) for k in range(bits)]
    return reduce(lambda p, q: p.bitwiseOR(q), parts) if parts else F.lit(0).cast("long")


def valid(points: DataFrame, domain: Domain) -> DataFrame:
    """Points without a null or a NaN coordinate: a filter by row, before anything is counted."""
    ok = reduce(lambda p, q: p & q, [F.col(n).isNotNull() & ~F.isnan(n) for n in domain.names])
    return points.where(ok)


def leaf_of(points: DataFrame, domain: Domain, h: int) -> DataFrame:
    """points with node_id, the leaf of a midpoint tree of height h."""
    out = valid(points, domain)
    cells = {f"_i{k}": axis_cell(F.col(a.name), a, 1 << h) for k, a in enumerate(domain.axes)}
    return out.withColumns(cells).withColumn("node_id", interleave([F.col(c) for c in cells], h)).drop(*cells)


def enumerate_nodes(spark: SparkSession, h: int, f: int) -> DataFrame:
    """level, node_id of the complete tree: nodes without points are released too."""
    levels = [spark.range(f ** (h - level)).select(F.lit(level).alias("level"), F.col("id").alias("node_id")) for level in range(h, -1, -1)]
    return reduce(DataFrame.unionByName, levels)


def with_boxes(nodes: DataFrame, domain: Domain, h: int, parents: bool = False) -> DataFrame:
    """nodes with the boxes of a midpoint tree (and of the parents, as p...; null at the root)."""
    d, new = domain.d, {}

    def ends(node: Column, level: Column, k: int, a: Axis) -> tuple[Column, Column]:
        cells = F.pow(F.lit(2.0), F.lit(h) - level)
        at = deinterleave(node, h, d, k)
        return tuple(F.lit(a.lo) + F.lit(a.hi - a.lo) * (at + e) / cells for e in (0, 1))

    for k, a in enumerate(domain.axes):
        new[f"{a.name}0"], new[f"{a.name}1"] = ends(F.col("node_id"), F.col("level"), k, a)
        if parents:
            lo, hi = ends(F.shiftright("node_id", d), F.col("level") + 1, k, a)
            new[f"p{a.name}0"], new[f"p{a.name}1"] = F.when(F.col("level") < h, lo), F.when(F.col("level") < h, hi)
    return nodes.withColumns(new)


def inside(domain: Domain, p: str = "", q: str = "q") -> Column:
    """The box with prefix p lies within that with prefix q."""
    return reduce(lambda x, y: x & y, [(F.col(f"{p}{n}0") >= F.col(f"{q}{n}0")) & (F.col(f"{p}{n}1") <= F.col(f"{q}{n}1")) for n in domain.names])


def overlaps(domain: Domain, p: str = "", q: str = "q") -> Column:
    return reduce(lambda x, y: x & y, [(F.col(f"{p}{n}0") < F.col(f"{q}{n}1")) & (F.col(f"{p}{n}1") > F.col(f"{q}{n}0")) for n in domain.names])


def fraction(domain: Domain, p: str = "", q: str = "q") -> Column:
    """Share of the box p that lies in q, if points spread evenly; an axis without width counts whole."""
    parts = []
    for n in domain.names:
        width = F.col(f"{p}{n}1") - F.col(f"{p}{n}0")
        part = F.least(f"{p}{n}1", f"{q}{n}1") - F.greatest(f"{p}{n}0", f"{q}{n}0")
        parts.append(F.when(width > 0, part / width).otherwise(F.lit(1.0)))
    return reduce(lambda x, y: x * y, parts)
