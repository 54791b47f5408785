"""Sinks and readers of released trees and answers."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from noisytree.functions.noise import Noise
from noisytree.plans.build import TreeSpec, build, split_budgets
from noisytree.plans.domain import Domain
from noisytree.plans.ledger import NEIGHBOR, Entry, Ledger, assert_within
from noisytree.plans.schema import assert_released


def release(nodes: DataFrame, path: str, entry: Entry, ledger: Ledger, noise: Noise, h: int, d: int = 2, eps_splits: float = 0.0, testing: bool = False) -> None:
    """Writes a tree once, by tree and level; the ledger refuses another release of the same id.

    Refused are noise of a public seed (anyone could draw it again and subtract it), unless told that this is a test, and a
    tree on one of whose paths counts and splits (``eps_splits``) cost more than the entry says. The entry
    comes before the data: a release that fails half-way has been paid for, never the other way round.
    """
    if not (noise.secure or testing):
        raise ValueError("the noise is drawn from a public seed: use Noise.fresh(), or testing=True for data that may be known")
    assert_released(nodes)
    counts = nodes.select("level", "node_id", "eps_count", F.lit(0.0).alias("eps_split"))
    assert_within(counts, entry.eps / NEIGHBOR[entry.neighbor] - eps_splits, h, d)
    ledger.append(entry)
    tagged = nodes.withColumn("tree_id", F.lit(entry.tree_id))
    tagged.repartitionByRange("level", "node_id").sortWithinPartitions("level", "node_id").write.mode("append").partitionBy("tree_id", "level").parquet(path)


def publish(points: DataFrame, domain: Domain, spec: TreeSpec, path: str, dataset: str, tree_id: str, ledger: Ledger, neighbor: str = "add_remove", testing: bool = False) -> None:
    """Builds and releases a tree in one step, private unless told that this is a test: the noise is drawn from a fresh
    secret, the tree's id is part of the key of every draw, and neighbours that differ by a replaced row, which moves two counts,
    have half the budget. Smooth splits add their delta for each level of a path."""
    if spec.exact_counts or spec.kind in ("kd", "hybrid", "hilbert") and spec.split == "exact":
        raise ValueError("exact counts and exact splits are no release")
    noise = spec.noise if testing or spec.noise.secure else Noise.fresh()
    own = spec.but(noise=noise, tree=tree_id, eps=spec.eps / NEIGHBOR[neighbor])
    counts, medians = split_budgets(own)
    depth = len(medians)
    entry = Entry(dataset, tree_id, spec.eps, spec.delta * depth * NEIGHBOR[neighbor] if spec.split == "smooth" else 0.0, neighbor, {"kind": spec.kind, "h": str(spec.h)})
    release(build(points, domain, own), path, entry, ledger, noise, spec.h, domain.d, own.eps - math.fsum(counts), testing)


def read_release(spark: SparkSession, path: str, tree_id: str) -> DataFrame:
    return spark.read.parquet(path).where(F.col("tree_id") == tree_id)


def write_answers(answers: DataFrame, path: str, fmt: str = "parquet") -> None:
    assert_released(answers).write.mode("errorifexists").format(fmt).save(path)


def to_wkt(x0: str = "x0", x1: str = "x1", y0: str = "y0", y1: str = "y1") -> Column:
    """A box as well-known text."""
    return F.format_string("POLYGON((%s %s,%s %s,%s %s,%s %s,%s %s))", *[F.col(c) for c in (x0, y0, x1, y0, x1, y1, x0, y1, x0, y0)])
