"""What a release spends: sensitivities, composition, and the append-only record of releases."""

from __future__ import annotations

import math
from collections.abc import Iterable
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from noisytree.plans.schema import LEDGER

#: How far one tuple moves a statistic under add or remove; "width" is that of the domain.
SENSITIVITY = {"count": "1", "cell_count": "1", "sum": "width", "median": "width"}
NEIGHBOR = {"add_remove": 1.0, "replace": 2.0}


def sensitivity_of(stat: str, width: float = 1.0, neighbor: str = "add_remove") -> float:
    return (width if SENSITIVITY[stat] == "width" else 1.0) * NEIGHBOR[neighbor]


@dataclass(frozen=True)
class Entry:
    dataset: str
    tree_id: str
    eps: float
    delta: float = 0.0
    neighbor: str = "add_remove"
    spec: dict[str, str] = field(default_factory=dict)


def compose_sequential(entries: Iterable[Entry]) -> tuple[float, float]:
    """Releases over the same tuples add up."""
    entries = list(entries)
    return math.fsum(e.eps for e in entries), math.fsum(e.delta for e in entries)


def compose_parallel(entries: Iterable[Entry]) -> tuple[float, float]:
    """Releases over disjoint tuples cost what the dearest costs."""
    entries = list(entries)
    return max((e.eps for e in entries), default=0.0), max((e.delta for e in entries), default=0.0)


def path_epsilon(nodes: DataFrame, h: int, d: int = 2) -> DataFrame:
    """leaf, eps: the sum over the leaf's path. nodes: level, node_id, eps_count, eps_split."""
    leaf = nodes.where("level = 0").select(F.col("node_id").alias("leaf"))
    path = leaf.select("leaf", F.explode(F.sequence(F.lit(0), F.lit(h))).alias("level"))
    path = path.withColumn("node_id", F.expr(f"shiftright(leaf, {d} * level)"))
    cost = nodes.select("level", "node_id", (F.coalesce("eps_count", F.lit(0.0)) + F.coalesce("eps_split", F.lit(0.0))).alias("eps"))
    return path.join(cost, ["level", "node_id"]).groupBy("leaf").agg(F.sum("eps").alias("eps"))


def assert_within(nodes: DataFrame, eps: float, h: int, d: int = 2) -> None:
    spent = path_epsilon(nodes, h, d).agg(F.max("eps")).first()[0]
    if spent is not None and spent > eps * (1 + 1e-9):
        raise ValueError(f"a path spends {spent}, more than {eps}")


class Ledger:
    """An append-only Parquet record; a tree is released once."""

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path

    def entries(self) -> DataFrame:
        try:
            return self.spark.read.schema(LEDGER).parquet(self.path)
        except Exception as missing:  # AnalysisException of a path that is not there yet
            if "PATH_NOT_FOUND" not in str(missing):
                raise
            return self.spark.createDataFrame([], LEDGER)

    def append(self, entry: Entry) -> None:
        if not self.entries().where(F.col("tree_id") == entry.tree_id).isEmpty():
            raise ValueError(f"{entry.tree_id} has been released; another release has to be paid for under another id")
        spec = F.create_map(*[F.lit(x) for kv in entry.spec.items() for x in kv]) if entry.spec else F.lit(None).cast("map<string,string>")
        row = self.spark.range(1).select(F.lit(entry.dataset).alias("dataset"), F.lit(entry.tree_id).alias("tree_id"), F.lit(entry.eps).alias("eps"), F.lit(entry.delta).alias("delta"), F.lit(entry.neighbor).alias("neighbor"), spec.alias("spec"), F.current_timestamp().alias("ts"))
        row.write.mode("append").parquet(self.path)

    def spent(self, dataset: str) -> tuple[float, float]:
        r = self.entries().where(F.col("dataset") == dataset).agg(F.sum("eps"), F.sum("delta")).first()
        return r[0] or 0.0, r[1] or 0.0
