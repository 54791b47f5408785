"""What the operators of this subpackage share: table access, lazy "let" bindings, shipping of
Arrow functions to the executors, durable cuts of the lineage, connected components.
"""

from __future__ import annotations

from pathlib import Path

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from noisytree.operators.durable import shared_folder

ROOT = str(Path(__file__).resolve().parents[2])
#: White space that separates words: space, tab, line feed, vertical tab, form feed, carriage return.
WS = r"[\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def let(value: Column, body) -> Column:
    """body(value) with value computed once a row.

    A lambda variable is bound to a value, whereas the optimizer may copy a named expression into
    a lambda that then computes it again for each element.
    """
    return F.transform(F.array(value), body)[0]


def free(name: str, taken) -> str:
    """name, with underscores before it until no column is called so."""
    lower = {c.lower() for c in taken}
    while name.lower() in lower:
        name = "_" + name
    return name


def sha256_text(c: Column) -> Column:
    return F.sha2(c.cast("binary"), 256)


def shipped(module: str, name: str, **kwargs):
    """A function of Arrow batches that runs module.name(batches, **kwargs) on an executor.

    It is pickled by value and imports the module by name over there, so a worker that is used
    again keeps the module's caches. The repository's folder is only tried where the package is
    not installed.
    """
    root = ROOT

    def run(batches):
        import importlib
        import sys

        try:
            found = importlib.import_module(module)
        except ModuleNotFoundError:
            sys.path.insert(0, root)
            found = importlib.import_module(module)
        yield from getattr(found, name)(batches, **kwargs)

    return run


def slices(batch, column: str = "text", most: int = 400_000):
    """Parts of an Arrow batch of about so many bytes of text, so that no more becomes Python objects at once."""
    import numpy as np
    import pyarrow.compute as pc

    size = np.cumsum(pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False)) // most
    edges = [0, *(np.flatnonzero(np.diff(size)) + 1).tolist(), batch.num_rows]
    for a, b in zip(edges, edges[1:], strict=False):
        if a < b:
            yield batch.slice(a, b - a)


def parts(batches, column: str = "text"):
    for batch in batches:
        yield from slices(batch, column)


def checkpoint_dir(spark: SparkSession) -> str:
    """The shared folder that the cluster names; a folder of our own only for a session within one machine."""
    return shared_folder(spark)


_RELEASED = [0.0]


def release_shuffles(spark: SparkSession, every: float = 10.0) -> None:
    """Frees shuffle files that no frame can read any more, if that was not done in the last seconds.

    Spark's cleaner removes them when the driver's JVM finds their handles unreachable, which a driver with
    little to do may not notice for hours while executors' disks fill up. The last query's plan is let go of
    only after a first collection. Steps of less time than ``every`` leave too little behind to be worth it.
    """
    import time

    if time.monotonic() - _RELEASED[0] < every:
        return
    spark.sparkContext._jvm.System.gc()
    time.sleep(0.2)
    spark.sparkContext._jvm.System.gc()
    _RELEASED[0] = time.monotonic()


def written(df: DataFrame) -> DataFrame:
    """df, written once to the shared folder as Parquet and read from there: lineage ends there, lost executors cost
    nothing, and the planner knows the table's true size. (A checkpoint() would keep the estimate of the plan that
    it cuts, and joins of such frames multiply these step after step.)"""
    import uuid

    spark, schema = df.sparkSession, df.schema
    path = f"{checkpoint_dir(spark)}/noisytree-{uuid.uuid4().hex}"
    df.write.parquet(path)
    del df  # the plan that ran would keep its shuffles
    release_shuffles(spark)
    return spark.read.schema(schema).parquet(path)


durable = written


def dropped(df: DataFrame) -> None:
    """Deletes the files of a frame that written() made and no later step reads."""
    sc = df.sparkSession.sparkContext
    home = checkpoint_dir(df.sparkSession)
    for path in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        if not path.rsplit("/", 1)[1].startswith("noisytree-"):
            raise ValueError(f"{path} was not written under {home} by written()")
        target = sc._jvm.org.apache.hadoop.fs.Path(path)
        target.getFileSystem(sc._jsc.hadoopConfiguration()).delete(target, True)


def components(edges: DataFrame, rounds: int = 60) -> DataFrame:
    """(node, comp): the least node of each node's component. edges: a, b of any order.

    Alternating large-star and small-star rewiring: every round only moves edges, so the number of
    rows never exceeds that of the input, and hubs are met through a partial minimum and a join
    whose skewed side can be split, never by gathering a hub's neighbours in a task.
    """
    e = durable(edges.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct())
    for _ in range(rounds):
        # Settled: each greater node has one lesser one, which has none itself. Counted by node with partial sums.
        ends = e.selectExpr("inline(array(struct(u as node, 1 as lower, 0 as upper), struct(v as node, 0 as lower, 1 as upper)))")
        unsettled = ends.groupBy("node").agg(F.sum("lower").alias("lower"), F.max("upper").alias("upper")).where("lower + upper > 1 and lower > 0")
        if not unsettled.count():
            break
        both = e.selectExpr("inline(array(struct(u, v), struct(v as u, u as v)))")
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.join(least, "u").where("v > u and v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        e = durable(small.unionByName(low.select("u", F.col("m").alias("v"))).distinct())
    else:
        raise RuntimeError("components did not settle")
    found = e.groupBy("u").agg(F.min("v").alias("comp")).select(F.col("u").alias("node"), "comp")
    return found.unionByName(found.select(F.col("comp").alias("node"), "comp").distinct())
