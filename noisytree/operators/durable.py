"""Cuts of the lineage in the shared folder that the session names."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession) -> str:
    """The checkpoint folder that the session names; a temporary one only for a session within one machine."""
    sc = spark.sparkContext
    found = sc.getCheckpointDir() or sc.getConf().get("spark.checkpoint.dir", None)
    if not found:
        if not sc.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir is not set: tables between steps need a folder that all executors share")
        found = tempfile.mkdtemp(prefix="noisytree-checkpoint-")
    if not sc.getCheckpointDir():
        sc.setCheckpointDir(found)
    return sc.getCheckpointDir()


def durable(df: DataFrame) -> DataFrame:
    """df, written once as Parquet and read from there: lineage ends, lost executors cost nothing, and the planner
    starts from the table's true size. (A checkpoint() keeps the size estimate of the plan that it cuts; joins of
    such frames multiply these level after level until planning takes longer than the data.)"""
    spark, schema = df.sparkSession, df.schema
    path = f"{shared_folder(spark)}/noisytree-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(schema).parquet(path)


#: Rows up to which a frame of nodes is broadcast; beyond, joins shuffle.
BROADCAST_NODES = 100_000
