"""Point views of the given tables, and readers of other formats. Only coordinate columns are read."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from noisytree.plans.domain import Domain


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def days(ts: str, origin: str) -> Column:
    return F.datediff(F.col(ts).cast("date"), F.lit(origin).cast("date")).cast("double")


def micros(ts: str, origin: str) -> Column:
    """Microseconds since origin, from the wall clock of a timestamp without zone."""
    # The parts of a wall clock do not depend on the session's zone.
    day = F.datediff(F.col(ts).cast("date"), F.lit(origin).cast("date")).cast("long")
    second = F.hour(ts) * 3600 + F.minute(ts) * 60
    fine = F.round(F.extract(F.lit("SECOND"), F.col(ts)) * 1_000_000).cast("long")
    return (day * 86_400 + second) * 1_000_000 + fine


def lineitem_key() -> Column:
    """Whole numbers that tell rows apart, as text: cents and days in place of doubles and times."""
    cents = F.round(F.col("l_extendedprice") * 100).cast("long")
    day = F.datediff(F.col("l_shipdate").cast("date"), F.lit("1995-01-01").cast("date"))
    return F.concat_ws(":", *[c.cast("string") for c in (F.col("l_orderkey"), F.col("l_linenumber"), cents, day)])


def points(spark: SparkSession, sf_dir: str, view: str, d: int = 3) -> DataFrame:
    """pid string and the coordinates of a view (see plans.domain for its domain)."""
    t = lambda name: table(spark, sf_dir, name)
    key = lambda c: F.col(c).cast("string").alias("pid")
    if view == "LI":
        return t("lineitem").select(lineitem_key().alias("pid"), F.col("l_extendedprice").cast("double").alias("x"), days("l_shipdate", "1995-01-01").alias("y"))
    if view == "EV":
        return t("events").select(key("event_id"), (micros("ts", "2024-01-01") / F.lit(86_400_000_000.0)).alias("x"), F.col("value").cast("double").alias("y"))
    if view == "OR":
        return t("orders").select(key("o_orderkey"), F.col("o_totalprice").cast("double").alias("x"), days("o_orderdate", "1995-01-01").alias("y"))
    if view == "EMB":
        return t("embeddings").select(key("vec_id"), *[F.element_at("embedding", k + 1).cast("double").alias("xyz"[k]) for k in range(d)])
    if view == "CUST":
        return t("customer").select(key("c_custkey"), F.col("c_acctbal").cast("double").alias("x"), F.col("c_nationkey").cast("double").alias("y"))
    if view == "SUPP":
        return t("supplier").select(key("s_suppkey"), F.col("s_acctbal").cast("double").alias("x"), F.col("s_nationkey").cast("double").alias("y"))
    if view == "PRICE":
        return t("lineitem").select(lineitem_key().alias("pid"), F.col("l_extendedprice").cast("double").alias("x"))
    if view == "VAL":
        return t("events").select(key("event_id"), F.col("value").cast("double").alias("x"), "event_type")
    if view == "LEN":
        return t("documents").select(key("doc_id"), F.col("n_chars").cast("double").alias("x"))
    raise ValueError(f"no view {view}")


def read_points(spark: SparkSession, fmt: str, path: str, mapping: dict[str, str], domain: Domain, schema: str | None = None, **options) -> DataFrame:
    """Points from any format that Spark reads; mapping: coordinate or pid to an SQL expression."""
    reader = spark.read.format(fmt).options(**options)
    if schema:
        reader = reader.schema(schema)
    wanted = {n: mapping[n] for n in (["pid"] if "pid" in mapping else []) + domain.names}
    return reader.load(path).select(*[F.expr(e).cast("string" if n == "pid" else "double").alias(n) for n, e in wanted.items()])
