"""Mixing sources to target weights by Poisson replication, in DataFrame operations only.

A source's target repetition rate is its share of the target size over its own size. A document's
number of copies is the inverse, at a uniform drawn from a hash of its id, of a Poisson distribution
with that rate; each copy is a row, and all rows are shuffled globally by a hash of id and copy.
The cumulative distribution is a short array per source; a large rate is a sum of equal parts, each
with a hash of its own, so nothing underflows and no count is capped.

Cases: a null source is a source of its own; sources without a single character take no part (their
rate is 0), nor do sources with weight 0 or none; rows with the same id get the same number of
copies; a null text counts as size 0; an empty table gives no rows; extra columns pass through.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from noisytree.llm.common import durable, let

#: Rate of one part of a source's Poisson variable.
PART = 64.0
#: Sources up to which their table is broadcast: some 600 kB at the longest arrays.
BROADCAST_SOURCES = 500
SALTS = 64


def uniform(*key: Column) -> Column:
    """A double in (0, 1) from the hash of the key; the same in any engine that has md5."""
    head = F.conv(F.substring(F.md5(F.concat_ws(":", *[k.cast("string") for k in key]).cast("binary")), 1, 13), 16, 10)
    return (head.cast("long").cast("double") + 0.5) / F.lit(2.0**52)


def sources(docs: DataFrame, weights: dict[str, float] | None = None, total: float = 1.0, source: str = "source", text: str = "text") -> DataFrame:
    """_mix_source, _mix_rate, _mix_parts, _mix_cdf. weights: target share of each source; None: as the square root of
    its size, which lies between the shares as they are and equal ones. total: size wanted over size at hand."""
    size = docs.groupBy(F.col(source).cast("string").alias("_mix_source")).agg(F.sum(F.coalesce(F.length(text), F.lit(0)).cast("long")).alias("size"))
    if weights is None:
        share = F.floor(F.sqrt("size") * 1_000_000)
    else:
        share = F.lit(0).cast("long")
        for name, w in weights.items():
            share = F.when(F.col("_mix_source") == name, F.lit(int(w * 1_000_000_000))).otherwise(share)
    size = size.withColumn("share", F.when(F.col("size") > 0, share).otherwise(F.lit(0)))
    size = durable(size)
    whole = size.agg(F.coalesce(F.sum("size"), F.lit(0)).alias("size"), F.coalesce(F.sum("share"), F.lit(0)).alias("share")).first()  # one row
    rate = F.lit(float(total)) * F.lit(whole["size"]) * (F.col("share") / F.lit(max(1, whole["share"]))) / F.col("size")
    out = size.withColumn("_mix_rate", F.when((F.col("size") > 0) & (F.col("share") > 0), rate).otherwise(F.lit(0.0)))
    parts = F.greatest(F.lit(1), F.ceil(F.col("_mix_rate") / PART)).cast("int")
    out = out.withColumn("_mix_parts", parts).withColumn("part_rate", F.col("_mix_rate") / F.col("_mix_parts"))
    zero = F.struct(F.exp(-F.col("part_rate")).alias("p"), F.array(F.exp(-F.col("part_rate"))).alias("cdf"))

    def step(state: Column, k: Column) -> Column:
        p = state["p"] * F.col("part_rate") / k
        return F.struct(p.alias("p"), F.concat(state["cdf"], F.array(F.element_at(state["cdf"], -1) + p)).alias("cdf"))

    # Beyond this the tail is below the smallest step of the uniform.
    last = F.ceil(F.col("part_rate") + 12 * F.sqrt("part_rate") + 40).cast("int")
    return out.select("_mix_source", "_mix_rate", "_mix_parts", F.aggregate(F.sequence(F.lit(1), last), zero, step)["cdf"].alias("_mix_cdf"))


def copies(doc_id: Column, seed: int) -> Column:
    """Number of copies, from the columns of sources()."""
    one = lambda part: let(uniform(F.lit(seed), doc_id, part), lambda u: F.size(F.filter("_mix_cdf", lambda c: c <= u)))
    return F.aggregate(F.sequence(F.lit(1), F.col("_mix_parts")), F.lit(0), lambda n, part: n + one(part))


def with_rates(docs: DataFrame, rates: DataFrame, source: str) -> DataFrame:
    """docs with the columns of sources() of their source; a source may hold most rows."""
    name = F.coalesce(F.col(source).cast("string"), F.lit("\0"))
    rates = rates.withColumn("_mix_source", F.coalesce("_mix_source", F.lit("\0")))
    docs = docs.withColumn("_mix_source", name)
    if rates.select(F.lit(1)).limit(BROADCAST_SOURCES + 1).count() <= BROADCAST_SOURCES:
        return docs.join(F.broadcast(rates), "_mix_source")
    salted = rates.withColumn("_mix_salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    return docs.withColumn("_mix_salt", F.pmod(F.xxhash64(*docs.columns), F.lit(SALTS)).cast("int")).join(salted, ["_mix_source", "_mix_salt"]).drop("_mix_salt")


def mix(docs: DataFrame, weights: dict[str, float] | None = None, total: float = 1.0, seed: int = 17, key: str = "doc_id", source: str = "source", text: str = "text") -> DataFrame:
    """The columns of docs, then _copy (from 1), _copies and _rate; rows in a global random order."""
    rates = sources(docs, weights, total, source, text)
    out = with_rates(docs, rates, source).withColumn("_copies", copies(F.col(key), seed)).where("_copies > 0")
    out = out.select(*docs.columns, F.explode(F.sequence(F.lit(1), F.col("_copies"))).alias("_copy"), "_copies", F.col("_mix_rate").alias("_rate"))
    order = F.xxhash64(F.lit(seed), F.col(key), F.col("_copy"))
    return out.withColumn("_order", order).repartition("_order").sortWithinPartitions("_order").drop("_order")
