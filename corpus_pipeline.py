"""A training corpus from documents in five stages.

Each function takes (spark, docs, sf_dir) and returns a frame, which is written as Parquet and read
again as the next one's docs; all but the last return the columns of documents.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from noisytree.llm import bpe, mixing, near_dup, quality_model, secrets
from noisytree.llm.common import free, table, written
from noisytree.llm.queries import tokenizer_path


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier rejects go. A null or empty text is scored by its structure alone; repeated rows
    get one score and stay or go together; without labels every score is 0.5, so all go; an empty table stays empty;
    columns of any name pass through."""
    name = free("_score", docs.columns)
    model = quality_model.fit(docs, table(spark, sf_dir, "labels"))
    return quality_model.score(docs, model, name=name).where(F.col(name) >= quality_model.THRESHOLD).select(*docs.columns)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of near duplicates stays: the one with the least id, of equal ids the one with the
    least hash of its text. A null text, or one without words, is like no other but its own repeated row; a missing id
    counts as the least; an empty table stays empty; columns of any name pass through."""
    return near_dup.deduplicated(docs)


def secret_scan(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Secrets that look live are replaced by a mark; widely copied examples stay. A null text stays null; repeated
    rows are changed alike; a missing id matches itself; an empty table stays empty; columns of any name pass through."""
    text, doc = F.coalesce(F.col("text"), F.lit("")), F.coalesce("doc_id", F.lit(-(1 << 63)).cast("long"))
    live = secrets.scan(docs).where(F.size("live") > 0).select(doc.alias("doc"), F.col("text_key").alias("key"), "live").dropDuplicates(["doc", "key"])
    # The row travels in one struct, so that no column can clash with the keys.
    rows = docs.select(doc.alias("doc"), F.xxhash64(text).alias("key"), F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row")).join(live, ["doc", "key"], "left")
    old = F.col("row.text")
    new = F.when(F.col("live").isNull(), old).otherwise(secrets.redacted(F.coalesce(old, F.lit("")), F.col("live")))
    changed = {"text": new, "n_chars": F.when(F.col("live").isNull(), F.col("row.n_chars")).otherwise(F.length(new).cast("long"))}
    return rows.select(*[changed.get(c, F.col(f"row.`{c}`")).alias(c) for c in docs.columns])


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sources at their target weights; a document stands as often as it is repeated, a repeated row for itself. A null
    source is a source; a source without text is left out; an empty table stays empty."""
    own = {c: free("_own" + c, docs.columns) for c in docs.columns if c.startswith("_")}  # mix() names columns so
    mixed = mixing.mix(docs.withColumnsRenamed(own)).select(*[own.get(c, c) for c in docs.columns])
    return mixed.withColumnsRenamed({v: k for k, v in own.items()})


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The ids of each text, with the digests of ids and of what they decode to. A null text has no ids; repeated rows
    get a row each; an empty table stays empty."""
    return bpe.encode(docs, tokenizer_path("byte_bpe_50k.json"), decoded=False, keep=("doc_id", "lang", "source"))


STAGES = [
    ("quality_model", quality),
    ("ngram_join", near_duplicates),
    ("secrets", secret_scan),
    ("mix", mix_sources),
    ("bpe", tokens),
]

#: Training a classifier and near duplicates are beyond SQL; tests hold run() against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES[:-1]:
        docs = written(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
