"""The queries of this subpackage: each applies its operator to its whole table."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from noisytree.llm import bpe, mixing, near_dup, passages, quality_model, quality_rules, secrets, token_count, topk, url_filter
from noisytree.llm.common import table


def tokenizer_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.encode(table(spark, sf_dir, "documents"), tokenizer_path("byte_bpe_50k.json"), ids=False, decoded=False)


def op2_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = topk.quantised(table(spark, sf_dir, "embeddings"), "vec_id", "embedding")
    return topk.topk(vectors, vectors.where("id % 20 = 0"), 20)


def op3_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secrets.digest(secrets.scan(table(spark, sf_dir, "documents").select("doc_id", "text", "source")))


def op4_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    mixed = mixing.mix(table(spark, sf_dir, "documents").select("doc_id", "source", "lang", "text"))
    return mixed.select("doc_id", "source", "lang", "text", F.col("_copy").alias("copy_no"), F.col("_copies").alias("n_copies"), F.round("_rate", 6).alias("rate"))


def op5_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_rules.judge(table(spark, sf_dir, "documents"))


def op6_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_count.token_counts(table(spark, sf_dir, "documents"), tokenizer_path("word_bpe_49k.json"))


def op7_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_filter.judge(table(spark, sf_dir, "pages").select("page_id", "url"))


def op8_quality_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = quality_model.fit(docs, table(spark, sf_dir, "labels"))
    scored = quality_model.score(docs, model, keep=("doc_id",))
    return scored.select("doc_id", quality_model.held_out(F.col("doc_id")).alias("held_out"), F.col("_score").alias("score"), (F.col("_score") >= quality_model.THRESHOLD).cast("int").alias("predicted"))


def op9_ngram_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dup.join(table(spark, sf_dir, "documents"))


def op10_passages(spark: SparkSession, sf_dir: str) -> DataFrame:
    return passages.passages(table(spark, sf_dir, "documents"))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict:
    own = (op1_bpe, op2_topk, op3_secrets, op4_mix, op5_rules, op6_token_counts, op7_url_filter, op8_quality_model, op9_ngram_join, op10_passages, pipeline)
    return {f.__name__: f for f in own}


_TOPK = """
WITH v AS (
  SELECT vec_id, list_transform(embedding, lambda x: floor(64 * x::DOUBLE)) AS v FROM embeddings
  WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
), s AS (
  SELECT q.vec_id AS query_id, c.vec_id, CAST(list_inner_product(q.v, c.v) AS BIGINT) AS score
  FROM v q JOIN v c ON q.vec_id <> c.vec_id AND len(q.v) = len(c.v) WHERE q.vec_id % 20 = 0
), r AS (
  SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS k FROM s
)
SELECT query_id, CAST(k AS INTEGER) AS rank, vec_id, score FROM r WHERE k <= 20
"""

_MIX = """
WITH RECURSIVE size AS (
  SELECT source, sum(coalesce(length(text), 0))::BIGINT AS size FROM documents GROUP BY source
), share AS (
  SELECT *, CASE WHEN size > 0 THEN floor(sqrt(size) * 1000000)::BIGINT ELSE 0 END AS share FROM size
), rate AS (
  SELECT source, 1.0::DOUBLE * (sum(size) OVER ())::DOUBLE * (share::DOUBLE / (sum(share) OVER ())::DOUBLE) / size::DOUBLE AS rate FROM share WHERE size > 0
), part AS (
  SELECT source, rate, greatest(1, ceil(rate / 64.0))::INTEGER AS parts FROM rate
), cdf AS (
  SELECT source, 0 AS k, exp(-(rate / parts)) AS p, exp(-(rate / parts)) AS c, rate / parts AS l,
         ceil(rate / parts + 12 * sqrt(rate / parts) + 40)::INTEGER AS last FROM part
  UNION ALL
  SELECT source, k + 1, p * l / (k + 1), c + p * l / (k + 1), l, last FROM cdf WHERE k < last
), draw AS (
  SELECT d.doc_id, d.source, d.lang, d.text, p.rate, i.part, row_number() OVER () AS row_id,
         (('0x' || substr(md5('17:' || d.doc_id || ':' || i.part), 1, 13))::BIGINT + 0.5) / 4503599627370496.0 AS u
  FROM documents d JOIN part p USING (source), LATERAL (SELECT unnest(range(1, p.parts + 1)) AS part) i
), n AS (
  SELECT doc_id, source, lang, text, rate, sum((SELECT count(*) FROM cdf WHERE cdf.source = draw.source AND cdf.c <= draw.u))::INTEGER AS n_copies
  FROM draw GROUP BY doc_id, source, lang, text, rate
)
SELECT doc_id, source, lang, text, unnest(range(1, n_copies + 1))::INTEGER AS copy_no, n_copies, round(rate, 6) AS rate FROM n WHERE n_copies > 0
"""


def _secrets_sql() -> str:
    quoted = {k: p.replace("'", "''").replace('\\"', '"').replace("\\''", "''") for k, p in (secrets.PATTERNS | {"rare": secrets.RARE}).items()}
    kinds = " UNION ALL ".join(
        f"SELECT rid, doc_id, source, '{k}' AS kind, {i} AS ord, {secrets.LEAST[k]} AS least, regexp_extract_all(t, '{p}', 0) AS h, regexp_extract_all(t, '{p}', {secrets.GROUP[k]}) AS s, string_split_regex(t, '{p}') AS g FROM d"
        for i, (k, p) in enumerate(quoted.items())
    )
    listed = "coalesce(string_agg(kind || ':' || a || ':' || b, ',' ORDER BY a, ord){}, '')"
    return f"""
WITH d AS (SELECT row_number() OVER () AS rid, doc_id, coalesce(source, '') AS source, coalesce(text, '') AS t FROM documents),
k AS ({kinds}),
u AS (SELECT rid, doc_id, source, kind, ord, least, i, h[i] AS hit, s[i] AS sec, g[i] AS gap FROM k, LATERAL (SELECT unnest(range(1, len(h) + 1)) AS i)),
p AS (SELECT *, (sum(length(gap)) OVER (PARTITION BY rid, kind ORDER BY i) + coalesce(sum(length(hit)) OVER (PARTITION BY rid, kind ORDER BY i ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))::BIGINT AS a FROM u),
sp AS (SELECT *, a + length(hit) AS b FROM p WHERE length(sec) >= least),
cand AS (SELECT * FROM sp WHERE kind <> 'rare' UNION ALL SELECT * FROM sp w WHERE kind = 'rare' AND regexp_matches(sec, '[0-9]') AND regexp_matches(sec, '[A-Za-z]')
  AND NOT EXISTS (SELECT 1 FROM sp b WHERE b.kind <> 'rare' AND b.rid = w.rid AND b.a < w.b AND b.b > w.a)),
own AS (SELECT sec, count(DISTINCT source) AS owners, count(DISTINCT (source, doc_id)) AS repos FROM cand GROUP BY 1),
j AS (SELECT c.*, len(list_distinct(string_split(sec, ''))) >= {secrets.VARIED} AND NOT (owners >= {secrets.EXAMPLE_OWNERS} AND repos >= {secrets.EXAMPLE_REPOS}) AS live FROM cand c JOIN own USING (sec)),
r AS (SELECT rid, count(*) FILTER (kind = 'assign') AS n_assign, count(*) FILTER (kind = 'access') AS n_access, count(*) FILTER (kind = 'hex') AS n_hex,
  {listed.format(" FILTER (kind <> 'rare')")} AS base, {listed.format(" FILTER (kind <> 'rare' OR live)")} AS spans,
  count(*) FILTER (live) AS n_live, count(*) FILTER (NOT live AND kind <> 'rare') AS n_example FROM j GROUP BY 1)
SELECT doc_id, coalesce(n_assign, 0) AS n_assign, coalesce(n_access, 0) AS n_access, coalesce(n_hex, 0) AS n_hex, sha256(coalesce(base, '')) AS base_sha256,
  coalesce(spans, '') AS spans, coalesce(n_live, 0) AS n_live, coalesce(n_example, 0) AS n_example FROM d LEFT JOIN r USING (rid)
"""


def oracle_sql() -> dict[str, str]:
    return {"op2_topk": _TOPK, "op3_secrets": _secrets_sql(), "op4_mix": _MIX}
