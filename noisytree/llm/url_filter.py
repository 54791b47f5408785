"""URL filters by association rules, in DataFrame operations and Spark's FP-growth.

Host and path rules label the urls that they fit. FP-growth mines combinations of url tokens and
label from these; rules "tokens imply label" that reach the least support and confidence judge the
urls that no host rule fits, by an inverted index: each rule stands under its rarest token, and a
url meets only the rules that stand under one of its tokens. The rule of the highest confidence
decides (then support, then more tokens, then their order); a url that none fits is allowed.

Tokens that occur in exactly the same labelled urls are mined as one item, so a long url copied many
times does not make FP-growth list every subset of its tokens.

Cases: a null url, or one without ``://``, has an empty host and path and no tokens, and is allowed;
repeated rows get a row each; with no labelled url there are no mined rules; an empty table gives
no rows; extra columns are ignored.
"""

from __future__ import annotations

from pyspark.ml.fpm import FPGrowth
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from noisytree.llm.common import durable

#: (host, path, verdict) (fixed values).
HOST_RULES = (("org", "/", "allow"), ("example.org", "/es/", "block"), ("example.org", "/en/1", "block"), ("com", "/fr/", "allow"), ("com", "/de/", "block"))
SUPPORT = 0.01
CONFIDENCE = 0.8
#: Mined rules up to which the index is broadcast: some 100 bytes each.
BROADCAST_RULES = 20_000


def host_path(url: Column) -> tuple[Column, Column]:
    rest = F.when(url.contains("://"), F.substring(url, F.locate("://", url) + 3, F.length(url))).otherwise(F.lit(""))
    rest = F.coalesce(rest, F.lit(""))
    raw = F.regexp_extract(rest, r"^([^/?#]*)", 1)
    host = F.translate(raw, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    path = F.regexp_extract(rest, r"(?s)^[^/?#]*(/[^?#]*)?", 1)
    return host, path


def fitted(host: Column, path: Column, rules=HOST_RULES) -> tuple[Column, Column]:
    """The longest rule that fits (host + path, like ``net/``) and its verdict; null where none does."""
    rule, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    for h, p, v in sorted(rules, key=lambda r: len(r[0] + r[1])):
        fits = ((host == h) | host.endswith("." + h)) & path.startswith(p)
        rule, verdict = F.when(fits, F.lit(h + p)).otherwise(rule), F.when(fits, F.lit(v)).otherwise(verdict)
    return rule, verdict


def tokens(host: Column, path: Column, url: Column) -> Column:
    """Distinct tokens of host labels, path and query."""
    query = F.regexp_extract(F.coalesce(url, F.lit("")), r"\?([^#]*)", 1)
    part = lambda c, mark: F.transform(F.filter(F.split(F.lower(c), r"[^\p{L}\p{N}]+"), lambda x: x != ""), lambda x: F.concat(F.lit(mark), x))
    return F.array_distinct(F.concat(part(host, "h:"), part(path, "p:"), F.when(host != "", part(query, "q:")).otherwise(F.array().cast("array<string>"))))


def mined(labelled: DataFrame, support: float = SUPPORT, confidence: float = CONFIDENCE) -> DataFrame:
    """tokens (array), verdict, confidence, support. labelled: row (any id), tokens, verdict."""
    n = labelled.count()
    empty = labelled.sparkSession.range(0).select(F.array().cast("array<string>").alias("tokens"), F.lit("").alias("verdict"), F.lit(0.0).alias("confidence"), F.lit(0.0).alias("support"))
    if not n:
        return empty
    each = labelled.select("row", F.explode("tokens").alias("token"))
    marks = each.groupBy("token").agg(F.count("*").alias("n"), F.sum(F.xxhash64("row").cast("decimal(38,0)")).alias("rows")).where(F.col("n") >= support * n)
    # An item is a class of tokens with the same rows; the least token names it.
    classes = marks.groupBy("n", "rows").agg(F.min("token").alias("item"), F.sort_array(F.collect_list("token")).alias("all_tokens")).select("item", "all_tokens")
    items = each.join(classes, each["token"] == classes["item"]).groupBy("row").agg(F.collect_list("item").alias("items"))
    baskets = items.join(labelled.select("row", "verdict"), "row").select(F.concat("items", F.array(F.concat(F.lit("="), F.col("verdict")))).alias("items"))
    baskets = durable(baskets)
    if baskets.isEmpty():
        return empty
    model = FPGrowth(itemsCol="items", minSupport=support, minConfidence=confidence).fit(baskets)
    rules = model.associationRules.where(F.col("consequent")[0].startswith("=") & ~F.exists("antecedent", lambda x: x.startswith("=")))
    rules = rules.select(F.monotonically_increasing_id().alias("id"), "antecedent", F.substring(F.col("consequent")[0], 2, 99).alias("verdict"), "confidence", "support")
    rules = durable(rules)
    whole = rules.select("id", F.explode("antecedent").alias("item")).join(classes, "item").groupBy("id").agg(F.array_sort(F.flatten(F.collect_list("all_tokens"))).alias("tokens"))
    return rules.join(whole, "id").select("tokens", "verdict", "confidence", "support")


def matched(urls: DataFrame, rules: DataFrame) -> DataFrame:
    """url, verdict, confidence by the best rule that fits. urls: url (distinct), tokens."""
    seen = rules.select(F.explode("tokens").alias("token"), "support").groupBy("token").agg(F.max("support").alias("most"))
    under = rules.withColumn("rule_id", F.xxhash64("tokens", "verdict")).select("rule_id", F.explode("tokens").alias("token")).join(seen, "token").groupBy("rule_id").agg(F.min(F.struct("most", "token")).alias("k")).select("rule_id", F.col("k.token").alias("token"))
    index = durable(rules.withColumn("rule_id", F.xxhash64("tokens", "verdict")).join(under, "rule_id").select("token", F.col("tokens").alias("needs"), "verdict", "confidence", "support"))
    if index.limit(BROADCAST_RULES + 1).count() <= BROADCAST_RULES:
        index = F.broadcast(index)
    hits = urls.select("url", "tokens", F.explode("tokens").alias("token")).join(index, "token").where(F.size(F.array_except("needs", "tokens")) == 0)
    best = F.max_by(F.struct("verdict", "confidence"), F.struct("confidence", "support", F.size("needs"), "needs", "verdict"))
    return hits.groupBy("url").agg(best.alias("b")).select("url", "b.verdict", "b.confidence")


def judge(pages: DataFrame, key: str = "page_id", url: str = "url", rules=HOST_RULES, support: float = SUPPORT, confidence: float = CONFIDENCE) -> DataFrame:
    """key, host, path, rule, verdict, confidence (of the mined rule; null where none decided)."""
    host, path = host_path(F.col("url"))
    rows = pages.select(F.col(key), F.col(url).cast("string").alias("url"))
    rows = rows.withColumn("host", host).withColumn("path", path)
    rule, verdict = fitted(F.col("host"), F.col("path"), rules)
    rows = rows.withColumn("rule", rule).withColumn("fixed", verdict)
    cut = rows.withColumn("tokens", tokens(F.col("host"), F.col("path"), F.col("url")))
    # Labels count pages, as the corpus holds them; the id of a row tells tokens with the same rows.
    labelled = cut.where("fixed is not null").select(F.xxhash64(key, "url").alias("row"), "tokens", F.col("fixed").alias("verdict")).dropDuplicates(["row"])
    open_urls = cut.where("fixed is null and size(tokens) > 0").select("url", "tokens").dropDuplicates(["url"])
    by_url = matched(open_urls, mined(labelled, support, confidence)).withColumnRenamed("verdict", "mined")
    out = rows.join(by_url, "url", "left")
    return out.select(key, "host", "path", "rule", F.coalesce("fixed", "mined", F.lit("allow")).alias("verdict"), F.when(F.col("fixed").isNull(), F.round("confidence", 6)).alias("confidence"))
