"""Secret scans with corpus-wide ownership frequency, in DataFrame operations only.

Base detectors find assignments, access keys and long hex strings. A wider detector adds
candidates: runs of 24 or more token characters that mix letters and digits. Every candidate's hash
is counted over the whole corpus by distinct repositories and distinct owners; one that many owners
share is a widely copied example, one that few own and whose characters are varied looks live. Live
wide candidates outside the base spans become spans of the kind ``rare``; base spans always stay.

Where a match starts is the total length of the parts that the pattern leaves between matches and
of the matches before it, so no position is searched for.

Cases: a null or empty text has no spans (the digest is that of the empty string); a repeated row
gives a row each; equal candidates within a row or a repeated row count once an owner; a null owner
or repository counts as one of its own; empty tables give no rows; extra columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from noisytree.llm.common import durable, let, sha256_text

#: Base patterns (fixed values) with the group that is the secret and the least length of it.
KINDS = ("assign", "access", "hex")
PATTERNS = {
    "assign": r"(?i:(password|passwd|secret|token|api_?key))[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)",
    "access": r"AKIA[A-Z0-9]+",
    "hex": r"[0-9a-f]{32,}",
}
GROUP = {"assign": 2, "access": 0, "hex": 0, "rare": 0}
LEAST = {"assign": 8, "access": 16, "hex": 32, "rare": 24}
RARE = r"[A-Za-z0-9+/_-]{24,}"
EXAMPLE_OWNERS = 4
EXAMPLE_REPOS = 4
VARIED = 8


def found(text: Column, kind: str) -> Column:
    """array<struct<start, end, kind, secret>> of the matches of a kind that are long enough."""
    pattern = PATTERNS.get(kind, RARE)

    def walk(arrays: Column) -> Column:
        # arrays: struct of matches, secrets and the parts between them
        zero = F.struct(F.lit(0).alias("at"), F.array().cast("array<struct<start:int,end:int,kind:string,secret:string>>").alias("out"))

        def step(state: Column, i: Column) -> Column:
            start = state["at"] + F.length(arrays["gaps"][i])
            end = start + F.length(arrays["hits"][i])
            one = F.struct(start.alias("start"), end.alias("end"), F.lit(kind).alias("kind"), arrays["secrets"][i].alias("secret"))
            kept = F.when(F.length(arrays["secrets"][i]) >= LEAST[kind], F.array(one)).otherwise(F.slice(F.array(one), 1, 0))
            return F.struct(end.alias("at"), F.concat(state["out"], kept).alias("out"))

        n = F.size(arrays["hits"])
        return F.when(n == 0, zero["out"]).otherwise(F.aggregate(F.sequence(F.lit(0), n - 1), zero, step)["out"])

    arrays = F.struct(
        F.regexp_extract_all(text, F.lit(pattern), F.lit(0)).alias("hits"),
        F.regexp_extract_all(text, F.lit(pattern), F.lit(GROUP[kind])).alias("secrets"),
        F.split(text, pattern, -1).alias("gaps"),
    )
    # Most texts hold no match at all: one scan for them.
    empty = F.array().cast("array<struct<start:int,end:int,kind:string,secret:string>>")
    return F.when(text.rlike(pattern), let(arrays, walk)).otherwise(empty)


def joined(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def order(spans: Column) -> Column:
    """By start, then by kind as listed (a kind's own spans do not overlap)."""
    rank = lambda s: F.array_position(F.array(*[F.lit(k) for k in (*KINDS, "rare")]), s["kind"])
    keyed = F.array_sort(F.transform(spans, lambda s: F.struct(s["start"].alias("a"), rank(s).alias("b"), s.alias("s"))))
    return F.transform(keyed, lambda x: x["s"])


def candidates(docs: DataFrame, key: str, owner: str, repo: str, text: str = "text") -> DataFrame:
    """key, owner, repo, base (ordered base spans), wide (rare candidates outside them)."""
    t = F.coalesce(F.col(text).cast("string"), F.lit(""))
    base = docs.select(F.col(key).alias("key"), F.col(owner).cast("string").alias("owner"), F.col(repo).cast("string").alias("repo"), order(F.concat(*[found(t, k) for k in KINDS])).alias("base"), found(t, "rare").alias("wide"))
    mixed = lambda s: s["secret"].rlike("[0-9]") & s["secret"].rlike("[A-Za-z]")
    apart = lambda s: F.forall("base", lambda b: (s["start"] >= b["end"]) | (s["end"] <= b["start"]))
    return base.withColumn("wide", F.filter("wide", lambda s: mixed(s) & apart(s)))


def ownership(found: DataFrame) -> DataFrame:
    """hash, n_owners, n_repos of every candidate of the corpus."""
    each = found.select("owner", "repo", F.explode(F.concat("base", "wide")).alias("s"))
    each = each.select(sha256_text(F.col("s.secret")).alias("hash"), F.coalesce("owner", F.lit("")).alias("owner"), F.coalesce("repo", F.lit("")).alias("repo")).distinct()
    # Two plain aggregations, first by owner: a candidate in a third of all rows shrinks before it moves.
    by_owner = each.groupBy("hash", "owner").agg(F.count("*").alias("n"))
    return by_owner.groupBy("hash").agg(F.count("*").alias("n_owners"), F.sum("n").alias("n_repos"))


def scan(docs: DataFrame, key: str = "doc_id", owner: str = "source", repo: str = "doc_id", text: str = "text", example_owners: int = EXAMPLE_OWNERS, example_repos: int = EXAMPLE_REPOS) -> DataFrame:
    """A row for each row of docs: key, base, live (spans judged live, base or rare), all (base and live rare spans), n_example.

    ``text_key`` tells rows of one key but different texts apart; rows alike in both share the result.
    """
    t = F.coalesce(F.col(text).cast("string"), F.lit(""))
    rows = docs.withColumn("text_key", F.xxhash64(t))
    # Spans only, written once: three steps read them, and each would run all patterns over all texts again.
    got = durable(candidates(rows.withColumn("_row", F.struct(F.col(key), F.col("text_key"))), "_row", owner, repo, text))
    some = got.where((F.size("base") > 0) | (F.size("wide") > 0))
    spans = some.select("key", F.explode(F.concat("base", "wide")).alias("s")).distinct()
    owned = ownership(some)
    varied = F.size(F.array_distinct(F.split(F.col("s.secret"), "(?!^)"))) >= VARIED
    example = (F.col("n_owners") >= example_owners) & (F.col("n_repos") >= example_repos)
    judged = spans.withColumn("hash", sha256_text(F.col("s.secret"))).join(owned, "hash").withColumn("live", varied & ~example)
    slim = F.struct(F.col("s.start").alias("start"), F.col("s.end").alias("end"), F.col("s.kind").alias("kind"))
    by_row = judged.groupBy("key").agg(F.collect_set(F.when(F.col("live"), slim)).alias("live"), F.collect_set(F.when(~F.col("live"), slim)).alias("dead"))
    base = got.select("key", F.transform("base", lambda s: F.struct(s["start"].alias("start"), s["end"].alias("end"), s["kind"].alias("kind"))).alias("base"))
    none = F.array().cast("array<struct<start:int,end:int,kind:string>>")
    out = base.join(by_row, "key", "left").withColumn("live", order(F.coalesce("live", none))).withColumn("dead", F.coalesce("dead", none))
    rare = F.filter("live", lambda s: s["kind"] == "rare")
    return out.select(F.col(f"key.{key}").alias(key), F.col("key.text_key").alias("text_key"), "base", "live", order(F.concat("base", rare)).alias("all"), F.size(F.filter("dead", lambda s: s["kind"] != "rare")).cast("long").alias("n_example"))


def digest(scanned: DataFrame, key: str = "doc_id") -> DataFrame:
    """What the query returns of scan()."""
    n = lambda k: F.size(F.filter("base", lambda s: s["kind"] == k)).cast("long").alias(f"n_{k}")
    return scanned.select(key, *[n(k) for k in KINDS], sha256_text(joined(F.col("base"))).alias("base_sha256"), joined(F.col("all")).alias("spans"), F.size("live").cast("long").alias("n_live"), "n_example")


def redacted(text: Column, spans: Column, mark: str = "[SECRET]") -> Column:
    """text with the spans, ordered by start, replaced by mark; overlapping spans count as one."""
    zero = F.struct(F.lit(0).alias("at"), F.lit("").alias("out"))

    def step(state: Column, s: Column) -> Column:
        lead = F.substring(text, state["at"] + 1, s["start"] - state["at"])
        inside = s["start"] < state["at"]
        return F.struct(F.greatest(state["at"], s["end"]).alias("at"), F.when(inside, state["out"]).otherwise(F.concat(state["out"], lead, F.lit(mark))).alias("out"))

    done = lambda st: F.concat(st["out"], F.substring(text, st["at"] + 1, F.length(text)))
    return F.when(F.size(spans) == 0, text).otherwise(F.aggregate(spans, zero, step, done))
