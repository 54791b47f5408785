"""Quality rules as weak supervision, in DataFrame operations only.

Each rule votes on its own measure for good (1) or for bad (-1), or abstains (0). A rule's votes for
good and for bad are two voters: passing a rule says little, failing it much. Expectation-maximisation
over the counts of the vote patterns (at most 3 to the number of rules, whatever the size of the corpus)
estimates how often each voter is right; a text's posterior probability of being good then follows
from a sum of log odds over its votes. A rule that abstains says nothing, and one whose bad votes fall
on texts that fail elsewhere no more often than on others comes to say little: such a vote alone is outvoted.

Cases: a null or empty text has no words and fails the base rules; repeated rows get a row each;
an empty table gives no rows; extra columns are ignored; long texts are handled whole.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from noisytree.llm.common import WS, durable, let

WINDOW = 8


def words(c: dict[str, Column]) -> Column:
    return F.greatest(c["n_words"], F.lit(1))


#: name: (measure, good up to, bad from). A measure up to "good up to" votes good, one from "bad from" on votes
#: bad, otherwise the rule abstains.
RULES = {
    "symbols": (lambda c: c["n_symbols"] / words(c), 0.05, 0.25),
    "lines": (lambda c: c["n_dup_lines"] / F.greatest(c["n_lines"], F.lit(1)), 0.10, 0.40),
    "repeats": (lambda c: c["n_repeat_words"] / words(c), 0.10, 0.30),
    "length": (lambda c: F.abs(c["word_chars"] / words(c) - 6.0), 3.0, 5.0),
    "sameness": (lambda c: F.sqrt(c["n_words"].cast("double")) / F.greatest(c["n_distinct"], F.lit(1)), 0.35, 0.60),
    "capitals": (lambda c: c["n_capitals"] / F.greatest(c["word_chars"], F.lit(1)), 0.15, 0.40),
    "bangs": (lambda c: c["n_bangs"] / words(c), 0.05, 0.30),
}
#: How often votes for bad and for good are taken to be right before any text is seen (six votes for good don't
#: outweigh one for bad), and what that is worth, as a share of the texts: votes that never meet another rule's
#: have nothing else to be judged by.
BAD_RIGHT, GOOD_RIGHT = 0.9, 0.57
PRIOR = 0.2
#: Texts of fewer words give the rules too little to vote on.
LEAST_WORDS = 20
KEEP_AT = 0.5
#: Odds that a text is good before any vote.
SHARE = 0.5


def less(text: Column, pattern: str) -> Column:
    """How many characters of text the pattern takes."""
    return (F.length(text) - F.length(F.regexp_replace(text, pattern, ""))).cast("long")


def repeat_words(h8: Column) -> Column:
    """Words within windows that occur twice or more. h8: the hash of the window at each position."""

    def covered(s: Column) -> Column:
        same = lambda x, j: F.coalesce(x["h"] == F.get(s, j - 1)["h"], F.lit(False)) | F.coalesce(x["h"] == F.get(s, j + 1)["h"], F.lit(False))
        starts = F.array_sort(F.transform(F.filter(s, same), lambda x: x["i"]))
        zero = F.struct(F.lit(-WINDOW).alias("before"), F.lit(0).cast("long").alias("n"))
        step = lambda st, p: F.struct(p.alias("before"), (st["n"] + F.least(F.lit(WINDOW), p - st["before"])).alias("n"))
        return F.aggregate(starts, zero, step)["n"]

    by_hash = F.array_sort(F.transform(h8, lambda x, i: F.struct(x.alias("h"), i.alias("i"))))
    return F.when(F.size(F.array_distinct(h8)) == F.size(h8), F.lit(0).cast("long")).otherwise(let(by_hash, covered))


def measures(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """key and the counts that the rules judge; one pass over the texts, nothing is shuffled."""
    t = docs.select(F.col(key), F.coalesce(F.col(text).cast("string"), F.lit("")).alias("t"))
    t = t.withColumn("words", F.array_remove(F.split("t", WS), ""))
    t = t.withColumn("h", F.transform("words", lambda w: F.xxhash64(w)))
    for name, of, gap in (("h2", "h", 1), ("h4", "h2", 2), ("h8", "h4", 4)):
        n = F.greatest(F.size(of) - gap, F.lit(0))
        t = t.withColumn(name, F.zip_with(F.slice(of, F.lit(1), n), F.slice(F.col(of), F.lit(1 + gap), n), lambda a, b: F.xxhash64(a, b)))
    lines = F.filter(F.split("t", "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))
    t = t.withColumn("lines", F.transform(lines, lambda x: F.xxhash64(x)))
    return t.select(
        F.col(key),
        F.size("words").cast("long").alias("n_words"),
        (F.length("t") - less(F.col("t"), WS)).cast("long").alias("word_chars"),
        less(F.col("t"), r"[#*$%&|<>]+").alias("n_symbols"),
        (F.size("lines") - F.size(F.array_distinct("lines"))).cast("long").alias("n_dup_lines"),
        repeat_words(F.col("h8")).alias("n_repeat_words"),
        F.size("lines").cast("long").alias("n_lines"),
        F.size(F.array_distinct("h")).cast("long").alias("n_distinct"),
        less(F.col("t"), r"\p{Lu}+").alias("n_capitals"),
        less(F.col("t"), r"[!?]+").alias("n_bangs"),
    )


def voted(counts: DataFrame) -> DataFrame:
    """counts with vote_<rule> of each rule."""
    enough = F.col("n_words") >= LEAST_WORDS
    c = {name: F.col(name) for name in counts.columns}
    return counts.withColumns({f"vote_{name}": F.when(enough & (measure(c) >= bad), F.lit(-1)).when(enough & (measure(c) <= good), F.lit(1)).otherwise(F.lit(0)) for name, (measure, good, bad) in RULES.items()})


def voters(votes: tuple[int, ...]) -> tuple[int, ...]:
    """The votes of the rules as those of twice as many voters: for bad only, then for good only."""
    return tuple(min(v, 0) for v in votes) + tuple(max(v, 0) for v in votes)


def fit(patterns: list[tuple[tuple[int, ...], int]], rounds: int = 200, share: float = SHARE, start: float | list[float] = 0.8, prior: float = 2.0) -> list[float]:
    """How often each voter is right when it votes, by expectation-maximisation.

    ``share`` of good texts is given, not estimated: votes alone cannot tell a rare class from wrong
    rules. Good and bad texts count as if they were in that proportion, so that a vote that most texts
    get is not taken for a right one. Accuracies are one half at least, where a vote has no weight, which
    fixes which of the two classes is the good one; ``prior`` pseudo-votes of ``start`` keep rare voters
    from certainty.
    """
    m = len(patterns[0][0]) if patterns else 0
    right = first = list(start) if isinstance(start, list) else [start] * m
    total = sum(n for _, n in patterns)
    for _ in range(rounds):
        good = [posterior(votes, share, right) for votes, _ in patterns]
        n_good = sum(n * p for (_, n), p in zip(patterns, good, strict=True))
        as_good, as_bad = share * total / max(n_good, 1), (1 - share) * total / max(total - n_good, 1)
        hit, all_ = [prior * a for a in first], [float(prior)] * m
        for (votes, n), p in zip(patterns, good, strict=True):
            g, b = n * p * as_good, n * (1 - p) * as_bad
            for j, v in enumerate(votes):
                if v:
                    all_[j] += g + b
                    hit[j] += g if v > 0 else b
        new = [min(max(a / b, 0.5), 0.995) for a, b in zip(hit, all_, strict=True)]
        moved = max(abs(x - y) for x, y in zip(new, right, strict=True)) if m else 0
        right = new
        if moved < 1e-10:
            break
    return right


def odds(share: float, right: list[float]) -> tuple[float, list[float]]:
    """Log odds of good to begin with, and what a vote of each rule moves them by."""
    return math.log(share / (1 - share)), [math.log(a / (1 - a)) for a in right]


def posterior(votes: tuple[int, ...], share: float, right: list[float]) -> float:
    x, moves = odds(share, right)
    return 1 / (1 + math.exp(-x - sum(v * w for v, w in zip(votes, moves, strict=True))))


def judge(docs: DataFrame, key: str = "doc_id", text: str = "text", keep_at: float = KEEP_AT, share: float = SHARE) -> DataFrame:
    """key, the counts, base_failed, quality (posterior of good) and kept, of every row of docs."""
    votes = [f"vote_{r}" for r in RULES]
    counts = durable(voted(measures(docs, key, text)))
    # At most 3 to the number of rules patterns reach the driver.
    seen = sorted((voters(tuple(r[v] for v in votes)), r["count"]) for r in counts.groupBy(*votes).count().collect())
    start = [BAD_RIGHT] * len(votes) + [GOOD_RIGHT] * len(votes)
    x, moves = odds(share, fit(seen, share=share, start=start, prior=PRIOR * sum(n for _, n in seen)) if seen else start)
    total = F.lit(x)
    for v, bad, good in zip(votes, moves, moves[len(votes) :], strict=False):
        total = total + F.when(F.col(v) < 0, F.lit(-bad)).when(F.col(v) > 0, F.lit(good)).otherwise(F.lit(0.0))
    failed = (F.col("n_words") < 20) | (100 * F.col("n_repeat_words") > 30 * F.col("n_words"))
    out = counts.withColumn("quality", 1 / (1 + F.exp(-total))).withColumn("base_failed", failed)
    return out.withColumn("kept", ~F.col("base_failed") & (F.col("quality") >= keep_at)).select(key, "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", F.round("quality", 6).alias("quality"))
