import hashlib
import re
from collections import Counter

import numpy as np
from pyspark.sql import functions as F

from noisytree.llm import quality_rules, secrets
from tests.llm.conftest import prose

ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A)
KEY = "AKIA" + "Q7" * 8
TEXTS = [
    "", None, "nothing here", 'password = "hunter2hunter2" and token: short', f"key {KEY} and AKIAX", "TOKEN=abcdefgh TOKEN=abcdefgh", "secret: token: abcdefghij",
    "0123456789abcdef" * 2, "deadbeef" * 5 + " " + "f" * 31, "é🙂 api_key='Zz9/+abc.def-ghi' 🙂 apikey=12345678", "password=\npasswd:   'x_y_z_1_2_3'", "tok " + "aB3dE5gH7jK9mN1pQ3sT5vX7", "passwordpassword=abcdefgh1",
]


def base_spans(t):
    t, out = t or "", []
    for m in ASSIGN.finditer(t):
        if len(m[2]) >= 8:
            out.append((m.start(), 0, "assign", m.end()))
    for m in re.finditer("AKIA[A-Z0-9]+", t):
        if len(m[0]) >= 16:
            out.append((m.start(), 1, "access", m.end()))
    for m in re.finditer("[0-9a-f]+", t):
        if len(m[0]) >= 32:
            out.append((m.start(), 2, "hex", m.end()))
    return sorted(out)


def test_base_spans_equal_a_plain_scan(docs):
    got = {r.doc_id: r for r in secrets.digest(secrets.scan(docs(TEXTS, extra=["base", "hash", "key"]))).collect()}
    for i, t in enumerate(TEXTS):
        want = base_spans(t)
        text = ",".join(f"{k}:{a}:{b}" for a, _, k, b in want)
        n = Counter(k for _, _, k, _ in want)
        assert (got[i].n_assign, got[i].n_access, got[i].n_hex) == (n["assign"], n["access"], n["hex"]), t
        assert got[i].base_sha256 == hashlib.sha256(text.encode()).hexdigest()
        assert [s for s in got[i].spans.split(",") if s and not s.startswith("rare")] == [s for s in text.split(",") if s]
    assert got[11].spans == "rare:4:28"  # seen once, owned by one


def test_copied_examples_and_live_secrets(docs):
    wide, live = "aB3dE5gH7jK9mN1pQ3sT5vX7", "zY2xW4vU6tS8rQ0pO1nM3lK5"
    texts = [f"see {wide} and token={live[:12]}{i}q7" for i in range(6)] + [f"mine {live}", "password=aaaaaaaaaaaa", "password=example12345"] + ["password=example12345"] * 4
    owners = [f"o{i}" for i in range(6)] + ["o1", "o2", "o3", "o4", "o5", "o6", "o7"]
    got = {r.doc_id: r for r in secrets.digest(secrets.scan(docs(texts, owners))).collect()}
    assert all("rare" not in got[i].spans and got[i].n_live == 1 for i in range(6))  # six owners: an example
    assert got[6].spans.startswith("rare") and got[6].n_live == 1
    assert got[7].n_live == 0 and got[7].n_example == 1  # too plain to be live
    assert got[8].n_live == 0 and got[8].n_assign == 1  # copied by five owners; its base span stays


def test_redaction(spark, docs):
    df = docs(["a password=abcdefgh1 b", "no", "x " + "0123456789abcdef" * 2 + " token=" + "0123456789abcdef" * 2])
    rows = secrets.scan(df).join(df, "doc_id").select("doc_id", secrets.redacted(F.col("text"), F.col("live")).alias("t")).collect()
    assert {r.doc_id: r.t for r in rows} == {0: "a [SECRET] b", 1: "no", 2: "x [SECRET] [SECRET]"}


def test_empty_table_repeated_rows_and_null_owner(spark, docs):
    assert secrets.scan(docs([])).count() == 0
    twice = docs(["token=abcdefgh12"] * 2, ids=[5, 5]).withColumn("source", F.lit(None).cast("string"))
    got = secrets.digest(secrets.scan(twice)).collect()
    assert len(got) == 2 and all(r.n_assign == 1 and r.n_live == 1 for r in got)


def test_missing_ids_are_redacted_too(spark, docs):
    import corpus_pipeline

    out = corpus_pipeline.secret_scan(spark, docs(["token=abcdefgh12", None, "x"], ids=[None, None, 2]), "")
    assert sorted((r.doc_id or -1, r.text or "") for r in out.collect()) == [(-1, ""), (-1, "[SECRET]"), (2, "x")]


def plain_counts(t):
    t = t or ""
    words = re.findall(r"[^\x20\x09-\x0D]+", t)
    lines = [x for x in t.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    runs = Counter(tuple(words[i : i + 8]) for i in range(len(words) - 7))
    hit = set()
    for i in range(len(words) - 7):
        if runs[tuple(words[i : i + 8])] > 1:
            hit |= set(range(i, i + 8))
    return len(words), sum(map(len, words)), len(re.findall(r"[#*$%&|<>]", t)), len(lines) - len(set(lines)), len(hit)


def test_counts_equal_a_plain_pass(docs):
    rng = np.random.default_rng(2)
    texts = ["", None, " \n \t", "a", "a b c d e f g h", "x " * 40, "one two\none two\n \n\nthree", "é🙂 *#| <b>\x0b\x0cq\x1cr"]
    for n in (30, 200, 3000):
        w = prose(rng, n)
        texts += [" ".join(w), " ".join(w + w[3:20] + w[:9]), "\n".join(" ".join(w[i : i + 7]) for i in range(0, n, 7)) * 2]
    got = {r.doc_id: r for r in quality_rules.judge(docs(texts, extra=["quality", "n_words"])).collect()}
    for i, t in enumerate(texts):
        r, want = got[i], plain_counts(t)
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == want, t
        assert r.base_failed == (want[0] < 20 or 100 * want[4] > 30 * want[0])
        assert not (r.base_failed and r.kept)


def test_votes_are_weighed_by_estimated_accuracy():
    # Ten rules of 0.9 or 0.6; the estimates must come near, from votes alone.
    rng = np.random.default_rng(3)
    truth = rng.random(6000) < 0.5
    acc = [0.9, 0.9, 0.85, 0.6, 0.6]
    votes = [tuple(int((1 if t else -1) * (1 if rng.random() < a else -1)) for a in acc) for t in truth]
    right = quality_rules.fit(sorted(Counter(votes).items()), share=0.5)
    assert all(abs(a - b) < 0.05 for a, b in zip(right, acc, strict=True))
    hit = np.mean([(quality_rules.posterior(v, 0.5, right) >= 0.5) == t for v, t in zip(votes, truth, strict=True)])
    assert hit > 0.93
    assert quality_rules.fit([]) == []


def test_junk_goes_and_prose_stays(docs):
    rng = np.random.default_rng(4)
    prose_ = [" ".join(prose(rng, 120)).capitalize() + "." for _ in range(40)]
    symbols = [" ".join(w + "***" for w in prose(rng, 120)) for _ in range(6)]
    shout = [" ".join(w.upper() + "!!" for w in prose(rng, 120)) for _ in range(6)]
    got = {r.doc_id: r.kept for r in quality_rules.judge(docs(prose_ + symbols + shout)).collect()}
    assert all(got[i] for i in range(40)) and not any(got[i] for i in range(40, 52))


def test_a_weak_bad_vote_is_outvoted(docs):
    # Every fourth text, good or junk, has long words; junk fails two other rules at once.
    rng = np.random.default_rng(5)
    texts = []
    for i in range(120):
        w = [x + "abcdefghij" * (i % 4 == 0) for x in prose(rng, 120)]
        texts.append(" ".join(x.upper() + "!!***" for x in w) if i % 5 == 0 else " ".join(w))
    df = docs(texts)
    votes = {r.doc_id: r for r in quality_rules.voted(quality_rules.measures(df)).collect()}
    got = {r.doc_id: r for r in quality_rules.judge(df).collect()}
    for i in range(120):
        v = [votes[i][f"vote_{r}"] for r in quality_rules.RULES]
        assert (votes[i].vote_length < 0) == (i % 4 == 0) and max(v) == 1 and (min(v) < 0) == (i % 4 == 0 or i % 5 == 0)
        assert got[i].kept == (i % 5 != 0), (i, v, got[i].quality)


def test_empty_table(docs):
    assert quality_rules.judge(docs([])).count() == 0
