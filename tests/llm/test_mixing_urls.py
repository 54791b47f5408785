import math

import numpy as np
from pyspark.sql import functions as F

from noisytree.llm import mixing, url_filter


def test_rates_reach_the_target(docs):
    texts = ["x" * 100] * 900 + ["y" * 50] * 300 + ["", None]
    df = docs(texts, ["big"] * 900 + ["small"] * 300 + ["none"] * 2, extra=["rate", "cdf", "parts"])
    out = mixing.mix(df, {"big": 0.5, "small": 0.5}).cache()
    size = {r.source: r.n for r in out.groupBy("source").agg(F.sum(F.length("text")).alias("n")).collect()}
    assert set(size) == {"big", "small"} and abs(size["big"] / size["small"] - 1) < 0.25
    # Copies are numbered, and a document has all of them.
    assert out.groupBy("doc_id").agg(F.count("*").alias("n"), F.max("_copy").alias("m"), F.max("_copies").alias("c")).where("n <> m or n <> c").isEmpty()
    assert out.columns[: len(df.columns)] == df.columns


def test_counts_are_poisson(docs, spark):
    df = docs(["z"] * 4000, ["a"] * 4000)
    for rate in (0.3, 2.5, 150.0):  # the last is a sum of parts
        out = mixing.mix(df, total=rate).groupBy("doc_id").count()
        n = np.zeros(4000)
        for r in out.collect():
            n[r.doc_id] = r["count"]
        assert abs(n.mean() - rate) < 5 * math.sqrt(rate / 4000) and abs(n.var() / rate - 1) < 0.15


def test_seeded_and_shuffled(docs):
    df = docs([f"t{i}" for i in range(300)], ["a", "b", None] * 100)
    one, two = ({(r.doc_id, r._copy) for r in mixing.mix(d, seed=3).collect()} for d in (df, df.repartition(5)))
    assert one == two and len(one) > 100
    order = [r.doc_id for r in mixing.mix(df, seed=3).collect()]
    assert order != sorted(order)
    assert mixing.mix(docs([])).count() == 0


def test_many_sources_are_salted(docs, monkeypatch):
    df = docs(["abc"] * 200, [f"s{i % 20}" for i in range(200)])
    want = sorted((r.doc_id, r._copy) for r in mixing.mix(df).collect())
    monkeypatch.setattr(mixing, "BROADCAST_SOURCES", 3)
    assert sorted((r.doc_id, r._copy) for r in mixing.mix(df).collect()) == want


URLS = ["http://A.Example.org/en/1?x", "https://example.org/es/5", "http://x.net", "http://org/", "HTTP://www.shop.com/fr/a", "http://com/de/", "http://notcom/de/x", None, "nourl", "http://example.org", "a://b.org?c/d", "http://example.org/es", "http://x.example.org:80/en/12"]


def test_host_rules(spark):
    df = spark.createDataFrame(list(enumerate(URLS)), "page_id long, url string").withColumn("rule", F.lit("clash")).withColumn("tokens", F.lit(1))
    got = {r.page_id: (r.host, r.path, r.rule, r.verdict) for r in url_filter.judge(df).collect()}
    assert got[0] == ("a.example.org", "/en/1", "example.org/en/1", "block")
    assert got[1] == ("example.org", "/es/5", "example.org/es/", "block")
    assert got[2] == ("x.net", "", None, "allow") and got[3] == ("org", "/", "org/", "allow")
    assert got[4] == ("www.shop.com", "/fr/a", "com/fr/", "allow") and got[5] == ("com", "/de/", "com/de/", "block")
    assert got[6][2] is None and got[7] == got[8] == ("", "", None, "allow")
    assert got[9] == ("example.org", "", None, "allow") and got[10][:3] == ("b.org", "", None)
    assert got[11] == ("example.org", "/es", "org/", "allow") and got[12][2] is None
    assert url_filter.judge(df.limit(0)).count() == 0


def test_mined_rules_judge_the_rest(spark):
    rows = [f"http://s{i}.spam.com/de/{i}" for i in range(60)] + [f"http://s{i}.good.com/fr/{i}" for i in range(60)] + ["http://q.spam.net/de/7", "http://q.good.net/fr/7", "http://unseen.net/zz"]
    df = spark.createDataFrame(list(enumerate(rows + rows[-3:])), "page_id long, url string")
    got = {r.page_id: (r.verdict, r.confidence) for r in url_filter.judge(df).collect()}
    assert got[120] == got[123] == ("block", 1.0) and got[121] == ("allow", 1.0) and got[122] == ("allow", None)


def test_tokens_that_go_together_are_one_item(spark):
    long = "http://bad.com/de/" + "/".join(f"t{i}" for i in range(60))  # 2**60 subsets otherwise
    df = spark.createDataFrame([(i, long) for i in range(50)] + [(99, long.replace("bad.com", "bad.net"))], "page_id long, url string")
    assert {r.verdict for r in url_filter.judge(df.withColumn("page_id", F.col("page_id"))).where("page_id = 0").collect()} == {"block"}
