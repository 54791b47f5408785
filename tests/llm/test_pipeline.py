import numpy as np
import public_tokenizers
import pytest
from pyspark.sql import functions as F
from tokenizers import Tokenizer

import corpus_pipeline
from noisytree.llm import mixing, queries, secrets
from noisytree.llm.common import table
from tests.conftest import TINY
from tests.llm.test_near import brute
from tests.test_queries import check


@pytest.mark.parametrize("name", sorted(queries.oracle_sql()))
def test_equals_sql(spark, duck, name):
    check(spark, duck, queries.queries()[name], queries.oracle_sql()[name])


@pytest.mark.parametrize("name", sorted(set(queries.queries()) - {"pipeline"}))
def test_queries_run_over_whole_tables(spark, name):
    n = queries.queries()[name](spark, TINY).count()
    of = {"op2_topk": ("embeddings", None), "op7_url_filter": ("pages", 1), "op4_mix": ("documents", None), "op10_passages": ("documents", None)}
    source, rows = of.get(name, ("documents", 1))
    assert n == table(spark, TINY, source).count() if rows else n > 0


def test_stages_one_by_one(spark, tmp_path):
    docs = table(spark, TINY, "documents")
    cols, kept = docs.columns, [docs]
    for i, (name, stage) in enumerate(corpus_pipeline.STAGES):
        out = stage(spark, kept[-1], TINY)
        out.write.parquet(str(tmp_path / name))
        kept.append(spark.read.parquet(str(tmp_path / name)))
        assert i == len(corpus_pipeline.STAGES) - 1 or kept[-1].columns == cols
    quality, near, clean, mixed, ids = kept[1:]
    # 2: one of each class of what the first stage kept.
    rows = sorted((r.doc_id, r.text) for r in quality.select("doc_id", "text").collect())
    classes, _ = brute([t for _, t in rows])
    assert sorted(r.doc_id for r in near.collect()) == sorted({rows[c][0] for c in classes})
    # 3: same documents, no live secret left.
    assert clean.count() == near.count() and secrets.scan(clean).where(F.size("live") > 0).isEmpty()
    assert clean.where(F.length("text") != F.col("n_chars")).join(near.where(F.length("text") != F.col("n_chars")), "doc_id", "left_anti").isEmpty()
    # 4 and 5: copies as drawn, each with the library's ids.
    assert sorted(r.doc_id for r in mixed.collect()) == sorted(r.doc_id for r in mixing.mix(clean).collect())
    lib = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    texts = {r.doc_id: r.text for r in clean.collect()}
    got = ids.collect()
    assert len(got) == mixed.count()
    for r in got[:200]:
        assert r.ids == lib.encode(texts[r.doc_id], add_special_tokens=False).ids
    assert sorted((r.doc_id, r.ids_sha256) for r in corpus_pipeline.run(spark, TINY).collect()) == sorted((r.doc_id, r.ids_sha256) for r in got)
    assert np.mean([r.n_tokens for r in got]) > 1


def test_stages_on_empty_tables_and_clashing_names(spark, docs, tmp_path):
    names = ["_score", "_text", "_doc", "_key", "_live", "row", "_copy", "_rate", "live", "item", "n_tokens"]
    spark.createDataFrame([], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    w = "a b c d e f g h i j k l m"
    for texts in ([], [w, w, None, "", "token = 'Zq81Kd0Lx7PwT3vB'"]):
        df = docs(texts, extra=names)
        for name, stage in corpus_pipeline.STAGES[1:]:
            got = stage(spark, df, str(tmp_path))
            assert got.count() == 0 or texts, name
            if name != "bpe":
                assert got.columns == df.columns and got.where(" or ".join(f"{c} <> 'x'" for c in names)).count() == 0
        assert corpus_pipeline.STAGES[0][1](spark, df, str(tmp_path)).columns == df.columns
    kept = corpus_pipeline.near_duplicates(spark, docs([w, w, None, ""]), str(tmp_path))
    assert sorted(r.doc_id for r in kept.collect()) == [0, 2, 3]
    scanned = corpus_pipeline.secret_scan(spark, docs([None, "token = 'Zq81Kd0Lx7PwT3vB'"]), str(tmp_path)).orderBy("doc_id").collect()
    assert scanned[0].text is None and "Zq81" not in scanned[1].text and scanned[1].n_chars == len(scanned[1].text)
