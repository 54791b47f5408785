import pytest

DOCS = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.fixture
def docs(spark):
    def make(texts, sources=None, ids=None, extra=None):
        rows = [(i if ids is None else ids[i], t, "en", (sources or ["s"] * len(texts))[i], len(t or "")) for i, t in enumerate(texts)]
        df = spark.createDataFrame(rows, DOCS)
        if extra:
            from pyspark.sql import functions as F

            for c in extra:
                df = df.withColumn(c, F.lit("x"))
        return df

    return make


def prose(rng, n, words=400):
    """n random words of a small vocabulary."""
    return [f"w{int(k)}" for k in rng.integers(0, words, n)]
