import numpy as np
import pytest

from noisytree.llm import topk


def brute(rows, k, step):
    ok = [(i, [int(np.floor(64 * float(np.float32(x)))) for x in v]) for i, v in rows if i is not None and v is not None and all(x is not None and np.isfinite(x) for x in v)]
    out = {}
    for qi, q in ok:
        if qi % step == 0:
            s = sorted((-sum(a * b for a, b in zip(q, v, strict=True)), i) for i, v in ok if i != qi and len(v) == len(q))
            out[qi] = [(r + 1, i, -x) for r, (x, i) in enumerate(s[:k])]
    return out


@pytest.mark.parametrize("tiles", [(16_384, 4_096, 16), (7, 3, 2)])
def test_equals_brute_force(spark, tiles):
    rng = np.random.default_rng(1)
    rows = [(i, [float(x) for x in np.round(rng.normal(0, 1, 4), 1)]) for i in range(120)]
    rows += [(130, None), (None, [1.0] * 4), (140, [1.0, None, 0.0, 0.0]), (150, [float("nan")] * 4), (160, [float("inf"), 0.0, 0.0, 0.0]), (170, [0.5, 0.5]), (175, [1.0, 2.0])]
    rows += [(180 + i, rows[0][1]) for i in range(30)]  # ties
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    v = topk.quantised(df, "vec_id", "embedding")
    got = {}
    for r in topk.topk(v, v.where("id % 10 = 0"), 5, *tiles).orderBy("query_id", "rank").collect():
        got.setdefault(r.query_id, []).append((r.rank, r.vec_id, r.score))
    assert got == {k: x for k, x in brute(rows, 5, 10).items() if x}


def test_empty_and_large_components(spark):
    none = spark.createDataFrame([], "vec_id long, embedding array<float>")
    v = topk.quantised(none, "vec_id", "embedding")
    assert topk.topk(v, v, 3).count() == 0
    big = spark.createDataFrame([(0, [3e7, 1.0]), (1, [3e7, 2.0]), (2, [-3e7, 1.0])], "vec_id long, embedding array<float>")
    v = topk.quantised(big, "vec_id", "embedding")
    r = topk.topk(v, v.where("id = 0"), 2).orderBy("rank").collect()
    x = int(np.floor(64 * float(np.float32(3e7))))
    assert [(a.vec_id, a.score) for a in r] == [(1, x * x + 64 * 128), (2, -x * x + 64 * 64)]
