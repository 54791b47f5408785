"""Quality classifier: a factorisation machine over hashed words and structure statistics of the text.

No metadata is used, though the method has it among its features: lang, source and doc_id must not be inputs.

A score is a bias, a weight for each feature and the inner products of the features' low-rank
vectors over all pairs, taken in time linear in the features as half the difference between the
square of the sum and the sum of the squares. Training runs on a bounded sample of labelled rows
(``SAMPLE``, the smallest hashes of their ids; the bound is a parameter); scoring reads whole texts
and ships only the model, whose size is fixed by ``BITS`` and ``RANK``.

Cases: a null or empty text has only its structure features and gets a score as any other; labels
that disagree for a document are averaged, null labels are ignored; with no labels every score is
0.5; repeated rows get a row each; an empty table gives none; extra columns are ignored.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from noisytree.llm.common import free, parts, shipped
from noisytree.llm.shingles import words

BITS = 14
RANK = 8
SAMPLE = 6_000
EPOCHS = 12
THRESHOLD = 0.7
#: Steps of each structure statistic; a value lights the steps that it reaches.
STEPS = 12
N_STATS = 12


def stats(raw: np.ndarray, n_words: int, n_distinct: int, lines: list[bytes]) -> list[float]:
    """Statistics of structure, each within 0 and 1."""
    n = max(1, len(raw))
    hist = np.bincount(raw, minlength=256)
    letters = hist[65:91].sum() + hist[97:123].sum() + hist[128:].sum()
    some = [x for x in lines if x.strip()]
    symbols = sum(int(hist[ord(c)]) for c in "#*$%&|<>@~^_=+\\{}[]")
    w = max(1, n_words)
    return [
        min(1.0, np.log1p(len(raw)) / 12),
        min(1.0, np.log1p(n_words) / 10),
        hist[65:91].sum() / max(1, letters),
        min(1.0, symbols / w),
        min(1.0, (hist[ord("!")] + hist[ord("?")]) / w),
        min(1.0, hist[ord("|")] / w),
        hist[48:58].sum() / n,
        min(1.0, (hist[ord(".")] + hist[ord(",")]) / w),
        min(1.0, letters / w / 15),
        n_distinct / w,
        1 - len(set(some)) / max(1, len(some)),
        min(1.0, len(some) / w),
    ]


def features(text: str | None) -> tuple[np.ndarray, np.ndarray]:
    """Ascending feature numbers and their values: hashed words, then steps of the statistics."""
    data = (text or "").encode("utf-8", "surrogatepass")
    h, _, _ = words(data)
    bucket, tf = np.unique((h >> np.uint64(64 - BITS)).astype(np.int64), return_counts=True)
    x = np.log1p(tf).astype(np.float32)
    if len(x):
        x /= np.sqrt((x * x).sum())
    s = stats(np.frombuffer(data, np.uint8), len(h), len(np.unique(h)), data.split(b"\n"))
    # Steps are finer towards 0, where most of these shares lie.
    reach = [int(STEPS * v**0.5) for v in s]
    at = [(1 << BITS) + i * STEPS + k for i, r in enumerate(reach) for k in range(min(r, STEPS))]
    return np.concatenate([bucket, np.array(at, np.int64)]), np.concatenate([x, np.full(len(at), 0.3, np.float32)])


WIDTH = (1 << BITS) + N_STATS * STEPS


def margin(model: dict, at: np.ndarray, x: np.ndarray) -> tuple[float, np.ndarray]:
    """The score before the logistic function, and the sums that its gradient needs."""
    v = model["v"][at] * x[:, None]
    total = v.sum(0)
    return float(model["b"] + model["w"][at] @ x + 0.5 * (total @ total - (v * v).sum())), total


def train(rows: list[tuple[np.ndarray, np.ndarray, float]], epochs: int = EPOCHS, seed: int = 5, rate: float = 0.08, decay: float = 2e-5) -> dict:
    """Adaptive gradient steps on the logistic loss; classes weigh alike. rows are in a fixed order."""
    rng = np.random.default_rng(seed)
    model = {"b": 0.0, "w": np.zeros(WIDTH, np.float32), "v": rng.normal(0, 0.02, (WIDTH, RANK)).astype(np.float32)}
    gw, gv, gb = np.full(WIDTH, 1e-2, np.float32), np.full((WIDTH, RANK), 1e-2, np.float32), 1e-2
    share = sum(y for _, _, y in rows) / max(1, len(rows))
    for _ in range(epochs if 0 < share < 1 else 0):
        for i in rng.permutation(len(rows)):
            at, x, y = rows[i]
            z, total = margin(model, at, x)
            g = (1 / (1 + np.exp(-max(-30.0, min(30.0, z)))) - y) * (0.5 / share if y > 0.5 else 0.5 / (1 - share))
            v = model["v"][at]
            dw = g * x + decay * model["w"][at]
            dv = g * (x[:, None] * total[None, :] - v * (x * x)[:, None]) + decay * v
            gw[at] += dw * dw
            gv[at] += dv * dv
            gb += g * g
            model["w"][at] -= rate * dw / np.sqrt(gw[at])
            model["v"][at] -= rate * dv / np.sqrt(gv[at])
            model["b"] -= rate * g / gb**0.5
    if share in (0, 1) and rows:
        model["b"] = 4.0 if share else -4.0
    return model


def feature_batches(batches):
    import pyarrow as pa

    for batch in parts(batches):
        got = [features(t) for t in batch.column("text").to_pylist()]
        cols = [pa.array([a for a, _ in got], pa.list_(pa.int64())), pa.array([x for _, x in got], pa.list_(pa.float32()))]
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("label"), *cols], ["doc_id", "label", "at", "x"])


def score_batches(batches, model: dict | None, keep: list[str], text: str, out: str):
    import pyarrow as pa

    for batch in parts(batches, text):
        scores = []
        for t in batch.column(text).to_pylist():
            z = margin(model, *features(t))[0] if model else 0.0
            scores.append(float(1 / (1 + np.exp(-max(-30.0, min(30.0, z))))))
        yield pa.RecordBatch.from_arrays([batch.column(c) for c in keep] + [pa.array(scores, pa.float64())], [*keep, out])


def held_out(key: Column) -> Column:
    """Rows whose labels training never reads."""
    return F.coalesce(F.pmod(F.crc32(key.cast("string").cast("binary")), F.lit(4)) == 2, F.lit(False))


def fit(docs: DataFrame, labels: DataFrame, key: str = "doc_id", label: str = "quality", text: str = "text", sample: int = SAMPLE) -> dict | None:
    """A model of ``label``; None without labels. At most ``sample`` rows reach the driver."""
    known = labels.where(F.col(label).isNotNull() & F.col(key).isNotNull() & ~held_out(F.col(key)))
    known = known.groupBy(F.col(key).alias("doc_id")).agg((F.avg(label) >= 0.5).cast("double").alias("label"))
    picked = known.orderBy(F.xxhash64(F.lit(1), "doc_id"), "doc_id").limit(sample)
    rows = docs.select(F.col(key).alias("doc_id"), F.col(text).cast("string").alias("text")).join(F.broadcast(picked), "doc_id")  # at most ``sample`` rows
    rows = rows.groupBy("doc_id").agg(F.max_by("text", F.struct(F.length("text"), "text")).alias("text"), F.max("label").alias("label"))
    kind = docs.schema[key].dataType.simpleString()
    got = rows.select("doc_id", "label", "text").mapInArrow(shipped("noisytree.llm.quality_model", "feature_batches"), f"doc_id {kind}, label double, at array<long>, x array<float>").toArrow()
    ids = got["doc_id"].to_pylist()
    order = sorted(range(len(ids)), key=lambda i: ids[i])
    at, x, y = got["at"], got["x"], got["label"].to_pylist()
    examples = [(at[i].values.to_numpy(), x[i].values.to_numpy(), y[i]) for i in order]
    return train(examples) if examples else None


def score(docs: DataFrame, model: dict | None, text: str = "text", keep: tuple[str, ...] | None = None, name: str = "_score") -> DataFrame:
    """keep... (all columns by default) and the score of each row as ``name``; a column of docs that is called so gives way."""
    keep = tuple(c for c in (docs.columns if keep is None else keep) if c.lower() != name.lower())
    fields = [f"`{c}` {docs.schema[c].dataType.simpleString()}" for c in keep] + [f"`{name}` double"]
    read = free("_text", docs.columns)
    run = shipped("noisytree.llm.quality_model", "score_batches", model=model, keep=list(keep), text=read, out=name)
    return docs.select(*[F.col(f"`{c}`") for c in keep], F.col(f"`{text}`").cast("string").alias(read)).mapInArrow(run, ", ".join(fields))
