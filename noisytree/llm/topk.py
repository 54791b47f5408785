"""Exact top-k search by inner product: tiles of queries and shards, then a tree of merges.

Rows are dealt by a hash to shards and queries to blocks; a (shard, block) tile is one matrix
product in one task, which keeps k candidates a query. The lists of a query are then merged in
groups of ``fan`` tiles until one is left, so no task sees more than fan * k rows of a query at once.
Tiles have a fixed number of rows, so a task's memory does not grow with the tables; the number of
tiles does, as the product of queries and rows demands.

Cases: vectors that are null, without an id, or hold a null or non-finite component take no part; vectors are
compared with those of their own length only; ties go to the smaller id; a repeated id is one row
for each of its vectors, and never a result of a query of its own id; empty tables give no rows.
Scores are exact: products are taken in doubles where no sum can pass 2**53, else in whole numbers
(kept to the range of a long).
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from noisytree.llm.common import shipped

SHARD_ROWS = 16_384
BLOCK_ROWS = 4_096
FAN = 16
LONG = (1 << 63) - 1


def quantised(vectors: DataFrame, id_col: str, vec_col: str, scale: int = 64) -> DataFrame:
    """id, v: array of longs floor(scale * x), of the vectors that take part."""
    ok = F.col(vec_col).isNotNull() & F.forall(vec_col, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x.cast("double")) < float("inf")))
    return vectors.where(F.col(id_col).isNotNull() & F.coalesce(ok, F.lit(False))).select(F.col(id_col).cast("long").alias("id"), F.transform(vec_col, lambda x: F.floor(F.lit(scale) * x.cast("double"))).alias("v"))


def tile_batches(pieces, k: int):
    """pieces: batches of one (dim, shard, block) tile: is_query, id, v."""
    import numpy as np
    import pyarrow as pa

    rows = pa.Table.from_batches(list(pieces))
    if not rows.num_rows:
        return
    is_query = rows["is_query"].to_numpy()
    ids = rows["id"].to_numpy()
    v = rows["v"].combine_chunks()
    flat = v.flatten().to_numpy().reshape(rows.num_rows, -1) if rows.num_rows else None
    q_ids, c_ids = ids[is_query], ids[~is_query]
    if not len(q_ids) or not len(c_ids):
        return
    order = np.argsort(c_ids, kind="stable")
    c_ids, c = c_ids[order], flat[~is_query][order]
    q = flat[is_query]
    dim = flat.shape[1]
    most = int(max(1, np.abs(q).max(initial=0))) * int(max(1, np.abs(c).max(initial=0))) * max(1, dim)
    plain = most < 1 << 53
    c_t = c.T.astype(np.float64) if plain else c.T.astype(object)
    for a in range(0, len(q_ids), 256):
        part, own = q[a : a + 256], q_ids[a : a + 256]
        if plain:
            s = part.astype(np.float64) @ c_t
        else:
            s = np.clip(part.astype(object) @ c_t, -LONG, LONG).astype(np.int64)
        out_q, out_c, out_s = [], [], []
        for i in range(len(own)):
            at = np.flatnonzero(c_ids != own[i])
            line = s[i][at]
            if len(line) > k:
                low = np.partition(line, len(line) - k)[len(line) - k]
                above, level = np.flatnonzero(line > low), np.flatnonzero(line == low)
                pick = np.concatenate([above, level[: k - len(above)]])  # ids ascend, so ties keep the smaller
            else:
                pick = np.arange(len(line))
            out_q.append(np.full(len(pick), own[i]))
            out_c.append(c_ids[at[pick]])
            out_s.append(line[pick].astype(np.int64))
        yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(x).astype(np.int64)) for x in (out_q, out_c, out_s)], ["query_id", "vec_id", "score"])


def tile_group(key, table, k: int):
    import pyarrow as pa

    got = list(tile_batches(table.to_batches(), k))
    names = ["query_id", "vec_id", "score"]
    merged = pa.Table.from_batches(got) if got else pa.table({n: pa.array([], pa.int64()) for n in names})
    shard = pa.array([key[1].as_py()] * merged.num_rows, pa.int32())
    return merged.append_column("shard", shard)


def tile_runner(k: int):
    """tile_group for applyInArrow, pickled by value (see common.shipped)."""
    from noisytree.llm.common import ROOT

    root = ROOT

    def run(key, table):
        import sys

        try:
            from noisytree.llm.topk import tile_group as group
        except ModuleNotFoundError:
            sys.path.insert(0, root)
            from noisytree.llm.topk import tile_group as group
        return group(key, table, k)

    return run


def topk(candidates: DataFrame, queries: DataFrame, k: int, shard_rows: int = SHARD_ROWS, block_rows: int = BLOCK_ROWS, fan: int = FAN) -> DataFrame:
    """query_id, rank, vec_id, score. Both inputs: id long, v array<long>."""
    n, m = candidates.count(), queries.count()
    shards, blocks = -(-n // shard_rows) or 1, -(-m // block_rows) or 1
    dim = F.size("v").alias("dim")
    c = candidates.select(dim, F.pmod(F.xxhash64("id", F.lit(1)), F.lit(shards)).cast("int").alias("shard"), F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("block"), F.lit(False).alias("is_query"), "id", "v")
    q = queries.select(dim, F.explode(F.sequence(F.lit(0), F.lit(shards - 1))).alias("shard"), F.pmod(F.xxhash64("id", F.lit(2)), F.lit(blocks)).cast("int").alias("block"), F.lit(True).alias("is_query"), "id", "v")
    lists = c.unionByName(q).groupBy("dim", "shard", "block").applyInArrow(tile_runner(k), "query_id long, vec_id long, score long, shard int")
    best = [F.col("score").desc(), F.col("vec_id")]
    while shards > 1:
        shards = -(-shards // fan)
        lists = lists.withColumn("shard", F.floor(F.col("shard") / fan).cast("int"))
        w = Window.partitionBy("query_id", "shard").orderBy(*best)
        lists = lists.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).drop("rank")
    w = Window.partitionBy("query_id").orderBy(*best)
    return lists.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")
