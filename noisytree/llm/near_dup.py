"""N-gram Jaccard join by chosen paths: all links between texts whose sets of word 5-shingles have a
Jaccard similarity of 0.8 or more, their classes (connected components) and each text's number of links.

Texts with one set are one item (a class of copies), so copies are never paired. Items are embedded
as minimal hashes of their sets, each a token (position, value). A run samples positions by a hash of
the node that an item stands in, and items that share a sampled token go to one child node: similar
items stay together, others part. Runs are repeated until a pair at the threshold meets with
probability ``RECALL``. In a node, items are first held against leaders (the least item not yet led), so
that each names one likely link; these are verified and settle most classes. Only links between
classes can still matter: in a node of several classes, the items outside its commonest class are held
against all others. A node where both are many is split again; those that do not part within
``DEPTH`` levels and have one least item are taken as one node, which is dealt to tiles. Minimal hashes alone are compared in nodes; texts are fetched for
the pairs that these leave, and every link is verified on the whole texts' sets.

Links within a class are counted exactly. A small class is one tile. In a larger one, each item's distance
(one less the similarity, a metric) from a pivot says of most pairs that they are linked or not: such pairs
are counted by their steps of distance, and only pairs of blocks that the distances leave open are compared, in
tiles of bounded bytes that return counts, never pairs.

Cases: a null text, or one without a word, has no shingles and no links and is a class of its own; a
text of 1 to 4 words is one shingle of all of them; rows that repeat an id and a text count as
copies; rows that repeat an id with other texts are taken apart by their text and returned a row
each; a missing id counts as the least of all; an empty table gives no rows; extra columns are ignored, and
deduplicated() returns them as they are, whatever their names.
"""

from __future__ import annotations

import hashlib
import itertools
import math
from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from noisytree.llm.common import components, durable, parts, shipped, written
from noisytree.llm.shingles import U, column_shingles, mix, shingle_set

THRESHOLD = 0.8
RECALL = 0.9999
POSITIONS = 128
#: Expected children of a node: 1 / SPLIT, so that pairs at the threshold keep 1 of them at least.
SPLIT = 0.75
#: A node of at most so many items, or of so many outside its commonest class, is not split further.
SMALL = 512
FEW = 32
DEPTH = 3
#: From so many items on, the first leaders of a node, so many at most, are those in the middle.
CROWD, CROWDS = 8, 16
#: Items of a side of a tile of sketches; pairs left by them for each item, beyond which a node is compared as a whole.
TILE, DENSE = 2048, 4
#: Items and shingles of a block of texts.
BLOCK, BLOCK_SHINGLES = 256, 400_000
#: A class of at most so many items and shingles is one tile.
SMALL_CLASS = 64
#: Share of 8-bit minimal hashes that a pair must have in common to be verified: 5 deviations below
#: the expectation at the threshold.
SKETCH_LEAST = 0.8 - 5 * math.sqrt(0.8 * 0.2 / POSITIONS)


def meets(depth: int, similarity: float = THRESHOLD, split: float = SPLIT) -> float:
    """Chance that a pair shares a node ``depth`` levels down in one run: a branching process whose
    number of common children is near to Poisson with mean similarity / split."""
    dead = 0.0
    for _ in range(depth):
        dead = math.exp(similarity / split * (dead - 1))
    return 1 - dead


def runs_for(recall: float = RECALL, depth: int = DEPTH) -> int:
    return math.ceil(math.log(1 - recall) / math.log(1 - meets(depth)))


_SEEDS = (mix(np.arange(POSITIONS, dtype=np.uint64), 11) >> U(32)).astype(np.uint32) | np.uint32(1)


def sketch(s: np.ndarray) -> np.ndarray:
    """The least 32-bit hash of the set under each of POSITIONS functions, mixed."""
    x = (s >> U(32)).astype(np.uint32)
    out = np.empty(POSITIONS, np.uint32)
    step = max(1, 64_000 // max(1, len(x)))  # products that stay in the processor's cache
    with np.errstate(over="ignore"):
        for a in range(0, POSITIONS, step):
            m = x[None, :] * _SEEDS[a : a + step, None]
            m ^= m >> np.uint32(15)
            m *= np.uint32(0x846CA68B)
            out[a : a + step] = m.min(1)
    return (mix(out.astype(np.uint64), 12) >> U(32)).astype(np.uint32)


def sketch_batches(batches):
    import pyarrow as pa

    for batch in parts(batches):
        keys, size, sigs = [], [], []
        text = batch.column("text")
        flat, many = column_shingles(text)
        end = np.cumsum(many)
        for i, (a, b) in enumerate(zip(end - many, end, strict=True)):
            s = np.unique(flat[a:b]) if b > a else shingle_set(text[i].as_py())  # a text of a few words
            size.append(len(s))
            keys.append(hashlib.blake2b(s.tobytes(), digest_size=16).digest() if len(s) else None)
            sigs.append(sketch(s).tobytes() if len(s) else None)
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("text_key"), pa.array(keys, pa.binary()), pa.array(size, pa.int32()), pa.array(sigs, pa.binary())], ["doc_id", "text_key", "set_key", "size", "sig"])


def children(node: np.ndarray, values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Nodes below ``node`` of items with these minimal hashes: (row, child). Which positions are
    sampled depends on the node alone, so that its items sample alike."""
    share = U(min((1 << 64) - 1, int((1 << 64) / (SPLIT * POSITIONS))))
    picked = mix(node[:, None] ^ mix(np.arange(POSITIONS, dtype=np.uint64), 13)[None, :], 14) < share
    row, at = np.nonzero(picked)
    return row, mix(mix(node[row] ^ at.astype(np.uint64), 15) + values[row, at].astype(np.uint64), 16)


def root_batches(batches, runs: int):
    """item and its nodes on the first level of each run."""
    import pyarrow as pa

    roots = mix(np.arange(runs, dtype=np.uint64), 17)
    for batch in batches:
        sig = batch.column("sig").to_pylist()
        if not sig:
            continue
        values = np.frombuffer(b"".join(sig), np.uint32).reshape(len(sig), POSITIONS)
        items, nodes = [], []
        at = np.arange(len(sig))
        for root in roots:
            row, child = children(np.full(len(sig), root), values)
            items.append(at[row])
            nodes.append(child)
        ids = batch.column("item").take(pa.array(np.concatenate(items)))
        yield pa.RecordBatch.from_arrays([ids, pa.array(np.concatenate(nodes).view(np.int64))], ["item", "node"])


def child_batches(batches):
    import pyarrow as pa

    for batch in batches:
        sig = batch.column("sig").to_pylist()
        if not sig:
            continue
        values = np.frombuffer(b"".join(sig), np.uint32).reshape(len(sig), POSITIONS)
        row, child = children(batch.column("node").to_numpy().view(np.uint64), values)
        yield pa.RecordBatch.from_arrays([batch.column("item").take(pa.array(row)), pa.array(child.view(np.int64))], ["item", "node"])


# -- verification ---------------------------------------------------------------------------------
def streamed(batches, keys: list[str]):
    """The groups of rows with equal keys, one after the other; the rows come sorted by them.

    A group is held as a table; what forms groups bounds their size.
    """
    import pyarrow as pa

    held: list = []
    last = None
    for batch in batches:
        n = batch.num_rows
        if not n:
            continue
        cols = [batch.column(k).to_numpy(zero_copy_only=False) for k in keys]
        change = np.flatnonzero(np.any([c[1:] != c[:-1] for c in cols], axis=0)) + 1
        for a, b in zip([0, *change], [*change, n], strict=True):
            key = tuple(c[a] for c in cols)
            if last is not None and key != last:
                yield last, pa.Table.from_batches(held)
                held = []
            held.append(batch.slice(a, b - a))
            last = key
    if held:
        yield last, pa.Table.from_batches(held)


def whole_groups(batches, keys: list[str], most: int = 40_000):
    """Tables of about ``most`` rows that hold whole groups of rows with equal keys, and where each row's
    group begins and ends. The rows come sorted by the keys; what forms groups bounds their size."""
    import pyarrow as pa

    held: list = []
    n = 0
    for batch in itertools.chain(batches, [None]):
        if batch is not None:
            held.append(batch)
            n += batch.num_rows
            if n < most:
                continue
        if not n:
            continue
        rows = pa.Table.from_batches(held).combine_chunks()
        cols = [rows[k].to_numpy() for k in keys]
        change = np.flatnonzero(np.any([c[1:] != c[:-1] for c in cols], axis=0)) + 1
        end = n if batch is None else (int(change[-1]) if len(change) else 0)
        if end:
            edges = np.concatenate([[0], change[change < end], [end]])
            size = np.diff(edges)
            yield rows.slice(0, end), np.repeat(edges[:-1], size), np.repeat(edges[1:], size)
        held, n = rows.slice(end).to_batches(), n - end


def lows_of(rows) -> np.ndarray:
    return np.frombuffer(b"".join(rows["low"].to_pylist()), np.uint8).reshape(-1, POSITIONS)


def alike(low: np.ndarray, size: np.ndarray, x: np.ndarray, y: np.ndarray, least: float, threshold: float) -> np.ndarray:
    """Which of the pairs of rows x and y may reach the threshold by their sizes and have ``least`` of their hashes in common."""
    ok = np.minimum(size[x], size[y]) >= threshold * np.maximum(size[x], size[y])
    at = np.flatnonzero(ok)
    for a in range(0, len(at), 100_000):
        part = at[a : a + 100_000]
        ok[part] = (low[x[part]] == low[y[part]]).mean(1) >= least
    return ok


def pairs_batch(a: list, b: list):
    import pyarrow as pa

    return pa.RecordBatch.from_arrays([pa.array(np.concatenate(x), pa.int64()) for x in (a, b)], ["a", "b"])


def medoid(low: np.ndarray) -> int:
    """The row with most of the hashes that are the commonest at their positions."""
    at = low + 256 * np.arange(POSITIONS)[None, :]
    mode = np.bincount(at.ravel(), minlength=256 * POSITIONS).reshape(POSITIONS, 256).argmax(1)
    return int((low == mode).sum(1).argmax())


def leader_batches(batches, threshold: float):
    """Groups (node, part) of items: each item with the first leader that it looks linked to. An item that no
    leader before it has is a leader: first, where many are left, the one in their middle, which is held against all
    that it may be linked to; then the least. All groups of a table take such a step at a time."""
    for rows, start, end in whole_groups(batches, ["node", "part"]):
        item, size, low = rows["item"].to_numpy(), rows["size"].to_numpy(), lows_of(rows)
        a, b = [], []
        gone = np.zeros(len(item), bool)
        for p in np.unique(start[end - start >= CROWD]):
            for _ in range(CROWDS):
                left = np.arange(p, end[p])[~gone[p : end[p]]]
                if len(left) < CROWD:
                    break
                lead = left[medoid(low[left])]
                may = left[alike(low, size, np.full(len(left), lead), left, SKETCH_LEAST, threshold)]
                a.append(np.full(len(may) - 1, item[lead]))
                b.append(item[may[may != lead]])
                led = alike(low, size, np.full(len(may), lead), may, threshold, threshold)
                gone[may[led]] = True
        order = np.lexsort((item, start))
        order = order[~gone[order]]
        while len(order) > 1:
            group = start[order]
            new = np.concatenate([[True], group[1:] != group[:-1]])
            lead = order[np.flatnonzero(new)[np.cumsum(new) - 1]]
            led = alike(low, size, lead, order, threshold, threshold) & ~new
            if led.any():
                a.append(item[lead[led]])
                b.append(item[order[led]])
            order = order[~led & ~new]
        if a:
            yield pairs_batch(a, b)


def cross_batches(batches, threshold: float):
    """Tiles (node, i, j): the pairs of a ``left`` and a ``right`` item of different classes that may be linked. The
    node of a tile of many such pairs is returned in place of them, to be compared as a whole."""
    import pyarrow as pa

    for rows, start, end in whole_groups(batches, ["node", "i", "j"]):
        item, size, comp, low = rows["item"].to_numpy(), rows["size"].to_numpy(), rows["comp"].to_numpy(), lows_of(rows)
        left, right = (rows[c].to_numpy() for c in ("left", "right"))
        xs = np.flatnonzero(left)
        many = np.cumsum(end[xs] - start[xs])
        a, b = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        for part in np.split(xs, np.flatnonzero(np.diff(many // 500_000)) + 1):
            n = end[part] - start[part]
            x = np.repeat(part, n)
            y = np.arange(len(x)) - np.repeat(np.cumsum(n) - n, n) + np.repeat(start[part], n)
            ok = right[y] & (comp[x] != comp[y]) & (item[x] != item[y])
            x, y = x[ok], y[ok]
            ok = alike(low, size, x, y, SKETCH_LEAST, threshold)
            a.append(x[ok])
            b.append(y[ok])
        x, y = np.concatenate(a), np.concatenate(b)
        met = np.bincount(start[x], minlength=len(item))
        dense = met > DENSE * (end - start)[np.arange(len(item))]
        few = ~dense[start[x]]
        x, y = x[few], y[few]
        names = np.flatnonzero(dense & (np.arange(len(item)) == start))
        no = pa.nulls(len(names), pa.int64())
        columns = ["a", "b", "node"]
        yield pa.RecordBatch.from_arrays([pa.array(np.minimum(item[x], item[y])), pa.array(np.maximum(item[x], item[y])), pa.nulls(len(x), pa.int64())], columns)
        yield pa.RecordBatch.from_arrays([no, no, pa.array(rows["node"].to_numpy()[names])], columns)


def dense_batches(batches, threshold: float):
    """Tiles (node, i, j) with texts: links that join classes, one for each step of joining them."""
    for _, rows in streamed(batches, ["node", "i", "j"]):
        item, comp = rows["item"].to_numpy(), rows["comp"].to_numpy()
        left, right = (np.flatnonzero(rows[c].to_numpy(zero_copy_only=False)) for c in ("left", "right"))
        sets = [shingle_set(t.as_py()) for t in rows["text"]]
        x, y = np.nonzero(similar([sets[k] for k in left], [sets[k] for k in right], threshold) & (comp[left][:, None] != comp[right][None, :]))
        if not len(x):
            continue
        x, y = left[x], right[y]
        _, first = np.unique(np.stack([np.minimum(comp[x], comp[y]), np.maximum(comp[x], comp[y])]), axis=1, return_index=True)
        top: dict[int, int] = {}

        def find(c: int) -> int:
            while top.setdefault(c, c) != c:
                top[c] = c = top[top[c]]
            return c

        kept = []
        for k in first:
            p, q = find(int(comp[x[k]])), find(int(comp[y[k]]))
            if p != q:
                top[max(p, q)] = min(p, q)
                kept.append(k)
        yield pairs_batch([np.minimum(item[x[kept]], item[y[kept]])], [np.maximum(item[x[kept]], item[y[kept]])])


def compare_batches(batches):
    """Groups of one left text (``left`` true) and the texts to hold against it: how many shingles each pair has in
    common and in all."""
    import pyarrow as pa

    for (item, _), rows in streamed(batches, ["a", "part"]):
        left = rows["left"].to_numpy(zero_copy_only=False)
        texts, ids = rows["text"], rows["item"].to_numpy()
        base = shingle_set(texts[int(np.flatnonzero(left)[0])].as_py())
        others = np.flatnonzero(~left)
        both, either = [], []
        for i in others:
            s = shingle_set(texts[int(i)].as_py())
            both.append(len(np.intersect1d(base, s, assume_unique=True)))
            either.append(len(s) + len(base) - both[-1])
        yield pa.RecordBatch.from_arrays([pa.array([item] * len(others), pa.int64()), pa.array(ids[others], pa.int64()), pa.array(both, pa.int32()), pa.array(either, pa.int32())], ["a", "b", "both", "either"])


def runs_of(sets: list[np.ndarray], most: int = 1_000_000) -> list[tuple[int, int]]:
    """Runs [a, b) of sets of about ``most`` members."""
    if not sets:
        return []
    at = np.cumsum([len(x) for x in sets]) // most
    edges = [0, *(np.flatnonzero(np.diff(at)) + 1).tolist(), len(sets)]
    return list(zip(edges, edges[1:], strict=False))


def similar(sets_a: list[np.ndarray], sets_b: list[np.ndarray], threshold: float) -> np.ndarray:
    """Which sets of a and of b reach the threshold; long sets are taken a few at a time."""
    out = np.zeros((len(sets_a), len(sets_b)), bool)
    for a, b in runs_of(sets_a):
        for c, d in runs_of(sets_b):
            out[a:b, c:d] = _similar(sets_a[a:b], sets_b[c:d], threshold)
    return out


def _similar(sets_a: list[np.ndarray], sets_b: list[np.ndarray], threshold: float) -> np.ndarray:
    """Which sets of a and of b reach the threshold: matrix products over runs of the common universe."""
    na, nb = np.array([len(s) for s in sets_a], np.float64), np.array([len(s) for s in sets_b], np.float64)
    flat = np.concatenate([*sets_a, *sets_b]) if sets_a or sets_b else np.zeros(0, np.uint64)
    owner = np.repeat(np.arange(len(sets_a) + len(sets_b)), np.concatenate([na, nb]).astype(np.int64))
    universe, at, count = np.unique(flat, return_inverse=True, return_counts=True)
    both = np.zeros((len(na), len(nb)))
    keep = count[at] > 1  # what only one set holds is in no intersection
    owner, at = owner[keep], at[keep]
    shared = np.flatnonzero(count > 1)
    rank = np.full(len(universe), -1)
    rank[shared] = np.arange(len(shared))
    at = rank[at]
    order = np.argsort(at, kind="stable")
    owner, at = owner[order], at[order]
    for lo in range(0, len(shared), 8192):
        a, b = np.searchsorted(at, [lo, lo + 8192])
        m = np.zeros((len(na) + len(nb), min(8192, len(shared) - lo)), np.float32)
        m[owner[a:b], at[a:b] - lo] = 1
        both += m[: len(na)] @ m[len(na) :].T
    union = na[:, None] + nb[None, :] - both
    return (both >= threshold * union) & (union > 0)


def count_batches(batches, threshold: float):
    """Tiles (group, i, j) of blocks i and j of a class: how many items and documents each item is linked with there."""
    import pyarrow as pa

    for (_, i, j), rows in streamed(batches, ["group", "i", "j"]):
        block, ids, n = rows["block"].to_numpy(), rows["item"].to_numpy(), rows["copies"].to_numpy()
        left, right = np.flatnonzero(block == i), np.flatnonzero(block == j)
        sets = [shingle_set(t.as_py()) for t in rows["text"]]
        hit = similar([sets[k] for k in left], [sets[k] for k in right], threshold)
        if i == j:
            np.fill_diagonal(hit, False)
        out_ids = [ids[left]] if i == j else [ids[left], ids[right]]
        items = [hit.sum(1)] if i == j else [hit.sum(1), hit.sum(0)]
        docs = [hit @ n[right]] if i == j else [hit @ n[right], n[left] @ hit]
        cols = [pa.array(np.concatenate(x).astype(np.int64)) for x in (out_ids, items, docs)]
        yield pa.RecordBatch.from_arrays(cols, ["item", "n_items", "n_docs"])


def compared(pairs: DataFrame, texts: DataFrame) -> DataFrame:
    """a, b, both, either of pairs of items (a, b, size: shingles of b). A left item's partners are dealt to parts of
    a bounded number of shingles, each with the left text once, so no item's partners are one task's."""
    many = pairs.groupBy("a").agg(F.ceil(F.sum("size") / BLOCK_SHINGLES).cast("int").alias("parts"))
    dealt = pairs.join(many, "a").select("a", "b", F.pmod(F.xxhash64("b"), F.greatest("parts", F.lit(1))).cast("int").alias("part"))
    rows = dealt.select("a", "part", F.col("b").alias("item"), F.lit(False).alias("left")).unionByName(dealt.select("a", "part").distinct().select("a", "part", F.col("a").alias("item"), F.lit(True).alias("left")))
    rows = rows.join(texts, "item").repartition("a", "part").sortWithinPartitions("a", "part").select("a", "part", "item", "left", "text")
    return rows.mapInArrow(shipped("noisytree.llm.near_dup", "compare_batches"), "a long, b long, both int, either int")


def low_batches(batches):
    """The low byte of each minimal hash."""
    import pyarrow as pa

    for batch in batches:
        low = [np.frombuffer(s, np.uint32).astype(np.uint8).tobytes() for s in batch.column("sig").to_pylist()]
        yield pa.RecordBatch.from_arrays([batch.column("item"), batch.column("size"), pa.array(low, pa.binary())], ["item", "size", "low"])


def no_id() -> Column:
    """Stands for a missing id within: the least of all, as null sorts."""
    return F.lit(-(1 << 63)).cast("long")


class Join:
    """The steps of one join. The corpus is read once for sketches, and again for the texts of items that a pair left
    by the sketches holds."""

    def __init__(self, docs: DataFrame, key: str = "doc_id", text: str = "text", threshold: float = THRESHOLD, recall: float = RECALL, small: int = SMALL, few: int = FEW, depth: int = DEPTH, tile: int = TILE, block: int = BLOCK, small_class: int = SMALL_CLASS):
        self.threshold, self.small, self.few, self.depth, self.tile, self.block, self.small_class = threshold, small, few, depth, tile, block, small_class
        t = docs.select(F.coalesce(F.col(key).cast("long"), no_id()).alias("doc_id"), F.coalesce(F.col(text).cast("string"), F.lit("")).alias("text"))
        self.docs = t.withColumn("text_key", F.xxhash64("text"))
        sketched = durable(self.docs.mapInArrow(shipped("noisytree.llm.near_dup", "sketch_batches"), "doc_id long, text_key long, set_key binary, size int, sig binary"))
        self.rows = sketched.select("doc_id", "text_key", F.xxhash64("set_key").alias("item"), F.col("set_key").isNotNull().alias("some"))
        # An item is named by a hash of its set, and read from the least document that has it.
        some = sketched.where("set_key is not null").groupBy(F.xxhash64("set_key").alias("item"))
        self.items = durable(some.agg(F.min(F.struct("doc_id", "text_key")).alias("k"), F.count("*").alias("copies"), F.first("size").alias("size"), F.first("sig").alias("sig")))
        run = shipped("noisytree.llm.near_dup", "root_batches", runs=runs_for(recall, depth))
        first = self.items.select("item", "sig").mapInArrow(run, "item long, node long")
        nodes = first.groupBy("node").agg(F.count("*").alias("n"), F.min("item").alias("head")).where("n > 1")
        self.level = durable(first.join(nodes, "node"))  # node, item, n, head
        self.lows = self.items.select("item", "size", "sig").mapInArrow(shipped("noisytree.llm.near_dup", "low_batches"), "item long, size int, low binary")
        repeated = durable(sketched.groupBy("doc_id", "text_key").agg(F.count("*").alias("n")).where("n > 1").select("doc_id", "text_key"))
        self.repeated = None if repeated.isEmpty() else repeated
        self.texts = None

    def fetch(self, items: DataFrame) -> None:
        """Adds the texts of the items to those at hand."""
        met = items.distinct()
        if self.texts is not None:
            met = met.join(self.texts.select("item"), "item", "left_anti")
        met = met.join(self.items.select("item", "k.doc_id", "k.text_key"), "item")
        new = written(once(self.docs.join(met, ["doc_id", "text_key"]), self.repeated).select("item", "text"))
        self.texts = new if self.texts is None else self.texts.unionByName(new)

    def linked(self, pairs: DataFrame) -> DataFrame:
        """Those of the pairs (a, b) that reach the threshold."""
        pairs = durable(pairs.join(self.items.select(F.col("item").alias("b"), "size"), "b"))
        self.fetch(pairs.select(F.col("a").alias("item")).unionByName(pairs.select(F.col("b").alias("item"))))
        return compared(pairs, self.texts).where(F.col("both") >= self.threshold * F.col("either")).select("a", "b")

    def likely(self) -> DataFrame:
        """Each item with one that it looks linked to, of each of its nodes. A large node is dealt to parts, and the
        node's least item to all of them."""
        parts = F.ceil(F.col("n") / self.tile).cast("int")
        mine = F.array(F.pmod(F.xxhash64("item"), parts).cast("int"))
        rows = self.level.withColumn("part", F.explode(F.when(F.col("item") == F.col("head"), F.sequence(F.lit(0), parts - 1)).otherwise(mine))).select("node", "part", "item")
        rows = rows.join(self.lows, "item").repartition("node", "part").sortWithinPartitions("node", "part")
        return rows.mapInArrow(shipped("noisytree.llm.near_dup", "leader_batches", threshold=self.threshold), "a long, b long").distinct()

    def mixed(self, rows: DataFrame) -> DataFrame:
        """rows (node, item, comp) of the nodes of several classes, with n (items), m (items outside the commonest
        class), most (that class) and head (the least item)."""
        by_class = rows.groupBy("node", "comp").agg(F.count("*").alias("c"), F.min("item").alias("head")).groupBy("node")
        mixed = by_class.agg(F.sum("c").alias("n"), F.max(F.struct("c", "comp")).alias("top"), F.count("*").alias("k"), F.min("head").alias("head")).where("k > 1")
        return durable(rows.join(mixed.select("node", "n", (F.col("n") - F.col("top.c")).alias("m"), F.col("top.comp").alias("most"), "head"), "node"))

    def tiles(self, nodes: DataFrame, tile: int) -> DataFrame:
        """node, i, j, left, right, item, comp: tiles of the items outside their node's commonest class against all of
        the node (see mixed)."""
        blocks = lambda n: F.greatest(F.lit(1), F.ceil(F.col(n) / tile).cast("int"))
        rows = nodes.withColumn("is", blocks("m")).withColumn("js", blocks("n")).withColumn("rare", F.col("comp") != F.col("most"))
        mine = lambda n: F.pmod(F.xxhash64("item"), F.col(n)).cast("int")
        place = lambda i, j, left, right: F.struct(i.alias("i"), j.alias("j"), left.alias("left"), right.alias("right"))
        no, yes = F.lit(False), F.lit(True)
        as_right = F.transform(F.sequence(F.lit(0), F.col("is") - 1), lambda i: place(i, mine("js"), no, yes))
        as_left = F.transform(F.sequence(F.lit(0), F.col("js") - 1), lambda j: place(mine("is"), j, yes, no))
        one = F.array(place(F.lit(0), F.lit(0), F.col("rare"), yes))
        places = F.when((F.col("is") == 1) & (F.col("js") == 1), one).when(F.col("rare"), F.concat(as_right, as_left)).otherwise(as_right)
        return rows.withColumn("place", F.explode(places)).select("node", "place.*", "item", "comp")

    def across(self, nodes: DataFrame) -> DataFrame:
        """Of nodes: pairs (a, b) that may be linked, and the nodes that have many."""
        rows = self.tiles(nodes, self.tile).join(self.lows, "item").repartition("node", "i", "j").sortWithinPartitions("node", "i", "j")
        return rows.mapInArrow(shipped("noisytree.llm.near_dup", "cross_batches", threshold=self.threshold), "a long, b long, node long")

    def joined(self, found: list[tuple[DataFrame, DataFrame]]) -> DataFrame:
        """Links (a, b) between classes. found: nodes and what across() says of each."""
        names = ["node", "i", "j"]
        whole = [nodes.join(said.where("a is null").select("node").distinct(), "node") for nodes, said in found]
        links = self.linked(reduce(DataFrame.unionByName, [said.where("a is not null").select("a", "b") for _, said in found]).distinct())
        # An item may stand in many such nodes: those of one least item are taken together.
        whole = self.mixed(reduce(DataFrame.unionByName, whole).select(F.col("head").alias("node"), "item", "comp").distinct())
        if whole.isEmpty():
            return links
        self.fetch(whole.select("item"))
        rows = self.tiles(whole, self.block).join(self.texts, "item").repartition(*names).sortWithinPartitions(*names)
        return links.unionByName(rows.mapInArrow(shipped("noisytree.llm.near_dup", "dense_batches", threshold=self.threshold), "a long, b long"))

    def classes(self) -> DataFrame:
        """node, comp of the items that are linked with another (comp: the least item of the class)."""
        level = self.level
        self.stars = durable(self.linked(self.likely()))
        known_classes = durable(components(self.stars))
        found = []
        for depth in range(1, self.depth + 1):
            # Only nodes that hold more than one class can add a link that matters.
            known = level.join(known_classes.withColumnRenamed("node", "item"), "item", "left").select("node", "item", F.coalesce("comp", "item").alias("comp"))
            known = self.mixed(known)
            ready = (F.col("n") <= self.small) | (F.col("m") <= self.few)
            found.append((known.where(ready), durable(self.across(known.where(ready)))))
            many = known.where(~ready)
            if many.isEmpty():
                break
            if depth == self.depth:
                # What does not part lies together in many nodes: those of one least item are taken together.
                known = self.mixed(many.select(F.col("head").alias("node"), "item", "comp").distinct())
                found.append((known, durable(self.across(known))))
                break
            level = durable(many.select("node", "item").join(self.items.select("item", "sig"), "item").mapInArrow(shipped("noisytree.llm.near_dup", "child_batches"), "item long, node long"))
        links = durable(self.joined(found))
        if links.isEmpty():
            return known_classes
        # The new links join classes: settle these, then name items by them.
        of = lambda side: known_classes.select(F.col("node").alias(side), F.col("comp").alias(f"comp_{side}"))
        raised = links.join(of("a"), "a", "left").join(of("b"), "b", "left").select(F.coalesce("comp_a", "a").alias("a"), F.coalesce("comp_b", "b").alias("b"))
        joined = durable(components(raised))
        moved = known_classes.join(joined.select(F.col("node").alias("comp"), F.col("comp").alias("new")), "comp", "left").select("node", F.coalesce("new", "comp").alias("comp"))
        return durable(moved.unionByName(joined.join(known_classes.select("node"), "node", "left_anti")))

    def counts(self, items: DataFrame) -> DataFrame:
        """item, n_items, n_docs: the links of each item of classes of several. items: item, comp, copies, size, n,
        total (items and shingles of the class)."""
        small = (F.col("n") <= self.small_class) & (F.col("total") <= BLOCK_SHINGLES)
        zero = F.lit(0)
        tiles = items.where(small).select(F.col("comp").alias("group"), zero.alias("i"), zero.alias("j"), zero.alias("block"), "item", "copies")
        large = durable(items.where(~small))
        sure = None
        if not large.isEmpty():
            # The pivot: the leader of most items.
            led = self.stars.groupBy("a").agg(F.count("*").alias("led")).withColumnRenamed("a", "item")
            pivots = large.join(led, "item", "left").groupBy("comp").agg(F.max(F.struct(F.coalesce("led", F.lit(0)).alias("led"), "item")).alias("k")).select("comp", F.col("k.item").alias("a"))
            pairs = large.join(pivots, "comp").where("item <> a").select("a", F.col("item").alias("b"), "size")
            # Steps of a quarter of the greatest distance that is a link.
            step = F.floor((1 - F.col("both") / F.col("either")) / ((1 - self.threshold) / 4)).cast("int")
            far = compared(pairs, self.texts).select(F.col("b").alias("item"), step.alias("step"))
            stepped = durable(large.join(far, "item", "left").withColumn("step", F.coalesce("step", zero)))
            by_step = stepped.groupBy("comp", "step").agg(F.count("*").alias("c"), F.sum("copies").alias("d"), F.greatest(F.ceil(F.count("*") / self.block), F.ceil(F.sum("size") / BLOCK_SHINGLES)).cast("int").alias("blocks"))
            seen = stepped.join(by_step.groupBy("comp").agg(F.collect_list(F.struct("step", "c", "d", "blocks")).alias("steps")), "comp")  # a step is a whole number from 0 to 20
            # Two distances of less than the greatest linked one in sum: linked. Further apart than it: not.
            near = F.filter("steps", lambda s: s["step"] + F.col("step") <= 2)
            total = lambda f: F.aggregate(near, F.lit(0).cast("long"), lambda acc, s: acc + s[f])
            own = F.col("step") <= 1
            sure = seen.select("item", (total("c") - F.when(own, 1).otherwise(0)).alias("n_items"), (total("d") - F.when(own, F.col("copies")).otherwise(0)).alias("n_docs"))
            wide = 1 << 24  # blocks of a step
            open_ = F.filter("steps", lambda s: (s["step"] + F.col("step") > 2) & (F.abs(s["step"] - F.col("step")) < 5))
            others = F.flatten(F.transform(open_, lambda s: F.transform(F.sequence(zero, s["blocks"] - 1), lambda k: s["step"] * wide + k)))
            blocks = F.filter("steps", lambda s: s["step"] == F.col("step"))[0]["blocks"]
            seen = seen.withColumn("block", F.col("step") * wide + F.pmod(F.xxhash64("item"), blocks).cast("int")).withColumn("other", F.explode(others))
            tiles = tiles.unionByName(seen.select(F.col("comp").alias("group"), F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j"), "block", "item", "copies"))
        tiles = tiles.join(self.texts, "item").repartition("group", "i", "j").sortWithinPartitions("group", "i", "j").select("group", "i", "j", "block", "item", "copies", "text")
        got = tiles.mapInArrow(shipped("noisytree.llm.near_dup", "count_batches", threshold=self.threshold), "item long, n_items long, n_docs long")
        return (got.unionByName(sure) if sure is not None else got).groupBy("item").agg(F.sum("n_items").alias("n_items"), F.sum("n_docs").alias("n_docs"))

    def classed(self) -> DataFrame:
        """item, doc_id (its least), copies, size, comp, class_id, n, total (items and shingles of its class)."""
        items = self.items.select("item", "k.doc_id", "copies", "size").join(self.classes().withColumnRenamed("node", "item"), "item", "left").withColumn("comp", F.coalesce("comp", "item"))
        return items.join(items.groupBy("comp").agg(F.min("doc_id").alias("class_id"), F.count("*").alias("n"), F.sum("size").alias("total")), "comp")

    def result(self) -> DataFrame:
        """doc_id, text_key, class_id (least doc_id of the class), copies, n_links and n_text_links: the other rows
        within the threshold, and the other sets among them."""
        items = durable(self.classed())
        items = items.join(self.counts(items.where("n > 1")), "item", "left").select("item", "class_id", "copies", "n_items", "n_docs", F.lit(True).alias("some"))
        out = self.rows.join(items, ["item", "some"], "left")
        known = lambda c: F.when(c != no_id(), c)
        return out.select(known(F.col("doc_id")).alias("doc_id"), "text_key", known(F.coalesce("class_id", "doc_id")).alias("class_id"), F.coalesce("copies", F.lit(1)).cast("long").alias("copies"), (F.coalesce("n_docs", F.lit(0)) + F.coalesce(F.col("copies") - 1, F.lit(0))).cast("long").alias("n_links"), F.coalesce("n_items", F.lit(0)).cast("long").alias("n_text_links"))

    def firsts(self) -> DataFrame:
        """doc_id, text_key of the first row of each class, by id, then by a hash of the text."""
        comps = self.classed().select("item", "comp", F.lit(True).alias("some"))
        named = self.rows.join(comps, ["item", "some"], "left").select("doc_id", "text_key", F.coalesce("comp", F.xxhash64("doc_id", "text_key")).alias("comp"))
        return named.groupBy("comp").agg(F.min(F.struct("doc_id", "text_key")).alias("k")).select("k.*")


def once(rows: DataFrame, repeated: DataFrame | None) -> DataFrame:
    """One of the rows alike in doc_id and text_key; only those that are ``repeated`` are gathered."""
    if repeated is None:
        return rows
    keys = ["doc_id", "text_key"]
    return rows.join(repeated, keys, "left_anti").unionByName(rows.join(repeated, keys, "left_semi").dropDuplicates(keys))


def join(docs: DataFrame, **options) -> DataFrame:
    """doc_id, class_id, copies, n_links, n_text_links of every row of docs."""
    return Join(docs, **options).result().drop("text_key")


def deduplicated(docs: DataFrame, key: str = "doc_id", text: str = "text", **options) -> DataFrame:
    """docs without the rows that are not their class's first (by key, then by a hash of the text)."""
    found = Join(docs, key, text, **options)
    first = durable(found.firsts())
    # The columns of docs travel in one struct, so that none can clash with the keys.
    rows = docs.select(F.coalesce(F.col(key).cast("long"), no_id()).alias("doc_id"), F.xxhash64(F.coalesce(F.col(text).cast("string"), F.lit(""))).alias("text_key"), F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"))
    return once(rows.join(first, ["doc_id", "text_key"], "left_semi"), found.repeated).select("row.*")
