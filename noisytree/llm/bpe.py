"""Byte-level BPE by a segment tree over the ranks of adjacent pairs, and its inverse.

Each symbol slot holds the key ``rank * width + slot`` of the pair that it begins; a tree of minima
over the slots has the leftmost pair of lowest rank at its root. A merge links a slot past its
right neighbour and touches three leaves, so it costs a logarithmic number of updates; the loop
ends when the root holds no mergeable pair. Short pieces are merged as a forest, one numpy row per
piece and all rows a step at a time; long ones have a tree of their own.

Cases: a null text counts as empty (no ids, the empty string decodes); repeated and extra rows or
columns pass through; an empty table gives no rows; the strings of special tokens inside a text
become these tokens, as the reference library does by default.
"""

from __future__ import annotations

import hashlib
import json
from functools import lru_cache
from itertools import chain

import numpy as np
from pyspark.sql import DataFrame

from noisytree.llm.common import shipped, slices

#: How texts are cut before merging: the published pattern of the byte-level vocabulary (fixed value).
PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
#: Pieces of at most so many bytes are merged in a forest.
FOREST_BYTES = 64
#: Distinct pieces in each of two generations of a worker's cache: a full one becomes the old one, and
#: what is not met again while the next fills is forgotten.
CACHE = 300_000
NONE = np.int64(1) << 62


def byte_letters() -> dict[int, str]:
    """The printable character that stands for each byte: itself where printable, else the next unused above 255."""
    keep = [*range(ord("!"), ord("~") + 1), *range(ord("¡"), ord("¬") + 1), *range(ord("®"), ord("ÿ") + 1)]
    rest = [b for b in range(256) if b not in set(keep)]
    return {b: chr(b) for b in keep} | {b: chr(256 + i) for i, b in enumerate(rest)}


class Codec:
    def __init__(self, path: str):
        import regex

        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        vocab = spec["model"]["vocab"]
        letters = byte_letters()
        back = {c: b for b, c in letters.items()}
        self.first = np.array([vocab[letters[b]] for b in range(256)], np.int64)
        self.bytes_of = {i: bytes(back[c] for c in w) for w, i in vocab.items()}
        self.special = {a["content"]: a["id"] for a in spec["added_tokens"]}
        self.bytes_of |= {i: s.encode() for s, i in self.special.items()}
        pairs = [(vocab[a], vocab[b], rank, vocab[a + b]) for rank, (a, b) in enumerate(spec["model"]["merges"])]
        self.by_id = [self.bytes_of.get(i, b"") for i in range(max(self.bytes_of) + 1)]
        self.merge = {(a, b): (rank, new) for a, b, rank, new in pairs}
        keys = np.array([(a << 20) | b for a, b, _, _ in pairs] or [-1], np.int64)
        order = np.argsort(keys)
        self.keys = keys[order]
        self.ranks = np.array([p[2] for p in pairs] or [0], np.int64)[order]
        self.news = np.array([p[3] for p in pairs] or [0], np.int64)[order]
        # Python's \s takes the separators 1C to 1F as well; the library's does not.
        pattern = PATTERN.replace(r"[^\s\p{L}\p{N}]", r"[^\p{White_Space}\p{L}\p{N}]").replace(r"\S", r"\P{White_Space}").replace(r"\s", r"\p{White_Space}")
        self.cut = regex.compile(pattern).findall
        marks = sorted(self.special, key=len, reverse=True)
        self.at_special = regex.compile("(" + "|".join(map(regex.escape, marks)) + ")").split if marks else lambda t: [t]
        self.marks = marks
        self.cache: dict[str, tuple[int, ...]] = {}
        self.old: dict[str, tuple[int, ...]] = {}
        self.text_of = [str(i) for i in range(max(self.bytes_of) + 1)]

    # -- encoding -----------------------------------------------------------------------------
    def rank_of(self, left: np.ndarray, right: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Rank and merged id of each pair; NONE where the pair does not merge."""
        key = (left << 20) | right
        at = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
        hit = self.keys[at] == key
        return np.where(hit, self.ranks[at], NONE), self.news[at]

    def forest(self, pieces: list[bytes]) -> list[tuple[int, ...]]:
        """The ids of pieces of 2 to FOREST_BYTES bytes, one tree a row."""
        n, width = len(pieces), 1 << (max(map(len, pieces)) - 1).bit_length()
        size = np.array([len(p) for p in pieces])
        slot = np.arange(width + 1)
        raw = np.zeros((n, width + 1), np.uint8)
        raw[slot[None, :] < size[:, None]] = np.frombuffer(b"".join(pieces), np.uint8)
        ids = self.first[raw]
        after = np.broadcast_to(slot + 1, (n, width + 1)).copy()
        before = np.broadcast_to(slot - 1, (n, width + 1)).copy()
        after[slot[None, :] + 1 >= size[:, None]] = width  # width: no symbol
        rank, _ = self.rank_of(ids[:, :-1], ids[:, 1:])
        rank[slot[None, :-1] + 1 >= size[:, None]] = NONE
        tree = np.full((n, 2 * width), NONE, np.int64)
        tree[:, width:] = np.where(rank == NONE, NONE, rank * width + slot[:-1])
        for k in range(width - 1, 0, -1):
            tree[:, k] = np.minimum(tree[:, 2 * k], tree[:, 2 * k + 1])
        alive = np.ones((n, width), bool)
        alive[slot[None, :-1] >= size[:, None]] = False
        live = np.flatnonzero(tree[:, 1] != NONE)

        def put(rows: np.ndarray, at: np.ndarray, key: np.ndarray) -> None:
            at = at + width
            tree[rows, at] = key
            while True:
                at = at >> 1
                if not at[0]:
                    break
                tree[rows, at] = np.minimum(tree[rows, 2 * at], tree[rows, 2 * at + 1])

        def pair(rows: np.ndarray, at: np.ndarray) -> np.ndarray:
            right = after[rows, at]
            rank, _ = self.rank_of(ids[rows, at], ids[rows, right])
            return np.where((right == width) | (rank == NONE), NONE, rank * width + at)

        while len(live):
            at = tree[live, 1] % width
            gone = after[live, at]
            _, new = self.rank_of(ids[live, at], ids[live, gone])
            ids[live, at] = new
            alive[live, gone] = False
            nxt = after[live, gone]
            after[live, at] = nxt
            before[live, nxt] = at  # the column past the last symbol is never read
            put(live, gone, np.full(len(live), NONE))
            put(live, at, pair(live, at))
            prev = before[live, at]
            has = prev >= 0
            if has.any():
                rows, prev = live[has], prev[has]
                put(rows, prev, pair(rows, prev))
            live = live[tree[live, 1] != NONE]
        flat = ids[:, :width][alive].tolist()
        end = np.cumsum(alive.sum(1)).tolist()
        return [tuple(flat[a:b]) for a, b in zip([0, *end], end, strict=False)]

    def single(self, piece: bytes) -> tuple[int, ...]:
        """The ids of one piece of any length: a tree of minima in plain lists."""
        ids, n, merge = self.first[np.frombuffer(piece, np.uint8)].tolist(), len(piece), self.merge
        width = 1 << (n - 1).bit_length()
        none = (1 << 62, 0)
        after, before = [*range(1, n), -1], list(range(-1, n - 1))
        tree = [none] * (2 * width)
        for i in range(n - 1):
            if hit := merge.get((ids[i], ids[i + 1])):
                tree[width + i] = (hit[0], i)
        for k in range(width - 1, 0, -1):
            tree[k] = min(tree[2 * k], tree[2 * k + 1])

        def put(at: int, key: tuple[int, int]) -> None:
            at += width
            tree[at] = key
            while at > 1:
                at >>= 1
                least = min(tree[2 * at], tree[2 * at + 1])
                if tree[at] == least:
                    break
                tree[at] = least

        def pair(at: int) -> tuple[int, int]:
            right = after[at]
            hit = merge.get((ids[at], ids[right])) if right >= 0 else None
            return (hit[0], at) if hit else none

        while tree[1] is not none and tree[1] != none:
            at = tree[1][1]
            gone = after[at]
            ids[at] = merge[ids[at], ids[gone]][1]
            ids[gone] = -1
            after[at] = after[gone]
            if after[at] >= 0:
                before[after[at]] = at
            put(gone, none)
            put(at, pair(at))
            if before[at] >= 0:
                put(before[at], pair(before[at]))
        return tuple(i for i in ids if i >= 0)

    def learn(self, pieces) -> None:
        """Put the ids of the pieces in the cache."""
        if len(self.cache) > CACHE:
            self.cache, self.old = {}, self.cache
        by_width: dict[int, list[str]] = {}
        raw: dict[str, bytes] = {}
        for p in pieces:
            if p in self.cache:
                continue
            if found := self.old.get(p):
                self.cache[p] = found
                continue
            b = raw[p] = p.encode("utf-8", "surrogatepass")
            if len(b) == 1:
                self.cache[p] = (int(self.first[b[0]]),)
            elif len(b) > FOREST_BYTES:
                self.cache[p] = self.single(b)
            else:
                by_width.setdefault((len(b) - 1).bit_length(), []).append(p)
        for group in by_width.values():
            for k in range(0, len(group), 4096):
                part = group[k : k + 4096]
                self.cache |= zip(part, self.forest([raw[p] for p in part]), strict=True)

    def pieces(self, text: str) -> list[str | int]:
        """The pieces of a text in order; a special token stands as its id."""
        if not any(m in text for m in self.marks):
            return self.cut(text)
        out: list[str | int] = []
        for part in self.at_special(text):
            out += [self.special[part]] if part in self.special else self.cut(part)
        return out

    def encode_all(self, texts: list[str]) -> list[list[int]]:
        cut = [self.pieces(t) for t in texts]
        distinct = set().union(*cut)
        marked = distinct.intersection(self.special.values())
        self.learn(distinct - marked)
        get = self.cache if not marked else self.cache | {i: (i,) for i in marked}
        return [list(chain.from_iterable(map(get.__getitem__, x))) for x in cut]

    # -- decoding -----------------------------------------------------------------------------
    def decode(self, ids: list[int]) -> str:
        return b"".join(map(self.by_id.__getitem__, ids)).decode("utf-8", "replace")


@lru_cache(maxsize=4)
def codec(path: str) -> Codec:
    return Codec(path)


def encode_batches(batches, path: str, keep: list[str], ids: bool, decoded: bool):
    """keep: columns that pass through. ids, decoded: give these too, not only their digests."""
    import pyarrow as pa

    own = codec(path)
    text_of = own.text_of.__getitem__
    for whole in batches:
        for batch in slices(whole, most=1_500_000):
            got = own.encode_all([t or "" for t in batch.column("text").to_pylist()])
            back = [own.decode(x) for x in got]
            cols = [batch.column(c) for c in keep] + [pa.array([len(x) for x in got], pa.int64())]
            cols.append(pa.array([hashlib.sha256(",".join(map(text_of, x)).encode()).hexdigest() for x in got], pa.string()))
            cols.append(pa.array([hashlib.sha256(x.encode("utf-8", "surrogatepass")).hexdigest() for x in back], pa.string()))
            names = [*keep, "n_tokens", "ids_sha256", "decoded_sha256"]
            if ids:
                offsets = np.concatenate([[0], np.cumsum([len(x) for x in got])]).astype(np.int32)
                flat = np.fromiter(chain.from_iterable(got), np.int32, offsets[-1])
                cols.append(pa.ListArray.from_arrays(pa.array(offsets), pa.array(flat)))
                names.append("ids")
            if decoded:
                cols.append(pa.array(back, pa.string()))
                names.append("decoded")
            yield pa.RecordBatch.from_arrays(cols, names)


def encode(docs: DataFrame, path: str, ids: bool = True, decoded: bool = True, keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """keep..., n_tokens, ids_sha256, decoded_sha256, and where asked for ids and decoded, of docs.text. A column to
    keep that is called as one of these gives way."""
    keep = tuple(c for c in keep if c not in ("n_tokens", "ids_sha256", "decoded_sha256", "ids", "decoded"))
    fields = [f"`{c}` {docs.schema[c].dataType.simpleString()}" for c in keep]
    fields += ["n_tokens long", "ids_sha256 string", "decoded_sha256 string"]
    fields += ["ids array<int>"] * ids + ["decoded string"] * decoded
    return docs.select(*keep, docs["text"].cast("string").alias("text")).mapInArrow(shipped("noisytree.llm.bpe", "encode_batches", path=path, keep=list(keep), ids=ids, decoded=decoded), ", ".join(fields))
