"""Token counts of texts of any length, by overlap resynchronisation.

A text beyond ``chunk`` characters is encoded in chunks that overlap. Two encodings of
neighbouring chunks are spliced at a place that is proven stable: white space in the text that both
put between two tokens. This vocabulary's normaliser folds white space to one blank and its
splitter drops blanks, so no piece, and hence no merge, reaches over white space, and what stands on
either side of it is encoded alike whatever lies beyond. (Composition of characters does not cross
it either: white space neither composes nor is reordered, except with combining marks right after
it, which are not taken as places to splice, and a splice is not taken within a special token's
string.) Both encodings must also give the same tokens between two such places of the overlap; where
the overlap holds none, it is doubled until it does or the chunk reaches the end of the text.

Other texts are cut at every place of white space (blank, tab, line feed, carriage return), which needs no overlap where
the vocabulary's file says that it works as above (`by_words`), and a word that a worker has counted is not counted
again while it is kept. With other vocabularies the library counts these texts whole.

Cases: a null or empty text has 0 bytes and 0 tokens; special tokens' strings inside a text count
as the library counts them; repeated rows and extra columns do no harm; an empty table gives none.
"""

from __future__ import annotations

import json
import os
import unicodedata
from functools import lru_cache

from pyspark.sql import DataFrame

from noisytree.llm.common import parts, shipped

CHUNK = 60_000
OVERLAP = 2_000
LIMIT = 2048
#: A worker keeps the counts of so many words, of up to so many characters each.
KEPT, LONGEST = 1 << 19, 64
#: A splitter of which no piece holds white space.
PIECES = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"


@lru_cache(maxsize=4)
def tokenizer(path: str):
    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    from tokenizers import Tokenizer

    found = Tokenizer.from_file(path)
    found.no_truncation()
    found.no_padding()
    return found


@lru_cache(maxsize=4)
def by_words(path: str) -> bool:
    """Whether white space always stands between two tokens, and nothing before it changes the tokens after it."""
    with open(path, encoding="utf-8") as f:
        says = json.load(f)
    outer, pre = says.get("normalizer") or {}, says.get("pre_tokenizer") or {}
    steps, splits = outer.get("normalizers", []), pre.get("pretokenizers", [])
    folds = {"type": "Replace", "pattern": {"Regex": r"\s+"}, "content": " "}
    return (
        outer.get("type") == pre.get("type") == "Sequence"
        and all(x["type"] in ("NFC", "Lowercase") or x == folds for x in steps)
        and len(splits) == 2
        and splits[0] == {"type": "Split", "pattern": {"Regex": PIECES}, "behavior": "Removed", "invert": True}
        and splits[1]["type"] == "ByteLevel"
        and not splits[1]["add_prefix_space"]
        and not splits[1]["use_regex"]
        and says["model"]["type"] == "BPE"
        and not says["model"].get("dropout")
        and not any(any(map(str.isspace, x["content"])) or x["lstrip"] or x["rstrip"] or x["single_word"] or x["normalized"] for x in says["added_tokens"])
    )


class Words:
    """Token counts of texts as sums over their words."""

    def __init__(self, tok, kept: int = KEPT):
        self.tok, self.kept, self.of = tok, kept, {"": 0}

    def count(self, texts: list[str]) -> list[int]:
        split = [t.replace("\n", " ").replace("\t", " ").replace("\r", " ").split(" ") for t in texts]
        new = list(set().union(*split).difference(self.of))
        for w, e in zip(new, self.tok.encode_batch_fast(new, add_special_tokens=False), strict=True):
            self.of[w] = len(e.ids)
        counts = [sum(map(self.of.__getitem__, words)) for words in split]
        for w in new:
            if len(w) > LONGEST:
                del self.of[w]
        if len(self.of) > self.kept:
            self.of = {"": 0}
        return counts


@lru_cache(maxsize=4)
def words_of(path: str) -> Words:
    return Words(tokenizer(path))


def stable_places(text: str, start: int, end: int, marks: list[str]) -> list[int]:
    """Positions p in (start, end) such that text[p-1] is plain white space and text[p] may begin a
    piece: nothing composes with, or is part of a special string around, the white space."""
    found = []
    for p in range(start + 1, end):
        if text[p - 1] in " \n\t\r" and not text[p].isspace() and unicodedata.combining(text[p]) == 0 and unicodedata.category(text[p])[0] != "M":
            if not any(m in text[max(0, p - len(m)) : p + len(m)] and any(c.isspace() for c in m) for m in marks):
                found.append(p)
    return found


def between(enc, offset: int, start: int, end: int) -> list[int] | None:
    """The ids of the tokens in [start, end) of the text; None if a token crosses either end."""
    ids = []
    for i, (a, b) in zip(enc.ids, enc.offsets, strict=True):
        a, b = a + offset, b + offset
        if b <= start or a >= end:
            continue
        if a < start or b > end:
            return None
        ids.append(i)
    return ids


def count_long(text: str, tok, chunk: int = CHUNK, overlap: int = OVERLAP) -> tuple[int, int, int]:
    """Tokens of one text, the number of chunks, and how often an overlap was widened."""
    marks = [t.content for t in tok.get_added_tokens_decoder().values()]
    total = chunks = widened = 0
    start = 0  # everything before this stable place has been counted
    while True:
        end = min(len(text), start + chunk)
        chunks += 1
        if end == len(text):
            return total + len(tok.encode(text[start:], add_special_tokens=False).ids), chunks, widened
        wide = overlap
        while True:
            last = min(len(text), end + wide)
            head = tok.encode(text[start:last], add_special_tokens=False)
            if last == len(text):
                return total + len(head.ids), chunks, widened
            places = stable_places(text, end, last, marks)
            if len(places) >= 2:
                # The next chunk begins at the first place; it must agree up to the last one.
                tail = tok.encode(text[places[0] : last], add_special_tokens=False)
                mine, other = between(head, start, places[0], places[-1]), between(tail, places[0], places[0], places[-1])
                before = between(head, start, start, places[0])
                if mine is not None and mine == other and before is not None:
                    total += len(before)
                    start = places[0]
                    break
            wide *= 2
            widened += 1


def count_batches(batches, path: str, keep: list[str], chunk: int, overlap: int, limit: int):
    import pyarrow as pa

    tok = tokenizer(path)
    for batch in parts(batches):
        texts = [t or "" for t in batch.column("text").to_pylist()]
        counts = [(0, 1, 0)] * len(texts)
        short: list[int] = []
        size = 0

        def flush() -> None:
            if by_words(path):
                for i, n in zip(short, words_of(path).count([texts[i] for i in short]), strict=True):
                    counts[i] = (n, 1, 0)
                return
            for i, e in zip(short, tok.encode_batch_fast([texts[i] for i in short], add_special_tokens=False), strict=True):
                counts[i] = (len(e.ids), 1, 0)

        for i, t in enumerate(texts):
            if len(t) > chunk + overlap:
                counts[i] = count_long(t, tok, chunk, overlap)
                continue
            short.append(i)
            size += len(t)
            if size > 1_000_000:
                flush()
                short, size = [], 0
        flush()
        n = [c[0] for c in counts]
        cols = [batch.column(c) for c in keep]
        cols += [pa.array([len(t.encode("utf-8", "surrogatepass")) for t in texts], pa.int64()), pa.array(n, pa.int64()), pa.array([x > limit for x in n], pa.bool_())]
        cols += [pa.array([c[1] for c in counts], pa.int32()), pa.array([c[2] for c in counts], pa.int32())]
        yield pa.RecordBatch.from_arrays(cols, [*keep, "n_bytes", "n_tokens", "over_limit", "n_chunks", "n_widened"])


def token_counts(docs: DataFrame, path: str, chunk: int = CHUNK, overlap: int = OVERLAP, limit: int = LIMIT, keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """keep..., n_bytes, n_tokens, over_limit, n_chunks, n_widened of docs.text."""
    fields = [f"`{c}` {docs.schema[c].dataType.simpleString()}" for c in keep]
    fields += ["n_bytes long", "n_tokens long", "over_limit boolean", "n_chunks int", "n_widened int"]
    run = shipped("noisytree.llm.token_count", "count_batches", path=path, keep=list(keep), chunk=chunk, overlap=overlap, limit=limit)
    return docs.select(*keep, docs["text"].cast("string").alias("text")).mapInArrow(run, ", ".join(fields))
