import hashlib
import random

import public_tokenizers
import pyarrow as pa
import pytest
from tokenizers import Tokenizer

from noisytree.llm import bpe, token_count

ODD = ["", None, " ", "\n\n  x\t\ty   ", "<|endoftext|>", "a<|endoftext|>b <|endoftext|><|endof", "a" * 5000, "ab" * 2000 + " " * 300 + "x", "déjà vu — 日本語 🙂🙂 ß İ ﬁ", "x\x1cy\x85z\xa0w", "it's we'll I'M don't", "1234567 12.5", "\x00\x01"]


@pytest.fixture(scope="module")
def byte_path():
    return public_tokenizers.path("byte_bpe_50k.json")


def fuzz(n):
    rng = random.Random(1)
    pick = [lambda: chr(rng.randrange(32, 127)), lambda: chr(rng.randrange(0, 0x300)), lambda: chr(rng.randrange(0x300, 0xD800)), lambda: " ", lambda: "\n", lambda: chr(rng.randrange(0x1F000, 0x20000))]
    return ["".join(rng.choice(pick)() for _ in range(rng.randrange(0, 80))) for _ in range(n)]


def test_encode_equals_the_library(spark, docs, byte_path):
    texts = ODD + fuzz(1500)
    lib = Tokenizer.from_file(byte_path)
    got = {r.doc_id: r for r in bpe.encode(docs(texts, extra=["ids", "decoded"]).repartition(3), byte_path).collect()}
    for i, t in enumerate(texts):
        ids = lib.encode(t or "", add_special_tokens=False).ids
        assert got[i].ids == ids and got[i].n_tokens == len(ids)
        assert got[i].decoded == lib.decode(ids, skip_special_tokens=False) == (t or "")
        assert got[i].ids_sha256 == hashlib.sha256(",".join(map(str, ids)).encode()).hexdigest()
        assert got[i].decoded_sha256 == hashlib.sha256((t or "").encode()).hexdigest()


def test_both_trees_merge_alike(byte_path):
    c, rng = bpe.codec(byte_path), random.Random(2)
    pieces = ["".join(rng.choice("aeinrst ") for _ in range(rng.randrange(2, 60))).encode() for _ in range(500)]
    for width in (8, 64):
        some = [p for p in pieces if len(p) <= width]
        assert c.forest(some) == [c.single(p) for p in some]


def test_decode_of_broken_bytes(byte_path):
    c, lib = bpe.codec(byte_path), Tokenizer.from_file(byte_path)
    for ids in ([6408], [50256, 1], list(range(180, 200)), []):
        assert c.decode(ids) == lib.decode(ids, skip_special_tokens=False)


def test_empty_table_and_repeated_rows(docs, byte_path):
    assert bpe.encode(docs([]), byte_path).count() == 0
    assert bpe.encode(docs(["a b", "a b"], ids=[1, 1]), byte_path).count() == 2


def test_long_texts_are_counted_as_whole(spark, docs):
    path = public_tokenizers.path("word_bpe_49k.json")
    tok, rng = token_count.tokenizer(path), random.Random(3)
    parts = [" ", "\n", "a", "B", "é", "e", "\u0301", "İ", "ß", "1", "<|endoftext|>", "'s", "!", "日本", " the ", "Σ", "가", "\x85"]
    texts = ["".join(rng.choice(parts) for _ in range(rng.randrange(0, 500))) for _ in range(300)] + ["x" * 3000, "a b " * 1000, "", None]
    df = docs(texts, extra=["n_tokens"])
    for chunk, overlap in ((60, 4), (200, 50), (60_000, 2_000)):
        got = {r.doc_id: r for r in token_count.token_counts(df, path, chunk, overlap, limit=100).collect()}
        for i, t in enumerate(texts):
            n = len(tok.encode(t or "", add_special_tokens=False).ids)
            assert (got[i].n_tokens, got[i].n_bytes, got[i].over_limit) == (n, len((t or "").encode()), n > 100)
    assert token_count.token_counts(docs([]), path).count() == 0
    # One word without white space: the overlap grows to the end.
    assert token_count.count_long("x" * 3000, tok, 60, 4)[2] > 0


def test_chunks_are_spliced(spark):
    tok = token_count.tokenizer(public_tokenizers.path("word_bpe_49k.json"))
    text = "some words of a long text, " * 500
    n, chunks, widened = token_count.count_long(text, tok, 500, 60)
    assert n == len(tok.encode(text, add_special_tokens=False).ids) and chunks > 20 and widened == 0


def test_a_word_is_counted_once_by_the_library(monkeypatch):
    path = public_tokenizers.path("word_bpe_49k.json")
    tok, sent = token_count.tokenizer(path), []

    class Spy:
        def encode_batch_fast(self, texts, **options):
            sent.extend(texts)
            return tok.encode_batch_fast(texts, **options)

    words = token_count.Words(Spy())
    monkeypatch.setattr(token_count, "tokenizer", lambda _: Spy())
    monkeypatch.setattr(token_count, "words_of", lambda _: words)
    texts = ["Some words, again\tand again. " * 200, "again<|endoftext|>and\r\nagain " * 200, None, "x" * 5000]
    batch = pa.RecordBatch.from_pydict({"doc_id": [0, 1, 2, 3], "text": pa.array(texts, pa.string())})
    for _ in range(2):
        got = [r["n_tokens"] for b in token_count.count_batches([batch], path, ["doc_id"], 60_000, 2_000, 2048) for r in b.to_pylist()]
        assert got == [len(tok.encode(t or "", add_special_tokens=False).ids) for t in texts]
    assert sum(map(len, sent)) < 11_000 and len(sent) == len(set(sent)) + 1  # the long word is not kept


def test_words_are_counted_as_in_their_text(byte_path):
    path = public_tokenizers.path("word_bpe_49k.json")
    tok, rng = token_count.tokenizer(path), random.Random(5)
    odd = [" ", "\n", "\t", "\r", "\x0b", "\x1c", "\x85", "\xa0", "\u2028", "\u0301", "\u0308", "\u1161", "가", "ᄀ", "Σ", "İ", "'", "s", "S", "'LL", "<|", "<|endoftext|>", "|>", "1", "-", "é", "ﬁ"]
    texts = [t or "" for t in ODD] + fuzz(1500) + ["".join(rng.choice(odd) for _ in range(60)) for _ in range(3000)]
    words = token_count.Words(tok, kept=500)
    for k in range(0, len(texts), 100):
        part = texts[k : k + 100]
        assert words.count(part) == [len(tok.encode(t, add_special_tokens=False).ids) for t in part]
    assert len(words.of) < 500 + 100 * 60
    assert token_count.by_words(path) and not token_count.by_words(byte_path)
