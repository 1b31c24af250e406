from __future__ import annotations

import hashlib
import os
import random
import zlib
from collections import defaultdict

import numpy as np
import pytest

os.environ["TOKENIZERS_PARALLELISM"] = "false"

import public_tokenizers
import sentencepiece
from tokenizers import Tokenizer

from curvetree.llm import bpe, packing, tokens

from .conftest import TEXTS


def wild(n: int) -> list[str]:
    rng, alphabet = random.Random(3), "ab \n\t.,'1é日😀▁<|>s"
    return ["".join(rng.choice(alphabet) for _ in range(rng.randint(1, 60))) for _ in range(n)]


def library(name: str) -> Tokenizer:
    return Tokenizer.from_file(public_tokenizers.path(name))


def test_counts_are_the_librarys():
    model = public_tokenizers.path("piece_bpe_32k.model")
    counter, sp = tokens.PieceCounter(model, room=50), sentencepiece.SentencePieceProcessor(model_file=model)
    for t in [t for t in TEXTS if t] + wild(800):
        assert counter.count(t) == len(sp.encode(t)), t[:40]
    assert counter.count(None) == counter.count("") == 0


def test_count_rows(odd_docs, no_docs):
    got = tokens.count_tokens(odd_docs, limit=100).collect()
    assert len(got) == len(TEXTS) and tokens.count_tokens(no_docs).count() == 0
    assert sorted(r["n_bytes"] for r in got) == sorted(len((t or "").encode()) for t in TEXTS)
    assert all(r["over_limit"] == (r["n_tokens"] > 100) for r in got)


@pytest.mark.parametrize("room", [0, 10, 10**6])
def test_ids_are_the_librarys_and_decode_back(room):
    coder, lib = bpe.ByteBpe(public_tokenizers.path("byte_bpe_50k.json"), room, 3000), library("byte_bpe_50k.json")
    texts = [t or "" for t in TEXTS] + wild(500)
    got = [x for _, block in coder.blocks(texts) for x in block]
    want = [e.ids for e in lib.encode_batch(texts, add_special_tokens=False)]
    assert [np.frombuffer(x, "<u4").tolist() for x in got] == want
    assert [coder.decode(x) for x in got] == [lib.decode(i, skip_special_tokens=False) for i in want]


def test_decoding_broken_bytes():
    coder, lib = bpe.coder("byte_bpe_50k.json"), library("byte_bpe_50k.json")
    for ids in ([222, 50256, 160], [*range(150, 256)], []):
        assert coder.decode(np.array(ids, "<u4").tobytes()) == lib.decode(ids, skip_special_tokens=False)


def test_encode_then_decode_columns(odd_docs, no_docs):
    back = bpe.decode(bpe.encode(odd_docs)).collect()
    assert sorted(r["text"] for r in back) == sorted(t or "" for t in TEXTS)
    assert bpe.encode(no_docs).count() == 0


def test_round_trip_digests(spark, sf_dir):
    lib = library("byte_bpe_50k.json")
    docs = dict(map(tuple, spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text").collect()))
    for r in bpe.op5_bpe_round_trip(spark, sf_dir).collect():
        ids = lib.encode(docs[r["doc_id"]] or "", add_special_tokens=False).ids
        assert (r["n_tokens"], r["ids_sha256"]) == (len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest())
        assert r["decoded_sha256"] == hashlib.sha256((docs[r["doc_id"]] or "").encode()).hexdigest()


@pytest.mark.parametrize("widths", [(1,), (4, 9), (8, 16, 32)])
def test_packed_ids_are_the_librarys(widths):
    encoder, lib = packing.WordEncoder(public_tokenizers.path("word_bpe_49k.json"), widths), library("word_bpe_49k.json")
    rng, alphabet = random.Random(5), "ab \n\x1c\x1f\t.,'1é日ßÉİĆ²_\xa0\u2003sT"
    texts = [*TEXTS, *wild(500), *("".join(rng.choice(alphabet) for _ in range(rng.randint(0, 60))) for _ in range(2000)), "<|endoftext|>x y", "", " "]
    for block in (texts, texts[::-1]):
        assert [np.frombuffer(x, "<u4").tolist() for x in encoder.encode(block)] == [e.ids for e in lib.encode_batch([t or "" for t in block], add_special_tokens=False)]


def check_pieces(rows, texts: dict, capacity: int, lib) -> float:
    """All ids in one piece each, sequences gapless and no longer than the capacity; returns the share of padding."""
    by_doc, by_sequence = defaultdict(list), defaultdict(list)
    for r in rows:
        by_doc[r["doc_id"]].append(r)
        by_sequence[r["sequence_id"]].append(r)
    assert by_doc.keys() == texts.keys()
    for doc, parts in by_doc.items():
        ids = [*lib.encode(texts[doc] or "", add_special_tokens=False).ids, 2]
        at = 0
        for p in sorted(parts, key=lambda p: p["start"]):
            assert p["start"] == at and p["doc_tokens"] == len(ids)
            at += p["length"]
            assert p["ids_crc32"] == zlib.crc32(np.array(ids[p["start"] : at], "<u4").tobytes())
        assert at == len(ids)
    padding = total = 0
    for parts in by_sequence.values():
        at = 0
        for p in sorted(parts, key=lambda p: p["offset"]):
            assert p["offset"] == at
            at += p["length"]
        assert at <= capacity
        total += at
        padding += 0 if at & (at - 1) == 0 else capacity - at
    return padding / total


@pytest.mark.parametrize(("cut", "capacity", "group_rows"), [("halves", 4096, 4000), ("halves", 64, 5), ("overlong", 100, 50)])
def test_packing(spark, sf_dir, cut, capacity, group_rows):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").limit(100).cache()
    texts = dict(map(tuple, docs.select("doc_id", "text").collect()))
    rows = packing.pack(docs, capacity, cut, group_rows=group_rows).collect()
    padding = check_pieces(rows, texts, capacity, library("word_bpe_49k.json"))
    assert cut == "overlong" or padding == 0


def test_packing_query(spark, sf_dir):
    """The registered query on all documents against the library."""
    texts = dict(map(tuple, spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text").collect()))
    assert check_pieces(packing.op10_harmonic_packing(spark, sf_dir).collect(), texts, 4096, library("word_bpe_49k.json")) == 0
    by = {r["cut"]: r for r in packing.packing_figures(spark, sf_dir).collect()}
    assert by["halves"]["padding"] == 0 and by["overlong"]["classes"] > by["halves"]["classes"] and by["overlong"]["pieces"] < by["halves"]["pieces"]
    assert {r["documents"] for r in by.values()} == {len(texts)} and by["halves"]["tokens"] == by["overlong"]["tokens"]


def test_packing_odd_rows(odd_docs, no_docs):
    assert packing.pack(no_docs).count() == 0
    rows = packing.pack(odd_docs, 128).collect()
    assert sum(r["length"] for r in rows) == sum(len(e.ids) + 1 for e in library("word_bpe_49k.json").encode_batch([t or "" for t in TEXTS], add_special_tokens=False))
    assert len({(r["sequence_id"], r["offset"]) for r in rows}) == len(rows)
    with pytest.raises(ValueError):
        packing.pack(odd_docs, 100)


def test_counted_tokens_query(spark, sf_dir):
    """The registered query's counts on all documents against the library."""
    sp = sentencepiece.SentencePieceProcessor(model_file=public_tokenizers.path("piece_bpe_32k.model"))
    texts = dict(map(tuple, spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text").collect()))
    got = {r["doc_id"]: (r["n_bytes"], r["n_tokens"], r["over_limit"]) for r in tokens.op2_token_counts(spark, sf_dir).collect()}
    want = {i: (len((t or "").encode()), len(sp.encode(t or ""))) for i, t in texts.items()}
    assert got == {i: (b, n, n > 4096) for i, (b, n) in want.items()}


def test_one_very_long_text(spark):
    """Megabytes in one row."""
    rng = random.Random(12)
    text = " ".join("".join(rng.choice("abcdeé'1.") for _ in range(rng.randint(1, 12))) for _ in range(400_000))
    docs = spark.createDataFrame([(1, text), (2, "x")], "doc_id long, text string")
    ids = len(library("word_bpe_49k.json").encode(text, add_special_tokens=False).ids) + 1
    assert {r["doc_id"]: r["n"] for r in packing.pack(docs).groupBy("doc_id").sum("length").withColumnRenamed("sum(length)", "n").collect()} == {1: ids, 2: 2}
