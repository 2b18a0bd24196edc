import hashlib
import base64
import zlib

import numpy as np
import public_tokenizers as P
import tiktoken
from tokenizers import Tokenizer

from roadweave.llm import bpe, packing

RANKS = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(P.path("byte_bpe_50k.tiktoken"), "rb"))}
ENCODING = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=RANKS, special_tokens={})


def check_bpe(docs):
    rows = docs.selectExpr("text as doc_id", "text").transform(bpe.encode).collect()
    assert len(rows) == docs.count()
    for r in rows:
        text = r["doc_id"] or ""
        ids = ENCODING.encode_ordinary(text)
        assert r["n_tokens"] == len(ids)
        assert r["ids_sha256"] == hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest(), text[:80]
        assert r["decoded_sha256"] == hashlib.sha256(text.encode()).hexdigest()


def test_bpe_equals_library(odd_docs, sample):
    check_bpe(odd_docs)
    check_bpe(sample)


def test_heap_and_matrix_agree():
    codec = bpe.codec_of(P.path("byte_bpe_50k.tiktoken"), P.PATTERN)
    for word in (b"ththening" * 20, b"a" * 200, b"abcabd" * 30):
        assert codec.encode_matches([word])[0].tolist() == codec._by_heap(word).tolist()


def test_bpe_full_output_round_trips(odd_docs):
    for r in bpe.encode(odd_docs.selectExpr("text as doc_id", "text"), keep_ids=True).collect():
        assert r["decoded"] == (r["doc_id"] or "") and len(r["ids"]) == r["n_tokens"]


def check_packing(docs):
    exact = Tokenizer.from_file(P.path("byte_bpe_50k.json"))
    docs = docs.selectExpr("text as doc_id", "text").distinct()
    rows = packing.pack(docs, keep_ids=True).collect()
    by = {}
    for r in rows:
        by.setdefault(r["doc_id"], []).append(r)
        assert r["length"] & (r["length"] - 1) == 0 and 1 <= r["length"] <= 1024 and r["offset"] == 0
        assert r["ids_crc32"] == zlib.crc32(np.array(r["ids"], "<u4").tobytes())
    assert len({r["sequence_id"] for r in rows}) == len(rows)
    assert len(by) == docs.count()
    for text, pieces in by.items():
        ids = exact.encode(text or "", add_special_tokens=False).ids + [0]
        pieces.sort(key=lambda r: r["start"])
        assert sum((r["ids"] for r in pieces), []) == ids
        assert [r["start"] for r in pieces] == np.cumsum([0] + [r["length"] for r in pieces])[:-1].tolist()
        assert {r["doc_tokens"] for r in pieces} == {len(ids)}


def test_packing_is_an_exact_cover(odd_docs, sample):
    check_packing(odd_docs)
    check_packing(sample)


def test_repeated_rows_and_empty_tables(odd_docs, spark):
    assert packing.pack(odd_docs).where("start = 0").count() == odd_docs.count()
    empty = spark.createDataFrame([], "doc_id long, text string, start string, length int")
    assert packing.pack(empty).count() == 0 and bpe.encode(empty).count() == 0
