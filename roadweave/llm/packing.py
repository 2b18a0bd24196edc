"""Packing by power-of-two decomposition.

A document's ids, closed by the separator id, are cut into pieces whose lengths
are powers of two: as many of ``max_len`` as fit, then the binary digits of the
rest from the largest down. A piece is a sequence of its own in the bucket of
its length, so no sequence crosses documents and none is padded.

Defined results: a null or empty text is the separator alone, one piece of
length 1; repeated rows and equal ids are packed row by row; a null id stays
null; an empty table gives an empty table; other columns are ignored.
"""

from __future__ import annotations

import base64
import re
import zlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import public_tokenizers
from pyspark.sql import DataFrame, functions as F, types as T

from . import arrow

#: Latin text and common punctuation, where both tokenizer libraries split alike; other texts go to the first of them.
PLAIN = re.compile("[^\x00-ɏ‐-‧€]")


class Ids:
    """Token ids of texts under one vocabulary.

    ``tokenizers`` defines the ids. ``tiktoken`` runs the same vocabulary about
    three times as fast and serves texts of Latin script without special
    tokens; whatever else comes goes to ``tokenizers`` itself.
    """

    def __init__(self, vocabulary: str, ranks: str | None):
        from tokenizers import Tokenizer

        self.exact = Tokenizer.from_file(vocabulary)
        self.special = [x.content for x in self.exact.get_added_tokens_decoder().values()]
        self.fast = None
        if ranks:
            import tiktoken

            with open(ranks, "rb") as lines:
                table = {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}
            self.fast = tiktoken.Encoding("ranks", pat_str=public_tokenizers.PATTERN, mergeable_ranks=table, special_tokens={})

    def __call__(self, text: str) -> np.ndarray:
        if self.fast is not None and not PLAIN.search(text) and not any(x in text for x in self.special) and "  " * 2000 not in text:
            return self.fast.encode_to_numpy(text, disallowed_special=())
        return np.array(self.exact.encode(text, add_special_tokens=False).ids, dtype=np.uint32)


@lru_cache(maxsize=2)
def ids_of(vocabulary: str, ranks: str | None) -> Ids:
    return Ids(vocabulary, ranks)


def binary_lengths(n: int, max_len: int) -> list[int]:
    """Lengths of the pieces of ``n`` ids, longest first; ``max_len`` is a power of two."""
    full, rest = divmod(n, max_len)
    return [max_len] * full + [1 << k for k in range(max_len.bit_length() - 2, -1, -1) if rest >> k & 1]


def pack(
    docs: DataFrame,
    *,
    id_col: str = "doc_id",
    text_col: str = "text",
    max_len: int = 1024,
    separator: int = 0,
    vocabulary: str | None = None,
    ranks: str | None = None,
    keep_ids: bool = False,
) -> DataFrame:
    """One row per piece; ``keep_ids`` adds the ids themselves.

    ``ranks`` is the same vocabulary as a rank file (None: the library of
    ``vocabulary`` alone). ``sequence_id`` is stable for a given layout of the
    input files, as a retried task numbers its rows alike.
    """
    if max_len < 1 or max_len & (max_len - 1):
        raise ValueError("max_len is a power of two")
    if vocabulary is None:
        vocabulary = public_tokenizers.path("byte_bpe_50k.json")
        ranks = ranks or public_tokenizers.path("byte_bpe_50k.tiktoken")
    id_type = docs.schema[id_col].dataType
    fields = [T.StructField("doc_id", id_type)] + [T.StructField(x, T.LongType()) for x in ("start", "length", "ids_crc32", "doc_tokens")]
    if keep_ids:
        fields.append(T.StructField("ids", T.ArrayType(T.IntegerType(), False)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = ids_of(vocabulary, ranks)
        for part, texts in arrow.text_chunks(batches, "text"):
            rows, starts, lengths, crcs, totals, kept = [], [], [], [], [], []
            for row, text in enumerate(texts):
                ids = np.append(encode(text.as_py() or ""), np.uint32(separator)).astype("<u4")
                at = 0
                for length in binary_lengths(len(ids), max_len):
                    piece = ids[at : at + length]
                    rows.append(row)
                    starts.append(at)
                    lengths.append(length)
                    crcs.append(zlib.crc32(piece.data))
                    totals.append(len(ids))
                    if keep_ids:
                        kept.append(piece.astype(np.int32))
                    at += length
            columns = [part.column("id").take(pa.array(rows, pa.int64()))] + [pa.array(x, pa.int64()) for x in (starts, lengths, crcs, totals)]
            if keep_ids:
                columns.append(pa.array(kept, pa.list_(pa.int32())))
            yield pa.RecordBatch.from_arrays(columns, names=[f.name for f in fields])

    pieces = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text")).mapInArrow(run, T.StructType(fields))
    return pieces.withColumn("sequence_id", F.monotonically_increasing_id()).withColumn("offset", F.lit(0).cast("long")).withColumn("bucket", F.log2("length").cast("int"))
