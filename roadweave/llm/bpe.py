"""Byte-level BPE over length-bucketed numpy matrices.

Texts are split by the tokenizer's pattern; each distinct match of a slice is
encoded once. Matches of like byte length form one matrix, shorter ones padded at
their end with an id that no pair has. In every round each
row merges its leftmost pair of minimum rank, found through a hashed table of
all mergeable pairs; the row then loses one column, so the matrix is compacted
by a column a round and by the rows that have no mergeable pair left. Only the
two pairs beside a merge are looked up again. Matches longer than
``MATRIX_BYTES`` would make quadratic work; a heap of the same (rank, place)
order merges them.

Defined results: null counts as empty; an empty text has no ids, and the
SHA-256 of no bytes; repeated rows are encoded each; null ids stay null; an
empty table gives an empty table; other columns are ignored.
"""

from __future__ import annotations

import base64
import hashlib
import heapq
from collections.abc import Iterable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import public_tokenizers
import regex
from pyspark.sql import DataFrame, functions as F, types as T

from . import arrow

MATRIX_BYTES = 256
#: Distinct matches that a worker remembers before it starts anew; results do not depend on it.
MEMO_WORDS = 200_000
NONE = np.int32(2**31 - 1)
#: Matches up to the first number of bytes share a matrix with those of equal length, longer ones with those of the same multiple of the second.
EXACT_BYTES, STEP_BYTES = 8, 8
PAD = np.int32(-1)


class PairTable:
    """Open-addressing hash table from pairs of ids to the rank of their union."""

    def __init__(self, left: np.ndarray, right: np.ndarray, rank: np.ndarray):
        self.bits = max(4, int(len(rank) * 4).bit_length())
        self.keys = np.full(1 << self.bits, -1, dtype=np.int64)
        self.ranks = np.full(1 << self.bits, NONE, dtype=np.int32)
        keys = left.astype(np.int64) << 32 | right
        slot, todo = self._slot(keys), np.arange(len(keys))
        while len(todo):
            free = self.keys[slot[todo]] == -1
            first = todo[free]
            _, at = np.unique(slot[first], return_index=True)
            put = first[at]
            self.keys[slot[put]] = keys[put]
            self.ranks[slot[put]] = rank[put]
            todo = todo[self.keys[slot[todo]] != keys[todo]]
            slot[todo] = (slot[todo] + 1) & ((1 << self.bits) - 1)

    def _slot(self, keys: np.ndarray) -> np.ndarray:
        return ((keys.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - self.bits)).astype(np.int64)

    def look_up(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """Rank of each pair, or ``NONE``."""
        keys = (left.astype(np.int64) << 32 | right).ravel()
        slot = self._slot(keys)
        seen = self.keys[slot]
        out = np.where(seen == keys, self.ranks[slot], NONE)
        todo = np.flatnonzero((seen != keys) & (seen != -1))
        while len(todo):
            slot[todo] = (slot[todo] + 1) & ((1 << self.bits) - 1)
            seen = self.keys[slot[todo]]
            hit = seen == keys[todo]
            out[todo[hit]] = self.ranks[slot[todo[hit]]]
            todo = todo[~hit & (seen != -1)]
        return out.reshape(left.shape)


class Codec:
    """Encoder and decoder of one rank file."""

    def __init__(self, ranks: dict[bytes, int], pattern: str):
        # White space as Unicode defines it: Python's own class also has U+001C to U+001F.
        self.pattern = regex.compile(pattern.replace(r"\s", r"\p{White_Space}").replace(r"\S", r"\P{White_Space}"))
        self.ranks = ranks
        self.byte_id = np.array([ranks[bytes([b])] for b in range(256)], dtype=np.int32)
        left, right, rank = [], [], []
        for token, r in ranks.items():
            for i in range(1, len(token)):
                a, b = ranks.get(token[:i]), ranks.get(token[i:])
                if a is not None and b is not None:
                    left.append(a)
                    right.append(b)
                    rank.append(r)
        self.pairs = PairTable(np.array(left, np.int64), np.array(right, np.int64), np.array(rank, np.int32))
        self.pair_rank: dict[tuple[int, int], int] = {}
        self._lists = (left, right, rank)
        size = max(ranks.values()) + 1
        by_id = [b""] * size
        for token, r in ranks.items():
            by_id[r] = token
        self.token_len = np.array([len(x) for x in by_id], dtype=np.int64)
        self.token_at = np.cumsum(self.token_len) - self.token_len
        self.token_bytes = np.frombuffer(b"".join(by_id), dtype=np.uint8)

    def encode_matches(self, matches: list[bytes]) -> list[np.ndarray]:
        """Ids of each match; matches of like length share a matrix."""
        out: list[np.ndarray] = [np.zeros(0, np.int32)] * len(matches)
        length = np.array([len(m) for m in matches], dtype=np.int64)
        width = np.where(length <= EXACT_BYTES, length, -(-length // STEP_BYTES) * STEP_BYTES)
        for i in np.flatnonzero(length > MATRIX_BYTES):
            out[i] = self._by_heap(matches[i])
        for n in np.unique(width[length <= MATRIX_BYTES]):
            at = np.flatnonzero((width == n) & (length <= MATRIX_BYTES))
            for part in np.array_split(at, max(1, len(at) * int(n) // 4_000_000)):
                flat = np.frombuffer(b"".join([matches[i].ljust(n, b"\0") for i in part]), dtype=np.uint8).reshape(len(part), n)
                ids = np.where(np.arange(n) < length[part, None], self.byte_id[flat], PAD)
                self._merge(ids, part, out)
        return out

    def _merge(self, ids: np.ndarray, rows: np.ndarray, out: list[np.ndarray]) -> None:
        rank = self.pairs.look_up(ids[:, :-1], ids[:, 1:])
        while len(rows):
            width = ids.shape[1]
            if width > 1:
                at = rank.argmin(axis=1)
                best = rank[np.arange(len(rows)), at]
                open_ = best != NONE
            else:
                open_ = np.zeros(len(rows), dtype=bool)
            if not open_.all():
                for i, row in zip(np.flatnonzero(~open_), rows[~open_]):
                    out[row] = ids[i][ids[i] != PAD]
                if not open_.any():
                    return
                ids, rank, rows, at, best = ids[open_], rank[open_], rows[open_], at[open_], best[open_]
            n = len(rows)
            ids[np.arange(n), at] = best
            column = np.arange(width - 1)
            ids = np.take_along_axis(ids, column[None, :] + (column[None, :] > at[:, None]), axis=1)
            column = column[:-1]
            rank = np.take_along_axis(rank, column[None, :] + (column[None, :] >= at[:, None]), axis=1)
            for side in (at - 1, at):
                has = np.flatnonzero((side >= 0) & (side < width - 2))
                rank[has, side[has]] = self.pairs.look_up(ids[has, side[has]], ids[has, side[has] + 1])

    def _by_heap(self, match: bytes) -> np.ndarray:
        if not self.pair_rank:
            left, right, rank = self._lists
            self.pair_rank = dict(zip(zip(left, right), rank))
        ids = self.byte_id[np.frombuffer(match, dtype=np.uint8)].tolist()
        n = len(ids)
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        heap = [(r, i, ids[i], ids[i + 1]) for i in range(n - 1) if (r := self.pair_rank.get((ids[i], ids[i + 1]))) is not None]
        heapq.heapify(heap)
        while heap:
            r, i, a, b = heapq.heappop(heap)
            j = after[i]
            if ids[i] != a or j >= n or ids[j] != b:
                continue
            ids[i], ids[j] = r, -1
            after[i] = k = after[j]
            if k < n:
                before[k] = i
                if (s := self.pair_rank.get((r, ids[k]))) is not None:
                    heapq.heappush(heap, (s, i, r, ids[k]))
            if (h := before[i]) >= 0 and (s := self.pair_rank.get((ids[h], r))) is not None:
                heapq.heappush(heap, (s, h, ids[h], r))
        return np.array([x for x in ids if x >= 0], dtype=np.int32)

    def decode(self, ids: np.ndarray) -> np.ndarray:
        """Bytes of a run of ids."""
        return _ragged(self.token_bytes, self.token_at[ids], self.token_len[ids])


def _ragged(flat: np.ndarray, at: np.ndarray, length: np.ndarray) -> np.ndarray:
    """Concatenation of ``flat[at[i] : at[i] + length[i]]``."""
    ends = np.cumsum(length)
    if not len(ends):
        return flat[:0]
    return flat[np.repeat(at - ends + length, length) + np.arange(ends[-1])]


class Memo:
    """Encoded matches of a worker: ids end to end, and their decimal form."""

    def __init__(self, codec: Codec):
        self.codec = codec
        self.clear()

    def clear(self) -> None:
        self.index: dict[str, int] = {}
        self.decimal: list[str] = []
        self.at = np.zeros(0, np.int64)
        self.length = np.zeros(0, np.int64)
        self.flat = np.zeros(0, np.int32)

    def add(self, matches: Iterable[str]) -> None:
        new = [m for m in matches if m not in self.index]
        if not new:
            return
        ids = self.codec.encode_matches([m.encode() for m in new])
        self.index.update(zip(new, range(len(self.index), len(self.index) + len(new))))
        self.decimal.extend(" ".join(map(str, x.tolist())) for x in ids)
        length = np.array([len(x) for x in ids], dtype=np.int64)
        self.at = np.concatenate([self.at, len(self.flat) + np.cumsum(length) - length])
        self.length = np.concatenate([self.length, length])
        self.flat = np.concatenate([self.flat, *ids])


@lru_cache(maxsize=2)
def codec_of(path: str, pattern: str) -> Codec:
    with open(path, "rb") as lines:
        return Codec({base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}, pattern)


def encode(
    docs: DataFrame,
    *,
    id_col: str = "doc_id",
    text_col: str = "text",
    ranks: str | None = None,
    pattern: str | None = None,
    keep_ids: bool = False,
) -> DataFrame:
    """Ids of every text and what they decode to, as counts and digests; ``keep_ids`` adds both in full."""
    ranks = ranks or public_tokenizers.path("byte_bpe_50k.tiktoken")
    pattern = pattern or public_tokenizers.PATTERN
    fields = [T.StructField("doc_id", docs.schema[id_col].dataType), T.StructField("n_tokens", T.LongType()), T.StructField("ids_sha256", T.StringType()), T.StructField("decoded_sha256", T.StringType())]
    if keep_ids:
        fields += [T.StructField("ids", T.ArrayType(T.IntegerType(), False)), T.StructField("decoded", T.StringType())]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = codec_of(ranks, pattern)
        memo = Memo(codec)
        for part, column in arrow.text_chunks(batches, "text"):
            if len(memo.index) > MEMO_WORDS:
                memo.clear()
            texts = [codec.pattern.findall(t or "") for t in column.to_pylist()]
            memo.add(set().union(*texts))
            counts, id_sums, byte_sums, ids, decoded = [], [], [], [], []
            for matches in texts:
                at = np.fromiter(map(memo.index.__getitem__, matches), dtype=np.int64, count=len(matches))
                own = _ragged(memo.flat, memo.at[at], memo.length[at])
                whole = codec.decode(own).tobytes()
                counts.append(len(own))
                id_sums.append(hashlib.sha256(" ".join(map(memo.decimal.__getitem__, at.tolist())).encode()).hexdigest())
                byte_sums.append(hashlib.sha256(whole).hexdigest())
                if keep_ids:
                    ids.append(own)
                    decoded.append(whole.decode())
            columns = [part.column("id"), pa.array(counts, pa.int64()), pa.array(id_sums, pa.string()), pa.array(byte_sums, pa.string())]
            if keep_ids:
                columns += [pa.array(ids, pa.list_(pa.int32())), pa.array(decoded, pa.string())]
            yield pa.RecordBatch.from_arrays(columns, names=[f.name for f in fields])

    return docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text")).mapInArrow(run, T.StructType(fields))
