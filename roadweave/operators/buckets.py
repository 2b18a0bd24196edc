"""All pairs of vertices that share a bucket, tile by tile, each pair once.

Every vertex has a row of as many buckets. The rows are written once to the
shared folder, dealt into tiles by a hash of the vertex, so vertices of one
large bucket part. A task takes two tiles and meets their buckets in memory;
a pair that shares several is given out once, so no pair is shuffled to find
its repetitions. Vertices of equal rows are met as one.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from ..scratch import discard, materialise, new_path
from .tiles import ENTRIES, LEAST, MOST, TASKS, rows_of, spread, strips

_ROWS = pa.schema([("v", pa.int64()), ("buckets", pa.list_(pa.int64()))])
_PAIRS = pa.schema([("a", pa.int64()), ("more", pa.list_(pa.int64()))])


class Rows(NamedTuple):
    """Entries ``(bucket, row)`` by bucket, of the distinct rows; the vertices of row u are ``v[begin[u] : begin[u + 1]]``."""

    bucket: np.ndarray
    row: np.ndarray
    v: np.ndarray
    begin: np.ndarray

    @staticmethod
    def read(folder: str, i: int) -> Rows:
        own = rows_of(folder, i, _ROWS)
        v = own.column("v").to_numpy()
        if not len(v):
            return Rows(v, v, v, np.zeros(1, np.int64))
        table = np.ascontiguousarray(own.column("buckets").combine_chunks().flatten().to_numpy().reshape(len(v), -1))
        _, first, unit = np.unique(table.view(f"V{table.strides[0]}").ravel(), return_index=True, return_inverse=True)
        bucket = table[first].ravel()
        by = np.argsort(bucket, kind="stable")
        return Rows(bucket[by], by // table.shape[1], v[np.argsort(unit, kind="stable")], np.append(0, np.cumsum(np.bincount(unit))))


def meet(left: Rows, right: Rows, same: bool) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """The pairs ``a < b`` of two tiles that share a bucket."""
    low = np.searchsorted(right.bucket, left.bucket, side="left")
    products = np.searchsorted(right.bucket, left.bucket, side="right") - low
    hit = np.flatnonzero(products)
    hit = hit[np.argsort(left.row[hit], kind="stable")]
    low, products, row = low[hit], products[hit], left.row[hit]
    width = len(right.begin) - 1
    # No cells are held, so only the products bound a strip.
    for start, stop in strips(products, row, 0):
        n = products[start:stop]
        at = np.repeat(low[start:stop] - (np.cumsum(n) - n), n) + np.arange(n.sum())
        i, j = np.divmod(np.unique(np.repeat(row[start:stop], n) * width + right.row[at]), width)
        if same:
            i, j = i[i <= j], j[i <= j]
        for a, b, k in spread(left, right, i, j):
            if same:
                once = (i[k] != j[k]) | (a < b)
                a, b = a[once], b[once]
            if len(a):
                yield np.minimum(a, b), np.maximum(a, b)


def sharing(rows: DataFrame, *, tile: int | None = None) -> DataFrame:
    """``(a, b)``, a < b, of all ``rows(v, buckets)`` that share a bucket; all have as many, and a vertex has one row."""
    spark = rows.sparkSession
    own = materialise(rows.select(F.col("v").cast("long").alias("v"), "buckets"), "bucket-rows")
    n, most = own.agg(F.count(F.lit(1)), F.max(F.size("buckets"))).first()
    size = tile or max(1, min(MOST, max(LEAST, n // 64), ENTRIES // max(1, most or 1)))
    tiles = max(1, -(-n // size))
    folder = new_path(spark, "buckets")
    dealt = own.withColumn("tile", F.pmod(F.xxhash64("v"), F.lit(tiles)).cast("int"))
    dealt.repartition(min(tiles, TASKS), "tile").write.partitionBy("tile").parquet(folder)
    discard(own)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: tuple[int, Rows] | None = None
        for batch in batches:
            for i, k in zip(batch.column("i").to_pylist(), batch.column("k").to_pylist()):
                if 2 * k == tiles and i >= k:
                    # Half the way round the other tile has this pair too.
                    continue
                if held is None or held[0] != i:
                    held = i, Rows.read(folder, i)
                for a, b in meet(held[1], held[1] if k == 0 else Rows.read(folder, (i + k) % tiles), k == 0):
                    by = np.argsort(a, kind="stable")
                    a, b = a[by], b[by]
                    first = np.flatnonzero(np.append(True, a[1:] != a[:-1]))
                    more = pa.ListArray.from_arrays(pa.array(np.append(first, len(a)), pa.int32()), pa.array(b))
                    yield pa.RecordBatch.from_arrays([pa.array(a[first]), more], schema=_PAIRS)

    # Each tile with itself and those that follow it half the way round, so all tasks have as many pairs of tiles.
    pairs = spark.range(0, tiles, 1, min(tiles, TASKS)).select(F.col("id").alias("i"), F.explode(F.sequence(F.lit(0), F.lit(tiles // 2))).alias("k"))
    return pairs.mapInArrow(run, "a long, more array<long>").select("a", F.explode("more").alias("b"))
