"""Products of sparse vectors, tile by tile, so that pairs are added up where they are made.

The vectors are written once to the shared folder, dealt into tiles of vertices.
A task takes two tiles, meets their features, adds up each pair in memory and
gives finished pairs out: no pair is shuffled, spilled or written on the way.
Within a task the rows are taken in strips of a bounded number of products.
Vertices are dealt out in the order of a hash of their vectors, so equal vectors
share a tile. They are multiplied once; all their pairs are given out, one
after another, which makes runs in a result that is written.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from functools import cached_property
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyarrow import fs, parquet
from pyspark.sql import DataFrame, functions as F

from ..scratch import materialise, new_path

#: Vertices of a tile at least where no size is asked for, at most, and entries of one at most on average.
LEAST, MOST, ENTRIES = 2_000, 16_000, 1_000_000
#: Products and cells of a strip, unless one row has more, and rows of a batch given out.
PRODUCTS, CELLS, ROWS = 2_000_000, 4_000_000, 250_000
#: Tasks at most; each takes an equal share of the pairs of tiles.
TASKS = 1_000

SCHEMA = "a long, b long, omega double, common long"
_ENTRIES = pa.schema([("v", pa.int64()), ("f", pa.int64()), ("w", pa.float64())])
_FIELDS = pa.schema([("a", pa.int64()), ("b", pa.int64()), ("omega", pa.float64()), ("common", pa.int64())])


class Tile:
    """The vectors of some vertices: entries ``(row, f, w)`` by row."""

    def __init__(self, v: np.ndarray, f: np.ndarray, w: np.ndarray):
        self.v, row = np.unique(v, return_inverse=True)
        order = np.argsort(row, kind="stable")
        self.row, self.f, self.w = row[order], f[order], w[order]

    @staticmethod
    def read(folder: str, i: int) -> Tile:
        own = rows_of(folder, i, _ENTRIES)
        return Tile(*(own.column(c).to_numpy() for c in _ENTRIES.names))

    @cached_property
    def units(self) -> Units:
        """The distinct vectors, equal to some 12 digits. Hashes only propose what is equal."""
        n = len(self.v)
        if not n:
            return Units(self, self.v, np.zeros(1, np.int64))
        order = np.lexsort((self.f, self.row))
        row, f, w = self.row[order], self.f[order], self.w[order]
        digits, power = np.frexp(w)
        digits = np.round(np.ldexp(digits, 40)).astype(np.int64)
        begin = np.searchsorted(row, np.arange(n))
        length = np.diff(np.append(begin, len(row)))
        x = f.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) + digits.astype(np.uint64) * np.uint64(0xBF58476D1CE4E5B9) + power.astype(np.uint64)
        x = (x ^ (x >> np.uint64(31))) * np.uint64(0x94D049BB133111EB)
        _, first, like = np.unique(np.add.reduceat(x ^ (x >> np.uint64(29)), begin), return_index=True, return_inverse=True)
        model = first[like]
        at = np.minimum(begin[model[row]] + np.arange(len(row)) - begin[row], len(row) - 1)
        other = np.logical_or.reduceat((f != f[at]) | (digits != digits[at]) | (power != power[at]), begin)
        model = np.where(other | (length != length[model]), np.arange(n), model)
        _, unit = np.unique(model, return_inverse=True)
        own = (model == np.arange(n))[row]
        return Units(Tile(unit[row[own]], f[own], w[own]), self.v[np.argsort(unit, kind="stable")], np.append(0, np.cumsum(np.bincount(unit))))


class Units(NamedTuple):
    """Distinct vectors, named by their places; the vertices of vector u are ``v[begin[u] : begin[u + 1]]``."""

    tile: Tile
    v: np.ndarray
    begin: np.ndarray


def rows_of(folder: str, i: int, schema: pa.Schema) -> pa.Table:
    """The rows of one tile; a tile of hashed vertices may be empty."""
    system, root = fs.FileSystem.from_uri(f"{folder}/tile={i}")
    if system.get_file_info(root).type == fs.FileType.NotFound:
        return schema.empty_table()
    files = [x.path for x in system.get_file_info(fs.FileSelector(root)) if x.path.endswith(".parquet")]
    return pa.concat_tables([parquet.ParquetFile(system.open_input_file(x)).read(schema.names).cast(schema) for x in files])


def strips(products: np.ndarray, row: np.ndarray, width: int) -> Iterator[tuple[int, int]]:
    """Runs of whole rows of the entries, each with a bounded number of products and cells."""
    ends = np.append(np.flatnonzero(np.diff(row)) + 1, len(row)) if len(row) else np.zeros(0, np.int64)
    sums = np.append(0, np.cumsum(products))
    start = 0
    while start < len(row):
        within = (sums[ends] - sums[start] <= PRODUCTS) & ((row[ends - 1] - row[start] + 1) * width <= CELLS)
        last = int(np.searchsorted(~within & (ends > start), True))
        stop = int(ends[max(last - 1, int(np.searchsorted(ends, start, side="right")))])
        yield start, stop
        start = stop


def terms(left: Tile, right: Tile) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """Strips of the products of two tiles: first row, cells, and of each product its cell in the strip and its value."""
    order = np.argsort(right.f, kind="stable")
    f, w, column = right.f[order], right.w[order], right.row[order]
    low = np.searchsorted(f, left.f, side="left")
    products = np.searchsorted(f, left.f, side="right") - low
    width = len(right.v)
    for start, stop in strips(products, left.row, width):
        n = products[start:stop]
        total = int(n.sum())
        if not total:
            continue
        at = np.repeat(low[start:stop] - (np.cumsum(n) - n), n) + np.arange(total)
        first = left.row[start]
        key = np.repeat((left.row[start:stop] - first) * width, n) + column[at]
        term = np.repeat(left.w[start:stop], n) * w[at]
        yield int(first), int(left.row[stop - 1] - first + 1) * width, key, term


def meet(left: Tile, right: Tile, same: bool, least: float) -> Iterator[pa.RecordBatch]:
    """All pairs of two tiles that share a feature, of at least this similarity."""
    own, others = left.units, right.units
    width = len(others.tile.v)
    for first, cells, key, term in terms(own.tile, others.tile):
        total = len(key)
        if total * 8 > cells:
            common = np.bincount(key, minlength=cells)
            omega = np.bincount(key, weights=term, minlength=cells)
            key = np.flatnonzero(common)
            common, omega = common[key], omega[key]
        else:
            by = np.argsort(key, kind="stable")
            key, term = key[by], term[by]
            begin = np.flatnonzero(np.append(True, key[1:] != key[:-1]))
            common, omega, key = np.diff(np.append(begin, total)), np.add.reduceat(term, begin), key[begin]
        i, j = key // width + first, key % width
        good = omega >= least
        if same:
            # Units are in order, so each pair is met once this way round; within a unit, vertices are.
            good &= i <= j
        if not good.all():
            i, j, omega, common = i[good], j[good], omega[good], common[good]
        for a, b, k in spread(own, others, i, j):
            within = (i[k] == j[k]) & (a >= b) if same else None
            if within is not None and within.any():
                a, b, k = a[~within], b[~within], k[~within]
            if len(a):
                found = np.minimum(a, b), np.maximum(a, b), omega[k], common[k]
                yield pa.RecordBatch.from_arrays([pa.array(x, t.type) for x, t in zip(found, _FIELDS)], schema=_FIELDS)


def spread(left: Units, right: Units, i: np.ndarray, j: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """The vertices of pairs of units, and of each row its pair's place, pair by pair and at most ``ROWS`` at a time."""
    across = np.diff(right.begin)[j]
    each = np.diff(left.begin)[i] * across
    ends = np.cumsum(each)
    total = int(ends[-1]) if len(ends) else 0
    for low in range(0, total, ROWS):
        high = min(low + ROWS, total)
        p, q = int(np.searchsorted(ends, low, side="right")), int(np.searchsorted(ends, high, side="left")) + 1
        start = ends[p:q] - each[p:q]
        k = np.repeat(np.arange(p, q), np.minimum(ends[p:q], high) - np.maximum(start, low))
        if len(k) == q - p and (each[p:q] == 1).all():
            line, column = left.begin[i[k]], right.begin[j[k]]
        else:
            line, column = np.divmod(np.arange(low, high) - start[k - p], across[k])
            line, column = line + left.begin[i[k]], column + right.begin[j[k]]
        yield left.v[line], right.v[column], k


def placed(entries: DataFrame) -> tuple[DataFrame, int]:
    """``(v, place)`` with places from 0 in the order of a hash of the vectors, and the number of vertices."""
    signed = entries.groupBy("v").agg(F.bit_xor(F.xxhash64("f", F.round("w", 12))).alias("hash"))
    # Equal hashes are parted by the vertex, so however many are equal, no task has more than its share.
    ranged = signed.repartitionByRange("hash", "v").sortWithinPartitions("hash", "v")
    # 33 bits of such an id count within a partition.
    at = materialise(ranged.select("v", F.monotonically_increasing_id().alias("at")), "tile-order")
    part = F.shiftright("at", 33).cast("int")
    count = {r["part"]: r["n"] for r in at.groupBy(part.alias("part")).agg(F.count(F.lit(1)).alias("n")).collect()}
    before = [0]
    for k in range(max(count, default=0) + 1):
        before.append(before[-1] + count.get(k, 0))
    base = F.element_at(F.array(*[F.lit(x).cast("long") for x in before]), part + 1)
    return at.select("v", (base + F.col("at").bitwiseAND(F.lit(2**33 - 1))).alias("place")), before[-1]


def products(vectors: DataFrame, *, tile: int | None = None, least: float = -np.inf) -> DataFrame:
    """``(a, b, omega, common)`` for all vertices a < b of ``vectors(v, f, w)`` that share a feature.

    ``omega`` is the inner product, and only pairs with at least ``least`` are
    given out; ``common`` counts the shared features.
    """
    spark = vectors.sparkSession
    own = vectors.select(F.col("v").cast("long").alias("v"), F.col("f").cast("long").alias("f"), F.col("w").cast("double").alias("w"))
    entries = new_path(spark, "tile-entries")
    own.write.parquet(entries)
    own = spark.read.schema(own.schema).parquet(entries)
    order, n = placed(own)
    rows = own.count()
    size = tile or min(MOST, max(LEAST, n // 64))
    tiles = max(1, -(-n // size), 1 if tile else -(-rows // ENTRIES))
    folder = new_path(spark, "tiles")
    # Places go evenly to tiles, so no tile has more vertices than another by more than one.
    dealt = own.join(order, "v").select("v", "f", "w", F.floor(F.col("place") * tiles / F.lit(max(1, n))).cast("int").alias("tile"))
    dealt.repartition(min(tiles, TASKS), "tile").write.partitionBy("tile").parquet(folder)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: tuple[int, Tile] | None = None
        for batch in batches:
            for k in batch.column(0).to_pylist():
                # Row i of the triangle of pairs begins after i rows of tiles, tiles - 1, ... pairs.
                i = 0
                while k >= tiles - i:
                    k -= tiles - i
                    i += 1
                j = i + k
                if held is None or held[0] != i:
                    held = i, Tile.read(folder, i)
                yield from meet(held[1], held[1] if i == j else Tile.read(folder, j), i == j, least)

    pairs = tiles * (tiles + 1) // 2
    return spark.range(0, pairs, 1, min(pairs, TASKS)).mapInArrow(run, SCHEMA)
