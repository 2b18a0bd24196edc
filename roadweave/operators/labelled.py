"""Co-clustering of a large graph with the label of every vertex in arrays on the driver.

The edges are written twice to the shared folder, in tiles of either side's
vertices, which have places from 0. What a task needs besides its tiles is a label for
every vertex, sent to it whole, so neither an exchange nor the blocks of a
partition needs a join or a shuffle of edges. The blocks of the many clusters
of a start are written in tiles of clusters; a task takes two of those and adds up in
memory what each merge of their clusters changes, so no pair of clusters that share
a block becomes a row.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F
from pyspark.sql.window import Window

from ..model import BipartiteGraph
from ..scratch import discard, materialise, new_path, release
from .kernel import SMALL, best_moves, log_factorials
from .tiles import rows_of

#: Vertices of both sides whose labels the driver holds, four bytes each.
LABELS = 20_000_000
#: Edges of a tile on average, tiles of a side at most, and tasks at most, of which each gives back the blocks it changed.
EDGES, TILES, TASKS = 500_000, 1_000, 64
#: Cells of a tile of clusters, and its clusters at most.
CELLS, LINES = 8_000_000, 512
#: Partners of a cluster that a pair of tiles gives matching to choose from, at least and at most, and rows of all about.
#: With few, all clusters of data without structure name the same partners, and a round merges hardly any.
FEW, MANY, ROWS = 8, 64, 2_000_000
#: Counts of a block up to which merges are products of matrices, at most.
FACTORED = 256

_EDGES = pa.schema([("i", pa.int32()), ("u", pa.int32()), ("n", pa.int64())])
_BLOCKS = pa.schema([("c", pa.int32()), ("d", pa.int32()), ("m", pa.int64())])
_MOVES = pa.schema([("kind", pa.string()), ("a", pa.binary()), ("b", pa.binary())])

Labels = tuple[np.ndarray, np.ndarray]


def hashed(places: np.ndarray, seed: int) -> np.ndarray:
    """A hash of 63 bits of each place."""
    x = places.astype(np.uint64) + np.uint64((seed + 1) * 0x9E3779B97F4A7C15 % 2**64)
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return (x ^ (x >> np.uint64(31))) >> np.uint64(1)


def cells_of(row: np.ndarray, cell: np.ndarray, n: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """``(row, cell, n)`` by row and cell, with the visits of equal ones added up."""
    key = row.astype(np.int64) * k + cell
    if len(key) and (int(row.max()) + 1) * k <= 32 * len(key):
        # A place for every cell costs less than sorting.
        sums = np.bincount(key, weights=n)
        at = np.flatnonzero(sums)
        return at // k, at % k, sums[at].astype(np.int64)
    by = np.argsort(key, kind="stable")
    key = key[by]
    begin = np.flatnonzero(np.append(True, key[1:] != key[:-1])) if len(key) else np.zeros(0, np.int64)
    return key[begin] // k, key[begin] % k, np.add.reduceat(n[by], begin) if len(key) else n


def dense(labels: np.ndarray) -> np.ndarray:
    return np.unique(labels, return_inverse=True)[1].astype(np.int32)


@dataclass
class Tiled:
    """A graph in tiles of either side: side 0 are trajectories, side 1 segments."""

    graph: BipartiteGraph
    places: list[DataFrame]
    offsets: list[np.ndarray]
    folders: list[str]

    @staticmethod
    def of(graph: BipartiteGraph, edges: int) -> Tiled:
        spark = graph.traversal.sparkSession
        tiles = min(TILES, max(1, -(-edges // EDGES)))
        places, offsets, folders = [], [], []
        for v in ("t", "s"):
            own = graph.traversal.select(F.col(v).alias("v")).distinct().withColumn("tile", F.pmod(F.xxhash64("v"), F.lit(tiles)).cast("int"))
            ranked = materialise(own.withColumn("rank", F.row_number().over(Window.partitionBy("tile").orderBy("v")) - 1), "cocluster-ranks")
            count = np.zeros(tiles, np.int64)
            for tile, n in ranked.groupBy("tile").count().collect():
                count[tile] = n
            offsets.append(np.append(0, np.cumsum(count)))
            base = F.array(*[F.lit(int(x)) for x in offsets[-1]])
            places.append(ranked.select("v", "tile", (F.element_at(base, F.col("tile") + 1) + F.col("rank")).cast("int").alias("i")))
        t, s = (p.select(F.col("v").alias(v), F.col("tile").alias(f"{v}_tile"), F.col("i").alias(f"{v}_i")) for p, v in zip(places, ("t", "s")))
        placed = graph.traversal.select("t", "s", "n").join(t, "t").join(s, "s")
        for own, other in (("t", "s"), ("s", "t")):
            folder = new_path(spark, "cocluster-edges")
            rows = placed.select(F.col(f"{own}_i").alias("i"), F.col(f"{other}_i").alias("u"), "n", F.col(f"{own}_tile").alias("tile"), F.col(f"{other}_tile").alias("back"))
            # The other side's tile is a salt: a vertex with a large share of the edges goes to several writers.
            rows.repartition(tiles, "tile", F.col("back") % 4).write.partitionBy("tile").parquet(folder)
            folders.append(folder)
            if own == "t":
                placed = spark.read.schema(rows.schema).parquet(folder).select(F.col("i").alias("t_i"), F.col("tile").alias("t_tile"), F.col("u").alias("s_i"), F.col("back").alias("s_tile"), "n")
        return Tiled(graph, places, offsets, folders)

    def sizes(self) -> tuple[int, int]:
        return int(self.offsets[0][-1]), int(self.offsets[1][-1])

    def release(self) -> None:
        for folder in self.folders:
            release(self.graph.traversal.sparkSession, folder)

    def collected(self, parts: tuple[DataFrame, DataFrame]) -> Labels:
        """The clusters of two tables ``(t, ct)`` and ``(s, cs)``, numbered from 0, by place."""
        out = []
        for places, part, (v, c), size in zip(self.places, parts, (("t", "ct"), ("s", "cs")), self.sizes()):
            got = places.join(part.select(F.col(v).alias("v"), F.col(c).cast("long").alias("c")), "v").select("i", "c").toArrow()
            label = np.zeros(size, np.int64)
            label[got["i"].to_numpy()] = got["c"].to_numpy()
            out.append(dense(label))
        return out[0], out[1]

    def parts(self, labels: Labels) -> tuple[DataFrame, DataFrame]:
        """Labels by place as tables ``(t, ct)`` and ``(s, cs)``."""
        out = []
        for places, label, (v, c) in zip(self.places, labels, (("t", "ct"), ("s", "cs"))):
            shared = places.sparkSession.sparkContext.broadcast(label)

            def run(batches: Iterable[pa.RecordBatch], shared=shared, names=(v, c)) -> Iterator[pa.RecordBatch]:
                for batch in batches:
                    yield pa.RecordBatch.from_arrays([batch.column("v"), pa.array(shared.value[batch.column("i").to_numpy()], pa.int64())], names=list(names))

            out.append(materialise(places.select("v", "i").mapInArrow(run, f"{v} long, {c} long"), "cocluster-part"))
        return out[0], out[1]

    def _tasks(self, run, schema: str) -> DataFrame:
        tiles = len(self.offsets[0]) - 1
        return self.graph.traversal.sparkSession.range(0, tiles, 1, min(tiles, TASKS)).mapInArrow(run, schema)

    def fixed(self) -> float:
        """ln n! of the visits of every vertex, summed."""
        total = 0.0
        for side in (0, 1):
            folder, offsets = self.folders[side], self.offsets[side]

            def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
                for tile in (x for batch in batches for x in batch.column(0).to_pylist()):
                    own = rows_of(folder, tile, _EDGES)
                    visits = np.bincount(own["i"].to_numpy() - offsets[tile], weights=own["n"].to_numpy())
                    yield pa.RecordBatch.from_arrays([pa.array([float(log_factorials(visits.astype(np.int64)).sum())])], names=["x"])

            total += self._tasks(run, "x double").agg(F.sum("x")).first()[0] or 0.0
        return total

    def blocks(self, labels: Labels) -> DataFrame:
        """``(c, d, m)``: visits by block."""
        folder = self.folders[0]
        shared = self.graph.traversal.sparkSession.sparkContext.broadcast(labels)

        def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            rows, columns = shared.value
            k = int(columns.max()) + 1
            for tile in (x for batch in batches for x in batch.column(0).to_pylist()):
                own = rows_of(folder, tile, _EDGES)
                c, d, m = cells_of(rows[own["i"].to_numpy()], columns[own["u"].to_numpy()], own["n"].to_numpy(), k)
                yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip((c.astype(np.int32), d.astype(np.int32), m), _BLOCKS.types)], schema=_BLOCKS)

        return self._tasks(run, "c int, d int, m long").groupBy("c", "d").agg(F.sum("m").alias("m"))

    def moves(self, side: int, labels: Labels, blocks: np.ndarray, half: int, seed: int) -> tuple[np.ndarray, np.ndarray]:
        """New labels of one side, its vertices of one half at their best cluster with all others held still, and the blocks then.

        ``blocks`` has a line for each cluster of the side.
        """
        folder, offsets = self.folders[side], self.offsets[side]
        size = np.bincount(labels[side], minlength=len(blocks))
        shared = self.graph.traversal.sparkSession.sparkContext.broadcast((labels[side], labels[1 - side], blocks, size))

        def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            own, other, matrix, size = shared.value
            k = matrix.shape[1]
            change, who, where = np.zeros(matrix.size, np.int64), [], []
            for tile in (x for batch in batches for x in batch.column(0).to_pylist()):
                edges, first = rows_of(folder, tile, _EDGES), int(offsets[tile])
                i, u, n = (edges[c].to_numpy() for c in _EDGES.names)
                may = hashed(i, seed) % np.uint64(2) == half
                row, cell, n = cells_of(i[may] - first, other[u[may]], n[may], k)
                if not len(row):
                    continue
                begin = np.flatnonzero(np.append(True, row[1:] != row[:-1]))
                vertex = row[begin] + first
                to = best_moves(matrix, size, matrix.sum(axis=1), own[vertex], begin, cell, n)
                moved = to != own[vertex]
                each = np.diff(np.append(begin, len(row)))
                np.subtract.at(change, (np.repeat(own[vertex].astype(np.int64), each) * k + cell)[np.repeat(moved, each)], n[np.repeat(moved, each)])
                np.add.at(change, (np.repeat(to, each) * k + cell)[np.repeat(moved, each)], n[np.repeat(moved, each)])
                who.append(vertex[moved].astype(np.int32))
                where.append(to[moved].astype(np.int32))
            at = np.flatnonzero(change)
            out = [("change", at.tobytes(), change[at].tobytes())] + [("moves", a.tobytes(), b.tobytes()) for a, b in zip(who, where)]
            yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*out), _MOVES.types)], schema=_MOVES)

        label, after = labels[side].copy(), blocks.flatten()
        for kind, a, b in self._tasks(run, "kind string, a binary, b binary").collect():
            if kind == "change":
                after[np.frombuffer(a, np.int64)] += np.frombuffer(b, np.int64)
            else:
                label[np.frombuffer(a, np.int32)] = np.frombuffer(b, np.int32)
        shared.destroy()
        return label, after.reshape(blocks.shape)


def matrix_of(blocks: DataFrame, shape: tuple[int, int]) -> np.ndarray:
    got = blocks.toArrow()
    out = np.zeros(shape, np.int64)
    out[got["c"].to_numpy(), got["d"].to_numpy()] = got["m"].to_numpy()
    return out


@lru_cache(maxsize=None)
def factors(most: int) -> tuple[np.ndarray, np.ndarray]:
    """Lines for x and y from 0 to ``most`` whose products are ln (x + y)! - ln x! - ln y!, to some 11 digits after the point."""
    x = np.arange(most + 1)
    f = log_factorials(x)
    u, s, v = np.linalg.svd(log_factorials(x[:, None] + x) - f[:, None] - f)
    rank = int((s > 1e-12 * max(1.0, s[0] / 1000)).sum())
    return np.ascontiguousarray((u[:, :rank] * s[:rank]).T), np.ascontiguousarray(v[:rank])


def merged_terms(left: np.ndarray, right: np.ndarray) -> np.ndarray:
    """Change of the blocks' terms by merging a line of ``left`` and one of ``right``; infinite where they share no cell.

    Cells of counts up to a bound are met by products of matrices, as a table of
    those changes is a product of few factors; the few larger ones are looked up.
    """
    largest, cells = max(left.max(initial=0), right.max(initial=0)), left.size + right.size
    above = lambda most: np.count_nonzero(left > most) + np.count_nonzero(right > most)
    most = 2
    while most < min(largest, FACTORED) and above(most) > 0.005 * cells:
        most *= 2
    if above(most) > 0.05 * cells:
        most = 0
    x, y = np.where(left > most, 0, left), np.where(right > most, 0, right)
    out = np.zeros((len(left), len(right)))
    for p, q in zip(*factors(most)) if most else ():
        out -= p.take(x, mode="clip") @ q.take(y, mode="clip").T
    look_up = SMALL.take if int(left.max(initial=0) + right.max(initial=0)) < len(SMALL) else log_factorials
    for many, few, change in ((left, right, out), (right, x, out.T)):
        if largest <= most or not few.any():
            continue
        own, turned = log_factorials(few), np.ascontiguousarray(few.T)
        for a in range(len(many)):
            at = np.flatnonzero(many[a] > most)
            if not len(at):
                continue
            z = many[a, at]
            change[a] += own[:, at].sum(axis=1) + log_factorials(z).sum()
            # A few cells at a time stay in the processor's cache.
            for k in range(0, len(at), 256):
                change[a] -= look_up(turned[at[k : k + 256]] + z[k : k + 256, None]).sum(axis=0)
    # A cell that both have changes the terms by ln 2 at least.
    out[out > -0.5] = np.inf
    return out


def partners(blocks: DataFrame, side: int, size: np.ndarray, mass: np.ndarray, others: int, count: int | None = None) -> pd.DataFrame:
    """``(a, b, delta)``, a < b: the merges of clusters that share a block, the best few of either cluster, and without ``count`` a matching of each pair of tiles.

    ``delta`` is what the merge changes, but for what depends on the number of
    clusters alone. The blocks are ``(c, d, m)``; ``side`` says whose clusters are merged.
    """
    spark, k = blocks.sparkSession, len(size)
    lines = int(min(LINES, max(32, CELLS // others), -(-k // 8)))
    tiles = -(-k // lines)
    # Without structure all name the same few partners, so a pair of tiles also gives one for every cluster that it can.
    whole = count is None
    count = count or max(FEW, min(MANY, ROWS // (tiles * k)))
    own = blocks if side == 0 else blocks.select(F.col("d").alias("c"), F.col("c").alias("d"), "m")
    folder = new_path(spark, "cocluster-lines")
    own.withColumn("tile", (F.col("c") / lines).cast("int")).repartition(min(tiles, TASKS), "tile").write.partitionBy("tile").parquet(folder)
    shared = spark.sparkContext.broadcast((size, mass))
    pairs = [(i, j) for i in range(tiles) for j in range(i, tiles)]

    def read(i: int) -> np.ndarray:
        got = rows_of(folder, i, _BLOCKS)
        out = np.zeros((min(lines, k - i * lines), others), np.int64)
        out[got["c"].to_numpy() - i * lines, got["d"].to_numpy()] = got["m"].to_numpy()
        return out

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        size, mass = shared.value
        margin = lambda size, mass: log_factorials(mass + size - 1) - log_factorials(size - 1)
        held: tuple[int, np.ndarray] | None = None
        for x in (x for batch in batches for x in batch.column(0).to_pylist()):
            i, j = pairs[x]
            held = held if held and held[0] == i else (i, read(i))
            delta = merged_terms(held[1], held[1] if i == j else read(j))
            a, b = (np.arange(t * lines, t * lines + n) for t, n in zip((i, j), delta.shape))
            delta += margin(size[a][:, None] + size[b][None, :], mass[a][:, None] + mass[b][None, :])
            delta = np.round(delta - margin(size[a], mass[a])[:, None] - margin(size[b], mass[b])[None, :], 9)
            if i == j:
                np.fill_diagonal(delta, np.inf)
            found = []
            for d, p, q in ((delta, a, b), (delta.T, b, a)):
                few = min(count, d.shape[1])
                best = np.argpartition(d, few - 1, axis=1)[:, :few]
                value = np.take_along_axis(d, best, axis=1)
                found.append((np.repeat(p, few), q[best].ravel(), value.ravel()))
            if whole:
                i, j = matching(delta)
                found.append((a[i], b[j], delta[i, j]))
            p, q, value = (np.concatenate(z) for z in zip(*found))
            good = np.isfinite(value)
            yield pa.RecordBatch.from_arrays([pa.array(np.minimum(p, q)[good]), pa.array(np.maximum(p, q)[good]), pa.array(value[good])], names=["a", "b", "delta"])

    found = spark.range(0, len(pairs), 1, min(len(pairs), 1_000)).mapInArrow(run, "a long, b long, delta double").toArrow()
    shared.destroy()
    release(spark, folder)
    return found.to_pandas().drop_duplicates(["a", "b"]).sort_values(["delta", "a", "b"], ignore_index=True)


def matching(delta: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Lines and columns of a pair of tiles matched by the least change first, each once, as long as any pair is finite."""
    order = np.argsort(delta, axis=None, kind="stable")[: np.count_nonzero(np.isfinite(delta))]
    lines, columns, out = [True] * len(delta), [True] * delta.shape[1], []
    left = min(delta.shape)
    for i, j in zip(*(x.tolist() for x in np.divmod(order, delta.shape[1]))):
        if lines[i] and columns[j]:
            lines[i] = columns[j] = False
            out.append((i, j))
            left -= 1
            if not left:
                break
    return np.array([i for i, _ in out], np.int64), np.array([j for _, j in out], np.int64)


def matched(pairs: pd.DataFrame, k: int, most: int) -> np.ndarray:
    """The cluster that each of ``k`` goes to: pairs by the least change first, each cluster once, at most so many merges."""
    to, free = np.arange(k), np.ones(k, bool)
    for a, b in zip(pairs["a"].tolist(), pairs["b"].tolist()):
        if most <= 0:
            break
        if free[a] and free[b]:
            to[b], free[a], free[b], most = a, False, False, most - 1
    return to


def reduced(tiled: Tiled, labels: Labels, until: int) -> Labels:
    """Matched merges, rises too, side by side in turn until either has at most ``until`` clusters or no pair shares a block; such leftovers are hashed."""
    out = [dense(x) for x in labels]
    blocks = materialise(tiled.blocks((out[0], out[1])), "cocluster-blocks")
    mass = []
    for side, c in ((0, "c"), (1, "d")):
        got = blocks.groupBy(c).agg(F.sum("m").alias("m")).toArrow()
        own = np.zeros(int(out[side].max()) + 1, np.int64)
        own[got[c].to_numpy()] = got["m"].to_numpy()
        mass.append(own)
    open_sides = {0, 1}
    while open_sides:
        for side in sorted(open_sides):
            k = len(mass[side])
            if k <= until:
                open_sides.discard(side)
                continue
            size = np.bincount(out[side], minlength=k)
            to = matched(partners(blocks, side, size, mass[side], len(mass[1 - side])), k, k - until)
            if (to == np.arange(k)).all():
                to = (hashed(np.arange(k), 0) % np.uint64(until)).astype(np.int64)
            to = dense(to)
            out[side] = to[out[side]]
            mass[side] = np.bincount(to, weights=mass[side]).astype(np.int64)
            c = "c" if side == 0 else "d"
            blocks, last = _renamed(blocks, c, to), blocks
            discard(last)
    discard(blocks)
    return out[0], out[1]


def _renamed(blocks: DataFrame, c: str, to: np.ndarray) -> DataFrame:
    shared = blocks.sparkSession.sparkContext.broadcast(to)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            new = {x: batch.column(x).to_numpy() for x in _BLOCKS.names}
            new[c] = shared.value[new[c]]
            yield pa.RecordBatch.from_arrays([pa.array(new[x], t) for x, t in zip(_BLOCKS.names, _BLOCKS.types)], schema=_BLOCKS)

    return materialise(blocks.select(*_BLOCKS.names).mapInArrow(run, "c int, d int, m long").groupBy("c", "d").agg(F.sum("m").alias("m")), "cocluster-blocks")
