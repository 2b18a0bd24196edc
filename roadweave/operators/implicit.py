"""Modularity of a projection that is never written: its edges are products of the vectors.

The weight of a vertex towards a community is the product of its vector with the
sum of the community's vectors, less its own share. So what is stored is the
vectors, the sums and the partition, and both grow with the entries, not with the
pairs. Vertices of equal vectors are one unit from the start wherever parting
them can't raise modularity. Units go through rounds of moves, half of them at a
time; a task takes a tile of them past all tiles of sums. Communities then become
units, and what is left of few enough is finished by the dense kernel.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from typing import NamedTuple

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, functions as F

from ..scratch import discard, materialise, new_path, release
from .modularity import LOCAL_EDGES, LOCAL_VERTICES, _matrix, dense_communities, dense_score, in_one_task
from .tiles import TASKS, Tile, meet, products, rows_of, terms

#: Units of a tile at least and at most.
LEAST, MOST = 500, 16_000

#: A row without feature holds the strength of its unit.
_DEALT = pa.schema([("v", pa.int64()), ("f", pa.int64()), ("w", pa.float64())])
_PLACED = pa.schema([("v", pa.int64()), ("c", pa.int64())])


class Dealt(NamedTuple):
    """Vectors and strengths dealt into tiles in the shared folder."""

    spark: SparkSession
    folder: str
    tiles: int

    @property
    def rows(self) -> DataFrame:
        return self.spark.read.schema("v long, f long, w double, tile int").parquet(self.folder).select("v", "f", "w")


def _deal(entries: DataFrame, n: int) -> Dealt:
    size = min(MOST, max(LEAST, n // 64))
    out = Dealt(entries.sparkSession, new_path(entries.sparkSession, "implicit-tiles"), max(1, -(-n // size)))
    tile = F.pmod(F.xxhash64("v"), F.lit(out.tiles)).cast("int")
    entries.withColumn("tile", tile).repartition(min(out.tiles, TASKS), "tile").write.partitionBy("tile").parquet(out.folder)
    return out


def _read(folder: str, i: int) -> tuple[Tile, np.ndarray]:
    """A tile's vectors, and the strength of each of its vertices in their order."""
    rows = rows_of(folder, i, _DEALT)
    bare = pc.is_null(rows.column("f"))
    strength, own = rows.filter(bare), rows.filter(pc.invert(bare))
    tile = Tile(*(own.column(c).to_numpy() for c in ("v", "f", "w")))
    # A vertex without features is no vertex here; strengths are sums over vertices that have some.
    return tile, strength.column("w").to_numpy()[np.argsort(strength.column("v").to_numpy())]


def _turn(v: np.ndarray, sweep: int) -> np.ndarray:
    """Which half a vertex belongs to, another in each sweep."""
    x = v.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) + np.uint64((sweep + 1) * 0xBF58476D1CE4E5B9 % 2**64)
    x = (x ^ (x >> np.uint64(31))) * np.uint64(0x94D049BB133111EB)
    return (x >> np.uint64(63)).astype(int)


def best_moves(left: Tile, k: np.ndarray, own: np.ndarray, sums: Iterable[tuple[Tile, np.ndarray]], scale: float) -> np.ndarray:
    """The community of most gain for every vertex of ``left``, each from its ``own`` and all others held still.

    ``sums`` are tiles of communities with their strengths; ``scale`` is the
    resolution over the sum of all strengths. Of equal gains staying wins, then
    the least community.
    """
    n = len(left.v)
    square = np.bincount(left.row, weights=left.w * left.w, minlength=n)
    stay, gain, to = np.full(n, -np.inf), np.full(n, -np.inf), own.copy()
    for right, strength in sums:
        if not len(right.v):
            continue
        width = len(right.v)
        place = np.minimum(np.searchsorted(right.v, own), width - 1)
        place = np.where(right.v[place] == own, place, -1)
        for first, cells, key, term in terms(left, right):
            if len(key) * 8 > cells:
                toward = np.bincount(key, weights=term, minlength=cells).reshape(-1, width)
                many = np.arange(first, first + len(toward))
                away = toward <= 0
                toward -= np.outer(scale * k[many], strength)
                home = np.flatnonzero(place[many] >= 0)
                at = many[home]
                stay[at] = toward[home, place[at]] - square[at] + scale * k[at] * k[at]
                away[home, place[at]] = True
                toward[away] = -np.inf
                column = toward.argmax(axis=1)
                most = toward[np.arange(len(toward)), column]
            else:
                by = np.argsort(key, kind="stable")
                key, term = key[by], term[by]
                begin = np.flatnonzero(np.append(True, key[1:] != key[:-1]))
                toward, key = np.add.reduceat(term, begin), key[begin]
                i, j = key // width + first, key % width
                toward = toward - scale * k[i] * strength[j]
                home = place[i] == j
                at = i[home]
                stay[at] = toward[home] - square[at] + scale * k[at] * k[at]
                toward[home] = -np.inf
                start = np.flatnonzero(np.append(True, i[1:] != i[:-1]))
                many = i[start]
                most = np.maximum.reduceat(toward, start)
                hit = np.flatnonzero(toward == np.repeat(most, np.diff(np.append(start, len(i)))))
                column = j[hit[np.unique(i[hit], return_index=True)[1]]]
            most, name = np.round(most, 12), right.v[column]
            better = (most > gain[many]) | ((most == gain[many]) & (name < to[many]))
            better &= np.isfinite(most)
            gain[many[better]], to[many[better]] = most[better], name[better]
    return np.where(gain > np.round(stay, 12), to, own)


def _moved(units: Dealt, placed: str | None, sums: Dealt, total: float, half: int, sweep: int, resolution: float) -> str:
    """The folder of a new partition, with one half of the units at their best community."""
    folder, tiles, others, parts, scale = units.folder, units.tiles, sums.folder, sums.tiles, resolution / total

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in batch.column(0).to_pylist():
                tile, k = _read(folder, i)
                own = tile.v.copy()
                if placed:
                    known = rows_of(placed, i, _PLACED).sort_by("v")
                    own = known.column("c").to_numpy().copy()
                may = _turn(tile.v, sweep) == half
                if may.any():
                    on = may[tile.row]
                    some = Tile(tile.v[tile.row[on]], tile.f[on], tile.w[on])
                    own[may] = best_moves(some, k[may], own[may], (_read(others, j) for j in range(parts)), scale)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(own), i), pa.int32()), pa.array(tile.v), pa.array(own)], names=["tile", "v", "c"])

    path = new_path(units.spark, "implicit-part")
    units.spark.range(0, tiles, 1, min(tiles, TASKS)).mapInArrow(run, "tile int, v long, c long").write.partitionBy("tile").parquet(path)
    return path


def _measured(sums: Dealt, loops: int, total: float, resolution: float) -> tuple[float, int]:
    """Modularity of the communities with these sums, and how many they are."""
    square = F.col("w") * F.col("w")
    of = F.col("f").isNull()
    inner, outer, n = sums.rows.agg(F.sum(F.when(~of, square)), F.sum(F.when(of, square)), F.count(F.when(of, 1))).first()
    return (inner - loops) / total - resolution * outer / total**2, n


def _units(own: DataFrame, *, resolution: float) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Vertices of equal vectors as one, by parent, where that can't lower the best modularity.

    Of unit vectors ``own(parent, v, f, w)``: members ``(parent, v, u)``, vectors
    ``(parent, u, f, w, m)`` of one member with the number of members, and
    strengths ``(parent, u, m, k)`` of one member. Vertices that share no feature
    are in none. With a of its vertices in one community and the rest in another,
    modularity is a square function of a with the leading term
    1 - resolution * k * k / total; where that is not negative, one end is best.
    """
    sums = own.groupBy("parent", "f").agg(F.sum("w").alias("all"), F.count(F.lit(1)).alias("d"))
    met = own.join(sums, ["parent", "f"])
    mark = lambda seed: F.bit_xor(F.xxhash64("f", F.round("w", 12), F.lit(seed)))
    vertex = met.groupBy("parent", "v").agg(F.sum(F.col("w") * F.greatest(F.col("all") - F.col("w"), F.lit(0.0))).alias("k"), F.max("d").alias("d"), F.count(F.lit(1)).alias("n"), mark(1).alias("x"), mark(2).alias("y"))
    vertex = materialise(vertex.where("d > 1").drop("d"), "implicit-vertices")
    total = vertex.groupBy("parent").agg(F.sum("k").alias("total"))
    classes = vertex.groupBy("parent", "n", "x", "y").agg(F.min("v").alias("u"), F.max("k").alias("most")).join(total, "parent")
    whole = classes.select("parent", "n", "x", "y", "u", (F.lit(resolution) * F.col("most") * F.col("most") <= F.col("total")).alias("whole"))
    members = vertex.join(whole, ["parent", "n", "x", "y"]).select("parent", "v", "k", F.when(F.col("whole"), F.col("u")).otherwise(F.col("v")).alias("u"))
    members = materialise(members, "implicit-members")
    strength = materialise(members.groupBy("parent", "u").agg(F.count(F.lit(1)).alias("m"), F.max("k").alias("k")), "implicit-strength")
    vectors = own.withColumnRenamed("v", "u").join(strength.select("parent", "u", "m"), ["parent", "u"]).select("parent", "u", "f", "w", "m")
    discard(vertex)
    return members.select("parent", "v", "u"), vectors, strength


def _bound(local_edges: int, local_vertices: int) -> int:
    """Vertices that a task takes even where all of them are joined."""
    return min(local_vertices, int((2 * local_edges) ** 0.5))


def communities(vectors: DataFrame, *, resolution: float = 1.0, local_edges: int = LOCAL_EDGES, local_vertices: int = LOCAL_VERTICES, max_levels: int = 10, max_sweeps: int = 8, tol: float = 1e-4) -> DataFrame:
    """``(v, c)`` for every vertex of unit ``vectors(v, f, w)``, w > 0, that shares a feature; ``c`` is the least vertex of its community."""
    own = materialise(vectors.select(F.lit(0).alias("parent"), F.col("v").cast("long").alias("v"), F.col("f").cast("long").alias("f"), F.col("w").cast("double").alias("w")), "implicit-vectors")
    members, entries, strength = _units(own, resolution=resolution)
    vertices, n, total = strength.agg(F.sum("m"), F.count(F.lit(1)), F.sum(F.col("m") * F.col("k"))).first()
    part = members.select("v", F.col("u").alias("c"))
    if not n:
        return part
    whole = entries.select(F.col("u").alias("v"), "f", (F.col("w") * F.col("m")).alias("w"))
    units = _deal(whole.unionByName(strength.select(F.col("u").alias("v"), F.lit(None).cast("long").alias("f"), (F.col("k") * F.col("m")).alias("w"))), n)
    bound = _bound(local_edges, local_vertices)
    for _ in range(max_levels):
        if n <= bound:
            break
        placed, sums, left = _spread(units, n, vertices, total, resolution, max_sweeps, tol)
        if placed is None:
            break
        level = units.spark.read.schema("v long, c long, tile int").parquet(placed).select(F.col("v").alias("c"), F.col("c").alias("up"))
        part = materialise(part.join(level, "c").select("v", F.col("up").alias("c")), "implicit-level")
        units, done, n = _deal(sums.rows, left), (units.folder, sums.folder, placed), left
        for path in done:
            release(units.spark, path)
    if n <= bound:
        features = units.rows.where("f is not null")
        size = part.groupBy("c").agg(F.count(F.lit(1)).alias("d"))
        loops = features.groupBy("v").agg(F.sum(F.col("w") * F.col("w")).alias("square")).join(size.withColumnRenamed("c", "v"), "v")
        loops = loops.select(F.col("v").alias("a"), F.col("v").alias("b"), (F.greatest(F.col("square") - F.col("d"), F.lit(0.0)) / 2).alias("omega"))
        top = in_one_task(products(features).select("a", "b", "omega").unionByName(loops).repartition(1), resolution=resolution)
        part = part.join(top.select(F.col("v").alias("c"), F.col("c").alias("up")), "c").select("v", F.col("up").alias("c"))
    return part.join(part.groupBy("c").agg(F.min("v").alias("least")), "c").select("v", F.col("least").alias("c"))


def _spread(units: Dealt, n: int, vertices: int, total: float, resolution: float, max_sweeps: int, tol: float) -> tuple[str | None, Dealt, int]:
    """One level of moves from single units: the folder of the partition, none if nothing moved, the communities' sums and number."""
    placed, sums, left = None, units, n
    now, _ = _measured(units, vertices, total, resolution)
    for sweep in range(max_sweeps):
        before = now
        for half in (0, 1):
            new = _moved(units, placed, sums, total, half, sweep, resolution)
            part = units.spark.read.schema("v long, c long, tile int").parquet(new).select("v", "c")
            added = _deal(units.rows.join(part, "v").groupBy(F.col("c").alias("v"), "f").agg(F.sum("w").alias("w")), left)
            then, k = _measured(added, vertices, total, resolution)
            better = then > now
            old = (placed, sums.folder) if better else (new, added.folder)
            if better:
                placed, sums, now, left = new, added, then, k
            for path in old:
                if path and path != units.folder:
                    release(units.spark, path)
        if now - before < tol:
            break
    return placed, sums, left


def _split(frame: pd.DataFrame, min_size: int, resolution: float) -> pd.DataFrame:
    """The sub-communities of the units of one parent, or itself where they gain nothing."""
    tile = Tile(frame["u"].to_numpy(), frame["f"].to_numpy(), frame["w"].to_numpy() * frame["m"].to_numpy())
    m = frame.groupby("u")["m"].first().to_numpy()
    square = np.bincount(tile.row, weights=tile.w * tile.w, minlength=len(tile.v))
    edges = [pd.DataFrame({"a": tile.v, "b": tile.v, "omega": np.maximum(square - m, 0.0) / 2})]
    edges += [b.to_pandas()[["a", "b", "omega"]] for b in meet(tile, tile, True, -np.inf)]
    a = _matrix(pd.concat(edges), tile.v)
    label = dense_communities(a, resolution=resolution) if m.sum() >= min_size else np.zeros(len(tile.v), dtype=int)
    if dense_score(a, label, resolution) <= 1e-9:
        label = np.zeros(len(tile.v), dtype=int)
    _, label = np.unique(label, return_inverse=True)
    first = np.full(label.max() + 1, np.iinfo(np.int64).max)
    np.minimum.at(first, label, tile.v)
    return pd.DataFrame({"parent": int(frame["parent"].iloc[0]), "u": tile.v, "cluster": first[label]})


def nested(vectors: DataFrame, *, max_depth: int = 2, min_size: int = 3, resolution: float = 1.0, local_edges: int = LOCAL_EDGES, local_vertices: int = LOCAL_VERTICES) -> DataFrame:
    """``(v, level, cluster, parent)`` as :func:`hierarchy.nested` gives them, of unit ``vectors(v, f, w)``."""
    limits = {"resolution": resolution, "local_edges": local_edges, "local_vertices": local_vertices}
    own = materialise(vectors.select("v", "f", "w"), "nested-vectors")
    spark = own.sparkSession
    level = communities(own, **limits).select("v", F.lit(1).alias("level"), F.col("c").alias("cluster"), F.lit(None).cast("long").alias("parent"))
    level = materialise(level, "nested-level")
    out = level
    for depth in range(2, max_depth + 1):
        of = level.select("v", F.col("cluster").alias("parent"))
        inner = materialise(own.join(of, "v").select("parent", "v", "f", "w"), "nested-inner")
        members, entries, _ = _units(inner, resolution=resolution)
        entries = materialise(entries, "nested-units")
        sizes = entries.groupBy("parent").agg(F.count(F.lit(1)).alias("entries"), F.count_distinct("u").alias("units"))
        wide = materialise(sizes.where((F.col("units") > _bound(local_edges, local_vertices)) | (F.col("entries") > local_edges)).select("parent"), "nested-wide")
        # What is left in a group fits a task by the counts above.
        small = entries.join(wide, "parent", "left_anti")
        found = small.groupBy("parent").applyInPandas(lambda f: _split(f, min_size, resolution), "parent long, u long, cluster long")
        found = members.join(found, ["parent", "u"]).select("v", "cluster")
        for row in wide.toLocalIterator():
            part = communities(inner.where(F.col("parent") == row["parent"]), **limits)
            found = found.unionByName(materialise(part.select("v", F.col("c").alias("cluster")), "nested-wide-part"))
        level = of.join(found, "v", "left").select("v", F.lit(depth).alias("level"), F.coalesce("cluster", "parent").alias("cluster"), "parent")
        level = materialise(level, "nested-level")
        out = out.unionByName(level)
    return out
