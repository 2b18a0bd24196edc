"""Direct co-clustering of the bipartite graph, with no number of clusters given.

A graph of few enough vertices is solved in one task from the finest model. A
larger one starts from as many hashed clusters a side as the square root of its
edges, with vertices of equal neighbours in the same one. Rounds of merges of
matched pairs leave at most ``LOCAL_START`` a
side; passes of exchanges over all edges lower the cost, the small matrix of blocks
is merged in one task, and exchanges over all edges finish. Up to ``labelled.LABELS``
vertices these steps send every vertex's label to the tasks (``labelled.py``); above, they join. Restarts disturb
the best model more and more, over all vertices, and keep whatever costs less. The
one-block model is always a candidate, so a result never costs more than it.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, Window, functions as F

from ..functions.scalar import log_factorial, log_partitions
from ..model import BipartiteGraph
from ..scratch import discard, materialise
from . import criterion, greedy, kernel, labelled, mutual

#: Of the dense kernel: cells of rows by columns, vertices of a side, and edges that one task takes.
LOCAL_CELLS, LOCAL_SIDE, LOCAL_EDGES = 4_000_000, 2_500, 2_000_000
#: Clusters a side that the exchanges and the merging task of a larger graph take; their blocks are sent to every task.
LOCAL_START = 500


@dataclass
class CoClustering:
    """A fitted model: ``row_part(t, ct)``, ``col_part(s, cs)``, ``trace`` of the search; clusters are named by their least vertex."""

    graph: BipartiteGraph
    row_part: DataFrame
    col_part: DataFrame
    trace: DataFrame
    #: Its cost and that of one block, where the search has counted both.
    known: tuple[float, float] | None = None

    @property
    def block(self) -> DataFrame:
        return mutual.crossed(self.graph, self.row_part, self.col_part)

    def cost(self) -> DataFrame:
        return criterion.cost(self.graph, self.row_part, self.col_part)

    def compression(self) -> DataFrame:
        """1 less the cost over that of one block."""
        if self.known:
            known = self.graph.traversal.sparkSession.range(1).select(*[F.lit(x).alias(c) for x, c in zip(self.known, ("cost", "null_cost"))])
            return known.withColumn("compression", 1 - F.col("cost") / F.col("null_cost"))
        own = self.cost().select(F.col("total").alias("cost"))
        null = criterion.cost(self.graph, *criterion.null_model(self.graph)).select(F.col("total").alias("null_cost"))
        return own.crossJoin(null).withColumn("compression", 1 - F.col("cost") / F.col("null_cost"))


def _local(frame: pd.DataFrame, *, seed: int, restarts: int, stop: str, refine: bool, merge: bool) -> tuple[pd.DataFrame, pd.DataFrame]:
    """Labels ``(side, v, c)`` and the search's trace, of a whole small graph."""
    ts, t = np.unique(frame["t"].to_numpy(), return_inverse=True)
    ss, s = np.unique(frame["s"].to_numpy(), return_inverse=True)
    n = frame["n"].to_numpy().astype(np.int64)
    best = kernel.descend(kernel.Model(t, s, n, np.arange(len(ts)), np.arange(len(ss))), stop=stop, refine=refine, merge=merge)
    trace = [{"step": "merge", **x} for x in best.trace]
    trace.append({"step": "start", "round": 0, "cost": best.cost})
    strength = 1
    for k in range(restarts):
        other = kernel.restart(t, s, n, best, seed=seed + k, strength=strength, stop=stop)
        better = other.cost < best.cost - 1e-9
        best, strength = (other, 1) if better else (best, strength + 1)
        trace.append({"step": "restart", "round": k + 1, "cost": best.cost})
    null = kernel.null_cost(t, s, n, len(ts), len(ss))
    if stop == "to_null" and null < best.cost:
        best = kernel.Found(np.zeros(len(ts), int), np.zeros(len(ss), int), null, [])
    trace.append({"step": "end", "round": restarts, "cost": best.cost})
    parts = []
    for side, vertices, label in (("t", ts, best.rows), ("s", ss, best.columns)):
        _, label = np.unique(label, return_inverse=True)
        first = np.full(label.max() + 1, np.iinfo(np.int64).max)
        np.minimum.at(first, label, vertices)
        parts.append(pd.DataFrame({"side": side, "v": vertices, "c": first[label]}))
    return pd.concat(parts), pd.DataFrame(trace)


_TRACE = {"step": "string", "round": "long", "side": "string", "a": "long", "b": "long", "delta": "double", "cost": "double", "pairs": "long"}


def _solve(traversal: DataFrame, **options) -> DataFrame:
    """Labels and trace of a small graph, as one table from one task."""

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held = list(frames)
        if not held or not sum(map(len, held)):
            return
        parts, trace = _local(pd.concat(held), **options)
        trace = trace.reindex(columns=list(_TRACE)).rename(columns={"side": "on"})
        out = pd.concat([parts.assign(kind="part"), trace.assign(kind="trace")])
        yield out.reindex(columns=["kind", "side", "v", "c", "step", "round", "on", "a", "b", "delta", "cost", "pairs"]).astype({c: "Int64" for c in ("v", "c", "round", "a", "b", "pairs")})

    schema = "kind string, side string, v long, c long, step string, round long, on string, a long, b long, delta double, cost double, pairs long"
    return materialise(traversal.select("t", "s", "n").coalesce(1).mapInPandas(run, schema), "cocluster")


def _unpacked(solved: DataFrame) -> tuple[DataFrame, DataFrame, DataFrame]:
    of = lambda side: solved.where((F.col("kind") == "part") & (F.col("side") == side))
    trace = solved.where("kind = 'trace'").select("step", "round", F.col("on").alias("side"), "a", "b", "delta", "cost", "pairs")
    return of("t").select(F.col("v").alias("t"), F.col("c").alias("ct")), of("s").select(F.col("v").alias("s"), F.col("c").alias("cs")), trace


def fit(graph: BipartiteGraph, *, seed: int = 42, restarts: int = 4, stop: str = "to_null", refine: bool = True, merge: bool = True, passes: int = 4, local_cells: int = LOCAL_CELLS, start: int | None = None) -> CoClustering:
    """Best model found. ``stop``, ``refine``, ``merge`` and ``restarts`` switch the parts of the search for ablations."""
    own = BipartiteGraph(materialise(graph.traversal, "cocluster-graph"))
    rows, columns = (own.traversal.select(v).distinct().count() for v in ("t", "s"))
    edges = own.traversal.count()
    if rows * columns <= local_cells and max(rows, columns) <= LOCAL_SIDE and edges <= LOCAL_EDGES:
        return CoClustering(own, *_unpacked(_solve(own.traversal, seed=seed, restarts=restarts, stop=stop, refine=refine, merge=merge)))
    steps = (_Labelled if rows + columns <= labelled.LABELS else _Joined)(own, edges, passes, {"stop": stop, "refine": refine, "merge": merge})
    parts = steps.start(start or max(2, int(math.sqrt(edges))), seed)
    trace: list[tuple[str, int, float]] = []

    def descended(parts, seed: int):
        parts = steps.merged(steps.exchanged(parts, seed, trace), seed)
        trace.append(("merge", 0, steps.total(parts)))
        if refine:
            parts = steps.exchanged(parts, seed, trace)
        return parts, trace[-1][2]

    parts, cost = descended(parts, seed)
    strength = 1
    for k in range(restarts):
        other, then = descended(steps.disturbed(parts, strength, seed + k + 1), seed + k + 1)
        better = then < cost - 1e-6
        parts, cost, strength = (other, then, 1) if better else (parts, cost, strength + 1)
        trace.append(("restart", k + 1, cost))
    null = steps.null()
    null_cost = steps.total(null)
    if stop == "to_null" and null_cost < cost:
        parts, cost = null, null_cost
        trace.append(("null", 0, null_cost))
    frame = own.traversal.sparkSession.createDataFrame(trace, "step string, round long, cost double")
    return CoClustering(own, *_named(steps.tables(parts)), frame.select("step", "round", *[F.lit(None).cast(_TRACE[c]).alias(c) for c in ("side", "a", "b", "delta")], "cost", F.lit(None).cast("long").alias("pairs")), (cost, null_cost))


class _Joined:
    """Steps of the search by joins, for graphs of more vertices than the driver holds labels of."""

    def __init__(self, graph: BipartiteGraph, edges: int, passes: int, options: dict):
        self.graph, self.passes, self.options, self.fixed = graph, passes, options, _fixed(graph)

    def start(self, k: int, seed: int):
        parts = hashed_start(self.graph, k, seed=seed)
        return _bounded(greedy.reduced(self.graph, parts, LOCAL_START)) if k > LOCAL_START else parts

    def exchanged(self, parts, seed: int, trace: list):
        return _exchanges(self.graph, parts, self.passes, seed, trace, self.fixed)

    def merged(self, parts, seed: int):
        return _merged_blocks(self.graph, parts, seed=seed, **self.options)

    def disturbed(self, parts, strength: int, seed: int):
        return _disturbed(parts, strength, seed)

    def null(self):
        return criterion.null_model(self.graph)

    def total(self, parts) -> float:
        return _total(self.graph, parts)

    def tables(self, parts):
        return parts


class _Labelled:
    """The same steps with a label of every vertex on the driver; a model is both sides' labels and the matrix of their blocks."""

    def __init__(self, graph: BipartiteGraph, edges: int, passes: int, options: dict):
        self.tiled, self.passes, self.options = labelled.Tiled.of(graph, edges), passes, options
        self.fixed = self.tiled.fixed()

    def _model(self, labels):
        labels = [labelled.dense(x) for x in labels]
        return labels, labelled.matrix_of(self.tiled.blocks((labels[0], labels[1])), (int(labels[0].max()) + 1, int(labels[1].max()) + 1))

    def start(self, k: int, seed: int):
        labels = self.tiled.collected(hashed_start(self.tiled.graph, k, seed=seed))
        return self._model(labelled.reduced(self.tiled, labels, LOCAL_START) if k > LOCAL_START else labels)

    def exchanged(self, model, seed: int, trace: list):
        for step in range(self.passes):
            now = cost = self.total(model)
            for side in (0, 1):
                for half in (0, 1):
                    labels, matrix = model
                    label, turned = self.tiled.moves(side, (labels[0], labels[1]), matrix if side == 0 else matrix.T, half, seed + step)
                    alive = np.flatnonzero(np.bincount(label, minlength=len(turned)))
                    place = np.zeros(len(turned), np.int32)
                    place[alive] = np.arange(len(alive))
                    label, turned = place[label], np.ascontiguousarray(turned[alive])
                    trial = ([label, labels[1]], turned) if side == 0 else ([labels[0], label], np.ascontiguousarray(turned.T))
                    then = self.total(trial)
                    if then < now - 1e-6:
                        model, now = trial, then
            trace.append(("exchange", step + 1, now))
            if now >= cost - 1e-6:
                break
        return model

    def merged(self, model, seed: int):
        labels, matrix = model
        t, s = np.nonzero(matrix)
        spark = self.tiled.graph.traversal.sparkSession
        block = spark.createDataFrame(pa.table({"t": pa.array(t, pa.int64()), "s": pa.array(s, pa.int64()), "n": pa.array(matrix[t, s], pa.int64())}))
        out = []
        for part, label in zip(_unpacked(_solve(block, seed=seed, restarts=0, **self.options)), labels):
            got = part.toArrow()
            to = np.zeros(len(got), np.int64)
            to[got.column(0).to_numpy()] = got.column(1).to_numpy()
            out.append(labelled.dense(to))
        merged = np.zeros((int(out[0].max()) + 1, int(out[1].max()) + 1), np.int64)
        np.add.at(merged, (out[0][t], out[1][s]), matrix[t, s])
        return [to[label] for to, label in zip(out, labels)], merged

    def disturbed(self, model, strength: int, seed: int):
        out = []
        for label, k in zip(model[0], model[1].shape):
            places = np.arange(len(label))
            some = labelled.hashed(places, seed) % np.uint64(100) < min(100, 15 * strength)
            to = labelled.hashed(places, seed + 7919) % np.uint64(min(k + 1 + strength, LOCAL_START))
            out.append(np.where(some, to.astype(np.int64), label))
        return self._model(out)

    def null(self):
        return [np.zeros(n, np.int32) for n in self.tiled.sizes()], np.array([[self.visits]])

    @property
    def visits(self) -> int:
        return int(self.tiled.graph.traversal.agg(F.sum("n")).first()[0])

    def total(self, model) -> float:
        labels, matrix = model
        sizes = [np.bincount(x, minlength=k) for x, k in zip(labels, matrix.shape)]
        return Blocks(np.arange(len(matrix)), np.arange(matrix.shape[1]), matrix, *sizes).cost(self.fixed)

    def tables(self, model):
        parts = self.tiled.parts((model[0][0], model[0][1]))
        self.tiled.release()
        return parts


def _exchanges(graph: BipartiteGraph, parts: tuple[DataFrame, DataFrame], passes: int, seed: int, trace: list[tuple[str, int, float]], fixed: float) -> tuple[DataFrame, DataFrame]:
    blocks = None
    for step in range(passes):
        parts, value, better, blocks = exchange_pass(graph, parts, seed=seed + step, fixed=fixed, blocks=blocks)
        trace.append(("exchange", step + 1, value))
        if not better:
            break
    return parts


def _merged_blocks(graph: BipartiteGraph, parts: tuple[DataFrame, DataFrame], **options) -> tuple[DataFrame, DataFrame]:
    """Partitions after the merges of their blocks: a block is one edge between clusters, and merging those is merging clusters."""
    block = mutual.crossed(graph, *parts).select(F.col("ct").alias("t"), F.col("cs").alias("s"), F.col("m").alias("n"))
    rows, columns, _ = _unpacked(_solve(block, restarts=0, **options))
    rows = parts[0].join(rows.select(F.col("t").alias("ct"), F.col("ct").alias("to")), "ct").select("t", F.col("to").alias("ct"))
    columns = parts[1].join(columns.select(F.col("s").alias("cs"), F.col("cs").alias("to")), "cs").select("s", F.col("to").alias("cs"))
    return materialise(rows, "cocluster-rows"), materialise(columns, "cocluster-columns")


def _bounded(parts: tuple[DataFrame, DataFrame]) -> tuple[DataFrame, DataFrame]:
    """At most ``LOCAL_START`` clusters a side: merges end above it where clusters share nothing, and hashes go on."""
    out = []
    for part, v, c in zip(parts, ("t", "s"), ("ct", "cs")):
        many = part.select(c).distinct().count() > LOCAL_START
        out.append(materialise(part.withColumn(c, F.pmod(F.xxhash64(c), F.lit(LOCAL_START))), "cocluster-start") if many else part)
    return out[0], out[1]


def _disturbed(parts: tuple[DataFrame, DataFrame], strength: int, seed: int) -> tuple[DataFrame, DataFrame]:
    """A hashed share of either side's vertices, growing with ``strength``, in random clusters, some of them new."""
    out = []
    for part, v, c in zip(parts, ("t", "s"), ("ct", "cs")):
        names = part.select(c).distinct()
        ranked = names.withColumn("i", F.row_number().over(Window.orderBy(c)) - 1)
        k = min(names.count() + 1 + strength, LOCAL_START)
        some = F.pmod(F.xxhash64(v, F.lit(seed)), F.lit(100)) < min(100, 15 * strength)
        # Clusters are at most LOCAL_START here.
        moved = part.join(F.broadcast(ranked), c).select(v, F.when(some, F.pmod(F.xxhash64(v, F.lit(seed + 7919)), F.lit(k))).otherwise(F.col("i").cast("long")).alias(c))
        out.append(materialise(moved, "cocluster-disturbed"))
    return out[0], out[1]


def _total(graph: BipartiteGraph, parts: tuple[DataFrame, DataFrame]) -> float:
    return criterion.cost(graph, *parts).first()["total"]


def _named(parts: tuple[DataFrame, DataFrame]) -> tuple[DataFrame, DataFrame]:
    """Clusters named by their least vertex."""
    rows, columns = parts
    least = lambda p, v, c: p.join(p.groupBy(c).agg(F.min(v).alias("least")), c).select(v, F.col("least").alias(c))
    return least(rows, "t", "ct"), least(columns, "s", "cs")


def hashed_start(graph: BipartiteGraph, k: int, *, seed: int) -> tuple[DataFrame, DataFrame]:
    """At most ``k`` clusters a side, by the vertex's least hashed neighbour: vertices of like neighbours often share it."""

    def side(v: str, u: str, c: str) -> DataFrame:
        hashed = F.xxhash64(u, F.lit(seed))
        own = graph.traversal.groupBy(v).agg(F.min(hashed).alias("h"))
        return materialise(own.select(v, F.pmod(F.xxhash64("h"), F.lit(k)).alias(c)), "cocluster-start")

    return side("t", "s", "ct"), side("s", "t", "cs")


def matched_start(graph: BipartiteGraph) -> tuple[DataFrame, DataFrame]:
    """Vertices with the same neighbours and visits in one cluster, each side by itself."""

    def side(v: str, u: str, c: str) -> DataFrame:
        signature = graph.traversal.groupBy(v).agg(F.sum(F.xxhash64(u, "n").cast("decimal(38,0)")).alias("a"), F.count(F.lit(1)).alias("d"))
        first = signature.groupBy("a", "d").agg(F.min(v).alias(c))
        return signature.join(first, ["a", "d"]).select(v, c)

    return side("t", "s", "ct"), side("s", "t", "cs")


@dataclass
class Blocks:
    """Visits by block, with each cluster's vertices: all that the cost needs of two partitions."""

    rows: np.ndarray
    columns: np.ndarray
    matrix: np.ndarray
    row_size: np.ndarray
    col_size: np.ndarray

    def turned(self) -> Blocks:
        return Blocks(self.columns, self.rows, self.matrix.T, self.col_size, self.row_size)

    def cost(self, fixed: float) -> float:
        """The total of :func:`criterion.cost`; ``fixed`` is ln n! of every vertex's visits, summed."""
        f, m = kernel.log_factorials, int(self.matrix.sum())
        choose = lambda n, k: f(n) - f(k) - f(n - k)
        t, s = int(self.row_size.sum()), int(self.col_size.sum())
        cells = len(self.rows) * len(self.columns)
        out = math.log(t) + math.log(s) + log_partitions(t, len(self.rows)) + log_partitions(s, len(self.columns))
        out += float(choose(np.array(m + cells - 1), np.array(cells - 1)) + f(np.array(m)) - f(self.matrix).sum()) - fixed
        for size, mass in ((self.row_size, self.matrix.sum(axis=1)), (self.col_size, self.matrix.sum(axis=0))):
            out += float((choose(mass + size - 1, size - 1) + f(mass)).sum())
        return out


def _fixed(graph: BipartiteGraph) -> float:
    """ln n! of the visits of every vertex, which no partition changes."""
    of = lambda v: graph.traversal.groupBy(v).agg(F.sum("n").alias("n")).agg(F.sum(log_factorial(F.col("n"))))
    return sum(of(v).first()[0] or 0.0 for v in ("t", "s"))


def _cells(graph: BipartiteGraph, own: DataFrame, other: DataFrame, side: str) -> DataFrame:
    """``(v, c, cells)``: each vertex of a side in one row, with its cluster and its visits by cluster of the other side."""
    v, c, u, d = ("t", "ct", "s", "cs") if side == "t" else ("s", "cs", "t", "ct")
    met = graph.traversal.select(v, u, "n").join(other.select(u, d), u).groupBy(F.col(v).alias("v"), F.col(d).cast("long").alias("d")).agg(F.sum("n").alias("n"))
    listed = met.groupBy("v").agg(F.collect_list(F.struct("d", "n")).alias("cells"))
    return materialise(listed.join(own.select(F.col(v).alias("v"), F.col(c).cast("long").alias("c")), "v").select("v", "c", "cells"), "cocluster-cells")


def _blocks(table: DataFrame) -> Blocks:
    """The blocks of a table of :func:`_cells` in one job: a cell without cluster counts the vertex."""
    one = F.array(F.struct(F.lit(None).cast("long").alias("d"), F.lit(1).cast("long").alias("n")))
    flat = table.select("c", F.explode(F.concat("cells", one)).alias("x")).groupBy("c", "x.d").agg(F.sum("x.n").alias("n")).toPandas()
    size = flat[flat["d"].isna()].set_index("c")["n"]
    met = flat[flat["d"].notna()]
    names, line = np.unique(met["c"].to_numpy(np.int64), return_inverse=True)
    others, cell = np.unique(met["d"].astype("int64").to_numpy(), return_inverse=True)
    matrix = np.zeros((len(names), len(others)), dtype=np.int64)
    matrix[line, cell] = met["n"].to_numpy(np.int64)
    return Blocks(names, others, matrix, size.reindex(names).to_numpy(np.int64), np.zeros(len(others), np.int64))


def exchange_pass(graph: BipartiteGraph, parts: tuple[DataFrame, DataFrame], *, seed: int, fixed: float, blocks: Blocks | None = None) -> tuple[tuple[DataFrame, DataFrame], float, bool, Blocks]:
    """One pass of exchanges over all edges: halves of either side in turn, each kept only if the cost falls.

    Edges are met with the other side's clusters once for both halves. The blocks
    that come back after a half give the cost, and the next half starts from them;
    those of ``parts`` are counted where they are not given.
    """
    now, better = None, False
    for side in ("t", "s"):
        v, c = ("t", "ct") if side == "t" else ("s", "cs")
        table = _cells(graph, *(parts if side == "t" else parts[::-1]), side)
        if blocks is None:
            blocks = _blocks(table)
            counted = parts[1].groupBy("cs").agg(F.count(F.lit(1)).alias("size")).toPandas().set_index("cs")["size"]
            blocks.col_size = counted.reindex(blocks.columns).to_numpy(np.int64)
        now = blocks.cost(fixed) if now is None else now
        for half in (0, 1):
            new = _exchanged(table, blocks, half, seed)
            trial = _blocks(new)
            trial.col_size = blocks.col_size
            then = trial.cost(fixed)
            if then < now - 1e-6:
                table, new, blocks, now, better = new, table, trial, then, True
            discard(new)
        part = table.select(F.col("v").alias(v), F.col("c").alias(c))
        parts = (part, parts[1]) if side == "t" else (parts[0], part)
        blocks = blocks.turned()
    return parts, now, better, blocks


def _exchanged(table: DataFrame, blocks: Blocks, half: int, seed: int) -> DataFrame:
    """A table of :func:`_cells` with the vertices of one half at their best cluster, others held still.

    The blocks, bounded by the number of start clusters squared, go to every task as a matrix.
    """
    mass = blocks.matrix.sum(axis=1)
    shared = table.sparkSession.sparkContext.broadcast((blocks.rows, blocks.columns, blocks.matrix, blocks.row_size, mass))

    def run(frames: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names, others, matrix, size, mass = shared.value
        for batch in frames:
            to = batch.column("c").to_numpy().copy()
            may = batch.column("may").to_numpy(zero_copy_only=False)
            cells = batch.column("cells").filter(pa.array(may))
            flat, edge = cells.flatten(), np.concatenate([[0], np.cumsum(pc.list_value_length(cells).to_numpy())]).astype(int)
            at, n = np.searchsorted(others, flat.field("d").to_numpy()), flat.field("n").to_numpy()
            lines = np.searchsorted(names, to[may])
            rows = [(int(k), at[i:j], n[i:j]) for k, i, j in zip(lines, edge[:-1], edge[1:])]
            if rows:
                to[may] = names[kernel.best_clusters(matrix, size, mass, rows)]
            yield pa.RecordBatch.from_arrays([batch.column("v"), pa.array(to, pa.int64()), batch.column("cells")], names=["v", "c", "cells"])

    may = F.pmod(F.xxhash64("v", F.lit(seed)), F.lit(2)) == half
    return materialise(table.withColumn("may", may).mapInArrow(run, table.schema), "cocluster-exchange")


def coarsen(model: CoClustering, k_t: int, k_s: int) -> DataFrame:
    """``(side, v, c)`` with at most ``k_t`` and ``k_s`` clusters by the cheapest merges, rises allowed."""
    block = model.block.select(F.col("ct").alias("t"), F.col("cs").alias("s"), F.col("m").alias("n"))

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        frame = pd.concat(list(frames))
        ts, t = np.unique(frame["t"].to_numpy(), return_inverse=True)
        ss, s = np.unique(frame["s"].to_numpy(), return_inverse=True)
        own = kernel.Model(t, s, frame["n"].to_numpy().astype(np.int64), np.arange(len(ts)), np.arange(len(ss)))
        pairs = own._pairs()
        for side, of, k in (("t", own.rows, k_t), ("s", own.columns, k_s)):
            while of.k > k:
                delta = pairs[side]
                a, b = sorted(divmod(int(delta.argmin()), len(delta)))
                own._merge(side, a, b, pairs)
        for side, vertices, of in (("t", ts, own.rows), ("s", ss, own.columns)):
            yield pd.DataFrame({"side": side, "v": vertices, "c": vertices[of.label]})

    small = block.coalesce(1).mapInPandas(run, "side string, v long, c long")
    rows = model.row_part.join(small.where("side = 't'").select(F.col("v").alias("ct"), "c"), "ct").select(F.lit("t").alias("side"), F.col("t").alias("v"), "c")
    columns = model.col_part.join(small.where("side = 's'").select(F.col("v").alias("cs"), "c"), "cs").select(F.lit("s").alias("side"), F.col("s").alias("v"), "c")
    return rows.unionByName(columns)


def assign(model: CoClustering, new: BipartiteGraph) -> DataFrame:
    """``(t, ct)`` for all new trajectories: the cluster whose visits make theirs most likely.

    Unknown segments tell nothing; a trajectory of unknown segments alone goes to
    the cluster with the most visits, of equal ones the least.
    """
    block = model.block
    columns = block.agg(F.count_distinct("cs").alias("k"))
    known = block.withColumn("p", F.col("m") / F.sum("m").over(Window.partitionBy("ct")))
    mine = new.traversal.join(model.col_part, "s").groupBy("t", "cs").agg(F.sum("n").alias("n"))
    clusters = block.select("ct").distinct()
    # Blocks are bounded by the model, not by the data to be assigned.
    pairs = mine.crossJoin(F.broadcast(clusters)).join(F.broadcast(known.select("ct", "cs", "p")), ["ct", "cs"], "left").crossJoin(F.broadcast(columns))
    score = F.sum(F.col("n") * F.ln(F.coalesce("p", F.lit(0.0)) * 0.999 + 0.001 / F.col("k")))
    best = pairs.groupBy("t", "ct").agg(F.round(score, 9).alias("score")).groupBy("t").agg(F.max(F.struct("score", (-F.col("ct")).alias("back"))).alias("best"))
    of = best.select("t", (-F.col("best.back")).alias("ct"))
    prior = block.groupBy("ct").agg(F.sum("m").alias("mass")).agg(F.max(F.struct("mass", (-F.col("ct")).alias("back"))).alias("most"))
    every = new.traversal.select("t").distinct().join(of, "t", "left").crossJoin(F.broadcast(prior))
    return every.select("t", F.coalesce("ct", -F.col("most.back")).alias("ct"))


def fit_sampled(graph: BipartiteGraph, *, share: float, seed: int = 42, **options) -> DataFrame:
    """``(t, ct)`` of all trajectories from a model of a hashed share of them: the way for graphs that fitting can't take whole."""
    chosen = F.pmod(F.xxhash64("t", F.lit(seed)), F.lit(1_000_000)) < int(share * 1_000_000)
    model = fit(BipartiteGraph(graph.traversal.where(chosen)), seed=seed, **options)
    return model.row_part.unionByName(assign(model, BipartiteGraph(graph.traversal.where(~chosen))))


def search(spark: SparkSession, graph: BipartiteGraph, *, restarts: int = 8, seed: int = 42, stop: str = "to_null") -> DataFrame:
    """Independent restarts in parallel, a task each: ``(restart, rows, columns, cost)``; the graph must fit a task."""
    if graph.traversal.limit(LOCAL_EDGES + 1).count() > LOCAL_EDGES:
        raise ValueError(f"parallel restarts take at most {LOCAL_EDGES} edges")
    frame = graph.traversal.select("t", "s", "n").toPandas()
    shared = spark.sparkContext.broadcast((np.unique(frame["t"], return_inverse=True)[1], np.unique(frame["s"], return_inverse=True)[1], frame["n"].to_numpy().astype(np.int64)))

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        t, s, n = shared.value
        for frame in frames:
            for i in frame["id"]:
                rng = np.random.default_rng(seed + int(i))
                k = [max(2, int(round(math.sqrt(x) * rng.uniform(0.5, 2)))) for x in (t.max() + 1, s.max() + 1)]
                labels = [np.arange(x) if not i else rng.integers(0, q, x) for x, q in zip((t.max() + 1, s.max() + 1), k)]
                found = kernel.descend(kernel.Model(t, s, n, *labels), stop=stop)
                yield pd.DataFrame({"restart": [i], "rows": [len(set(found.rows))], "columns": [len(set(found.columns))], "cost": [found.cost]})

    return spark.range(0, restarts, 1, restarts).mapInPandas(run, "restart long, rows long, columns long, cost double")


def alternate(graph: BipartiteGraph, k_t: int, k_s: int, *, seed: int = 42, rounds: int = 10) -> tuple[DataFrame, DataFrame]:
    """The rival with fixed numbers of clusters: each side in turn goes to the cluster of least divergence."""
    parts = hashed_start(graph, max(k_t, k_s), seed=seed)
    parts = parts[0].withColumn("ct", F.pmod("ct", F.lit(k_t))), parts[1].withColumn("cs", F.pmod("cs", F.lit(k_s)))
    last = None
    for _ in range(rounds):
        for side in ("t", "s"):
            v, c, u, d = ("t", "ct", "s", "cs") if side == "t" else ("s", "cs", "t", "ct")
            own, other = (parts[0], parts[1]) if side == "t" else (parts[1], parts[0])
            block = mutual.crossed(graph, *parts).withColumn("p", F.col("m") / F.sum("m").over(Window.partitionBy(c)))
            mine = graph.traversal.join(other, u).groupBy(v, d).agg(F.sum("n").alias("n"))
            clusters = F.broadcast(block.select(c).distinct())
            met = mine.crossJoin(clusters).join(F.broadcast(block.select(c, d, "p")), [c, d], "left")
            score = F.round(F.sum(F.col("n") * F.ln(F.coalesce("p", F.lit(1e-9)))), 9)
            best = met.groupBy(v, c).agg(score.alias("score")).groupBy(v).agg(F.max(F.struct("score", (-F.col(c)).alias("back"))).alias("best"))
            new = materialise(best.select(v, (-F.col("best.back")).alias(c)), "alternate")
            parts = (new, parts[1]) if side == "t" else (parts[0], new)
        mi = mutual.total(mutual.contributions(mutual.crossed(graph, *parts))).first()[0]
        if last is not None and mi <= last + 1e-9:
            break
        last = mi
    return parts
