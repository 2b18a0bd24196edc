"""Modularity of partitions, and communities that raise it.

Large graphs go through rounds of joins: vertices move to the neighbouring
community of most gain, half of them at a time so that neighbours don't swap
for ever, and only if modularity rises; communities then become vertices. What
is left of at most ``local_edges`` edges is finished in one task by greedy
merging and single moves.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, functions as F

from ..scratch import discard, materialise
from .similarity import symmetric

#: Edges that one task takes at most, and vertices of its dense kernel.
LOCAL_EDGES, LOCAL_VERTICES = 2_000_000, 3_000


def score(edges: DataFrame, part: DataFrame, *, resolution: float = 1.0) -> DataFrame:
    """Modularity of ``part(v, c)`` on ``edges(a, b, omega)``, as one row."""
    ends = edges.join(part.select(F.col("v").alias("a"), F.col("c").alias("ca")), "a").join(part.select(F.col("v").alias("b"), F.col("c").alias("cb")), "b")
    inside = ends.select(F.sum(F.when(F.col("ca") == F.col("cb"), F.col("omega")).otherwise(0.0)).alias("inside"), F.sum("omega").alias("total"))
    strength = ends.select(F.explode(F.array("ca", "cb")).alias("c"), "omega").groupBy("c").agg(F.sum("omega").alias("k")).agg(F.sum(F.col("k") * F.col("k")).alias("squares"))
    return inside.crossJoin(strength).select((F.col("inside") / F.col("total") - resolution * F.col("squares") / (4 * F.col("total") * F.col("total"))).alias("modularity"))


def dense_score(a: np.ndarray, c: np.ndarray, resolution: float = 1.0) -> float:
    """Modularity of labels ``c`` on a symmetric matrix."""
    total = a.sum()
    if total <= 0:
        return 0.0
    _, c = np.unique(c, return_inverse=True)
    onto = np.eye(c.max() + 1)[c]
    inner = onto.T @ a @ onto
    k = inner.sum(axis=1)
    return float(np.trace(inner) / total - resolution * (k @ k) / total**2)


def dense_communities(a: np.ndarray, *, resolution: float = 1.0) -> np.ndarray:
    """Labels from greedy merging of all vertices, refined by single moves between every merge level kept.

    The merges run down to one community and the best partition on the way is
    kept; single vertices then move while that raises modularity.
    """
    n = len(a)
    total = a.sum()
    if n == 0 or total <= 0:
        return np.arange(n)
    b = a / total
    k = b.sum(axis=1)
    gain = 2 * (b - resolution * np.outer(k, k))
    joined = b > 0
    np.fill_diagonal(joined, False)
    label = np.arange(n)
    best, now, most = label.copy(), 0.0, 0.0
    # The first of the best partners of each vertex, kept up to date, so that a merge looks at few rows again.
    open_ = np.where(joined, gain, -np.inf)
    partner = open_.argmax(axis=1)
    value = open_[np.arange(n), partner]
    for _ in range(n - 1):
        i = int(value.argmax())
        i, j = sorted((i, int(partner[i])))
        if not np.isfinite(open_[i, j]):
            break
        now += gain[i, j]
        gain[i] += gain[j]
        gain[:, i] = gain[i]
        joined[i] |= joined[j]
        joined[i, [i, j]] = False
        open_[i] = open_[:, i] = np.where(joined[i], gain[i], -np.inf)
        joined[:, i] = joined[i]
        joined[j] = joined[:, j] = False
        open_[j] = open_[:, j] = -np.inf
        better = (open_[:, i] > value) | ((open_[:, i] == value) & (i < partner))
        stale = (partner == i) | (partner == j)
        stale[[i, j]] = True
        partner[better], value[better] = i, open_[better, i]
        again = np.flatnonzero(stale)
        partner[again] = open_[again].argmax(axis=1)
        value[again] = open_[again, partner[again]]
        label[label == j] = i
        if now > most + 1e-12:
            best, most = label.copy(), now
    return _moved(b, k, best, resolution)


def _moved(b: np.ndarray, k: np.ndarray, label: np.ndarray, resolution: float, sweeps: int = 50) -> np.ndarray:
    """Single moves, in the order of the vertices, until none pays."""
    n = len(b)
    own = b - np.diag(np.diag(b))
    size = np.bincount(label, minlength=n)
    strength = np.bincount(label, weights=k, minlength=n)
    for _ in range(sweeps):
        still = True
        for v in range(n):
            c = label[v]
            strength[c] -= k[v]
            size[c] -= 1
            toward = np.bincount(label, weights=own[v], minlength=n)
            reach = toward > 0
            reach[[c, int((size == 0).argmax())]] = True
            gain = np.where(reach, toward - resolution * k[v] * strength, -np.inf)
            to = int(gain.argmax())
            if gain[to] <= gain[c] + 1e-12:
                to = c
            still &= to == c
            label[v] = to
            strength[to] += k[v]
            size[to] += 1
        if still:
            break
    return np.unique(label, return_inverse=True)[1]


def _matrix(frame: pd.DataFrame, vertices: np.ndarray) -> np.ndarray:
    i, j = np.searchsorted(vertices, frame["a"].to_numpy()), np.searchsorted(vertices, frame["b"].to_numpy())
    a = np.zeros((len(vertices), len(vertices)))
    np.add.at(a, (i, j), frame["omega"].to_numpy())
    np.add.at(a, (j, i), np.where(i == j, 0.0, frame["omega"].to_numpy()))
    # A loop of weight w counts twice in a vertex's strength, as its edge has both ends there.
    np.fill_diagonal(a, 2 * np.diag(a))
    return a


def local_communities(frame: pd.DataFrame, *, resolution: float = 1.0) -> pd.DataFrame:
    """``(v, c)`` of a small graph; ``c`` is the least vertex of its community."""
    if frame.empty:
        return pd.DataFrame({"v": pd.Series(dtype="int64"), "c": pd.Series(dtype="int64")})
    vertices = np.unique(np.concatenate([frame["a"], frame["b"]]))
    label = dense_communities(_matrix(frame, vertices), resolution=resolution)
    first = np.full(label.max() + 1, np.iinfo(np.int64).max)
    np.minimum.at(first, label, vertices)
    return pd.DataFrame({"v": vertices, "c": first[label]})


def in_one_task(edges: DataFrame, *, resolution: float = 1.0) -> DataFrame:
    """The dense kernel on a graph that was counted to be small."""

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held = list(frames)
        if held:
            yield local_communities(pd.concat(held), resolution=resolution)

    return edges.select("a", "b", "omega").coalesce(1).mapInPandas(run, "v long, c long")


def contract(edges: DataFrame, part: DataFrame) -> DataFrame:
    """Communities as vertices; an edge within one becomes its loop."""
    met = edges.join(part.select(F.col("v").alias("a"), F.col("c").alias("ca")), "a").join(part.select(F.col("v").alias("b"), F.col("c").alias("cb")), "b")
    return met.groupBy(F.least("ca", "cb").alias("a"), F.greatest("ca", "cb").alias("b")).agg(F.sum("omega").alias("omega"))


def _sweep(ends: DataFrame, strength: DataFrame, part: DataFrame, total: float, half: int, sweep: int, resolution: float) -> DataFrame:
    """One half of the vertices, another in each sweep, at their best community; ``ends`` has both directions and no loops."""
    sums = strength.join(part, "v").groupBy("c").agg(F.sum("k").alias("kc"))
    toward = ends.join(part.select(F.col("v").alias("b"), "c"), "b").groupBy(F.col("a").alias("v"), "c").agg(F.sum("omega").alias("w"))
    stay = part.select("v", "c").withColumn("w", F.lit(0.0))
    options = toward.unionByName(stay).groupBy("v", "c").agg(F.sum("w").alias("w")).join(strength, "v").join(sums, "c").join(part.withColumnRenamed("c", "own"), "v")
    rest = F.col("kc") - F.when(F.col("c") == F.col("own"), F.col("k")).otherwise(0.0)
    gain = F.round(F.col("w") - resolution * F.col("k") * rest / (2 * total), 12)
    best = options.groupBy("v").agg(F.max(F.struct(gain.alias("gain"), (F.col("c") == F.col("own")).alias("stays"), (-F.col("c")).alias("back"))).alias("best"))
    may = F.pmod(F.xxhash64("v", F.lit(sweep)), F.lit(2)) == half
    return part.join(best, "v", "left").select("v", F.when(may & F.col("best").isNotNull(), -F.col("best.back")).otherwise(F.col("c")).alias("c"))


def spread(edges: DataFrame, *, resolution: float = 1.0, max_sweeps: int = 8, tol: float = 1e-4) -> tuple[DataFrame, float]:
    """One level of moves by joins: the partition and its modularity, from single vertices. ``edges`` is read in every sweep, so it is a stored table."""
    both = symmetric(edges.select("a", "b", "omega").withColumn("common", F.lit(0)))
    # Both directions are made anew where they are read; stored, they would take twice the edges.
    ends = both.where("a <> b").select("a", "b", "omega")
    strength = materialise(both.groupBy(F.col("a").alias("v")).agg(F.sum("omega").alias("k")), "modularity-strength")
    total = edges.agg(F.sum("omega")).first()[0] or 0.0
    part = strength.select("v", F.col("v").alias("c"))
    now = score(edges, part, resolution=resolution).first()[0] if total else 0.0
    for sweep in range(max_sweeps if total else 0):
        before = now
        for half in (0, 1):
            new = materialise(_sweep(ends, strength, part, total, half, sweep, resolution), "modularity-part")
            then = score(edges, new, resolution=resolution).first()[0]
            if then > now:
                part, now = new, then
        if now - before < tol:
            break
    return part, now


def communities(edges: DataFrame, *, resolution: float = 1.0, local_edges: int = LOCAL_EDGES, local_vertices: int = LOCAL_VERTICES, mode: str = "auto", max_levels: int = 10) -> DataFrame:
    """``(v, c)`` for every end of an edge; ``c`` is the least vertex of its community.

    ``mode`` is ``local`` for the kernel, ``distributed`` for joins first, or
    ``auto`` for the kernel where the graph is counted to be small.
    """
    own = materialise(edges.select(F.col("a").cast("long").alias("a"), F.col("b").cast("long").alias("b"), F.col("omega").cast("double").alias("omega")), "modularity-graph")

    def fits(graph: DataFrame) -> bool:
        if not graph.limit(local_edges + 1).count() <= local_edges:
            return False
        return graph.select(F.explode(F.array("a", "b"))).distinct().limit(local_vertices + 1).count() <= local_vertices

    if mode == "local" or (mode == "auto" and fits(own)):
        return in_one_task(own, resolution=resolution)
    part, graph = None, own
    for _ in range(max_levels):
        level, _ = spread(graph, resolution=resolution)
        part = level if part is None else part.join(level.select(F.col("v").alias("c"), F.col("c").alias("up")), "c").select("v", F.col("up").alias("c"))
        part = materialise(part, "modularity-level")
        finer, graph = graph, materialise(contract(graph, level), "modularity-graph")
        discard(finer)
        if fits(graph) or level.where("v <> c").isEmpty():
            break
    if fits(graph):
        top = in_one_task(graph, resolution=resolution)
        part = part.join(top.select(F.col("v").alias("c"), F.col("c").alias("up")), "c", "left").select("v", F.coalesce("up", "c").alias("c"))
    return part.join(part.groupBy("c").agg(F.min("v").alias("least")), "c").select("v", F.col("least").alias("c"))
