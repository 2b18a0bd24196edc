"""Projections of the bipartite graph: an edge for each pair that shares a feature.

A feature of degree d makes d * (d - 1) / 2 products. Features that all vertices
have weigh nothing and go first. The others meet in tiles of vertices
(``tiles.py``): a task adds up the products of two tiles in memory and gives out
finished pairs, so none is shuffled, and with a least similarity those below it
never leave the task.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window, functions as F

from ..model import BipartiteGraph
from .buckets import sharing
from .tiles import products
from .weights import of_side


def unit(weights: DataFrame) -> DataFrame:
    """Vectors of length 1; a vector of zeros has null weights and thus no similarity."""
    norm = F.sqrt(F.sum(F.col("w") * F.col("w")).over(Window.partitionBy("v")))
    return weights.withColumn("w", F.col("w") / F.nullif(norm, F.lit(0.0)))


def vectors(graph: BipartiteGraph, *, side: str = "t") -> DataFrame:
    """The vectors ``(v, f, w)`` whose products are the edges of :func:`project`."""
    return unit(of_side(graph, side, normalise=False, keep_zero=False)).where("w > 0")


def norms(weights: DataFrame) -> DataFrame:
    """Euclidean length of each vertex's vector."""
    return weights.groupBy("v").agg(F.sqrt(F.sum(F.col("w") * F.col("w"))).alias("norm"))


def cosine_pairs(weights: DataFrame, *, min_sim: float = 0.0, top_k: int | None = None, keep_zero: bool = False, tile: int | None = None) -> DataFrame:
    """Edges ``(a, b, omega, common)`` with a < b and their cosine similarity.

    ``common`` counts shared features of those given. ``keep_zero`` also keeps
    pairs whose shared features all weigh nothing. ``top_k`` keeps an edge that
    is among the best of either end.
    """
    vectors = unit(weights)
    vectors = vectors.where("w is not null") if keep_zero else vectors.where("w > 0")
    edges = products(vectors, tile=tile, least=min_sim - 1e-12 if min_sim > 0 else -math.inf).withColumn("omega", F.least("omega", F.lit(1.0)))
    if not keep_zero:
        edges = edges.where("omega > 0")
    return edges if top_k is None else strongest(edges, top_k)


def common_pairs(graph: BipartiteGraph, *, side: str = "t", tile: int | None = None) -> DataFrame:
    """The plain rival: edges weighted by the number of shared neighbours."""
    other = "s" if side == "t" else "t"
    vectors = graph.traversal.select(F.col(side).alias("v"), F.col(other).alias("f"), F.lit(1.0).alias("w"))
    return products(vectors, tile=tile)


def project(graph: BipartiteGraph, *, side: str = "t", weight: str = "cosine", **options) -> DataFrame:
    """The similarity graph of one side; ``weight`` is ``cosine`` or ``common``."""
    if weight == "common":
        return common_pairs(graph, side=side)
    keep_zero = options.get("keep_zero", False)
    return cosine_pairs(of_side(graph, side, normalise=False, keep_zero=keep_zero), **options)


def minhash_candidates(graph: BipartiteGraph, *, side: str = "t", bands: int = 24, rows: int = 2, tile: int | None = None) -> DataFrame:
    """All pairs ``(a, b)`` that share a band of sampled neighbours, as candidates where all pairs are too many.

    A pair whose sets have Jaccard similarity j is found with probability
    1 - (1 - j**rows)**bands. A bucket of n vertices gives all its n * (n - 1) / 2
    pairs; they meet in tiles of vertices (``buckets.py``), and none is shuffled.
    """
    other = "s" if side == "t" else "t"
    minima = [F.min(F.xxhash64(other, F.lit(k))).alias(f"h{k}") for k in range(bands * rows)]
    # Neighbours go to their vertex first: minima of parts of its neighbours would be more than those.
    signed = graph.traversal.select(F.col(side).alias("v"), other).repartition("v").groupBy("v").agg(*minima)
    keys = F.array(*[F.xxhash64(*[f"h{b * rows + r}" for r in range(rows)], F.lit(b)) for b in range(bands)])
    return sharing(signed.select("v", keys.alias("buckets")), tile=tile)


def symmetric(edges: DataFrame) -> DataFrame:
    """Both directions of every edge."""
    return edges.unionByName(edges.withColumns({"a": F.col("b"), "b": F.col("a")}))


def strongest(edges: DataFrame, k: int) -> DataFrame:
    """Edges among the ``k`` best of at least one end; ties, to nine places, go to the smaller neighbour."""
    best = Window.partitionBy("a").orderBy(F.desc(F.round("omega", 9)), F.asc("b"))
    ranked = symmetric(edges).withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k)
    return ranked.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"), "omega", "common").distinct()


def density(edges: DataFrame, vertices: int) -> DataFrame:
    """Share of pairs that are edges, and quantiles of the degrees."""
    degree = symmetric(edges).groupBy("a").agg(F.count(F.lit(1)).alias("d"))
    pairs = max(1, vertices * (vertices - 1) // 2)
    q = lambda p: F.percentile("d", F.lit(p))
    return degree.agg((F.sum("d") / 2 / pairs).alias("density"), q(0.5).alias("median_degree"), F.max("d").alias("max_degree"))
