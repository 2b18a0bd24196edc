"""Weights of a vertex's features, after term frequency and inverse document frequency.

On the trajectory side a segment weighs its share of the trajectory's distance
times the logarithm of how few trajectories use it. On the segment side a
trajectory weighs its share of the segment's visits times the logarithm of how
few segments it uses; lengths play no part there. A share's denominator is the
same for all features of a vertex and cancels in the cosine, so
``normalise=False`` saves its shuffle where only similarities are wanted.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window, functions as F

from ..functions.scalar import idf
from ..model import BipartiteGraph


def _total(graph: BipartiteGraph, side: str) -> DataFrame:
    return graph.traversal.agg(F.count_distinct(side).alias("total"))


def _weighted(graph: BipartiteGraph, v: str, f: str, mass, *, use_idf: bool, normalise: bool, keep_zero: bool) -> DataFrame:
    own = graph.traversal.select(F.col(v).alias("v"), F.col(f).alias("f"), mass.alias("mass"))
    if normalise:
        own = own.withColumn("mass", F.col("mass") / F.sum("mass").over(Window.partitionBy("v")))
    if not use_idf:
        return own.select("v", "f", F.col("mass").alias("w"))
    # One row, so it is broadcast at any size of the graph.
    degree = own.groupBy("f").agg(F.count(F.lit(1)).alias("d")).crossJoin(F.broadcast(_total(graph, v)))
    degree = degree.select("f", idf(F.col("total"), F.col("d")).alias("idf"))
    if not keep_zero:
        # A feature that all vertices have weighs nothing; the widest hubs never reach the join.
        degree = degree.where("idf > 0")
    return own.join(degree, "f").select("v", "f", (F.col("mass") * F.col("idf")).alias("w"))


def spatial_tfidf(graph: BipartiteGraph, *, use_length: bool = True, use_idf: bool = True, normalise: bool = True, keep_zero: bool = True) -> DataFrame:
    """Weights ``(v, f, w)`` of segments for trajectories; without length it is plain tf-idf."""
    mass = F.col("n") * F.col("length") if use_length else F.col("n").cast("double")
    return _weighted(graph, "t", "s", mass, use_idf=use_idf, normalise=normalise, keep_zero=keep_zero)


def visit_tfidf(graph: BipartiteGraph, *, use_idf: bool = True, normalise: bool = True, keep_zero: bool = True) -> DataFrame:
    """Weights ``(v, f, w)`` of trajectories for segments."""
    return _weighted(graph, "s", "t", F.col("n").cast("double"), use_idf=use_idf, normalise=normalise, keep_zero=keep_zero)


def of_side(graph: BipartiteGraph, side: str, **options) -> DataFrame:
    return spatial_tfidf(graph, **options) if side == "t" else visit_tfidf(graph, **options)
