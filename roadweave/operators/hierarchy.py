"""Nested communities: coarse ones first, then each refined on its own induced graph."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, functions as F

from ..scratch import materialise, new_path
from .modularity import LOCAL_EDGES, LOCAL_VERTICES, _matrix, communities, dense_communities, dense_score


def _random_gain(a: np.ndarray, rng: np.random.Generator, resolution: float, times: int = 3) -> float:
    """Best modularity of the same weights set on other pairs, as what chance alone gives."""
    i, j = np.triu_indices(len(a), 1)
    best = 0.0
    for _ in range(times):
        b = np.zeros_like(a)
        b[i, j] = rng.permutation(a[i, j])
        b += b.T
        best = max(best, dense_score(b, dense_communities(b, resolution=resolution), resolution))
    return best


def _split(frame: pd.DataFrame, gate: str, min_size: int, resolution: float) -> pd.DataFrame:
    """The sub-communities of one community, or itself where the gate says that it is one."""
    vertices = np.unique(np.concatenate([frame["a"], frame["b"]]))
    a = _matrix(frame, vertices)
    label = dense_communities(a, resolution=resolution) if len(vertices) >= min_size else np.zeros(len(vertices), dtype=int)
    gain = dense_score(a, label, resolution)
    least = 1e-9 if gate == "gain" else _random_gain(a, np.random.default_rng(int(vertices[0]) & 0x7FFFFFFF), resolution)
    if gain <= least:
        label = np.zeros(len(vertices), dtype=int)
    first = np.full(label.max() + 1, np.iinfo(np.int64).max)
    np.minimum.at(first, label, vertices)
    return pd.DataFrame({"v": vertices, "cluster": first[label]})


def nested(edges: DataFrame, *, max_depth: int = 2, min_size: int = 3, gate: str = "gain", resolution: float = 1.0, local_edges: int = LOCAL_EDGES, local_vertices: int = LOCAL_VERTICES) -> DataFrame:
    """``(v, level, cluster, parent)`` for levels 1 to ``max_depth``; a cluster is named by its least vertex.

    All parents of a level are refined in one job, each by one task; a parent
    with more edges or vertices than a task takes goes through joins of its own.
    """
    own = materialise(edges.select("a", "b", "omega"), "nested-edges")
    level = communities(own, resolution=resolution).select("v", F.col("c").alias("cluster"))
    level = materialise(level.select("v", F.lit(1).alias("level"), "cluster", F.lit(None).cast("long").alias("parent")), "nested-level")
    out = level
    for depth in range(2, max_depth + 1):
        of = level.select("v", F.col("cluster").alias("parent"))
        inner = own.join(of.select(F.col("v").alias("a"), "parent"), "a").join(of.select(F.col("v").alias("b"), F.col("parent").alias("other")), "b").where("parent = other")
        inner = materialise(inner.select("parent", "a", "b", "omega"), "nested-inner")
        ends = inner.select("parent", F.col("a").alias("v")).unionByName(inner.select("parent", F.col("b").alias("v"))).distinct()
        sizes = inner.groupBy("parent").agg(F.count(F.lit(1)).alias("edges")).join(ends.groupBy("parent").agg(F.count(F.lit(1)).alias("vertices")), "parent")
        wide = materialise(sizes.where((F.col("edges") > local_edges) | (F.col("vertices") > local_vertices)).select("parent"), "nested-wide")
        # What is left in a group fits a task by the counts above.
        small = inner.join(wide, "parent", "left_anti")
        found = small.groupBy("parent").applyInPandas(lambda f: _split(f, gate, min_size, resolution), "v long, cluster long")
        own_path = new_path(own.sparkSession, "nested-wide-parts")
        for row in wide.toLocalIterator():
            part = communities(inner.where(F.col("parent") == row["parent"]), resolution=resolution, local_edges=local_edges, local_vertices=local_vertices)
            part.select("v", F.col("c").alias("cluster")).write.mode("append").parquet(own_path)
        if not wide.isEmpty():
            found = found.unionByName(own.sparkSession.read.schema("v long, cluster long").parquet(own_path))
        level = of.join(found, "v", "left").select("v", F.lit(depth).alias("level"), F.coalesce("cluster", F.when(F.col("v").isNotNull(), F.col("parent"))).alias("cluster"), "parent")
        level = materialise(level, "nested-level")
        out = out.unionByName(level)
    return out


def refine(edges: DataFrame, membership: DataFrame, cluster: int, *, level: int = 1, gate: str = "gain", resolution: float = 1.0) -> DataFrame:
    """The sub-communities of one cluster alone."""
    inside = membership.where((F.col("level") == level) & (F.col("cluster") == cluster)).select("v")
    own = edges.join(inside.withColumnRenamed("v", "a"), "a", "left_semi").join(inside.withColumnRenamed("v", "b"), "b", "left_semi")
    return communities(own, resolution=resolution).select("v", F.col("c").alias("cluster"))


def cut(membership: DataFrame, *, level: int | None = None, k: int | None = None) -> DataFrame:
    """``(v, c)`` of one level, or of the finest level with at most ``k`` clusters."""
    if level is None:
        counts = levels(membership).where(F.col("clusters") <= k)
        level = counts.agg(F.coalesce(F.max("level"), F.lit(1))).first()[0]
    return membership.where(F.col("level") == level).select("v", F.col("cluster").alias("c"))


def levels(membership: DataFrame) -> DataFrame:
    """Clusters of each level."""
    return membership.groupBy("level").agg(F.count_distinct("cluster").alias("clusters"))
