"""Rival clusterings: spectral on the similarity graph, and k-means on positions that ignores the network."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.ml.clustering import KMeans, PowerIterationClustering
from pyspark.ml.feature import VectorAssembler
from pyspark.sql import DataFrame, functions as F

from .modularity import LOCAL_EDGES, LOCAL_VERTICES, _matrix


def _kmeans(x: np.ndarray, k: int, seed: int, rounds: int = 100) -> np.ndarray:
    """Lloyd's rounds from spread-out starts, the best of ten."""
    rng, best, least = np.random.default_rng(seed), np.zeros(len(x), int), np.inf
    for _ in range(10):
        centres = [x[rng.integers(len(x))]]
        for _ in range(k - 1):
            d = np.min([((x - c) ** 2).sum(axis=1) for c in centres], axis=0)
            centres.append(x[rng.choice(len(x), p=d / d.sum())] if d.sum() > 0 else x[rng.integers(len(x))])
        c = np.array(centres)
        for _ in range(rounds):
            d = ((x[:, None, :] - c[None]) ** 2).sum(axis=2)
            label = d.argmin(axis=1)
            new = np.array([x[label == i].mean(axis=0) if (label == i).any() else c[i] for i in range(k)])
            if np.allclose(new, c):
                break
            c = new
        cost = d.min(axis=1).sum()
        if cost < least:
            best, least = label, cost
    return best


def spectral(edges: DataFrame, k: int, *, seed: int = 42) -> DataFrame:
    """``(v, c)`` by the normalised Laplacian where the graph is counted to be small, else by power iteration."""
    small = edges.limit(LOCAL_EDGES + 1).count() <= LOCAL_EDGES and edges.select(F.explode(F.array("a", "b"))).distinct().limit(LOCAL_VERTICES + 1).count() <= LOCAL_VERTICES
    if not small:
        found = PowerIterationClustering(k=k, maxIter=30, srcCol="a", dstCol="b", weightCol="omega").assignClusters(edges.select("a", "b", "omega"))
        return found.select(F.col("id").alias("v"), F.col("cluster").cast("long").alias("c"))

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        frame = pd.concat(list(frames))
        vertices = np.unique(np.concatenate([frame["a"], frame["b"]]))
        a = _matrix(frame, vertices)
        scale = 1 / np.sqrt(np.maximum(a.sum(axis=1), 1e-12))
        _, vectors = np.linalg.eigh(a * scale[:, None] * scale[None, :])
        x = vectors[:, -k:]
        x = x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-12)
        yield pd.DataFrame({"v": vertices, "c": _kmeans(x, k, seed)})

    return edges.select("a", "b", "omega").coalesce(1).mapInPandas(run, "v long, c long")


def euclidean(points: DataFrame, k: int, *, features: list[str], seed: int = 42) -> DataFrame:
    """``(v, c)`` by k-means over positions such as the endpoints of trajectories."""
    own = VectorAssembler(inputCols=features, outputCol="__features").transform(points)
    model = KMeans(k=k, seed=seed, featuresCol="__features", predictionCol="c").fit(own)
    return model.transform(own).select("v", F.col("c").cast("long").alias("c"))
