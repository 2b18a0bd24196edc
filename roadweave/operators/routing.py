"""Shortest paths between vertices of the network."""

from __future__ import annotations

import heapq
from collections import defaultdict
from collections.abc import Iterator
from functools import cached_property

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, functions as F

from ..scratch import materialise

#: Segments of a network that is sent to every task at most; larger ones are routed by joins.
NETWORK_ROWS = 2_000_000


class Network:
    """A network's segments, and what leaves each vertex; a worker builds the latter once, for all its tasks."""

    def __init__(self, rows: np.ndarray):
        self.rows = rows

    @cached_property
    def out(self) -> dict[int, list[tuple[int, int, int]]]:
        own: dict[int, list[tuple[int, int, int]]] = defaultdict(list)
        for a, b, s, w in self.rows.tolist():
            own[a].append((b, s, w))
        return own

    def __getstate__(self) -> dict:
        return {"rows": self.rows}


def _tree(out: dict[int, list[tuple[int, int, int]]], src: int, targets: set[int] | None) -> tuple[dict[int, int], dict[int, tuple[int, int]]]:
    """Distances from a vertex, and the last vertex and segment of a best path, to all vertices or until ``targets`` are reached; equal paths prefer smaller vertices."""
    done: dict[int, int] = {}
    last: dict[int, tuple[int, int]] = {}
    best = {src: 0}
    heap = [(0, src)]
    left = None if targets is None else set(targets)
    while heap and (left is None or left):
        d, v = heapq.heappop(heap)
        if v in done:
            continue
        done[v] = d
        if left is not None:
            left.discard(v)
        for u, s, w in out.get(v, ()):
            new = d + w
            if u not in done and (u not in best or new < best[u] or (new == best[u] and (v, s) < last[u])):
                best[u], last[u] = new, (v, s)
                heapq.heappush(heap, (new, u))
    return done, last


def shortest(segments: DataFrame, pairs: DataFrame, *, weight: str = "travel_time") -> DataFrame:
    """``(t, pos, s)`` of each pair ``(t, src, dst)``; pairs without a path, or of one vertex, have no rows.

    The network goes to every task, behind a count of its rows. Pairs are dealt
    by source, and a source's tree is grown once for all pairs of a batch.
    """
    if segments.limit(NETWORK_ROWS + 1).count() > NETWORK_ROWS:
        return by_joins(segments, pairs, weight=weight)
    own = segments.select("src", "dst", "s", F.col(weight).cast("long").alias("w")).toPandas()
    shared = pairs.sparkSession.sparkContext.broadcast(Network(own.to_numpy(np.int64)))

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        out, before, last, whole = shared.value.out, None, {}, False
        for frame in frames:
            for src, group in frame.groupby("src"):
                # A source whose pairs go on in a further batch gets its whole tree, once.
                again = src == before
                if not (again and whole):
                    _, last = _tree(out, int(src), None if again else set(group["dst"].tolist()))
                before, whole = src, again
                t, pos, s = [], [], []
                for trip, dst in zip(group["t"].tolist(), group["dst"].tolist()):
                    path, v = [], dst
                    while v != src and v in last:
                        v, segment = last[v]
                        path.append(segment)
                    if v == src:
                        t += [trip] * len(path)
                        pos += range(len(path))
                        s += path[::-1]
                yield pd.DataFrame({"t": t, "pos": pos, "s": s})

    dealt = pairs.select("t", "src", "dst").repartition("src").sortWithinPartitions("src")
    return dealt.mapInPandas(run, "t long, pos int, s long")


def by_joins(segments: DataFrame, pairs: DataFrame, *, weight: str = "travel_time", max_rounds: int = 100_000) -> DataFrame:
    """The same for a network that fits no task: labels spread from all sources, a hop a round, until none falls."""
    own = materialise(segments.select(F.col("src").alias("v"), F.col("dst").alias("u"), "s", F.col(weight).cast("double").alias("w")), "routing-network")
    start = pairs.select("src").distinct().select("src", F.col("src").alias("v"), F.lit(0.0).alias("d"), F.array().cast("array<bigint>").alias("path"))
    best = frontier = materialise(start, "routing-start")
    for _ in range(max_rounds):
        step = frontier.join(own, "v").select("src", F.col("u").alias("v"), (F.col("d") + F.col("w")).alias("d"), F.concat("path", F.array("s")).alias("path"))
        step = step.groupBy("src", "v").agg(F.min(F.struct("d", "path")).alias("x")).select("src", "v", "x.d", "x.path")
        known = best.select("src", "v", F.col("d").alias("old"))
        frontier = materialise(step.join(known, ["src", "v"], "left").where("old is null or d < old").select("src", "v", "d", "path"), "routing-frontier")
        if frontier.isEmpty():
            break
        best = materialise(best.join(frontier.select("src", "v"), ["src", "v"], "left_anti").unionByName(frontier), "routing-best")
    met = pairs.select("t", "src", F.col("dst").alias("v")).join(best, ["src", "v"])
    return met.select("t", F.posexplode("path").alias("pos", "s"))


def costs(segments: DataFrame, seq: DataFrame, *, weight: str = "travel_time") -> DataFrame:
    """Cost of each path ``(t, pos, s)``."""
    return seq.join(segments.select("s", weight), "s").groupBy("t").agg(F.sum(weight).alias("cost"), F.count(F.lit(1)).alias("hops"))
