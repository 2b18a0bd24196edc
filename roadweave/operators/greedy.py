"""Greedy merges of clusters by joins, for block matrices that fit no single task.

Only pairs of clusters that share a cluster of the other side change more than
their margins by a merge, so candidates come from a self-join of the blocks on
the other side. ``single`` applies the best merge of a round; ``matched`` all
pairs that are each other's best, and falls back to the single best where that
doesn't lower the cost.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from ..functions.scalar import log_factorial
from ..model import BipartiteGraph
from ..scratch import materialise
from . import criterion, mutual


def candidates(graph: BipartiteGraph, parts: tuple[DataFrame, DataFrame], side: str) -> DataFrame:
    """``(a, b, delta)``: what a merge of two clusters changes, but for the terms that depend on their number alone."""
    v, c, d = ("t", "ct", "cs") if side == "t" else ("s", "cs", "ct")
    own = parts[0] if side == "t" else parts[1]
    block = materialise(mutual.crossed(graph, *parts).select(F.col(c).alias("c"), F.col(d).alias("d"), "m"), "greedy-block")
    margin = block.groupBy("c").agg(F.sum("m").alias("mass")).join(own.groupBy(F.col(c).alias("c")).agg(F.count(v).alias("size")), "c")
    left, right = (block.select(F.col("c").alias(n), "d", F.col("m").alias(f"m{n}")) for n in ("a", "b"))
    joined = F.sum(log_factorial(F.col("ma")) + log_factorial(F.col("mb")) - log_factorial(F.col("ma") + F.col("mb")))
    pairs = left.join(right, "d").where("a < b").groupBy("a", "b").agg(joined.alias("blocks"))
    for n in ("a", "b"):
        pairs = pairs.join(margin.select(F.col("c").alias(n), F.col("mass").alias(f"mass_{n}"), F.col("size").alias(f"size_{n}")), n)
    cost = lambda size, mass: log_factorial(mass + size - 1) - log_factorial(size - 1)
    alone = cost(F.col("size_a"), F.col("mass_a")) + cost(F.col("size_b"), F.col("mass_b"))
    both = cost(F.col("size_a") + F.col("size_b"), F.col("mass_a") + F.col("mass_b"))
    return pairs.select("a", "b", F.round(F.col("blocks") + both - alone, 9).alias("delta"))


def choose(pairs: DataFrame, batch: str) -> DataFrame:
    """``(c, to)`` of the clusters that a round merges."""
    if batch == "single":
        return pairs.orderBy("delta", "a", "b").limit(1).select(F.col("b").alias("c"), F.col("a").alias("to"))
    ends = pairs.unionByName(pairs.select(F.col("b").alias("a"), F.col("a").alias("b"), "delta"))
    best = ends.groupBy("a").agg(F.min(F.struct("delta", "b")).alias("x")).select("a", F.col("x.b").alias("b"), F.col("x.delta").alias("delta"))
    back = best.select(F.col("a").alias("b"), F.col("b").alias("a"))
    return best.join(back, ["a", "b"]).where("a < b").select(F.col("b").alias("c"), F.col("a").alias("to"))


def _applied(part: DataFrame, merges: DataFrame, v: str, c: str) -> DataFrame:
    renamed = part.join(merges.select(F.col("c").alias(c), "to"), c, "left")
    return materialise(renamed.select(v, F.coalesce("to", c).alias(c)), "greedy-part")


def merge(graph: BipartiteGraph, start: tuple[DataFrame, DataFrame], *, batch: str = "matched", max_rounds: int = 1000) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Both partitions after merges, side by side in turn, until neither side's merge lowers the cost; and the costs by round."""
    parts, trace = start, []
    now = criterion.cost(graph, *parts).first()["total"]
    trace.append((0, "start", now))
    for k in range(max_rounds):
        gained = False
        for side in ("t", "s"):
            pairs = materialise(candidates(graph, parts, side), "greedy-pairs")
            for how in dict.fromkeys((batch, "single")):
                merges = materialise(choose(pairs, how), "greedy-merges")
                trial = (_applied(parts[0], merges, "t", "ct"), parts[1]) if side == "t" else (parts[0], _applied(parts[1], merges, "s", "cs"))
                then = criterion.cost(graph, *trial).first()["total"]
                if then < now - 1e-9:
                    parts, now, gained = trial, then, True
                    trace.append((k + 1, f"{side} {how}", now))
                    break
        if not gained:
            break
    return *parts, graph.traversal.sparkSession.createDataFrame(trace, "round long, step string, cost double")


def reduced(graph: BipartiteGraph, parts: tuple[DataFrame, DataFrame], until: int) -> tuple[DataFrame, DataFrame]:
    """Merges of all pairs that are each other's best, rises too, until either side has at most ``until`` clusters or no pair is left."""
    open_sides = {"t", "s"}
    while open_sides:
        for side in sorted(open_sides):
            v, c = ("t", "ct") if side == "t" else ("s", "cs")
            part = parts[0] if side == "t" else parts[1]
            k = part.select(c).distinct().count()
            merges = materialise(choose(candidates(graph, parts, side), "matched"), "greedy-merges") if k > until else None
            if merges is None or merges.isEmpty():
                open_sides.discard(side)
                continue
            new = _applied(part, merges, v, c)
            parts = (new, parts[1]) if side == "t" else (parts[0], new)
    return parts
