"""The bipartite graph of trajectories and segments, as a table of traversals.

A traversal is one row per trajectory ``t`` and segment ``s`` with the number of
visits ``n`` and the segment's ``length``. Rows with a null end and rows with
``n`` or ``length`` of 0 or less are left out and counted; a null length is 1.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window, functions as F

#: Columns and types of a traversal table.
TRAVERSAL = {"t": "bigint", "s": "bigint", "n": "bigint", "length": "double"}


def require(df: DataFrame, columns: dict[str, str]) -> DataFrame:
    """``df`` with just these columns, cast; raises where one is missing."""
    missing = [c for c in columns if c not in df.columns]
    if missing:
        raise ValueError(f"missing columns: {', '.join(missing)}")
    return df.select(*[F.col(c).cast(t).alias(c) for c, t in columns.items()])


def collapse(seq: DataFrame, *, t: str = "t", pos: str = "pos", s: str = "s") -> DataFrame:
    """A path without immediate repetitions of a segment."""
    order = Window.partitionBy(t).orderBy(pos)
    return seq.withColumn("__before", F.lag(s).over(order)).where(F.col("__before").isNull() | (F.col("__before") != F.col(s))).drop("__before")


def to_traversals(seq: DataFrame, lengths: DataFrame | None = None) -> DataFrame:
    """Visits of each trajectory to each segment from paths ``(t, pos, s)``; ``lengths`` has ``(s, length)``."""
    visits = collapse(seq).groupBy("t", "s").agg(F.count(F.lit(1)).alias("n"))
    if lengths is None:
        return visits.withColumn("length", F.lit(1.0))
    return visits.join(lengths.select("s", "length"), "s", "left").select("t", "s", "n", F.coalesce("length", F.lit(1.0)).alias("length"))


@dataclass(frozen=True)
class BipartiteGraph:
    """A checked traversal table; segments are those with a traversal."""

    traversal: DataFrame

    @staticmethod
    def of(df: DataFrame, *, t: str | Column = "t", s: str | Column = "s", n: str | Column | None = "n", length: str | Column | None = "length") -> BipartiteGraph:
        """Declare any table a graph; repeated (t, s) rows add their visits."""
        col = lambda c: F.col(c) if isinstance(c, str) else c
        own = df.select(
            col(t).cast("bigint").alias("t"),
            col(s).cast("bigint").alias("s"),
            (F.lit(1) if n is None else col(n)).cast("bigint").alias("n"),
            F.coalesce((F.lit(1.0) if length is None else col(length)).cast("double"), F.lit(1.0)).alias("length"),
        )
        good = own.where("t is not null and s is not null and n > 0 and length > 0")
        return BipartiteGraph(good.groupBy("t", "s").agg(F.sum("n").alias("n"), F.max("length").alias("length")))

    @staticmethod
    def rejected(df: DataFrame, *, t: str = "t", s: str = "s", n: str = "n", length: str = "length") -> DataFrame:
        """How many rows :meth:`of` leaves out, by reason."""
        null = F.col(t).isNull() | F.col(s).isNull()
        count = lambda c: F.coalesce(F.sum(c.cast("bigint")), F.lit(0))
        return df.agg(count(null).alias("null_end"), count(~null & (F.col(n) <= 0)).alias("no_visit"), count(~null & (F.col(n) > 0) & (F.col(length) <= 0)).alias("no_length"))

    def degrees(self, side: str = "t") -> DataFrame:
        """Of each vertex: its distinct neighbours and its visits."""
        return self.traversal.groupBy(side).agg(F.count(F.lit(1)).alias("degree"), F.sum("n").alias("visits"))

    def stats(self) -> DataFrame:
        """Vertices, edges and visits."""
        return self.traversal.agg(F.count_distinct("t").alias("trajectories"), F.count_distinct("s").alias("segments"), F.count(F.lit(1)).alias("edges"), F.coalesce(F.sum("n"), F.lit(0)).alias("visits"))

    def binarize(self) -> BipartiteGraph:
        """Existence only: every visit count is 1."""
        return BipartiteGraph(self.traversal.withColumn("n", F.lit(1).cast("bigint")))

    def transposed(self) -> BipartiteGraph:
        return BipartiteGraph(self.traversal.select(F.col("s").alias("t"), F.col("t").alias("s"), "n", "length"))

    def coverage(self, segments: DataFrame) -> DataFrame:
        """Visited segments among all ``segments(s)``, and their share."""
        seen = self.traversal.select("s").distinct()
        met = segments.select("s").distinct().join(seen.withColumn("seen", F.lit(1)), "s", "left")
        return met.agg(F.count("seen").alias("visited"), F.count(F.lit(1)).alias("segments"), F.round(F.count("seen") / F.count(F.lit(1)), 6).alias("share"))
