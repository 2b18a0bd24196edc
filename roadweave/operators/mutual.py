"""Blocks of two partitions read together: frequencies and shares of mutual information."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window, functions as F

from ..model import BipartiteGraph


def crossed(graph: BipartiteGraph, row_part: DataFrame, col_part: DataFrame) -> DataFrame:
    """``(ct, cs, m, edges)`` of ``row_part(t, ct)`` and ``col_part(s, cs)``: visits and edges of each block that has any."""
    met = graph.traversal.join(row_part.select("t", "ct"), "t").join(col_part.select("s", "cs"), "s")
    return met.groupBy("ct", "cs").agg(F.sum("n").alias("m"), F.count(F.lit(1)).alias("edges"))


def contributions(block: DataFrame, *, log_base: float = math.e, margin: str = "traversal", sizes: tuple[DataFrame, DataFrame] | None = None) -> DataFrame:
    """Each block's share p of the visits, what independence would give, and its part of the mutual information.

    Margins are shares of visits; ``margin="vertex"`` takes shares of vertices
    instead, from ``sizes``: tables ``(ct, n)`` and ``(cs, n)``. Blocks without
    visits contribute nothing and are absent.
    """
    everything = Window.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    total = F.sum("m").over(everything)
    # The table has as many rows as there are blocks.
    own = block.select("ct", "cs", "m").withColumn("p", F.col("m") / total)
    if margin == "vertex":
        rows, columns = (s.withColumn(name, F.col("n") / F.sum("n").over(everything)).drop("n") for s, name in zip(sizes, ("p_t", "p_s")))
        own = own.join(F.broadcast(rows), "ct").join(F.broadcast(columns), "cs")
    else:
        own = own.withColumn("p_t", F.sum("p").over(Window.partitionBy("ct"))).withColumn("p_s", F.sum("p").over(Window.partitionBy("cs")))
    own = own.withColumn("expected", F.col("p_t") * F.col("p_s"))
    return own.withColumn("mi", F.when(F.col("p") > 0, F.col("p") * F.ln(F.col("p") / F.col("expected")) / math.log(log_base)).otherwise(0.0))


def total(parts: DataFrame) -> DataFrame:
    return parts.agg(F.sum("mi").alias("mutual_information"))


def profile(graph: BipartiteGraph, row_part: DataFrame, col_part: DataFrame) -> DataFrame:
    """Density of each block, and how unevenly its segments are used."""
    rows = row_part.groupBy("ct").agg(F.count(F.lit(1)).alias("rows"))
    columns = col_part.groupBy("cs").agg(F.count(F.lit(1)).alias("columns"))
    met = graph.traversal.join(row_part.select("t", "ct"), "t").join(col_part.select("s", "cs"), "s")
    used = met.groupBy("ct", "cs", "s").agg(F.count(F.lit(1)).alias("edges")).join(F.broadcast(rows), "ct").withColumn("fill", F.col("edges") / F.col("rows"))
    # Segments of the block that nobody of the row cluster uses have fill 0.
    of = used.groupBy("ct", "cs").agg(F.sum("edges").alias("edges"), F.sum("fill").alias("fill"), F.sum(F.col("fill") * F.col("fill")).alias("squares"), F.first("rows").alias("rows"))
    of = of.join(F.broadcast(columns), "cs")
    mean = F.col("fill") / F.col("columns")
    return of.select("ct", "cs", "edges", (F.col("edges") / (F.col("rows") * F.col("columns"))).alias("density"), F.sqrt(F.greatest(F.col("squares") / F.col("columns") - mean * mean, F.lit(0.0))).alias("dispersion"))


def reordered(graph: BipartiteGraph, row_part: DataFrame, col_part: DataFrame) -> DataFrame:
    """The matrix with rows and columns of a cluster side by side: ranks by cluster, then degree."""
    place = lambda side, c: Window.orderBy(c, F.desc("degree"), side)
    rows = graph.degrees("t").join(row_part.select("t", "ct"), "t").withColumn("row_rank", F.row_number().over(place("t", "ct")))
    columns = graph.degrees("s").join(col_part.select("s", "cs"), "s").withColumn("col_rank", F.row_number().over(place("s", "cs")))
    return graph.traversal.join(rows.select("t", "ct", "row_rank"), "t").join(columns.select("s", "cs", "col_rank"), "s").select("row_rank", "col_rank", "n", "ct", "cs")


def roles(block: DataFrame, *, hub_entropy: float = 0.7, rare_quantile: float = 0.25) -> DataFrame:
    """Role of each segment cluster: hub, secondary or rare.

    A hub's visits spread over the trajectory clusters, with at least
    ``hub_entropy`` of the most entropy that these allow; of the others, those
    in the lowest ``rare_quantile`` of visits are rare. ``contrast`` is the
    range of the cluster's contributions to mutual information.
    """
    parts = contributions(block)
    clusters = F.count_distinct("ct")
    most = F.broadcast(block.agg(F.ln(F.greatest(clusters, F.lit(2))).alias("most")))
    share = F.col("m") / F.sum("m").over(Window.partitionBy("cs"))
    of = parts.withColumn("share", share).groupBy("cs").agg(
        F.sum("m").alias("visits"), F.sum(-F.col("share") * F.ln("share")).alias("entropy"), (F.max("mi") - F.min("mi")).alias("contrast"), F.stddev_pop("mi").alias("spread")
    )
    of = of.crossJoin(most).withColumn("evenness", F.col("entropy") / F.col("most")).drop("most")
    rank = F.percent_rank().over(Window.orderBy("visits"))
    kind = F.when(F.col("evenness") >= hub_entropy, "hub").when(rank <= rare_quantile, "rare").otherwise("secondary")
    return of.withColumn("role", kind)
