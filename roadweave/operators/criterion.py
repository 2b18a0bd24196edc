"""Code length of a co-clustering: prior of the model and likelihood of the data, in nats."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from ..functions.scalar import log_choose, log_factorial, log_partitions
from ..model import BipartiteGraph
from .mutual import crossed


def cost(graph: BipartiteGraph, row_part: DataFrame, col_part: DataFrame) -> DataFrame:
    """One row with every term and the total; ``row_part(t, ct)``, ``col_part(s, cs)``."""
    block = crossed(graph, row_part, col_part)
    of_block = block.agg(F.sum("m").alias("m"), F.sum(log_factorial(F.col("m"))).alias("blocks"))

    def side(v: str, c: str, part: DataFrame) -> DataFrame:
        degree = graph.traversal.groupBy(v).agg(F.sum("n").alias("n")).join(part.select(v, c), v)
        of_vertex = degree.groupBy(c).agg(F.count(F.lit(1)).alias("size"), F.sum("n").alias("m"), F.sum(log_factorial(F.col("n"))).alias("own"))
        return of_vertex.agg(
            F.sum("size").alias(f"{v}_n"),
            F.count(F.lit(1)).alias(f"{v}_k"),
            F.sum(log_choose(F.col("m") + F.col("size") - 1, F.col("size") - 1)).alias(f"{v}_counts"),
            F.sum(log_factorial(F.col("m")) - F.col("own")).alias(f"{v}_margins"),
        )

    # Three one-row tables; the numbers of partitions are scalars of the sizes.
    one = of_block.crossJoin(side("t", "ct", row_part)).crossJoin(side("s", "cs", col_part)).first()
    spark = graph.traversal.sparkSession
    if not one or not one["m"]:
        return spark.createDataFrame([], ", ".join(f"{c} double" for c in TERMS))
    cells = one["t_k"] * one["s_k"]
    known = spark.range(1).select(*[F.lit(one[c]).alias(c) for c in one.asDict()])
    terms = {
        "cluster_counts": F.ln(F.lit(float(one["t_n"]))) + F.ln(F.lit(float(one["s_n"]))),
        "partitions": F.lit(log_partitions(one["t_n"], one["t_k"]) + log_partitions(one["s_n"], one["s_k"])),
        "block_counts": log_choose(F.col("m") + cells - 1, F.lit(cells - 1).cast("long")),
        "vertex_counts": F.col("t_counts") + F.col("s_counts"),
        "like_blocks": log_factorial(F.col("m")) - F.col("blocks"),
        "like_margins": F.col("t_margins") + F.col("s_margins"),
    }
    out = known.select(*[e.alias(c) for c, e in terms.items()])
    return out.withColumn("total", sum((F.col(c) for c in terms), F.lit(0.0)))


TERMS = ("cluster_counts", "partitions", "block_counts", "vertex_counts", "like_blocks", "like_margins", "total")


def finest(graph: BipartiteGraph) -> tuple[DataFrame, DataFrame]:
    """Every vertex its own cluster."""
    return graph.traversal.select("t").distinct().withColumn("ct", F.col("t")), graph.traversal.select("s").distinct().withColumn("cs", F.col("s"))


def null_model(graph: BipartiteGraph) -> tuple[DataFrame, DataFrame]:
    """One block."""
    return graph.traversal.select("t").distinct().withColumn("ct", F.lit(0).cast("long")), graph.traversal.select("s").distinct().withColumn("cs", F.lit(0).cast("long"))
