"""How a partition agrees with known classes."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window, functions as F


def confusion(labels: DataFrame, part: DataFrame) -> DataFrame:
    """``(klass, cluster, n, ratio)``: counts, and the share of the class that lies in the cluster."""
    counts = labels.select("v", "klass").join(part.select("v", F.col("c").alias("cluster")), "v").groupBy("klass", "cluster").agg(F.count(F.lit(1)).alias("n"))
    return counts.withColumn("ratio", F.col("n") / F.sum("n").over(Window.partitionBy("klass")))


def ari(table: DataFrame) -> DataFrame:
    """Adjusted Rand Index of a contingency table ``(klass, cluster, n)``; 1 where both sides are one class or all single."""
    pairs = lambda c: F.sum(c * (c - 1) / 2)
    n = F.col("n").cast("double")
    cells = table.agg(pairs(n).alias("both"), F.sum(n).alias("total"))
    rows = table.groupBy("klass").agg(F.sum(n).alias("n")).agg(pairs(F.col("n")).alias("rows"))
    columns = table.groupBy("cluster").agg(F.sum(n).alias("n")).agg(pairs(F.col("n")).alias("columns"))
    every = F.col("total") * (F.col("total") - 1) / 2
    expected = F.when(every > 0, F.col("rows") * F.col("columns") / every).otherwise(0.0)
    most = (F.col("rows") + F.col("columns")) / 2
    value = F.when(most == expected, F.lit(1.0)).otherwise((F.col("both") - expected) / (most - expected))
    return cells.crossJoin(rows).crossJoin(columns).select(value.alias("ari"))


def purity(table: DataFrame) -> DataFrame:
    """Share of members in their cluster's main class, and whether every cluster has one class."""
    of = table.groupBy("cluster").agg(F.max("n").alias("main"), F.sum("n").alias("n"))
    return of.agg((F.sum("main") / F.sum("n")).alias("purity"), (F.sum("main") == F.sum("n")).alias("all_pure"), F.count(F.lit(1)).alias("clusters"))


def recovery(table: DataFrame) -> DataFrame:
    """Of each class: clusters that have it, whether they have nothing else, and what became of it."""
    of_cluster = Window.partitionBy("cluster")
    seen = table.withColumn("alone", F.count(F.lit(1)).over(of_cluster) == 1)
    of = seen.groupBy("klass").agg(F.count(F.lit(1)).alias("clusters"), F.min("alone").alias("pure"))
    kind = F.when(~F.col("pure"), "merged").when(F.col("clusters") == 1, "exact").otherwise("over-partitioned")
    return of.withColumn("outcome", kind)
