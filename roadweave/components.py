"""Connected components by rounds of joins, for edges that fit no single machine."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from .joins import key_join
from .scratch import discard, materialise


def components(links: DataFrame, *, a: str = "a", b: str = "b") -> DataFrame:
    """``(v, c)`` for every vertex of a link; ``c`` is the least vertex of its component.

    A round takes the least label among a vertex and its neighbours and then
    jumps to that label's own label, so chains shorten by powers of two. Each
    round is written to the shared folder; the driver sees two counts a round.
    """
    ends = links.select(F.col(a).alias("u"), F.col(b).alias("v"))
    edges = materialise(ends.unionByName(ends.select(F.col("v").alias("u"), F.col("u").alias("v"))).distinct(), "component-edges")
    labels = materialise(edges.groupBy("v").agg(F.least(F.min("u"), F.first("v")).alias("c")).select("v", "c"), "component-labels")
    while True:
        near = edges.join(labels.select(F.col("v").alias("u"), "c"), "u").groupBy("v").agg(F.min("c").alias("near"))
        met = materialise(labels.join(near, "v").select("v", F.col("c").alias("was"), F.least("c", "near").alias("c")), "component-met")
        # Only labels are looked up, and each of them once, so a giant component is one row here.
        used = met.select("c").distinct()
        jump = met.join(used.withColumnRenamed("c", "v"), "v", "left_semi").where("c <> v").select(F.col("v").alias("c"), F.col("c").alias("next"))
        jump = materialise(jump, "component-jumps")
        new = materialise(key_join(met, jump, ["c"], "left").select("v", "was", F.coalesce("next", "c").alias("c")), "component-labels")
        for old in (labels, met, jump):
            discard(old)
        labels = new
        if new.where("was <> c").isEmpty():
            discard(edges)
            return new.select("v", "c")
