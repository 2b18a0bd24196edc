"""Functions for SQL and DataFrames where built-in ones can't express the semantics."""

from __future__ import annotations

from collections.abc import Iterator
from difflib import SequenceMatcher

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession, types as T
from pyspark.sql.functions import pandas_udf, udf, udtf


@udf(T.DoubleType(), useArrow=True)
def edit_similarity(a: str, b: str) -> float:
    """Share of two strings that matches in order; null with a null."""
    return None if a is None or b is None else SequenceMatcher(None, a, b).ratio()


@pandas_udf(T.LongType())
def weighted_mode(value: pd.Series, weight: pd.Series) -> int:
    """The value of most weight in a group; ties go to the smallest."""
    total = weight.groupby(value).sum()
    return int(total[total == total.max()].index.min()) if len(total) else None


@pandas_udf(T.DoubleType())
def log_gamma(n: Iterator[pd.Series]) -> Iterator[pd.Series]:
    """ln of the gamma function, by batches."""
    from math import lgamma

    for x in n:
        yield pd.Series(np.array([lgamma(v) for v in x.to_numpy(dtype=float)]))


@udtf(returnType=T.StructType([T.StructField("pos", T.IntegerType()), T.StructField("a", T.LongType()), T.StructField("b", T.LongType())]))
class PathSteps:
    """Consecutive pairs of a path."""

    def eval(self, path: list[int]):
        for i, (a, b) in enumerate(zip(path or [], (path or [])[1:])):
            yield i, a, b


@udtf(returnType=T.StructType([T.StructField("v", T.LongType())]))
class ZoneVertices:
    """Vertices of a zone of the lattice."""

    def eval(self, zone: int, side: int, zones: int):
        width = side // zones
        for i in range(width):
            for j in range(width):
                yield (((zone // zones) * width + i) * side + (zone % zones) * width + j,)


def register(spark: SparkSession) -> None:
    """Make the functions known to SQL, and a SQL function with them."""
    spark.udf.register("edit_similarity", edit_similarity)
    spark.udf.register("weighted_mode", weighted_mode)
    spark.udtf.register("path_steps", PathSteps)
    spark.udtf.register("zone_vertices", ZoneVertices)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION idf(n DOUBLE, d DOUBLE) RETURNS DOUBLE RETURN ln(n / d)")


