"""Dropping rows by verdicts that were found apart from them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F

from ..joins import key_join, small
from ..scratch import materialise


def content_key(text_col: str) -> Column:
    """With the id, what a row is known by in a second reading of its table."""
    return F.xxhash64(F.coalesce(F.col(text_col).cast("string"), F.lit("")))


def fresh(df: DataFrame, name: str) -> str:
    """A column name like ``name`` that ``df`` does not have, in whatever case."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name = f"{name}_"
    return name


def quoted(names: list[str]) -> list[Column]:
    """Columns by their names as they stand, dots and all."""
    return [F.col("`" + n.replace("`", "``") + "`") for n in names]


def drop(docs: DataFrame, verdicts: DataFrame, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``docs`` without the rows whose verdict is not to be kept; of repeated rows as many stay as one at most.

    ``verdicts`` has ``doc_id``, ``key`` (see :func:`content_key`) and ``kept``, and rows for all whose group has others.
    """
    of_key = verdicts.groupBy("doc_id", "key").agg(F.max("kept").alias("any_kept"), F.count(F.lit(1)).alias("times"))
    gone = materialise(of_key.where("not any_kept or times > 1"), "losers")
    names, key = docs.columns, fresh(docs, "content_key")
    tagged = docs.withColumn(key, content_key(text_col))

    def same(keys: DataFrame) -> Column:
        return tagged[id_col].eqNullSafe(keys["doc_id"]) & (tagged[key] == keys["key"])

    rest = key_join(tagged, gone, same(gone), "left_anti").select(*quoted(names))
    repeated = gone.where("any_kept")
    if small(repeated, 0):
        return rest
    again = key_join(tagged, repeated, same(repeated), "left_semi").dropDuplicates([id_col, key]).select(*quoted(names))
    return rest.unionByName(again)
