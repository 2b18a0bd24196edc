"""Exact deduplication by content hash with a byte check.

Texts are equal when they are identical without white space. Rows are grouped
by a 128-bit hash of that normalised text; of a group the row with the most
code points in its original text stays, then the smallest id. Groups of two or
more are then compared byte by byte: the smallest and the largest normalised
text of a group must be the same bytes. The comparison is an aggregate, which
combines on the map side, so a group with a third of all rows is no hot spot.
Groups that fail it are hash collisions and are regrouped by the bytes.

Defined results: null counts as empty; of repeated rows (same id and text) one
row stays; a null id is the smallest; an empty table gives an empty table;
other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, functions as F

from ..joins import key_join, small
from ..scratch import materialise
from . import losers

#: White space that equality ignores: space and 0x09 to 0x0D.
WHITE = " \t\n\x0b\x0c\r"


def content_hash(normalised: Column) -> Column:
    """128-bit hash of a text."""
    return F.unhex(F.md5(normalised))


def _keyed(docs: DataFrame, id_col: str, text_col: str, hashed: Callable[[Column], Column]) -> DataFrame:
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    own = docs.select(F.col(id_col).alias("doc_id"), F.length(text).cast("long").alias("n_points"), losers.content_key(text_col).alias("key"), F.translate(text, WHITE, "").alias("norm"))
    return own.withColumn("h", hashed(F.col("norm")))


def _winners(rows: DataFrame, by: list[str]) -> DataFrame:
    """Of each group: its size and the row that stays."""
    best = F.min(F.struct((-F.col("n_points")).alias("less"), "doc_id", "row_id"))
    return rows.groupBy(*by).agg(F.count(F.lit(1)).alias("group_size"), best.alias("best"))


_RESULT = ("doc_id", "keep_id", "group_size", "kept", "text_sha256", "key")


def _marked(rows: DataFrame, groups: DataFrame, by: list[str]) -> DataFrame:
    joined = rows.join(groups, by)
    return joined.select(
        "doc_id",
        F.col("best.doc_id").alias("keep_id"),
        "group_size",
        (F.col("row_id") == F.col("best.row_id")).alias("kept"),
        F.lower(F.hex("sha")).alias("text_sha256"),
        "key",
    )


def exact_groups(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", hashed: Callable[[Column], Column] = content_hash) -> DataFrame:
    """One row per document with the row that stays of its group.

    Only ids, lengths and hashes are written and shuffled for grouping; texts
    move for the byte check alone, and only those whose hash occurs twice.
    """
    keyed = _keyed(docs, id_col, text_col, hashed)
    narrow = keyed.select("doc_id", "n_points", "key", "h", F.unhex(F.sha2("norm", 256)).alias("sha")).withColumn("row_id", F.monotonically_increasing_id())
    narrow = materialise(narrow, "exact-keys")
    # Written, so that the join below deals both sides anew and a hot group can be split.
    groups = materialise(_winners(narrow, ["h"]), "exact-groups")
    doubled = materialise(groups.where("group_size > 1").select("h"), "exact-doubled")
    members = key_join(keyed.select("h", "norm"), doubled, ["h"], "left_semi")
    collided = materialise(members.groupBy("h").agg(F.min("norm").alias("a"), F.max("norm").alias("b")).where("a <> b").select("h"), "exact-collided")
    if small(collided, 0):
        return _marked(narrow, groups, ["h"]).select(*_RESULT)
    clean = _marked(key_join(narrow, collided, ["h"], "left_anti"), groups, ["h"])
    mixed = key_join(keyed.withColumn("sha", F.unhex(F.sha2("norm", 256))), collided, ["h"], "left_semi").withColumn("row_id", F.monotonically_increasing_id())
    mixed = materialise(mixed, "exact-mixed")
    return clean.select(*_RESULT).unionByName(_marked(mixed, _winners(mixed, ["h", "norm"]), ["h", "norm"]).select(*_RESULT))


def drop_copies(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The documents without those of which another copy stays; all columns are kept."""
    verdicts = exact_groups(docs, id_col=id_col, text_col=text_col).where("group_size > 1").select("doc_id", "key", "kept")
    return losers.drop(docs, verdicts, id_col=id_col, text_col=text_col)
