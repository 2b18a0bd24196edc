"""The given tables, and the bipartite graphs on them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F

from ..model import BipartiteGraph, to_traversals
from ..operators import ingest, network, routing

#: Runs of letters.
WORD = r"(\p{L}+)"
HREF = r'href="([^"]*)"'


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events with a zoned timestamp and the cell of their props."""
    own = table(spark, sf_dir, "events")
    return own.withColumn("ts", F.col("ts").cast("timestamp")).withColumn("k", F.get_json_object("props", "$.k").cast("int"))


def planted(spark: SparkSession, sf_dir: str, *, span: int = 2, classes=network.CLASSES, noise: int = 0, ties: str = "arterial") -> tuple[BipartiteGraph, DataFrame, DataFrame]:
    """The planted routes: graph, labels ``(v, klass)`` and paths ``(t, pos, s)``.

    Of equally fast routes ``ties="arterial"`` takes the one by the first arterial
    alone, ``"vertex"`` the one by smaller vertices, which may mix arterials.
    """
    pairs = network.planted_pairs(table(spark, sf_dir, "orders"), table(spark, sf_dir, "customer"), classes=classes, span=span)
    roads = network.segments(spark)
    weight = {"arterial": "ranked", "vertex": "travel_time"}[ties]
    paths = routing.shortest(network.first_arterials(roads), network.noisy_labels(pairs, noise) if noise else pairs, weight=weight)
    graph = BipartiteGraph.of(to_traversals(paths, roads))
    return graph, pairs.select(F.col("t").alias("v"), "klass"), paths


def word_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``(doc_id, word, n)``."""
    words = F.explode(F.regexp_extract_all(F.lower(F.col("text")), F.lit(WORD), F.lit(1)))
    return table(spark, sf_dir, "documents").select("doc_id", words.alias("word")).groupBy("doc_id", "word").agg(F.count(F.lit(1)).alias("n"))


def words(spark: SparkSession, sf_dir: str) -> BipartiteGraph:
    """Documents and their words."""
    return BipartiteGraph.of(word_rows(spark, sf_dir), t="doc_id", s=F.xxhash64("word"), length=F.length("word"))


def baskets(spark: SparkSession, sf_dir: str) -> BipartiteGraph:
    """Customers and the parts they ordered."""
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey")
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    parts = table(spark, sf_dir, "part").select("p_partkey", "p_size")
    joined = lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).join(parts, F.col("l_partkey") == F.col("p_partkey"))
    return BipartiteGraph.of(joined, t="o_custkey", s="l_partkey", n=None, length="p_size")


def shipments(spark: SparkSession, sf_dir: str) -> BipartiteGraph:
    """Orders and their suppliers."""
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey")
    return BipartiteGraph.of(lines, t="l_orderkey", s="l_suppkey", n=None, length=None)


def sessions(spark: SparkSession, sf_dir: str, *, gap: str = "24 hours") -> DataFrame:
    """Events with their trip's number, and an id of the trip in ``t``."""
    own = ingest.sessionize(events(spark, sf_dir), key="user_id", ts="ts", gap=gap, tie="event_id")
    return own.withColumn("t", F.col("user_id").cast("long") * 1_000_000 + F.col("trip"))


def session_cells(spark: SparkSession, sf_dir: str, *, gap: str = "24 hours") -> BipartiteGraph:
    """Trips and the cells they passed."""
    return BipartiteGraph.of(sessions(spark, sf_dir, gap=gap), t="t", s="k", n=None, length=None)


def link_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``(page_id, href, n)``."""
    links = F.explode(F.regexp_extract_all("html", F.lit(HREF), F.lit(1)))
    return table(spark, sf_dir, "pages").select("page_id", links.alias("href")).groupBy("page_id", "href").agg(F.count(F.lit(1)).alias("n"))


def links(spark: SparkSession, sf_dir: str) -> BipartiteGraph:
    """Pages and what they link to."""
    depth = F.size(F.split("href", "/"))
    return BipartiteGraph.of(link_rows(spark, sf_dir), t="page_id", s=F.xxhash64("href"), length=depth)


def vectors(spark: SparkSession, sf_dir: str, *, top: int = 8) -> BipartiteGraph:
    """Embeddings and their strongest dimensions, each sign a segment."""
    indexed = F.transform("embedding", lambda x, i: F.struct((-F.abs(x)).alias("less"), i.alias("i"), (x < 0).cast("int").alias("sign")))
    own = table(spark, sf_dir, "embeddings").select("vec_id", F.explode(F.slice(F.array_sort(indexed), 1, top)).alias("d"))
    return BipartiteGraph.of(own, t="vec_id", s=F.col("d.i") * 2 + F.col("d.sign"), n=None, length=None)


def flows(spark: SparkSession, sf_dir: str) -> BipartiteGraph:
    """Nations of customers and of suppliers, with the order lines between them."""
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey")
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    customers = table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey")
    suppliers = table(spark, sf_dir, "supplier").select("s_suppkey", "s_nationkey")
    joined = lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).join(customers, F.col("o_custkey") == F.col("c_custkey")).join(suppliers, F.col("l_suppkey") == F.col("s_suppkey"))
    return BipartiteGraph.of(joined.groupBy("c_nationkey", "s_nationkey").agg(F.count(F.lit(1)).alias("n")), t="c_nationkey", s="s_nationkey", length=None)


def dialogues(spark: SparkSession, sf_dir: str) -> BipartiteGraph:
    """Conversations and their words."""
    word = F.explode(F.regexp_extract_all(F.lower(F.col("text")), F.lit(WORD), F.lit(1)))
    own = table(spark, sf_dir, "conversations").select("conv_id", word.alias("word"))
    return BipartiteGraph.of(own, t=F.xxhash64(F.col("conv_id").cast("string")), s=F.xxhash64("word"), n=None, length=F.length("word"))
