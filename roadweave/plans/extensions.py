"""Queries of the user-defined functions."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions import udfs
from ..sources.tables import events, table
from .registry import Catalog

catalog = Catalog()
add = catalog.add


@add("SELECT n_nationkey, 1.0::DOUBLE AS same FROM nation")
def udf_edit_similarity(spark, d):
    return table(spark, d, "nation").select("n_nationkey", udfs.edit_similarity("n_name", F.concat("n_name", F.lit(""))).alias("same"))


@add("SELECT user_id, arg_min(k, (-w, k)) AS mode FROM (SELECT user_id, json_extract(props, '$.k')::BIGINT AS k, round(sum(value), 6) AS w FROM events GROUP BY 1, 2) GROUP BY 1")
def udaf_weighted_mode(spark, d):
    own = events(spark, d).groupBy("user_id", F.col("k").cast("long").alias("k")).agg(F.round(F.sum("value"), 6).alias("w"))
    return own.groupBy("user_id").agg(udfs.weighted_mode("k", "w").alias("mode"))


@add("SELECT user_id, (i - 1)::INT AS pos, ks[i] AS a, ks[i + 1] AS b FROM (SELECT user_id, ks, unnest(range(1, len(ks))) AS i FROM (SELECT user_id, list(json_extract(props, '$.k')::BIGINT ORDER BY ts, event_id) AS ks FROM events GROUP BY user_id))")
def udtf_path_steps(spark, d):
    udfs.register(spark)
    ordered = F.array_sort(F.collect_list(F.struct("ts", "event_id", F.col("k").cast("long").alias("k"))))
    events(spark, d).groupBy("user_id").agg(F.transform(ordered, lambda x: x["k"]).alias("path")).createOrReplaceTempView("rw_paths")
    return spark.sql("SELECT user_id, s.pos, s.a, s.b FROM rw_paths, LATERAL path_steps(path) s")


@add("SELECT n_nationkey, 256::BIGINT AS vertices FROM nation")
def udtf_zone_vertices(spark, d):
    udfs.register(spark)
    table(spark, d, "nation").createOrReplaceTempView("rw_nations")
    return spark.sql("SELECT n_nationkey, count(*) AS vertices FROM rw_nations, LATERAL zone_vertices(n_nationkey, 80, 5) z GROUP BY n_nationkey")


@add("SELECT p_partkey, round(ln(51.0 / p_size), 6) AS w FROM part")
def sql_function_idf(spark, d):
    udfs.register(spark)
    table(spark, d, "part").createOrReplaceTempView("rw_parts")
    return spark.sql("SELECT p_partkey, round(idf(51.0D, CAST(p_size AS DOUBLE)), 6) AS w FROM rw_parts")


@add("SELECT o_orderkey, round(lgamma(o_orderkey % 5000 + 1.5), 6) AS g FROM orders")
def udf_log_gamma(spark, d):
    return table(spark, d, "orders").select("o_orderkey", F.round(udfs.log_gamma((F.col("o_orderkey") % 5000 + 1.5).cast("double")), 6).alias("g"))
