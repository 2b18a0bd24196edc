"""Scans, joins, aggregates, windows, sorting and set operations around the methods."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window, functions as F

from ..scratch import new_path
from ..sources.tables import events, link_rows, table
from .registry import Catalog

catalog = Catalog()
add = catalog.add

# scans and sinks


@add("SELECT l_orderkey, l_suppkey, l_quantity FROM lineitem WHERE l_shipdate >= TIMESTAMP '1998-01-01' AND l_quantity < 10")
def scan_parquet_pruned(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "lineitem").where((F.col("l_shipdate") >= F.lit("1998-01-01").cast("timestamp_ntz")) & (F.col("l_quantity") < 10)).select("l_orderkey", "l_suppkey", "l_quantity")


@add("SELECT o_orderkey, o_totalprice, year(o_orderdate)::INT AS y FROM orders WHERE year(o_orderdate) = 1997")
def scan_partitioned(spark, d):
    path = new_path(spark, "orders-by-year")
    table(spark, d, "orders").withColumn("y", F.year("o_orderdate")).write.partitionBy("y").parquet(path)
    return spark.read.parquet(path).where("y = 1997").select("o_orderkey", "o_totalprice", "y")


def _round_trip(spark, df: DataFrame, kind: str, **options) -> DataFrame:
    path = new_path(spark, f"trip-{kind}")
    df.write.options(**options).format(kind).save(path)
    return spark.read.schema(df.schema).options(**options).format(kind).load(path)


_NATIONS = "SELECT n_nationkey, n_name, n_regionkey FROM nation"


@add(_NATIONS)
def scan_csv_roundtrip(spark, d):
    return _round_trip(spark, table(spark, d, "nation"), "csv", header="true")


@add(_NATIONS)
def scan_json_roundtrip(spark, d):
    return _round_trip(spark, table(spark, d, "nation"), "json")


@add(_NATIONS)
def scan_orc_roundtrip(spark, d):
    return _round_trip(spark, table(spark, d, "nation"), "orc")


@add("SELECT n_name AS value FROM nation")
def scan_text_lines(spark, d):
    path = new_path(spark, "trip-text")
    table(spark, d, "nation").select("n_name").write.text(path)
    return spark.read.text(path)


@add("SELECT y::INT AS y, count(*) AS n FROM (SELECT year(o_orderdate) AS y FROM orders) GROUP BY y")
def sink_partition_overwrite(spark, d):
    """Two years are written again; dynamic overwriting leaves the others."""
    path, own = new_path(spark, "overwrite"), table(spark, d, "orders").withColumn("y", F.year("o_orderdate")).select("o_orderkey", "y")
    own.write.partitionBy("y").parquet(path)
    own.where("y in (1996, 1997)").write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("y").parquet(path)
    return spark.read.parquet(path).groupBy("y").agg(F.count(F.lit(1)).alias("n"))


@add("SELECT l_suppkey, count(*) AS n FROM lineitem GROUP BY l_suppkey")
def sink_parquet_bucketed(spark, d):
    """Edges bucketed by their key, so the aggregate needs no exchange."""
    name = f"bucketed_{abs(hash(d)) % 10**8}"
    table(spark, d, "lineitem").select("l_suppkey", "l_orderkey").write.mode("overwrite").option("path", new_path(spark, "bucketed")).bucketBy(8, "l_suppkey").sortBy("l_suppkey").format("parquet").saveAsTable(name)
    return spark.table(name).groupBy("l_suppkey").agg(F.count(F.lit(1)).alias("n"))


# projections and filters


@add("SELECT o_custkey AS t, l_partkey AS s, count(*) AS n, max(p_size)::DOUBLE AS length FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey GROUP BY 1, 2")
def edges_g3(spark, d):
    from ..sources.tables import baskets

    return baskets(spark, d).traversal


@add("SELECT l_orderkey AS t, l_suppkey AS s, count(*) AS n, 1.0::DOUBLE AS length FROM lineitem GROUP BY 1, 2")
def edges_g4(spark, d):
    from ..sources.tables import shipments

    return shipments(spark, d).traversal


@add("WITH e AS (SELECT DISTINCT l_orderkey, l_suppkey FROM lineitem) SELECT l_suppkey AS s, count(*) AS degree FROM e GROUP BY 1 HAVING count(*) > (SELECT count(*) / count(DISTINCT l_suppkey) FROM e)")
def filter_hub_segments(spark, d):
    e = table(spark, d, "lineitem").select("l_orderkey", F.col("l_suppkey").alias("s")).distinct()
    of = e.groupBy("s").agg(F.count(F.lit(1)).alias("degree"))
    mean = of.agg(F.avg("degree").alias("mean"))
    return of.crossJoin(F.broadcast(mean)).where("degree > mean").select("s", "degree")


@add("WITH w AS (SELECT DISTINCT doc_id, unnest(regexp_extract_all(lower(text), '[\\p{L}]+')) AS word FROM documents) SELECT word, count(*) AS df FROM w GROUP BY word HAVING count(*) BETWEEN 3 AND 50")
def filter_df_band(spark, d):
    from ..sources.tables import word_rows

    return word_rows(spark, d).groupBy("word").agg(F.count(F.lit(1)).alias("df")).where(F.col("df").between(3, 50))


@add("SELECT p_partkey, p_name FROM part WHERE p_brand IN ('Brand#1', 'Brand#2') AND p_size BETWEEN 5 AND 15 AND p_name LIKE '%ring%'")
def predicate_in_between_like(spark, d):
    return table(spark, d, "part").where(F.col("p_brand").isin("Brand#1", "Brand#2") & F.col("p_size").between(5, 15) & F.col("p_name").like("%ring%")).select("p_partkey", "p_name")


@add("SELECT c_custkey, coalesce(nullif(c_mktsegment, 'BUILDING'), 'none') AS segment, c_acctbal IS DISTINCT FROM NULL AS known FROM customer")
def null_handling(spark, d):
    return table(spark, d, "customer").select("c_custkey", F.coalesce(F.nullif("c_mktsegment", F.lit("BUILDING")), F.lit("none")).alias("segment"), (~F.col("c_acctbal").eqNullSafe(F.lit(None))).alias("known"))


# joins


@add("SELECT o_orderkey, c_name, c_nationkey FROM orders JOIN customer ON o_custkey = c_custkey")
def join_order_customer(spark, d):
    return table(spark, d, "orders").join(table(spark, d, "customer"), F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", "c_name", "c_nationkey")


@add("SELECT c_custkey, n_name, r_name FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey")
def join_nation_broadcast(spark, d):
    # Nations and regions are fixed small sets.
    nations = table(spark, d, "nation").join(F.broadcast(table(spark, d, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return table(spark, d, "customer").join(F.broadcast(nations), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "n_name", "r_name")


_LINES = "SELECT o_custkey, round(sum(l_quantity), 2) AS quantity FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY o_custkey"


def _lines(spark, d, hint: str) -> DataFrame:
    joined = table(spark, d, "lineitem").join(table(spark, d, "orders").hint(hint), F.col("l_orderkey") == F.col("o_orderkey"))
    return joined.groupBy("o_custkey").agg(F.round(F.sum("l_quantity"), 2).alias("quantity"))


@add(_LINES)
def join_lineitem_orders_smj(spark, d):
    return _lines(spark, d, "merge")


@add(_LINES)
def join_lineitem_orders_shuffle_hash(spark, d):
    return _lines(spark, d, "shuffle_hash")


@add("WITH e AS (SELECT DISTINCT l_orderkey AS t, l_suppkey AS s FROM lineitem) SELECT x.s AS a, y.s AS b, count(*) AS common FROM e x JOIN e y ON x.t = y.t AND x.s < y.s GROUP BY 1, 2")
def join_self_projection(spark, d):
    e = table(spark, d, "lineitem").select(F.col("l_orderkey").alias("t"), F.col("l_suppkey").alias("s")).distinct()
    return e.select("t", F.col("s").alias("a")).join(e.select("t", F.col("s").alias("b")), "t").where("a < b").groupBy("a", "b").agg(F.count(F.lit(1)).alias("common"))


@add("SELECT p_partkey, count(l_orderkey) AS visits FROM part LEFT JOIN lineitem ON p_partkey = l_partkey GROUP BY p_partkey")
def join_left_visits(spark, d):
    return table(spark, d, "part").join(table(spark, d, "lineitem").select("l_partkey", "l_orderkey"), F.col("p_partkey") == F.col("l_partkey"), "left").groupBy("p_partkey").agg(F.count("l_orderkey").alias("visits"))


@add("SELECT n_name, s_suppkey FROM nation RIGHT JOIN supplier ON n_nationkey = s_nationkey")
def join_right_suppliers(spark, d):
    return table(spark, d, "nation").join(table(spark, d, "supplier"), F.col("n_nationkey") == F.col("s_nationkey"), "right").select("n_name", "s_suppkey")


@add("WITH a AS (SELECT DISTINCT l_suppkey AS s FROM lineitem WHERE l_quantity = 50 AND l_discount >= 0.1), b AS (SELECT DISTINCT l_suppkey AS s FROM lineitem WHERE l_quantity = 1 AND l_tax >= 0.08) SELECT coalesce(a.s, b.s) AS s, a.s IS NOT NULL AS in_a, b.s IS NOT NULL AS in_b FROM a FULL JOIN b ON a.s = b.s")
def join_full_unvisited_segments(spark, d):
    e = table(spark, d, "lineitem").select("l_quantity", "l_discount", "l_tax", F.col("l_suppkey").alias("s"))
    side = lambda which, c: e.where(which).select("s").distinct().withColumn(c, F.lit(True))
    return side("l_quantity = 50 and l_discount >= 0.1", "in_a").join(side("l_quantity = 1 and l_tax >= 0.08", "in_b"), "s", "full").select("s", F.col("in_a").isNotNull().alias("in_a"), F.col("in_b").isNotNull().alias("in_b"))


@add("SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 200000)")
def join_active_customers(spark, d):
    return table(spark, d, "customer").join(table(spark, d, "orders").where("o_totalprice > 200000"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey")


@add("SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderstatus = 'F')")
def join_never_ordered(spark, d):
    return table(spark, d, "customer").join(table(spark, d, "orders").where("o_orderstatus = 'F'"), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey")


@add("SELECT a.n_nationkey AS departure, b.n_nationkey AS arrival FROM nation a JOIN nation b ON a.n_nationkey <> b.n_nationkey AND abs(a.n_nationkey - b.n_nationkey) > 12")
def join_zone_pairs_theta(spark, d):
    n = table(spark, d, "nation").select("n_nationkey")
    return n.alias("a").join(F.broadcast(n.alias("b")), F.expr("a.n_nationkey <> b.n_nationkey and abs(a.n_nationkey - b.n_nationkey) > 12")).select(F.col("a.n_nationkey").alias("departure"), F.col("b.n_nationkey").alias("arrival"))


@add("SELECT n.n_nationkey, r.r_regionkey FROM nation n CROSS JOIN region r")
def join_zone_cross(spark, d):
    return table(spark, d, "nation").select("n_nationkey").crossJoin(F.broadcast(table(spark, d, "region").select("r_regionkey")))


@add("SELECT event_id, s_suppkey FROM events JOIN supplier ON s_acctbal BETWEEN value * 100 - 5 AND value * 100 + 5")
def join_events_price_band(spark, d):
    """A range join through grid cells as wide as the band."""
    own = table(spark, d, "events").select("event_id", "value").withColumn("cell", F.explode(F.array(*[F.floor(F.col("value") * 10) + i for i in (-1, 0, 1)])))
    other = table(spark, d, "supplier").select("s_suppkey", "s_acctbal").withColumn("cell", F.floor(F.col("s_acctbal") / 10))
    return own.join(other, "cell").where("s_acctbal between value * 100 - 5 and value * 100 + 5").select("event_id", "s_suppkey")


@add("SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_id <> b.event_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def join_trip_window(spark, d):
    """An interval join by hour cells of each user."""
    e = events(spark, d).select("event_id", "user_id", "ts").withColumn("cell", F.floor(F.unix_timestamp("ts") / 3600))
    later = e.select(F.col("event_id").alias("b"), "user_id", F.col("ts").alias("late"), "cell")
    own = e.withColumn("cell", F.explode(F.array(F.col("cell"), F.col("cell") + 1)))
    return own.join(later, ["user_id", "cell"]).where("event_id <> b and late >= ts and late <= ts + interval 1 hour").select(F.col("event_id").alias("a"), "b")


@add("SELECT p.event_id, l.event_id AS last_view FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'view') l ON p.user_id = l.user_id AND p.ts >= l.ts")
def join_asof_last_event(spark, d):
    """As-of join without a range: both kinds in one window, the last view is carried on."""
    e = events(spark, d).where("event_type in ('purchase', 'view')")
    order = Window.partitionBy("user_id").orderBy("ts", F.col("event_type") == "purchase", "event_id").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    seen = F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(order)
    return e.withColumn("last_view", seen).where("event_type = 'purchase'").select("event_id", "last_view")


@add("SELECT n_nationkey, c_custkey FROM nation, LATERAL (SELECT c_custkey FROM customer WHERE c_nationkey = n_nationkey ORDER BY c_acctbal DESC, c_custkey LIMIT 2)")
def join_lateral_topk(spark, d):
    order = Window.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"), "c_custkey")
    best = table(spark, d, "customer").withColumn("r", F.row_number().over(order)).where("r <= 2")
    return table(spark, d, "nation").join(best, F.col("n_nationkey") == F.col("c_nationkey")).select("n_nationkey", "c_custkey")


# aggregates

_G4 = "(SELECT DISTINCT l_orderkey AS t, l_suppkey AS s FROM lineitem)"


@add(f"SELECT t, count(*) AS degree FROM {_G4} GROUP BY t")
def agg_degree_t(spark, d):
    from ..sources.tables import shipments

    return shipments(spark, d).degrees("t").select("t", "degree")


@add(f"SELECT s, count(*) AS degree FROM {_G4} GROUP BY s")
def agg_degree_s(spark, d):
    from ..sources.tables import shipments

    return shipments(spark, d).degrees("s").select("s", "degree")


@add("SELECT l_returnflag, count(DISTINCT l_suppkey) AS segments FROM lineitem GROUP BY 1")
def agg_distinct_segments(spark, d):
    return table(spark, d, "lineitem").groupBy("l_returnflag").agg(F.count_distinct("l_suppkey").alias("segments"))


@add("SELECT r_name, n_name, count(*) AS orders FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)")
def agg_visits_rollup(spark, d):
    own = table(spark, d, "orders").join(table(spark, d, "customer"), F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(table(spark, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(table(spark, d, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return own.rollup("r_name", "n_name").agg(F.count(F.lit(1)).alias("orders"))


@add("SELECT l_returnflag, l_linestatus, count(*) AS n, grouping(l_returnflag)::INT AS g FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def agg_cube_flags(spark, d):
    return table(spark, d, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"), F.grouping("l_returnflag").cast("int").alias("g"))


@add("SELECT lang, source, count(*) AS n FROM documents GROUP BY GROUPING SETS ((lang), (source), ())")
def agg_grouping_sets_margins(spark, d):
    own = table(spark, d, "documents")
    return own.groupingSets([["lang"], ["source"], []], "lang", "source").agg(F.count(F.lit(1)).alias("n"))


@add("SELECT source, count(*) FILTER (lang = 'en') AS en, count(*) FILTER (lang = 'fr') AS fr, count(*) FILTER (lang = 'de') AS de, count(*) FILTER (lang = 'es') AS es FROM documents GROUP BY source")
def agg_pivot_confusion(spark, d):
    pivoted = table(spark, d, "documents").groupBy("source").pivot("lang", ["en", "fr", "de", "es"]).count()
    return pivoted.na.fill(0)


@add("SELECT l_suppkey, count(*) FILTER (l_returnflag = 'R') AS returned, count(*) AS n FROM lineitem GROUP BY l_suppkey")
def agg_filter_clause(spark, d):
    return table(spark, d, "lineitem").groupBy("l_suppkey").agg(F.count_if(F.col("l_returnflag") == "R").alias("returned"), F.count(F.lit(1)).alias("n"))


@add("SELECT true AS close FROM lineitem LIMIT 1")
def agg_approx_distinct(spark, d):
    own = table(spark, d, "lineitem").agg(F.approx_count_distinct("l_partkey", 0.02).alias("a"), F.count_distinct("l_partkey").alias("b"))
    return own.select((F.abs(F.col("a") / F.col("b") - 1) < 0.1).alias("close"))


@add("SELECT l_returnflag, round(quantile_cont(l_extendedprice, 0.5), 4) AS median, round(quantile_cont(l_extendedprice, 0.9), 4) AS p90 FROM lineitem GROUP BY 1")
def agg_percentiles(spark, d):
    p = lambda q: F.round(F.percentile("l_extendedprice", F.lit(q)), 4)
    return table(spark, d, "lineitem").groupBy("l_returnflag").agg(p(0.5).alias("median"), p(0.9).alias("p90"))


@add("SELECT c_nationkey, max_by(c_custkey, c_acctbal) AS richest, max(c_acctbal) AS balance FROM customer GROUP BY 1")
def agg_max_by(spark, d):
    return table(spark, d, "customer").groupBy("c_nationkey").agg(F.max_by("c_custkey", "c_acctbal").alias("richest"), F.max("c_acctbal").alias("balance"))


@add("SELECT user_id, string_agg(event_type, '>' ORDER BY ts, event_id) AS path FROM events GROUP BY user_id")
def agg_listagg_path(spark, d):
    ordered = F.array_sort(F.collect_list(F.struct("ts", "event_id", "event_type")))
    return events(spark, d).groupBy("user_id").agg(F.array_join(F.transform(ordered, lambda x: x["event_type"]), ">").alias("path"))


@add("SELECT l_returnflag, round(stddev_samp(l_quantity), 6) AS sd, round(var_pop(l_quantity), 6) AS var, round(corr(l_quantity, l_extendedprice), 6) AS corr FROM lineitem GROUP BY 1")
def agg_stddev_corr(spark, d):
    return table(spark, d, "lineitem").groupBy("l_returnflag").agg(F.round(F.stddev_samp("l_quantity"), 6).alias("sd"), F.round(F.var_pop("l_quantity"), 6).alias("var"), F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("corr"))


@add()
def agg_topk_sketch(spark, d):
    """Most frequent suppliers by sketch, beside the distinct parts by another."""
    return table(spark, d, "lineitem").agg(F.expr("approx_top_k(l_suppkey, 5)").alias("top"), F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey")).alias("parts"))


# windows


@add("SELECT c_custkey, rank() OVER w AS r, dense_rank() OVER w AS dr, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) AS rn, ntile(4) OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey)::INT AS q, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_acctbal DESC)")
def win_rank_segments(spark, d):
    w = Window.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"))
    u = Window.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"), "c_custkey")
    return table(spark, d, "customer").select("c_custkey", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("dr"), F.row_number().over(u).alias("rn"), F.ntile(4).over(u).alias("q"), F.round(F.percent_rank().over(w), 6).alias("pr"), F.round(F.cume_dist().over(w), 6).alias("cd"))


@add("WITH x AS (SELECT event_type AS a, lead(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS b FROM events) SELECT a, b, count(*) AS n FROM x WHERE b IS NOT NULL GROUP BY 1, 2")
def win_lag_lead_transitions(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return events(spark, d).select(F.col("event_type").alias("a"), F.lead("event_type").over(w).alias("b")).where("b is not null").groupBy("a", "b").agg(F.count(F.lit(1)).alias("n"))


@add("SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 4 PRECEDING AND CURRENT ROW), 6) AS run FROM events")
def win_running_distance(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-4, 0)
    return events(spark, d).select("event_id", F.round(F.sum("value").over(w), 6).alias("run"))


@add("SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderdate RANGE BETWEEN INTERVAL 7 DAY PRECEDING AND CURRENT ROW) AS week FROM orders")
def win_range_7d(spark, d):
    w = Window.partitionBy("o_custkey").orderBy(F.unix_timestamp(F.col("o_orderdate").cast("timestamp"))).rangeBetween(-7 * 86400, 0)
    return table(spark, d, "orders").select("o_orderkey", F.count(F.lit(1)).over(w).alias("week"))


@add("SELECT l_orderkey, l_linenumber, round(l_quantity / sum(l_quantity) OVER (PARTITION BY l_orderkey), 6) AS share FROM lineitem")
def win_share_of_total(spark, d):
    return table(spark, d, "lineitem").select("l_orderkey", "l_linenumber", F.round(F.col("l_quantity") / F.sum("l_quantity").over(Window.partitionBy("l_orderkey")), 6).alias("share"))


@add("SELECT event_id, first_value(event_type) OVER w AS f, last_value(event_type) OVER w AS l, nth_value(event_type, 2) OVER w AS second FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
def win_first_last_nth(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return events(spark, d).select("event_id", F.first("event_type").over(w).alias("f"), F.last("event_type").over(w).alias("l"), F.nth_value("event_type", 2).over(w).alias("second"))


# sorting and limits


@add("SELECT c_custkey FROM customer ORDER BY c_acctbal DESC, c_custkey LIMIT 25")
def topk_customers(spark, d):
    return table(spark, d, "customer").orderBy(F.desc("c_acctbal"), "c_custkey").limit(25).select("c_custkey")


@add("SELECT c_custkey, c_nationkey FROM (SELECT *, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) AS r FROM customer) WHERE r <= 3")
def topk_per_group_neighbours(spark, d):
    w = Window.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"), "c_custkey")
    return table(spark, d, "customer").withColumn("r", F.row_number().over(w)).where("r <= 3").select("c_custkey", "c_nationkey")


@add("SELECT c_custkey FROM customer ORDER BY nullif(c_mktsegment, 'BUILDING') NULLS LAST, c_custkey LIMIT 50")
def sort_nulls_last(spark, d):
    return table(spark, d, "customer").orderBy(F.nullif("c_mktsegment", F.lit("BUILDING")).asc_nulls_last(), "c_custkey").limit(50).select("c_custkey")


@add("SELECT o_orderkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20 OFFSET 40")
def limit_offset(spark, d):
    return table(spark, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(40).limit(20).select("o_orderkey")


# sets


_FIRST, _SECOND = "l_quantity = 50 AND l_returnflag = 'R'", "l_quantity = 1 AND l_returnflag = 'N'"


def _keys(spark, d, which: str) -> DataFrame:
    return table(spark, d, "lineitem").where(which).select(F.col("l_suppkey").alias("s"))


def _key_sql(operator: str) -> str:
    return f"SELECT l_suppkey AS s FROM lineitem WHERE {_FIRST} {operator} SELECT l_suppkey AS s FROM lineitem WHERE {_SECOND}"


for _name, _operator, _run in (
    ("set_union_all", "UNION ALL", lambda a, b: a.unionAll(b)),
    ("set_union_distinct", "UNION", lambda a, b: a.union(b).distinct()),
    ("set_intersect_common_segments", "INTERSECT", lambda a, b: a.intersect(b)),
    ("set_except_missing", "EXCEPT", lambda a, b: a.subtract(b)),
    ("set_intersect_all", "INTERSECT ALL", lambda a, b: a.intersectAll(b)),
    ("set_except_all", "EXCEPT ALL", lambda a, b: a.exceptAll(b)),
):
    add(_key_sql(_operator), name=_name)(lambda spark, d, run=_run: run(_keys(spark, d, _FIRST), _keys(spark, d, _SECOND)))


@add("SELECT c_custkey AS key, c_name AS name, NULL::DOUBLE AS balance FROM customer UNION ALL SELECT s_suppkey, s_name, s_acctbal FROM supplier")
def union_by_name(spark, d):
    a = table(spark, d, "customer").select(F.col("c_custkey").alias("key"), F.col("c_name").alias("name"))
    b = table(spark, d, "supplier").select(F.col("s_acctbal").alias("balance"), F.col("s_name").alias("name"), F.col("s_suppkey").alias("key"))
    return a.unionByName(b, allowMissingColumns=True)


# subqueries and recursion


@add("SELECT o_orderkey FROM orders o WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey AND l_quantity > 49)")
def sub_exists_correlated(spark, d):
    return table(spark, d, "orders").join(table(spark, d, "lineitem").where("l_quantity > 49"), F.col("o_orderkey") == F.col("l_orderkey"), "left_semi").select("o_orderkey")


@add("SELECT c_custkey FROM customer c WHERE c_acctbal > (SELECT avg(c_acctbal) FROM customer x WHERE x.c_nationkey = c.c_nationkey)")
def sub_scalar_avg(spark, d):
    own = table(spark, d, "customer")
    return own.withColumn("mean", F.avg("c_acctbal").over(Window.partitionBy("c_nationkey"))).where("c_acctbal > mean").select("c_custkey")


@add("WITH RECURSIVE p(v, hops) AS (SELECT min(o_orderkey), 0 FROM orders UNION ALL SELECT o_orderkey, hops + 1 FROM p JOIN orders ON o_orderkey = v + 7 WHERE hops < 10) SELECT v::BIGINT AS v, hops::INT AS hops FROM p")
def cte_recursive_path(spark, d):
    """A path over the orders: from the first, ten times on to the one whose key is seven more."""
    keys = table(spark, d, "orders").select(F.col("o_orderkey").cast("long").alias("key"))
    # A path has one end, so it is broadcast at any number of orders.
    walk = "WITH RECURSIVE p(v, hops) AS (SELECT min(key), 0 FROM {keys} UNION ALL SELECT /*+ BROADCAST(p) */ k.key, hops + 1 FROM p JOIN {keys} k ON k.key = p.v + 7 WHERE hops < 10)"
    return spark.sql(walk + " SELECT v, hops FROM p", keys=keys)


@add("SELECT o_orderkey FROM orders WHERE (o_orderkey * 2654435761) % 1000 < 100")
def sample_hash_trajectories(spark, d):
    """A tenth of the orders, the same in every run."""
    return table(spark, d, "orders").where((F.col("o_orderkey") * 2654435761) % 1000 < 100).select("o_orderkey")


@add()
def sample_stratified_class(spark, d):
    return table(spark, d, "documents").sampleBy("lang", {"en": 0.1, "fr": 0.3, "de": 0.3, "es": 0.3}, seed=42).select("doc_id", "lang")


@add("SELECT href, count(DISTINCT page_id) AS pages FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS href FROM pages) GROUP BY href")
def str_href_extract(spark, d):
    return link_rows(spark, d).groupBy("href").agg(F.count(F.lit(1)).alias("pages"))
