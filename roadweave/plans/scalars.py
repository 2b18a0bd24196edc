"""String, date, mathematical, array, map and JSON functions around the methods."""

from __future__ import annotations


from pyspark.sql import functions as F

from ..functions.scalar import haversine_km, log_factorial
from ..sources.tables import events, table, word_rows
from .registry import Catalog

catalog = Catalog()
add = catalog.add


@add("SELECT doc_id, word, count(*) AS n FROM (SELECT doc_id, unnest(regexp_extract_all(lower(text), '[\\p{L}]+')) AS word FROM documents) GROUP BY 1, 2")
def str_tokenise_words(spark, d):
    return word_rows(spark, d)


@add("SELECT page_id, regexp_extract(url, '^[a-z]+://[^/]+/([a-z]{2})/', 1) AS lang, regexp_extract(url, '^[a-z]+://([^/]+)/', 1) AS host FROM pages")
def str_url_lang(spark, d):
    return table(spark, d, "pages").select("page_id", F.regexp_extract("url", "^[a-z]+://[^/]+/([a-z]{2})/", 1).alias("lang"), F.parse_url("url", F.lit("HOST")).alias("host"))


@add("SELECT p_partkey, upper(trim(p_name)) AS name, lpad(p_partkey::VARCHAR, 6, '0') AS code, reverse(p_brand) AS brand, replace(p_type, 'A', 'a') AS kind FROM part")
def str_normalise(spark, d):
    return table(spark, d, "part").select("p_partkey", F.upper(F.trim("p_name")).alias("name"), F.lpad(F.col("p_partkey").cast("string"), 6, "0").alias("code"), F.reverse("p_brand").alias("brand"), F.replace("p_type", F.lit("A"), F.lit("a")).alias("kind"))


@add("SELECT p_partkey, split_part(p_brand, '#', 2)::INT AS brand, split_part(p_name, ' ', 1) AS size FROM part")
def str_split_brand(spark, d):
    return table(spark, d, "part").select("p_partkey", F.split_part("p_brand", F.lit("#"), F.lit(2)).cast("int").alias("brand"), F.split_part("p_name", F.lit(" "), F.lit(1)).alias("size"))


@add("SELECT a.n_name AS a, b.n_name AS b, levenshtein(a.n_name, b.n_name)::INT AS d FROM nation a JOIN nation b ON a.n_nationkey < b.n_nationkey")
def str_levenshtein_names(spark, d):
    n = table(spark, d, "nation")
    return n.alias("a").join(F.broadcast(n.alias("b")), F.expr("a.n_nationkey < b.n_nationkey")).select(F.col("a.n_name").alias("a"), F.col("b.n_name").alias("b"), F.levenshtein("a.n_name", "b.n_name").alias("d"))


@add("SELECT date_trunc('month', o_orderdate)::DATE AS month, count(*) AS n FROM orders GROUP BY 1")
def date_trunc_month(spark, d):
    return table(spark, d, "orders").groupBy(F.to_date(F.date_trunc("month", "o_orderdate")).alias("month")).agg(F.count(F.lit(1)).alias("n"))


@add("SELECT user_id, date_diff('second', min(date_trunc('second', ts)), max(date_trunc('second', ts))) AS seconds FROM events GROUP BY user_id")
def date_trip_duration(spark, d):
    second = F.unix_timestamp("ts")
    return events(spark, d).groupBy("user_id").agg((F.max(second) - F.min(second)).alias("seconds"))


@add("SELECT time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '1970-01-01') AS bin, count(*) AS n FROM events GROUP BY 1")
def date_bins(spark, d):
    own = events(spark, d).groupBy(F.window("ts", "6 hours").alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return own.select(F.col("w.start").cast("timestamp_ntz").alias("bin"), "n")


@add("SELECT l_orderkey, l_linenumber, date_diff('day', o_orderdate, l_shipdate) AS days, dayofweek(l_shipdate)::INT + 1 AS dow FROM lineitem JOIN orders ON l_orderkey = o_orderkey")
def date_diff_ship(spark, d):
    own = table(spark, d, "lineitem").join(table(spark, d, "orders"), F.col("l_orderkey") == F.col("o_orderkey"))
    return own.select("l_orderkey", "l_linenumber", F.datediff("l_shipdate", "o_orderdate").cast("long").alias("days"), F.dayofweek("l_shipdate").alias("dow"))


@add("SELECT event_id, strftime(ts, '%Y-%m-%d %H:%M:%S') AS shown FROM events")
def ts_cast_ntz(spark, d):
    return events(spark, d).select("event_id", F.date_format("ts", "yyyy-MM-dd HH:mm:ss").alias("shown"))


@add("WITH e AS (SELECT DISTINCT l_orderkey, l_suppkey FROM lineitem) SELECT l_suppkey AS s, round(ln((SELECT count(DISTINCT l_orderkey) FROM e)::DOUBLE / count(*)), 6) AS idf FROM e GROUP BY 1")
def math_idf(spark, d):
    e = table(spark, d, "lineitem").select("l_orderkey", "l_suppkey").distinct()
    total = F.broadcast(e.agg(F.count_distinct("l_orderkey").alias("n")))
    return e.groupBy(F.col("l_suppkey").alias("s")).agg(F.count(F.lit(1)).alias("d")).crossJoin(total).select("s", F.round(F.ln(F.col("n") / F.col("d")), 6).alias("idf"))


@add("SELECT o_orderkey, round(lgamma(o_orderkey % 1000 + 1), 6) AS lf FROM orders")
def math_log_factorial(spark, d):
    return table(spark, d, "orders").select("o_orderkey", F.round(log_factorial(F.col("o_orderkey") % 1000), 6).alias("lf"))


@add("SELECT o_orderkey, (o_orderkey * 31 + 7) % 256 AS cell, ((o_orderkey - 500) % 7 + 7) % 7 AS p FROM orders")
def math_hash_mod(spark, d):
    return table(spark, d, "orders").select("o_orderkey", ((F.col("o_orderkey") * 31 + 7) % 256).alias("cell"), F.pmod(F.col("o_orderkey") - 500, F.lit(7)).alias("p"))


@add("SELECT c_custkey, round(2 * 6371.0 * asin(sqrt(pow(sin(radians(c_nationkey - 10.0) / 2), 2) + cos(radians(10.0)) * cos(radians(c_nationkey::DOUBLE)) * pow(sin(radians(c_custkey % 90 - 20.0) / 2), 2))), 4) AS km FROM customer")
def math_haversine(spark, d):
    lat, lon = F.col("c_nationkey").cast("double"), (F.col("c_custkey") % 90).cast("double")
    return table(spark, d, "customer").select("c_custkey", F.round(haversine_km(F.lit(10.0), F.lit(20.0), lat, lon), 4).alias("km"))


@add("SELECT l_orderkey, l_linenumber, floor(l_extendedprice)::BIGINT AS f, ceil(l_extendedprice)::BIGINT AS c, round(l_extendedprice, 0)::BIGINT AS r FROM lineitem")
def math_round_modes(spark, d):
    p = F.col("l_extendedprice")
    return table(spark, d, "lineitem").select("l_orderkey", "l_linenumber", F.floor(p).alias("f"), F.ceil(p).alias("c"), F.round(p, 0).cast("long").alias("r"))


def _paths(spark, d):
    ordered = F.array_sort(F.collect_list(F.struct("ts", "event_id", "event_type")))
    return events(spark, d).groupBy("user_id").agg(F.transform(ordered, lambda x: x["event_type"]).alias("path"))


_PATHS = "(SELECT user_id, list(event_type ORDER BY ts, event_id) AS path FROM events GROUP BY user_id)"


@add(f"SELECT user_id, path[i] || '>' || path[i + 1] AS gram, count(*) AS n FROM (SELECT user_id, path, unnest(range(1, len(path))) AS i FROM {_PATHS}) GROUP BY 1, 2")
def arr_path_ngrams(spark, d):
    pair = F.transform(F.sequence(F.lit(0), F.size("path") - 2), lambda i: F.concat_ws(">", F.get("path", i), F.get("path", i + 1)))
    return _paths(spark, d).where(F.size("path") > 1).select("user_id", F.explode(pair).alias("gram")).groupBy("user_id", "gram").agg(F.count(F.lit(1)).alias("n"))


@add(f"WITH p AS (SELECT user_id, list_sort(list_distinct(path)) AS s FROM {_PATHS}) SELECT a.user_id AS a, b.user_id AS b, round(len(list_intersect(a.s, b.s))::DOUBLE / len(list_distinct(list_concat(a.s, b.s))), 6) AS j FROM p a JOIN p b ON b.user_id = a.user_id + 1")
def arr_overlap_jaccard(spark, d):
    p = _paths(spark, d).select("user_id", F.array_distinct("path").alias("s"))
    met = p.alias("a").join(p.alias("b"), F.col("b.user_id") == F.col("a.user_id") + 1)
    return met.select(F.col("a.user_id").alias("a"), F.col("b.user_id").alias("b"), F.round(F.size(F.array_intersect("a.s", "b.s")) / F.size(F.array_union("a.s", "b.s")), 6).alias("j"))


@add(f"SELECT user_id, (i - 1)::INT AS pos, path[i] AS step FROM (SELECT user_id, path, unnest(range(1, len(path) + 1)) AS i FROM {_PATHS})")
def arr_explode_pos(spark, d):
    return _paths(spark, d).select("user_id", F.posexplode("path").alias("pos", "step"))


@add("SELECT a.vec_id, round(list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 5) AS sim FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1")
def arr_zip_cosine(spark, d):
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p.cast("double") * q.cast("double")), F.lit(0.0), lambda s, v: s + v)
    e = table(spark, d, "embeddings")
    met = e.alias("a").join(e.select(F.col("vec_id").alias("other"), F.col("embedding").alias("y")), F.col("other") == F.col("a.vec_id") + 1)
    x, y = F.col("a.embedding"), F.col("y")
    return met.select("vec_id", F.round(dot(x, y) / F.sqrt(dot(x, x) * dot(y, y)), 5).alias("sim"))


@add(f"SELECT user_id, list_sum(list_transform(path, lambda x: len(x)))::BIGINT AS total, len(list_filter(path, lambda x: x = 'view'))::BIGINT AS views, list_sort(list_distinct(path))[1] AS first FROM {_PATHS}")
def arr_reduce_filter_sort(spark, d):
    return _paths(spark, d).select("user_id", F.aggregate("path", F.lit(0).cast("long"), lambda s, x: s + F.length(x)).alias("total"), F.size(F.filter("path", lambda x: x == "view")).cast("long").alias("views"), F.array_sort(F.array_distinct("path"))[0].alias("first"))


def _weights(spark, d):
    own = events(spark, d).groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n"))
    return own.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", F.col("n").cast("double")))).alias("w"))


@add("SELECT user_id, coalesce(count(*) FILTER (event_type = 'view'), 0)::DOUBLE AS view, count(DISTINCT event_type) AS kinds FROM events GROUP BY user_id")
def map_weights_by_segment(spark, d):
    return _weights(spark, d).select("user_id", F.coalesce(F.element_at("w", F.lit("view")), F.lit(0.0)).alias("view"), F.size("w").cast("long").alias("kinds"))


@add("WITH c AS (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY 1, 2) SELECT a.user_id, sum(a.n * b.n)::DOUBLE AS dot FROM c a JOIN c b ON b.user_id = a.user_id + 1 AND a.event_type = b.event_type GROUP BY 1")
def map_zip_dot(spark, d):
    w = _weights(spark, d)
    met = w.alias("a").join(w.select(F.col("user_id").alias("u"), F.col("w").alias("y")), F.col("u") == F.col("user_id") + 1)
    products = F.map_values(F.map_zip_with("w", "y", lambda k, p, q: F.coalesce(p * q, F.lit(0.0))))
    return met.select("user_id", F.aggregate(products, F.lit(0.0), lambda s, v: s + v).alias("dot")).where("dot > 0")


@add("WITH c AS (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY 1, 2) SELECT user_id, count(*) AS frequent FROM c WHERE n >= 3 GROUP BY 1")
def map_filter_top(spark, d):
    return _weights(spark, d).select("user_id", F.size(F.map_filter("w", lambda k, v: v >= 3)).cast("long").alias("frequent")).where("frequent > 0")


@add("SELECT event_id, json_extract(props, '$.k')::INT AS k FROM events")
def json_props_k(spark, d):
    return table(spark, d, "events").select("event_id", F.get_json_object("props", "$.k").cast("int").alias("k"))


@add("SELECT json_extract(props, '$.k')::INT AS k, count(*) AS n FROM events GROUP BY 1")
def json_to_struct(spark, d):
    return table(spark, d, "events").select(F.from_json("props", "k int").alias("p")).groupBy("p.k").agg(F.count(F.lit(1)).alias("n"))


@add("SELECT event_id, json_extract(props, '$.k')::BIGINT AS k FROM events")
def variant_get_k(spark, d):
    return table(spark, d, "events").select("event_id", F.try_variant_get(F.parse_json("props"), "$.k", "bigint").alias("k"))


@add("SELECT n_nationkey, '{\"zone\":' || n_nationkey || ',\"name\":\"' || n_name || '\"}' AS model FROM nation")
def json_emit_model(spark, d):
    return table(spark, d, "nation").select("n_nationkey", F.to_json(F.struct(F.col("n_nationkey").alias("zone"), F.col("n_name").alias("name"))).alias("model"))


@add("SELECT n_regionkey, count(*) AS zones, min(n_name) AS first FROM nation GROUP BY 1")
def struct_nested_model(spark, d):
    own = table(spark, d, "nation").groupBy("n_regionkey").agg(F.array_sort(F.collect_list(F.struct("n_name", "n_nationkey"))).alias("zones"))
    nested = own.select(F.struct("n_regionkey", "zones").alias("model"))
    return nested.select("model.n_regionkey", F.size("model.zones").cast("long").alias("zones"), F.col("model.zones")[0]["n_name"].alias("first"))


