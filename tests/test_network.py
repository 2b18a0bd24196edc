import math

import pytest
from pyspark.sql import functions as F

from roadweave.model import to_traversals
from roadweave.operators import ingest, network, routing
from roadweave.sources import roadgrid

D = "/root/testdata/sf0.001"


def test_lattice(spark):
    s = network.segments(spark).cache()
    assert s.count() == 14_062 == s.select("s").distinct().count() == s.select("src", "dst").distinct().count()
    arterial = sorted(r[0] for r in s.where("length = 200").select((F.col("src") % 80).alias("c")).distinct().collect())
    assert arterial == [4, 13, 22, 31, 40, 49, 58, 67, 76]
    assert network.vertices(spark).groupBy("zone").count().where("count <> 256").count() == 0


def test_data_source_is_the_lattice(spark):
    roadgrid.register(spark)
    own = spark.read.format("roadgrid").load()
    assert own.exceptAll(network.segments(spark)).count() == 0 and own.count() == 14_062


def test_classes_have_the_published_sizes(spark):
    orders, customers = (spark.read.parquet(f"{D}/{t}.parquet") for t in ("orders", "customer"))
    sizes = {r["klass"]: r["count"] for r in network.planted_pairs(orders, customers).groupBy("klass").count().collect()}
    assert sizes == {"1": 14, "2": 19, "3": 20, "4": 20, "5": 12}
    drawn = network.zone_pairs(spark, 6)
    assert all(c.departure != c.arrival and 10 <= c.last - c.first + 1 <= 25 for c in drawn) and len(drawn) == 6


def closed_form(src, dst):
    (i, j), (k, m) = divmod(src, 80), divmod(dst, 80)
    if i == k:
        return 3 * abs(j - m)
    return min(3 * (abs(j - a) + abs(a - m)) + (1 + a // 9 % 2) * abs(i - k) for a in range(4, 80, 9))


def test_routes_against_the_closed_form(spark):
    orders = spark.read.parquet(f"{D}/orders.parquet").limit(60)
    pairs = network.all_pairs(orders).cache()
    roads = network.segments(spark)
    paths = routing.shortest(roads, pairs).cache()
    cost = {r["t"]: r["cost"] for r in routing.costs(roads, paths).collect()}
    for r in pairs.collect():
        if r["src"] != r["dst"]:
            assert cost[r["t"]] == closed_form(r["src"], r["dst"])
    ends = paths.join(roads, "s").groupBy("t").agg(F.min_by("src", "pos").alias("a"), F.max_by("dst", "pos").alias("b")).join(pairs, "t")
    assert ends.where("a <> src or b <> dst").count() == 0


def test_routes_by_joins_cost_the_same(spark):
    roads = network.segments(spark, side=6, first=1, step=3)
    pairs = spark.createDataFrame([(1, None, 0, 35), (2, None, 0, 14), (3, None, 30, 2)], "t long, klass string, src long, dst long")
    a, b = (routing.costs(roads, f(roads, pairs)).select("t", "cost").collect() for f in (routing.shortest, routing.by_joins))
    assert sorted(a) == sorted(b) and len(a) == 3


def test_traversals_collapse_immediate_repeats(spark):
    seq = spark.createDataFrame([(1, 0, 7), (1, 1, 7), (1, 2, 8), (1, 3, 7)], "t long, pos int, s long")
    assert sorted(tuple(r) for r in to_traversals(seq).collect()) == [(1, 7, 2, 1.0), (1, 8, 1, 1.0)]


def test_trips(spark):
    rows = [(1, "2024-01-01 00:00:00"), (1, "2024-01-01 23:00:00"), (1, "2024-01-03 00:00:00"), (2, "2024-01-01 00:00:00")]
    points = spark.createDataFrame(rows, "u int, ts string").withColumn("ts", F.to_timestamp("ts"))
    assert sorted(r["trip"] for r in ingest.sessionize(points, key="u", ts="ts").collect()) == [0, 0, 0, 1]


@pytest.mark.parametrize("method", ["snap", "hmm"])
def test_map_matching_finds_the_street(spark, method):
    streets = [(10, 0.0, 0.0, 1.0, 0.0), (11, 1.0, 0.0, 2.0, 0.0), (12, 1.0, 0.0, 1.0, 1.0)]
    points = [(1, 0, 0.3, 0.05), (1, 1, 0.8, -0.04), (1, 2, 1.5, 0.03)]
    got = ingest.match_points(spark.createDataFrame(points, "t long, pos int, x double, y double"), spark.createDataFrame(streets, "s long, x1 double, y1 double, x2 double, y2 double"), method=method, radius=0.4)
    assert [r["s"] for r in got.orderBy("pos").collect()] == [10, 10, 11]


def test_snapping_against_brute_force(spark):
    streets = [(i, math.sin(i) * 5, math.cos(i * 2) * 5, math.sin(i) * 5 + math.cos(i), math.cos(i * 2) * 5 + math.sin(i * 3)) for i in range(60)]
    points = [(1, i, math.sin(i * 1.7) * 5, math.cos(i * 0.9) * 5) for i in range(80)]

    def away(p, s):
        dx, dy = s[3] - s[1], s[4] - s[2]
        u = max(0.0, min(1.0, ((p[2] - s[1]) * dx + (p[3] - s[2]) * dy) / (dx * dx + dy * dy)))
        return math.hypot(p[2] - s[1] - u * dx, p[3] - s[2] - u * dy)

    expected = {}
    for p in points:
        d, s = min((away(p, s), s[0]) for s in streets)
        if d <= 0.8:
            expected[p[1]] = s
    got = ingest.match_points(spark.createDataFrame(points, "t long, pos int, x double, y double"), spark.createDataFrame(streets, "s long, x1 double, y1 double, x2 double, y2 double"), radius=0.8)
    assert {r["pos"]: r["s"] for r in got.collect()} == expected
