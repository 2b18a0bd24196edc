import math
import random
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from roadweave.components import components
from roadweave.functions import udfs
from roadweave.model import BipartiteGraph
from roadweave.operators import cocluster, criterion, greedy, hierarchy, kernel, mutual, network, rivals, similarity, weights
from roadweave.sources import tables
from roadweave.streaming import flows

D = "/root/testdata/sf0.001"
SCHEMA = "t long, s long, n long, length double"


def planted_graph(spark, seed=3, rows=14, columns=16):
    rng = random.Random(seed)
    own = [(t, s, rng.randint(1, 5), 1.0) for t in range(rows) for s in range(columns) if rng.random() < (0.9 if (t < rows // 2) == (s < columns // 2) else 0.1)]
    return BipartiteGraph.of(spark.createDataFrame(own, SCHEMA))


def test_components_against_union_find(spark):
    rng = random.Random(1)
    links = [(rng.randrange(200), rng.randrange(200)) for _ in range(120)] + [(1000 + i, 1001 + i) for i in range(40)]
    links = [(a, b) for a, b in links if a != b]
    parent = {}

    def root(x):
        parent.setdefault(x, x)
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in links:
        low, high = sorted((root(a), root(b)))
        parent[high] = low
    got = {r["v"]: r["c"] for r in components(spark.createDataFrame(links, "a long, b long")).collect()}
    assert got == {v: root(v) for v in parent}


@pytest.mark.parametrize("batch", ["single", "matched"])
def test_merges_by_joins_lower_the_cost(spark, batch):
    graph = planted_graph(spark, rows=8, columns=8)
    rows, columns, trace = greedy.merge(graph, criterion.finest(graph), batch=batch)
    costs = [r["cost"] for r in trace.orderBy(F.desc("cost")).collect()]
    assert costs == sorted(costs, reverse=True) and len(costs) > 3
    assert abs(criterion.cost(graph, rows, columns).first()["total"] - costs[-1]) < 1e-6
    best = cocluster.fit(graph, restarts=1).cost().first()["total"]
    assert best <= costs[-1] + 1e-6


def test_delta_of_a_merge_is_the_difference_of_the_costs(spark):
    graph = planted_graph(spark, rows=6, columns=6)
    start = criterion.finest(graph)
    before = criterion.cost(graph, *start).first()
    pair = greedy.candidates(graph, start, "t").orderBy("a", "b").first()
    merged = start[0].withColumn("ct", F.when(F.col("ct") == pair["b"], pair["a"]).otherwise(F.col("ct")))
    after = criterion.cost(graph, merged, start[1]).first()
    rest = [k for k in criterion.TERMS if k not in ("total", "partitions", "block_counts")]
    assert abs(sum(after[k] - before[k] for k in rest) - pair["delta"]) < 1e-6


def test_assignment_finds_the_cluster_of_its_like(spark):
    graph = planted_graph(spark, rows=20)
    given = cocluster.fit_sampled(graph, share=0.6, restarts=1)
    halves = given.withColumn("half", F.col("t") < 10).groupBy("half").agg(F.collect_set("ct").alias("c")).collect()
    assert given.count() == 20 and not set(halves[0]["c"]) & set(halves[1]["c"])


def test_assignment_has_a_row_for_trajectories_of_unknown_segments(spark):
    graph = planted_graph(spark, rows=20)
    model = cocluster.fit(graph, restarts=0)
    mass = {r["ct"]: r["m"] for r in model.block.groupBy("ct").agg(F.sum("m").alias("m")).collect()}
    segment = graph.traversal.first()["s"]
    new = spark.createDataFrame([(1000, segment, 3), (1000, -5, 1), (1001, -5, 2), (1001, -6, 1)], "t long, s long, n long").withColumn("length", F.lit(1.0))
    given = {r["t"]: r["ct"] for r in cocluster.assign(model, BipartiteGraph(new)).collect()}
    assert given.keys() == {1000, 1001}
    assert given[1001] == min(c for c, m in mass.items() if m == max(mass.values()))


def test_coarsening_reaches_the_numbers_asked_for(spark):
    model = cocluster.fit(planted_graph(spark), restarts=0)
    part = cocluster.coarsen(model, 1, 2)
    found = {r["side"]: r["n"] for r in part.groupBy("side").agg(F.count_distinct("c").alias("n")).collect()}
    assert found["t"] == 1 and found["s"] <= 2


def test_fixed_numbers_of_clusters(spark):
    graph = planted_graph(spark)
    rows, columns = cocluster.alternate(graph, 2, 2, rounds=4)
    assert rows.select("ct").distinct().count() <= 2 and columns.select("cs").distinct().count() <= 2
    assert mutual.total(mutual.contributions(mutual.crossed(graph, rows, columns))).first()[0] >= 0


def test_equal_neighbours_start_together(spark):
    own = [(1, 1, 1, 1.0), (2, 1, 1, 1.0), (3, 1, 2, 1.0), (1, 2, 1, 1.0), (2, 2, 1, 1.0)]
    rows, _ = cocluster.matched_start(BipartiteGraph.of(spark.createDataFrame(own, SCHEMA)))
    assert {r["t"]: r["ct"] for r in rows.collect()} == {1: 1, 2: 1, 3: 3}


def test_rivals_tell_two_blocks_apart(spark):
    graph = planted_graph(spark, rows=16)
    edges = similarity.project(graph, weight="common")
    of = {r["v"]: r["c"] for r in rivals.spectral(edges, 2).collect()}
    assert len({of[t] for t in range(8)}) == 1 and len({of[t] for t in range(8, 16)}) == 1 and of[0] != of[8]
    points = spark.createDataFrame([(i, float(i // 5 * 100 + i)) for i in range(10)], "v long, x double")
    of = {r["v"]: r["c"] for r in rivals.euclidean(points, 2, features=["x"]).collect()}
    assert len({of[i] for i in range(5)}) == 1 and of[0] != of[9]


def test_sampled_minima_find_similar_sets(spark):
    rows = [(v, f, 1, 1.0) for v in range(6) for f in range(v // 2 * 100, v // 2 * 100 + 20)]
    got = similarity.minhash_candidates(BipartiteGraph.of(spark.createDataFrame(rows, SCHEMA)))
    assert {tuple(r) for r in got.collect()} == {(0, 1), (2, 3), (4, 5)}


def test_roles(spark):
    block = spark.createDataFrame([(0, 0, 50), (1, 0, 50), (0, 1, 90), (1, 1, 1), (1, 2, 2), (1, 3, 60)], "ct long, cs long, m long")
    assert {r["cs"]: r["role"] for r in mutual.roles(block).collect()} == {0: "hub", 1: "secondary", 2: "rare", 3: "secondary"}


def test_profile_counts_unused_segments(spark):
    graph = BipartiteGraph.of(spark.createDataFrame([(1, 1, 1, 1.0), (2, 1, 1, 1.0), (1, 2, 1, 1.0)], SCHEMA))
    rows = spark.createDataFrame([(1, 0), (2, 0)], "t long, ct long")
    columns = spark.createDataFrame([(1, 0), (2, 0)], "s long, cs long")
    r = mutual.profile(graph, rows, columns).first()
    assert abs(r["density"] - 0.75) < 1e-9 and abs(r["dispersion"] - 0.25) < 1e-9


def test_reordered_matrix_is_a_permutation(spark):
    graph = planted_graph(spark)
    model = cocluster.fit(graph, restarts=0)
    own = mutual.reordered(model.graph, model.row_part, model.col_part).collect()
    assert Counter(r["n"] for r in own) == Counter(r["n"] for r in graph.traversal.collect())
    by = defaultdict(set)
    for r in own:
        by[r["ct"]].add(r["row_rank"])
    assert all(max(x) - min(x) + 1 == len(x) for x in by.values())


def test_plans_push_down_and_stay_off_python(spark):
    plan = lambda df: df._jdf.queryExecution().explainString(spark._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))
    own = tables.table(spark, D, "lineitem").where("l_quantity < 10").select("l_orderkey")
    assert "PushedFilters: [IsNotNull(l_quantity), LessThan(l_quantity,10.0)]" in plan(own)
    assert "ReadSchema: struct<l_orderkey:bigint,l_quantity:double>" in plan(own)
    projected = plan(similarity.project(tables.shipments(spark, D), side="s"))
    assert "CartesianProduct" not in projected and "Python" not in projected
    assert "Python" not in plan(weights.spatial_tfidf(tables.baskets(spark, D)))


def test_same_result_for_any_partitioning(spark):
    graph = planted_graph(spark)
    parts = []
    for n in (1, 7):
        model = cocluster.fit(BipartiteGraph(graph.traversal.repartition(n)), restarts=1)
        parts.append(sorted(map(tuple, model.row_part.collect())))
    assert parts[0] == parts[1]


def test_stream_equals_batch(spark):
    events = tables.events(spark, D)
    batch = events.groupBy(F.col("user_id").alias("t"), F.col("k").cast("long").alias("s")).agg(F.count(F.lit(1)).alias("n"))
    stream = flows.latest(flows.run(flows.edge_counts(flows.events(spark, D)), "test", mode="complete"))
    assert stream.select("t", "s", "n").exceptAll(batch).count() == 0 and stream.count() == batch.count()


def test_closed_trips_are_those_of_the_batch(spark):
    closed = {(r["user_id"], round(r["first"], 3), r["n"]) for r in flows.run(flows.trip_states(flows.events(spark, D)), "test-trips").collect()}
    own = tables.sessions(spark, D).groupBy("user_id", "trip").agg(F.min(F.col("ts").cast("double")).alias("first"), F.count(F.lit(1)).alias("n"))
    every = {(r["user_id"], round(r["first"], 3), r["n"]) for r in own.collect()}
    assert closed and closed <= every


def test_functions(spark):
    udfs.register(spark)
    assert spark.sql("SELECT edit_similarity('abc', 'abd')").first()[0] == pytest.approx(2 / 3)
    assert spark.sql("SELECT edit_similarity(NULL, 'abd')").first()[0] is None
    assert [tuple(r) for r in spark.sql("SELECT * FROM path_steps(array(5, 6, 7))").collect()] == [(0, 5, 6), (1, 6, 7)]
    assert spark.sql("SELECT count(*) FROM zone_vertices(3, 80, 5)").first()[0] == 256


def test_noise_moves_ends_and_drops_segments(spark):
    orders, customers = (spark.read.parquet(f"{D}/{t}.parquet") for t in ("orders", "customer"))
    pairs = network.planted_pairs(orders, customers)
    moved = network.noisy_labels(pairs, 30).join(pairs.select("t", F.col("dst").alias("was")), "t").where("dst <> was").count()
    assert 0 < moved < 60
    seq = spark.createDataFrame([(1, i, i) for i in range(1000)], "t long, pos int, s long")
    assert 700 < network.noisy_paths(seq, 20).count() < 900


def test_best_cluster_of_a_vertex_is_that_of_least_cost():
    rng = np.random.default_rng(8)
    t, s = np.repeat(np.arange(12), 9), np.tile(np.arange(9), 12)
    n = rng.integers(0, 4, len(t)) + (t % 3 == s % 3) * rng.integers(200, 400, len(t))
    t, s, n = t[n > 0], s[n > 0], n[n > 0]
    rows, columns = np.arange(12) // 4, np.arange(9) // 3
    model = kernel.Model(t, s, n, rows, columns)
    for v in range(12):
        at = t == v
        cells, where = np.unique(columns[s[at]], return_inverse=True)
        visits = np.bincount(where, weights=n[at]).astype(np.int64)
        costs = [kernel.Model(t, s, n, np.where(np.arange(12) == v, c, rows), columns).cost() for c in range(3)]
        best = kernel.best_clusters(model.block, model.rows.size, model.rows.mass, [(int(rows[v]), cells, visits)])
        assert abs(costs[best[0]] - min(costs)) < 1e-6
    x = np.array([0, 1, 2, 20, 254, 255, 256, 257, 10**6, 10**9])
    assert np.allclose(kernel.log_factorials(x), [math.lgamma(i + 1) for i in x.tolist()], rtol=1e-12)


def test_parents_that_fit_no_task_are_refined_by_joins(spark):
    edges = similarity.project(planted_graph(spark, rows=20), side="t")
    for limits in ({"local_vertices": 4}, {"local_edges": 5}):
        rows = [r.asDict() for r in hierarchy.nested(edges, max_depth=2, **limits).collect()]
        first = {r["v"]: r["cluster"] for r in rows if r["level"] == 1}
        second = {r["v"]: r for r in rows if r["level"] == 2}
        assert set(first) == set(second) and len(rows) == 2 * len(first)
        assert all(r["parent"] == first[v] for v, r in second.items())
        of = {}
        assert all(of.setdefault(r["cluster"], r["parent"]) == r["parent"] for r in second.values())


def test_fine_starts_are_merged_by_joins_and_restarts_never_cost_more(spark, monkeypatch):
    monkeypatch.setattr(cocluster, "LOCAL_START", 5)
    graph = planted_graph(spark, rows=20)
    null = criterion.cost(graph, *criterion.null_model(graph)).first()["total"]
    costs = []
    for restarts in (0, 1):
        model = cocluster.fit(graph, local_cells=10, start=12, passes=2, restarts=restarts)
        costs.append(model.cost().first()["total"])
        assert model.row_part.count() == graph.traversal.select("t").distinct().count()
    assert costs[1] <= costs[0] + 1e-6 and costs[0] <= null + 1e-6


def test_all_pairs_of_a_bucket_are_candidates(spark):
    """Four equal sets share every bucket, so all six pairs are candidates, and with several tiles each once."""
    rows = [(v, f, 1, 1.0) for v in range(4) for f in range(20)] + [(v, f, 1, 1.0) for v in range(10, 40) for f in range(v * 7, v * 7 + 21)]
    graph = BipartiteGraph.of(spark.createDataFrame(rows, SCHEMA))
    least = lambda k: F.min(F.xxhash64("s", F.lit(k)))
    signs = graph.traversal.groupBy("t").agg(*[least(k).alias(f"h{k}") for k in range(6)]).collect()
    expected = sorted((a["t"], b["t"]) for a in signs for b in signs if a["t"] < b["t"] and any(a[k] == b[k] for k in range(1, 7)))
    assert {(1, 3), (0, 1), (0, 2), (0, 3), (1, 2), (2, 3)} < set(expected)
    for tiles in ({}, {"tile": 3}, {"tile": 9}):
        got = similarity.minhash_candidates(graph, bands=6, rows=1, **tiles)
        assert sorted(tuple(r) for r in got.collect()) == expected
