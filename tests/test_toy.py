import itertools
import math
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

import toy
from roadweave.functions.scalar import log_factorial, log_partitions
from roadweave.model import BipartiteGraph
from roadweave.operators import agreement, cocluster, criterion, hierarchy, kernel, modularity, mutual, similarity, weights


@pytest.fixture(scope="module")
def graph(spark):
    return BipartiteGraph.of(spark.createDataFrame(toy.rows(), "t long, s long, n long, length double").cache())


def as_dict(df, *keys, value):
    return {tuple(r[k] for k in keys): r[value] for r in df.collect()}


def close(got, expected, tol=2e-6):
    assert got.keys() == expected.keys()
    for k in got:
        assert abs(got[k] - expected[k]) < tol, (k, got[k], expected[k])


def test_weights(graph):
    close(as_dict(weights.spatial_tfidf(graph), "v", "f", value="w"), toy.SPATIAL)
    own = as_dict(weights.visit_tfidf(graph), "v", "f", value="w")
    assert abs(own[1, 1] - 0.490415) < 1e-6 and abs(own[4, 5] - 0.231049) < 1e-6 and abs(own[8, 5] - 0.693147) < 1e-6


@pytest.mark.parametrize("normalise", [True, False])
def test_similarities_with_and_without_the_denominators(graph, normalise):
    close(as_dict(similarity.cosine_pairs(weights.spatial_tfidf(graph, normalise=normalise)), "a", "b", value="omega"), toy.OMEGA_T)
    close(as_dict(similarity.cosine_pairs(weights.visit_tfidf(graph, normalise=normalise)), "a", "b", value="omega"), toy.OMEGA_S)


def test_tiles_prefixes_and_best_neighbours(graph):
    own = weights.visit_tfidf(graph)
    close(as_dict(similarity.cosine_pairs(own, tile=1), "a", "b", value="omega"), toy.OMEGA_S)
    close(as_dict(similarity.cosine_pairs(own, min_sim=0.5), "a", "b", value="omega"), {k: v for k, v in toy.OMEGA_S.items() if v >= 0.5})
    best = as_dict(similarity.cosine_pairs(weights.spatial_tfidf(graph), top_k=1), "a", "b", value="omega")
    assert set(best) == {(1, 3), (1, 2), (4, 5)}


def test_random_vectors_lose_no_pair(spark):
    rng = random.Random(2)
    rows = [(v, f, rng.random()) for v in range(60) for f in rng.sample(range(40), 8)]
    own = spark.createDataFrame(rows, "v long, f long, w double")
    whole = as_dict(similarity.cosine_pairs(own), "a", "b", value="omega")
    close(as_dict(similarity.cosine_pairs(own, min_sim=0.4, tile=7), "a", "b", value="omega"), {k: v for k, v in whole.items() if v >= 0.4})
    close(as_dict(similarity.cosine_pairs(own, tile=3), "a", "b", value="omega"), whole)


def test_common_counts(graph):
    close(as_dict(similarity.common_pairs(graph), "a", "b", value="common"), toy.COMMON)


def partitions(n):
    def grow(prefix, top):
        if len(prefix) == n:
            yield tuple(prefix)
            return
        for c in range(top + 2):
            yield from grow([*prefix, c], max(top, c))

    yield from grow([0], 0)


@pytest.mark.parametrize(("omega", "n", "best"), [(toy.OMEGA_T, 5, 0.263530720773), (toy.OMEGA_S, 8, 0.385125534761)])
def test_communities_reach_the_brute_force_optimum(spark, omega, n, best):
    a = np.zeros((n, n))
    for (i, j), w in omega.items():
        a[i - 1, j - 1] = a[j - 1, i - 1] = w
    assert abs(max(modularity.dense_score(a, np.array(p)) for p in partitions(n)) - best) < 1e-5
    edges = spark.createDataFrame([(i, j, w) for (i, j), w in omega.items()], "a long, b long, omega double")
    part = modularity.communities(edges).cache()
    assert abs(modularity.score(edges, part).first()[0] - best) < 1e-5
    by_joins = modularity.communities(edges, mode="distributed", local_edges=0)
    assert modularity.score(edges, by_joins).first()[0] > 0.8 * best


def test_nested_levels(spark):
    edges = spark.createDataFrame([(i, j, w) for (i, j), w in toy.OMEGA_S.items()], "a long, b long, omega double")
    m = hierarchy.nested(edges, max_depth=3).cache()
    assert m.groupBy("level").count().where("count <> 8").count() == 0
    parents = m.where("level > 1").groupBy("level", "cluster").agg(F.count_distinct("parent").alias("n"))
    assert parents.where("n <> 1").count() == 0
    assert hierarchy.cut(m, k=2).select("c").distinct().count() <= 2


def toy_parts(spark, copies=1):
    rows = [(t + 10 * k, s, n, x) for k in range(copies) for t, s, n, x in toy.rows()]
    graph = BipartiteGraph.of(spark.createDataFrame(rows, "t long, s long, n long, length double"))
    planted = (
        graph.traversal.select("t").distinct().withColumn("ct", (F.col("t") % 10 > 3).cast("long")),
        graph.traversal.select("s").distinct().withColumn("cs", (F.col("s") > 4).cast("long")),
    )
    return graph, planted


def test_cost_terms(spark):
    graph, planted = toy_parts(spark)
    got = criterion.cost(graph, *planted).first()
    expected = {"cluster_counts": 3.688879, "partitions": 2.772589 + 4.852030, "block_counts": 7.038784, "vertex_counts": 4.189655 + 2.079442 + 5.897154 + 4.430817, "like_blocks": 11.821410, "like_margins": 11.898188 + 16.339157, "total": 75.008103}
    for k, v in expected.items():
        assert abs(got[k] - v) < 5e-6, k
    assert abs(criterion.cost(graph, *criterion.null_model(graph)).first()["total"] - 72.676744) < 5e-6
    assert abs(criterion.cost(graph, *criterion.finest(graph)).first()["total"] - 80.996464) < 5e-6


@pytest.mark.parametrize(("copies", "null", "planted"), [(2, 163.877195, 162.498906), (3, 262.986263, 257.496891), (4, 367.428249, 357.659445), (6, 587.652906, 569.079234), (8, 818.948055, 791.397456)])
def test_more_evidence_shows_structure(copies, null, planted):
    rows = [(t - 1 + 5 * k, s - 1, n) for k in range(copies) for t, s, n, _ in toy.rows()]
    t, s, n = (np.array(x) for x in zip(*rows))
    assert abs(kernel.null_cost(t, s, n, 5 * copies, 8) - null) < 5e-6
    own = kernel.Model(t, s, n, (np.arange(5 * copies) % 5 > 2).astype(int), (np.arange(8) > 3).astype(int))
    assert abs(own.cost() - planted) < 5e-6


def test_fit_finds_the_optimum_of_all_models(spark):
    t, s, n = (np.array(x) for x in zip(*[(t - 1, s - 1, n) for t, s, n, _ in toy.rows()]))
    rng = random.Random(0)
    columns = rng.sample(list(partitions(8)), 150)
    least = min(kernel.Model(t, s, n, np.array(p), np.array(q)).cost() for p in partitions(5) for q in [(0,) * 8, *columns])
    assert abs(least - 72.676744) < 5e-6
    graph, _ = toy_parts(spark)
    assert abs(cocluster.fit(graph, restarts=1).cost().first()["total"] - 72.676744) < 5e-6
    graph, _ = toy_parts(spark, 4)
    model = cocluster.fit(graph, restarts=1)
    assert model.cost().first()["total"] <= 357.659445 + 1e-6
    assert model.compression().first()["compression"] > 0


def random_counts(seed, rows=12, columns=15):
    rng = np.random.default_rng(seed)
    a = rng.poisson(0.6 + 2 * ((np.arange(rows)[:, None] < 6) == (np.arange(columns)[None, :] < 7)), (rows, columns))
    t, s = np.nonzero(a)
    return t, s, a[t, s], rows, columns


@pytest.mark.parametrize("seed", range(4))
def test_changes_of_cost_add_up(seed):
    t, s, n, rows, columns = random_counts(seed)
    model = kernel.Model(t, s, n, np.arange(rows), np.arange(columns))
    start = model.cost()
    trace = model.merges()
    null = kernel.null_cost(t, s, n, rows, columns)
    assert abs(start + sum(x["delta"] for x in trace) - null) < 1e-6 and abs(trace[-1]["cost"] - null) < 1e-6
    assert abs(model.cost() - min([start] + [x["cost"] for x in trace])) < 1e-6
    strict = kernel.Model(t, s, n, np.arange(rows), np.arange(columns)).merges(stop="first_rise")
    assert all(x["delta"] < 0 for x in strict)
    rng = np.random.default_rng(seed)
    other = kernel.Model(t, s, n, rng.integers(0, 4, rows), rng.integers(0, 4, columns))
    before = other.cost()
    other.exchange()
    again = kernel.Model(t, s, n, other.rows.label, other.columns.label)
    assert other.cost() <= before + 1e-9 and abs(other.cost() - again.cost()) < 1e-6
    turned = kernel.Model(s, t, n, other.columns.label, other.rows.label)
    assert abs(turned.cost() - other.cost()) < 1e-6


def test_large_route_lowers_the_cost_and_never_exceeds_one_block(spark):
    t, s, n, _, _ = random_counts(7, 40, 50)
    graph = BipartiteGraph.of(spark.createDataFrame([(int(a), int(b), int(c), 1.0) for a, b, c in zip(t, s, n)], "t long, s long, n long, length double"))
    model = cocluster.fit(graph, local_cells=10, start=8, restarts=0, passes=2)
    row = model.compression().first()
    assert row["cost"] <= row["null_cost"] + 1e-6
    assert model.row_part.count() == graph.traversal.select("t").distinct().count()


def test_mutual_information(spark):
    graph, planted = toy_parts(spark)
    parts = mutual.contributions(mutual.crossed(graph, *planted))
    close(as_dict(parts, "ct", "cs", value="mi"), {(0, 0): 0.256069, (1, 0): -0.088858, (1, 1): 0.313166})
    assert abs(mutual.total(parts).first()[0] - 0.480377) < 1e-6
    finer = (planted[0], graph.traversal.select("s").distinct().withColumn("cs", F.col("s")))
    assert mutual.total(mutual.contributions(mutual.crossed(graph, *finer))).first()[0] >= 0.480377 - 1e-9


def test_agreement(spark):
    table = spark.createDataFrame([("1", 10, 3), ("1", 11, 3), ("1", 12, 8), ("2", 20, 19), ("3", 30, 10), ("3", 31, 10), ("4", 40, 20), ("5", 50, 12)], "klass string, cluster long, n long")
    assert round(agreement.ari(table).first()[0], 4) == 0.8491
    assert agreement.purity(table).first()["all_pure"]
    outcome = {r["klass"]: r["outcome"] for r in agreement.recovery(table).collect()}
    assert outcome == {"1": "over-partitioned", "2": "exact", "3": "over-partitioned", "4": "exact", "5": "exact"}
    same = spark.createDataFrame([("1", 1, 5), ("2", 2, 7)], "klass string, cluster long, n long")
    assert agreement.ari(same).first()[0] == 1.0


def test_log_factorial(spark):
    values = [0, 1, 2, 19, 20, 21, 30, 100, 10_000, 10**9]
    rows = spark.createDataFrame([(v,) for v in values], "n long").select("n", log_factorial(F.col("n")).alias("f")).collect()
    for r in rows:
        assert abs(r["f"] - math.lgamma(r["n"] + 1)) <= 2e-11 * max(1.0, math.lgamma(r["n"] + 1))


def test_numbers_of_partitions():
    count = lambda n, k: sum(1 for p in partitions(n) if max(p) < k)
    for n, k in itertools.product((1, 4, 7), (1, 2, 3, 7)):
        assert abs(log_partitions(n, k) - math.log(count(n, min(n, k)))) < 1e-9
    assert abs(log_partitions(4096, 12) - log_partitions(4097, 12)) < 3


def test_edge_cases(spark):
    rows = [(1, 1, 1, 1.0), (1, 1, 2, 1.0), (None, 1, 1, 1.0), (2, None, 1, 1.0), (2, 1, 0, 1.0), (2, 2, 1, -1.0), (2, 2, 1, None)]
    df = spark.createDataFrame(rows, "t long, s long, n long, length double")
    graph = BipartiteGraph.of(df)
    assert sorted(tuple(r) for r in graph.traversal.collect()) == [(1, 1, 3, 1.0), (2, 2, 1, 1.0)]
    assert tuple(BipartiteGraph.rejected(df).first()) == (2, 1, 1)
    one = BipartiteGraph.of(spark.createDataFrame([(1, 1, 1, 1.0), (1, 2, 1, 1.0)], df.schema))
    assert similarity.project(one).count() == 0 and {r["w"] for r in weights.spatial_tfidf(one).collect()} == {0.0}
    shared = BipartiteGraph.of(spark.createDataFrame([(1, 1, 1, 1.0), (2, 1, 1, 1.0)], df.schema))
    assert similarity.project(shared).count() == 0
    empty = BipartiteGraph.of(spark.createDataFrame([], df.schema))
    assert similarity.project(empty).count() == 0 and modularity.communities(similarity.project(empty)).count() == 0
    assert criterion.cost(empty, *criterion.null_model(empty)).count() == 0
