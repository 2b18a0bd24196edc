import itertools

import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from roadweave import scratch
from roadweave.operators import hierarchy, implicit, modularity, similarity, tiles

D = "/root/testdata/sf0.001"
SCHEMA = "v long, f long, w double"


def unit(rows):
    length = {}
    for v, _, w in rows:
        length[v] = length.get(v, 0.0) + w * w
    return [(v, f, w / length[v] ** 0.5) for v, f, w in rows]


def planted(groups: int, each: int, seed: int, copies: int = 1):
    rng = np.random.default_rng(seed)
    rows = []
    for i in range(groups * each):
        chosen = {int(f) + 10 * (i % groups) for f in rng.choice(10, 4, replace=False)} | {int(rng.integers(0, 10 * groups))}
        rows += [(i + k * groups * each, f, 1.0) for k in range(copies) for f in chosen]
    return unit(rows)


def sets(frame, c="c"):
    return {frozenset(r["vs"]) for r in frame.groupBy(c).agg(F.collect_set("v").alias("vs")).collect()}


@pytest.mark.parametrize("bounds", [(2_000_000, 4_000_000), (40, 60), (2_000_000, 10_000_000)])
def test_best_moves_equal_brute_force(monkeypatch, bounds):
    monkeypatch.setattr(tiles, "PRODUCTS", bounds[0])
    monkeypatch.setattr(tiles, "CELLS", bounds[1])
    for seed, span in itertools.product(range(6), (12, 400)):
        rng = np.random.default_rng(seed)
        x = np.where(rng.random((30, span)) < 4 / span, rng.random((30, span)) + 0.1, 0.0)
        x[np.arange(30), rng.integers(0, span, 30)] += 0.5
        own = rng.integers(0, 9, 30) * 10
        names = np.unique(own)
        k, scale = rng.random(30) * 3, 0.02
        sums, strength = np.array([x[own == c].sum(axis=0) for c in names]), np.array([k[own == c].sum() for c in names])
        entries = lambda m, v: implicit.Tile(*(np.concatenate(z) for z in zip(*[(np.full((r > 0).sum(), name), np.flatnonzero(r), r[r > 0]) for name, r in zip(v, m)])))
        dealt = [(entries(sums[h::2], names[h::2]), strength[h::2]) for h in (0, 1)]
        got = implicit.best_moves(entries(x, np.arange(30)), k, own, dealt, scale)
        for v in range(30):
            at = list(names).index(own[v])
            gain = sums @ x[v] - scale * k[v] * strength
            gain[at] += scale * k[v] ** 2 - x[v] @ x[v]
            gain[(sums @ x[v] <= 0) & (names != own[v])] = -np.inf
            best = np.round(gain, 12).max()
            assert got[v] == (own[v] if np.round(gain[at], 12) == best else names[np.round(gain, 12) == best][0])


def test_equal_vectors_are_one_unit(spark):
    rows = planted(3, 4, seed=1, copies=5)
    members, _, strength = implicit._units(spark.createDataFrame(rows, SCHEMA).withColumn("parent", F.lit(0)), resolution=1.0)
    assert strength.count() <= 12 and members.count() == 60
    edges = {}
    for r in similarity.symmetric(tiles.products(spark.createDataFrame(rows, SCHEMA))).collect():
        edges[r["a"]] = edges.get(r["a"], 0.0) + r["omega"]
    for r in members.join(strength, "u").collect():
        assert r["k"] == pytest.approx(edges[r["v"]])


def test_twins_that_modularity_would_part_are_not_one_unit(spark):
    """Hubs with equal vectors over vertices of one feature each: strength squared passes the sum of all strengths."""
    rows = unit([(v, f, 1.0) for v in (0, 1) for f in range(40)] + [(2 + f, f, 1.0) for f in range(40)])
    members, _, strength = implicit._units(spark.createDataFrame(rows, SCHEMA).withColumn("parent", F.lit(0)), resolution=1.0)
    k = {r["u"]: r["k"] for r in strength.collect()}
    assert k[0] ** 2 > sum(r["m"] * r["k"] for r in strength.collect()) and k[1] == pytest.approx(k[0])


@pytest.mark.parametrize("limit", [3000, 1])
def test_communities_equal_those_of_written_edges(spark, monkeypatch, limit):
    monkeypatch.setattr(implicit, "LEAST", 7)
    own = spark.createDataFrame(planted(4, 12, seed=2, copies=2), SCHEMA)
    edges = scratch.materialise(tiles.products(own), "edges")
    part = scratch.materialise(implicit.communities(own, local_vertices=limit), "part")
    score = modularity.score(edges, part).first()[0]
    assert part.count() == 96 and score > modularity.score(edges, modularity.communities(edges)).first()[0] - (1e-9 if limit > 1 else 0.02)
    assert all(min(s) in {r["c"] for r in part.collect()} for s in sets(part))


@pytest.mark.parametrize("limit", [3000, 5])
def test_nested_equals_that_of_written_edges(spark, limit):
    own = spark.createDataFrame(planted(3, 8, seed=4) + [(900, 999, 1.0)], SCHEMA)
    got = implicit.nested(own, local_vertices=limit)
    assert got.where("v = 900").isEmpty()
    if limit > 5:
        old = hierarchy.nested(tiles.products(own))
        assert {tuple(r) for r in got.collect()} == {tuple(r) for r in old.select("v", "level", "cluster", "parent").collect()}
    rows = got.where("level = 2").collect()
    assert len(rows) == 24 and all(r["cluster"] >= r["parent"] for r in rows)


def test_empty(spark):
    assert implicit.communities(spark.createDataFrame([], SCHEMA)).isEmpty()
    assert implicit.nested(spark.createDataFrame([(1, 1, 1.0)], SCHEMA)).isEmpty()


def test_the_control_writes_no_pairs(spark):
    """what is stored grows with the entries of the vectors."""
    before = len(scratch._written)
    assert entry.queries()["negative_control_g7"](spark, D).count() == 1
    assert not [p for _, p in scratch._written[before:] if "modularity-graph" in p or "projected" in p]


def test_pages_write_no_pairs(spark):
    """F12."""
    before = len(scratch._written)
    assert entry.queries()["trajectory_only_g6"](spark, D).count() == 1
    assert not [p for _, p in scratch._written[before:] if "modularity-graph" in p]


def test_crossed_clusters_write_no_pairs(spark):
    """neither side's projection is written."""
    before = len(scratch._written)
    assert not entry.queries()["crossed_g6"](spark, D).isEmpty()
    assert not [p for _, p in scratch._written[before:] if "modularity-graph" in p or "projected" in p]


def test_both_levels_of_pages_write_no_pairs(spark):
    """F4."""
    before = len(scratch._written)
    assert entry.queries()["ari_both_routes_g6"](spark, D).count() == 3
    assert not [p for _, p in scratch._written[before:] if "modularity-graph" in p or "projected" in p or "nested-edges" in p]
