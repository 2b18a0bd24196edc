"""Co-clustering with labels on the driver, against the same steps vertex by vertex and by joins."""

import math

import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from roadweave.model import BipartiteGraph
from roadweave.operators import cocluster, greedy, kernel, labelled


@pytest.fixture(scope="module")
def graph(spark):
    rng = np.random.default_rng(3)
    t, s = rng.integers(0, 90, 1500), rng.integers(0, 70, 1500)
    own = pd.DataFrame({"t": t * 7 - 20, "s": s + (t % 3) * 60, "n": rng.integers(1, 90, 1500)}).drop_duplicates(["t", "s"])
    return BipartiteGraph.of(spark.createDataFrame(own), length=None)


@pytest.fixture(scope="module")
def tiled(graph):
    before, labelled.EDGES = labelled.EDGES, 300
    try:
        yield labelled.Tiled.of(graph, graph.traversal.count())
    finally:
        labelled.EDGES = before


def parts_of(graph, k):
    side = lambda v, c: graph.traversal.select(v).distinct().withColumn(c, F.pmod(F.xxhash64(v, F.lit(5)), F.lit(k)))
    return side("t", "ct"), side("s", "cs")


def test_no_table_of_logarithms_grows_with_the_visits():
    """a model of 133 million visits made a table of 2 GB and more."""
    n = np.array([150_000_000, 1])
    model = kernel.Model(np.array([0, 1]), np.array([0, 1]), n, np.arange(2), np.arange(2))
    assert model.log_f.table is None
    x = np.array([0, 1, 65_535, 65_536, 10**6, 3 * 10**8])
    assert np.allclose(kernel.log_factorials(x), [math.lgamma(i + 1) for i in x.tolist()], rtol=1e-12)
    assert math.isclose(float(kernel.log_factorials(np.array(70_000))), math.lgamma(70_001), rel_tol=1e-12)


def test_many_vertices_move_as_each_would():
    """F6, F11."""
    rng = np.random.default_rng(1)
    label, visits = rng.integers(0, 9, 200), rng.integers(0, 4, (200, 12)) * rng.integers(1, 200, (200, 12))
    visits[:, 0] += 1
    block = np.zeros((9, 12), np.int64)
    np.add.at(block, label, visits)
    size = np.bincount(label, minlength=9)
    rows = [(int(c), np.flatnonzero(v), v[v > 0]) for c, v in zip(label, visits)]
    each = [len(x[1]) for x in rows]
    got = kernel.best_moves(block, size, block.sum(axis=1), label, np.cumsum([0, *each[:-1]]), np.concatenate([x[1] for x in rows]), np.concatenate([x[2] for x in rows]))
    assert got.tolist() == kernel.best_clusters(block, size, block.sum(axis=1), rows) and (got != label).any()


def test_places_labels_and_blocks(spark, graph, tiled):
    parts = parts_of(graph, 8)
    labels = tiled.collected(parts)
    assert len(tiled.offsets[0]) > 4 and tiled.sizes() == tuple(graph.traversal.select(v).distinct().count() for v in ("t", "s"))
    blocks = labelled.matrix_of(tiled.blocks(labels), (8, 8))
    met = graph.traversal.join(parts[0], "t").join(parts[1], "s").groupBy("ct", "cs").agg(F.sum("n")).collect()
    assert {(a, b): m for a, b, m in met} == {(a, b): m for (a, b), m in np.ndenumerate(blocks) if m}
    back = tiled.parts(labels)
    assert sorted(back[0].collect()) == sorted(parts[0].collect()) and sorted(back[1].collect()) == sorted(parts[1].collect())
    assert math.isclose(tiled.fixed(), cocluster._fixed(graph), rel_tol=1e-12)
    for side in (0, 1):
        label, after = tiled.moves(side, labels, blocks if side == 0 else blocks.T, 1, 4)
        new = (label, labels[1]) if side == 0 else (labels[0], label)
        assert (label != labels[side]).any()
        assert (labelled.matrix_of(tiled.blocks(new), (8, 8)) == (after if side == 0 else after.T)).all()


@pytest.mark.parametrize("side", ["t", "s"])
def test_partners_are_those_of_the_join(graph, tiled, monkeypatch, side):
    """the join of blocks made a row for every two clusters that share one."""
    monkeypatch.setattr(labelled, "CELLS", 300)
    monkeypatch.setattr(labelled, "LINES", 7)
    parts = parts_of(graph, 30)
    labels = tiled.collected(parts)
    blocks = tiled.blocks(labels)
    matrix = labelled.matrix_of(blocks, tuple(int(x.max()) + 1 for x in labels))
    at = 0 if side == "t" else 1
    others = matrix.shape[1 - at]
    got = labelled.partners(blocks, at, np.bincount(labels[at]), matrix.sum(axis=1 - at), others, count=30)
    name = {c: i for i, c in enumerate(sorted({x[1] for x in parts[at].collect()}))}
    expected = {(name[a], name[b]): d for a, b, d in greedy.candidates(graph, parts, side).collect()}
    found = {(a, b): d for a, b, d in got.itertuples(index=False)}
    assert found.keys() == expected.keys() and all(math.isclose(found[x], expected[x], abs_tol=1e-6) for x in expected)
    few = labelled.partners(blocks, at, np.bincount(labels[at]), matrix.sum(axis=1 - at), others, count=2)
    best = {x: d for x, d in expected.items() if d == min(e for y, e in expected.items() if set(x) & set(y))}
    assert best.keys() <= {(a, b) for a, b, _ in few.itertuples(index=False)}


def test_merges_end_at_the_bound(spark, graph, tiled):
    labels = tiled.collected(parts_of(graph, 40))
    rows, columns = labelled.reduced(tiled, labels, 9)
    assert len(set(rows.tolist())) == 9 and len(set(columns.tolist())) == 9
    # Clusters that share nothing are hashed.
    apart = BipartiteGraph.of(spark.createDataFrame([(i, i, 1) for i in range(20)], "t long, s long, n long"), length=None)
    own = labelled.Tiled.of(apart, 20)
    rows, columns = labelled.reduced(own, (np.arange(20), np.arange(20)), 6)
    assert len(set(rows.tolist())) <= 6 and len(set(columns.tolist())) <= 6


def test_no_pair_of_clusters_is_joined(spark, graph, monkeypatch):
    """the whole search, from more clusters than the bound; the cost is that of the model it returns."""
    monkeypatch.setattr(cocluster, "LOCAL_START", 12)
    monkeypatch.setattr(greedy, "candidates", None)
    model = cocluster.fit(graph, restarts=1, local_cells=1)
    trace = [x["cost"] for x in model.trace.where("step != 'merge'").collect()]
    assert math.isclose(model.cost().first()["total"], trace[-1], rel_tol=1e-9)
    assert model.row_part.count() == graph.traversal.select("t").distinct().count()
    assert 0 <= model.compression().first()["compression"] < 1
    # By joins, as for more vertices than the driver holds labels of.
    monkeypatch.undo()
    monkeypatch.setattr(labelled, "LABELS", 0)
    joined = cocluster.fit(graph, restarts=0, local_cells=1, start=12, passes=1, refine=False)
    assert math.isclose(joined.cost().first()["total"], joined.trace.where("step != 'exchange'").collect()[-1]["cost"], rel_tol=1e-9)


class Counted:
    """A table that counts what is looked up in it."""

    def __init__(self, table):
        self.table, self.n = table, 0

    def __len__(self):
        return len(self.table)

    def take(self, at):
        self.n += np.size(at)
        return self.table.take(at)


def test_merges_are_products_of_matrices(monkeypatch):
    """Changes by all merges, against sums cell by cell; only few cells are looked up pair by pair."""
    rng = np.random.default_rng(5)
    f = kernel.log_factorials
    for mean, most in ((0.05, 1), (1, 1), (6, 90), (150, 1), (150, 3_000), (400, 1)):
        left, right = (rng.poisson(mean, (n, 120)) for n in (40, 30))
        left[3, 5] *= most
        right[:2, 7:9] *= most
        table = Counted(kernel.SMALL)
        monkeypatch.setattr(labelled, "SMALL", table)
        got = labelled.merged_terms(left, right)
        x, y = left[:, None, :], right[None, :, :]
        expected = np.where(((x > 0) & (y > 0)).any(axis=2), (f(x) + f(y) - f(x + y)).sum(axis=2), np.inf)
        assert np.isfinite(got).tolist() == np.isfinite(expected).tolist()
        assert np.allclose(got[np.isfinite(got)], expected[np.isfinite(got)], rtol=0, atol=1e-7)
        assert mean > 256 or table.n < 0.1 * left.size * len(right)


def test_many_vertices_move_as_each_alone():
    """Moves by products of matrices and by look-ups are those of each vertex by itself."""
    rng = np.random.default_rng(6)
    for k, wide, each, top in ((30, 25, 12, 3), (30, 25, 1, 1), (12, 40, 9, 500)):
        vertices = 300
        cell = np.concatenate([np.sort(rng.choice(wide, each, replace=False)) for _ in range(vertices)])
        n = rng.choice([1, 1, 1, 2, top], len(cell))
        begin, own = np.arange(vertices) * each, rng.integers(1, k, vertices)
        block = rng.poisson(3, (k, wide))
        block[0] = 0
        np.add.at(block, (np.repeat(own, each), cell), n)
        size = np.bincount(own, minlength=k)
        rows = [(int(own[v]), cell[b : b + each], n[b : b + each]) for v, b in enumerate(begin)]
        assert kernel.best_moves(block, size, block.sum(axis=1), own, begin, cell, n).tolist() == kernel.best_clusters(block, size, block.sum(axis=1), rows)


def test_all_clusters_find_a_partner():
    """Where all lines name the same column, a pair of tiles still matches every line, the least changes first."""
    weight = np.arange(1.0, 9.0)
    delta = -weight[:, None] * weight
    assert set(delta.argmin(axis=1)) == {7}
    i, j = labelled.matching(delta)
    assert list(zip(i.tolist(), j.tolist())) == [(k, k) for k in range(7, -1, -1)]
    i, j = labelled.matching(np.array([[3.0, 1.0], [np.inf, 2.0]]))
    assert list(zip(i.tolist(), j.tolist())) == [(0, 1)]
