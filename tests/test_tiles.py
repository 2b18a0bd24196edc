import numpy as np
import pytest

from roadweave.model import BipartiteGraph
from roadweave.operators import similarity, tiles, weights


def some(vertices: int, features: int, seed: int) -> list[tuple[int, int, float]]:
    rng = np.random.default_rng(seed)
    return [(int(v) * 7 + 1, int(f), float(rng.integers(0, 4))) for v in range(vertices) for f in np.flatnonzero(rng.random(features) < 0.3)]


def expected(rows, least):
    out = {}
    for v, f, w in rows:
        for u, g, x in rows:
            if f == g and v < u:
                total, count = out.get((v, u), (0.0, 0))
                out[v, u] = total + w * x, count + 1
    return {k: v for k, v in out.items() if v[0] >= least}


@pytest.mark.parametrize("bounds", [(2_000_000, 4_000_000), (7, 4_000_000), (2_000_000, 60), (1, 1)])
def test_meet_equals_brute_force(monkeypatch, bounds):
    monkeypatch.setattr(tiles, "PRODUCTS", bounds[0])
    monkeypatch.setattr(tiles, "CELLS", bounds[1])
    monkeypatch.setattr(tiles, "ROWS", 5)
    for least in (-np.inf, 3.0):
        rows = some(30, 12, seed=3)
        pick = lambda keep: tiles.Tile(*(np.array([r[k] for r in rows if keep(r[0])]) for k in range(3)))
        even, odd = pick(lambda v: v % 2 == 0), pick(lambda v: v % 2 == 1)
        batches = [*tiles.meet(even, even, True, least), *tiles.meet(odd, odd, True, least), *tiles.meet(even, odd, False, least)]
        got = [r for b in batches for r in zip(*(c.to_pylist() for c in b.columns))]
        assert len(got) == len({r[:2] for r in got}) and max(b.num_rows for b in batches) <= 5
        assert {r[:2]: r[2:] for r in got} == expected(rows, least)


@pytest.mark.parametrize("tile", [None, 1, 4, 100])
def test_products_of_any_tile(spark, tile):
    rows = some(17, 9, seed=5)
    got = tiles.products(spark.createDataFrame(rows, "v long, f long, w double"), tile=tile)
    assert {(r["a"], r["b"]): (r["omega"], r["common"]) for r in got.collect()} == expected(rows, -np.inf)
    assert tiles.products(spark.createDataFrame([], "v long, f long, w double"), tile=tile).count() == 0


def graph(spark) -> BipartiteGraph:
    return BipartiteGraph.of(spark.createDataFrame([(v, f, 1, 1.0) for v, f, _ in some(20, 9, seed=7)], "t long, s long, n long, length double"))


def test_common_counts_are_not_shuffled(spark):
    """sums of pairs are made where the products are."""
    assert "Exchange" not in similarity.common_pairs(graph(spark))._jdf.queryExecution().executedPlan().toString()


def test_cosines_are_not_shuffled(spark):
    """F8."""
    assert "Exchange" not in similarity.project(graph(spark))._jdf.queryExecution().executedPlan().toString()


def test_pruned_cosines_are_not_shuffled(spark):
    """pairs below the least similarity never leave a task."""
    assert "Exchange" not in similarity.cosine_pairs(weights.spatial_tfidf(graph(spark)), min_sim=0.5)._jdf.queryExecution().executedPlan().toString()


def copied(rows, times):
    return [(v + 1_000 * k, f, w) for v, f, w in rows for k in range(times)]


def test_equal_vectors_are_multiplied_once(monkeypatch):
    """F8: copies meet as one vector, and all their pairs come out, one pair of vectors after another."""
    products, terms = [], tiles.terms

    def counted(left, right):
        for x in terms(left, right):
            products.append(len(x[2]))
            yield x

    monkeypatch.setattr(tiles, "terms", counted)
    monkeypatch.setattr(tiles, "ROWS", 7)
    rows = [r for r in some(12, 9, seed=11) if r[2]]
    both = copied(rows, 5)
    pick = lambda own, keep: tiles.Tile(*(np.array([r[k] for r in own if keep(r[0])]) for k in range(3)))
    for least in (-np.inf, 3.0):
        got, counts = {}, []
        for own in (rows, both):
            products.clear()
            one, two = pick(own, lambda v: v % 1_000 < 40), pick(own, lambda v: v % 1_000 >= 40)
            batches = [*tiles.meet(one, one, True, least), *tiles.meet(two, two, True, least), *tiles.meet(one, two, False, least)]
            counts.append(sum(products))
            got = [r for b in batches for r in zip(*(c.to_pylist() for c in b.columns))]
            assert len(got) == len({r[:2] for r in got}) and max(b.num_rows for b in batches) <= 7
            assert {r[:2]: r[2:] for r in got} == expected(own, least)
        assert counts[0] == counts[1]


def test_vectors_that_differ_stay_apart():
    """Equal features with other weights, more features or very small weights are other vectors."""
    vectors = [{1: 1.0, 2: 2.0}, {1: 1.0, 2: 2.0}, {1: 1.0, 2: 2.5}, {1: 1.0, 2: 2.0, 3: 1.0}, {1: 1e-15}, {1: 3e-15}, {1: 1e-15}]
    tile = tiles.Tile(*(np.array(x) for x in zip(*[(v, f, w) for v, own in enumerate(vectors) for f, w in own.items()])))
    own = tile.units
    assert sorted(sorted(own.v[a:b].tolist()) for a, b in zip(own.begin, own.begin[1:])) == [[0, 1], [2], [3], [4, 6], [5]]


def test_equal_vectors_share_a_tile(spark):
    """copies have places beside each other, and any tile gives all pairs of them."""
    rows = copied(some(9, 9, seed=13), 4)
    frame = spark.createDataFrame(rows, "v long, f long, w double")
    order, n = tiles.placed(frame)
    place = {r["v"]: r["place"] for r in order.collect()}
    assert n == len(place) and sorted(place.values()) == list(range(n))
    vector = {v: tuple(sorted((f, w) for u, f, w in rows if u == v)) for v in place}
    for x in set(vector.values()):
        at = [place[v] for v in place if vector[v] == x]
        assert max(at) - min(at) == len(at) - 1
    got = tiles.products(frame, tile=5)
    assert {(r["a"], r["b"]): (r["omega"], r["common"]) for r in got.collect()} == expected(rows, -np.inf)
