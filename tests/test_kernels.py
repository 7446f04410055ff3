import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from farpoint.functions.distance import METRICS, minkowski
from farpoint.operators import kernels, threshold


def naive(x, k, dist):
    picks, keys = [0], [np.inf]
    while len(picks) < k:
        low = [min(dist(p, x[c]) for c in picks) for p in x]
        far = max(range(len(x)), key=lambda i: (low[i], -i))
        if low[far] <= 0:
            break
        picks.append(far)
        keys.append(low[far])
    return picks, keys


points = st.lists(st.tuples(st.integers(-50, 50), st.integers(-50, 50)), min_size=1, max_size=40)


@settings(max_examples=60, deadline=None)
@given(points, st.integers(1, 8))
def test_traversal_is_the_naive_one(rows, k):
    x = np.array(rows, float)
    for name, dist in (("euclidean", lambda a, b: ((a - b) ** 2).sum()), ("manhattan", lambda a, b: np.abs(a - b).sum()), ("chebyshev", lambda a, b: np.abs(a - b).max())):
        picks, keys, radius = kernels.farthest_first(x, k, 0, 0.0, name)
        want, want_keys = naive(x, k, dist)
        assert picks.tolist() == want and keys.tolist() == want_keys
        assert radius == max(min(dist(p, x[c]) for c in want) for p in x)
    pruned = kernels.farthest_first_pruned(x, k)
    plain = kernels.farthest_first(x, k)
    assert pruned[0].tolist() == plain[0].tolist() and pruned[1].tolist() == plain[1].tolist() and pruned[2] == plain[2]


@settings(max_examples=40, deadline=None)
@given(points, st.integers(1, 5), st.integers(2, 5))
def test_metamorphic(rows, k, scale):
    x = np.array(rows, float)
    picks, keys, radius = kernels.farthest_first(x, k)
    assert kernels.farthest_first(x * scale, k)[2] == radius * scale**2
    assert kernels.farthest_first(x + 1000, k)[2] == radius
    assert kernels.farthest_first(np.concatenate([x, x[:1]]), k)[2] == radius
    more = kernels.farthest_first(x, k + 1)
    assert more[0][: len(picks)].tolist() == picks.tolist() and more[2] <= radius


def test_fixtures():
    line = np.array([[0.0], [1], [5], [9], [10]])
    picks, _, radius = kernels.farthest_first(line, 2)
    assert picks.tolist() == [0, 4] and radius == 25
    assert kernels.farthest_first(line, 3)[2] == 1
    dup = np.array([[3.0, 3]] * 4 + [[9, 9]])
    picks, _, radius = kernels.farthest_first(dup, 3)
    assert len(picks) == 2 and radius == 0
    square = np.array([[0.0, 0], [0, 2], [2, 0], [2, 2]])
    picks, _, radius = kernels.farthest_first(square, 2)
    assert picks.tolist() == [0, 3] and radius == 4
    assert kernels.farthest_first(line, 9)[2] == 0 and len(kernels.farthest_first(np.empty((0, 1)), 3)[0]) == 0


def test_nearest_forms_agree(monkeypatch):
    rng = np.random.default_rng(0)
    for dims, n in ((20, 300), (2, 700)):
        x, c = rng.integers(-1000, 1000, (5_000, dims)).astype(float), rng.integers(-1000, 1000, (n, dims)).astype(float)
        far = np.full(len(x), np.inf)
        tiles, lowered, floats = kernels.nearest(x, c), kernels.lower_keys(x, far, c), kernels.lower_keys(x + 0.25, far, c + 0.25)
        with monkeypatch.context() as m:
            m.setattr(kernels, "PRODUCTS", 10**9)
            which, key = kernels.nearest(x, c)
            assert (lowered == kernels.lower_keys(x, far, c)).all()
        assert (tiles[0] == which).all() and (tiles[1] == key).all() and (lowered == key).all() and (floats == key).all()
        assert (kernels.lower_keys(x, np.full(len(x), 500.0), c) == np.minimum(key, 500)).all()
    assert not kernels.products_are_exact(x * 2.0**20, c) and not kernels.products_are_exact(x + 0.5, c)


@pytest.mark.parametrize("name", [*METRICS, "minkowski"])
def test_metric_rules_and_expressions(spark, name):
    m = minkowski(3) if name == "minkowski" else METRICS[name]
    rng = np.random.default_rng(1)
    x = rng.integers(0, 4, (12, 3)).astype(float) + (1 if name == "angular" else 0)
    if name == "haversine":
        x = np.column_stack([rng.uniform(-80, 80, 12), rng.uniform(-170, 170, 12)])
    d = np.array([[m.finish(v) for v in m.kernel(x, c)] for c in x])
    assert np.allclose(d, d.T, atol=1e-9) and np.allclose(np.diag(d), 0, atol=1e-7)
    assert all(d[i, j] <= d[i, h] + d[h, j] + 1e-7 for i in range(12) for j in range(12) for h in range(12))
    frame = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "id int, coords array<double>")
    got = [r[0] for r in frame.orderBy("id").select(m.expr(frame["coords"], x[0].tolist()).cast("double")).collect()]
    assert np.allclose(got, m.kernel(x, x[0]), atol=1e-9)


@settings(max_examples=30, deadline=None)
@given(points, st.integers(1, 4))
def test_threshold_solver_is_a_2_approximation(rows, k):
    import itertools

    x = np.array(rows[:12], float)
    _, _, radius = threshold.threshold_solver(x, k)
    opt = min(kernels.nearest(x, x[list(c)])[1].max() for c in itertools.combinations(range(len(x)), min(k, len(x))))
    assert radius <= 4 * opt + 1e-9
    assert kernels.farthest_first(x, k)[2] <= 4 * opt + 1e-9
