"""Trees, bounds and walks in one process, against plain numpy."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from hypernear.operators.grow import COUNTERS, Options, grow, random_keys, walk


def with_ones(P):
    return np.column_stack([P, np.ones(len(P))])


def brute(X, ids, q, k):
    margins = X[:, 0] * q[0]
    for j in range(1, X.shape[1]):
        margins = margins + X[:, j] * q[j]
    margins = np.abs(margins)
    order = np.lexsort((ids, margins))[:k]
    return [(margins[i], ids[i]) for i in order]


def unit_plane(random, d, scale=1.0):
    w = random.standard_normal(d)
    return np.append(w / np.linalg.norm(w), random.uniform(-scale, scale))


VARIANTS = [dict(ball=b, cone=c, derive_sibling=s, preference=p) for b in (0, 1) for c in (0, 1) for s in (0, 1) for p in ("center", "bound")]


@settings(max_examples=25, deadline=None)
@given(st.integers(0, 10**6), st.integers(1, 300), st.integers(1, 5), st.sampled_from([1, 3, 20]), st.booleans())
def test_walk_equals_scan(seed, n, d, leaf, coarse):
    random = np.random.default_rng(seed)
    P = random.standard_normal((n, d)) * random.choice([1e-3, 1.0, 1e3])
    P = np.round(P, 1) if coarse else P  # coarse values make ties and duplicates
    X, ids = with_ones(P), random.permutation(10 * n)[:n].astype(np.int64)
    tree = grow(ids, X, leaf, 7)
    q = unit_plane(random, d, 3.0)
    for variant in VARIANTS:
        for k in (1, 4, n + 3):
            found, cost = walk(tree, q, float(np.linalg.norm(q)), Options(k=k, **variant))
            assert found == brute(X, ids, q, k)
            assert set(cost) == set(COUNTERS) and cost["verified"] <= n


def test_bounds_hold_and_cone_contains_ball():
    random = np.random.default_rng(1)
    X, ids = with_ones(random.standard_normal((500, 4))), np.arange(500)
    tree = grow(ids, X, 25, 3)
    for scale in (1.0, 6.0):
        for _ in range(40):
            q = unit_plane(random, 4, scale)
            length = np.linalg.norm(q)
            for at in range(len(tree.node)):
                span = slice(tree.lo[at], tree.hi[at])
                ip, margins = tree.centers[at] @ q, np.abs(tree.X[span] @ q)
                assert max(abs(ip) - length * tree.radii[at], 0) <= margins.min() + 1e-9
                if tree.is_leaf(at):
                    along = ip / tree.norms[at]
                    across = np.sqrt(max(length**2 - along**2, 0))
                    ball = np.maximum(abs(ip) - length * tree.r_x[span], 0)
                    low, high = along * tree.x_par[span] - across * tree.x_perp[span], along * tree.x_par[span] + across * tree.x_perp[span]
                    cone = np.where(low > 0, low, np.where(high < 0, -high, 0))
                    assert (cone <= margins + 1e-7).all() and (cone >= ball - 1e-7).all()
                    # The angle form of the same bound.
                    theta, phi = np.arccos(np.clip(along / length, -1, 1)), np.arctan2(tree.x_perp[span], tree.x_par[span])
                    size = length * np.hypot(tree.x_par[span], tree.x_perp[span])
                    by_angle = np.where((np.cos(theta + phi) > 0) & (np.cos(theta) > 0), size * np.cos(theta + phi), np.where(np.cos(theta - phi) < 0, -size * np.cos(theta - phi), 0))
                    assert np.allclose(by_angle, cone, atol=1e-6)
                    assert np.allclose(tree.r_x[span] ** 2, tree.x_perp[span] ** 2 + (tree.norms[at] - tree.x_par[span]) ** 2)


def test_invariants_and_rolled_up_centres():
    random = np.random.default_rng(2)
    X, ids = with_ones(random.standard_normal((700, 3))), np.arange(700)
    tree = grow(ids, X, 20, 5)
    for at in range(len(tree.node)):
        assert np.allclose(tree.centers[at], tree.X[tree.lo[at] : tree.hi[at]].mean(axis=0))
        if tree.is_leaf(at):
            assert tree.n(at) <= 20
            assert (np.diff(tree.r_x[tree.lo[at] : tree.hi[at]]) <= 0).all()
        else:
            assert tree.n(at) == tree.n(tree.left[at]) + tree.n(tree.right[at])
    assert sorted(tree.ids) == list(ids)


@pytest.mark.parametrize("P", [np.zeros((0, 2)), np.ones((1, 2)), np.ones((50, 2)), np.array([[2.0**k, 0.0] for k in range(40)]), np.arange(30.0)[:, None] * 1e6])
def test_degenerate_sets(P):
    X, ids = with_ones(P), np.arange(len(P))
    tree = grow(ids, X, 4, 1)
    if len(P) == 50:
        assert tree.flat[0] and tree.is_leaf(0)
    q = np.append(np.eye(P.shape[1])[0], -1.0)
    found, _ = walk(tree, q, float(np.linalg.norm(q)), Options(k=3))
    assert found == brute(X, ids, q, 3)


def test_counts_halve_with_derived_siblings():
    random = np.random.default_rng(3)
    X, ids = with_ones(random.standard_normal((3000, 4))), np.arange(3000)
    tree = grow(ids, X, 30, 5)
    for _ in range(20):
        q = unit_plane(random, 4)
        length = float(np.linalg.norm(q))
        direct = walk(tree, q, length, Options(derive_sibling=False))[1]["center_products"]
        derived = walk(tree, q, length, Options(derive_sibling=True, rederive=1 << 30))[1]["center_products"]
        assert derived == (direct + 1) / 2


def test_budget_recall_rises_and_quota_holds():
    random = np.random.default_rng(4)
    X, ids = with_ones(random.standard_normal((2000, 4))), np.arange(2000)
    tree = grow(ids, X, 50, 5)
    q = unit_plane(random, 4)
    truth = {i for _, i in brute(X, ids, q, 10)}
    recalls = []
    for quota in (20, 200, 2000):
        found, cost = walk(tree, q, float(np.linalg.norm(q)), Options(), quota=quota)
        assert cost["verified"] <= quota
        recalls.append(len(truth & {i for _, i in found}))
    assert recalls == sorted(recalls) and recalls[-1] == 10


def test_random_keys_are_sparks(spark):
    from pyspark.sql import functions as F

    ids = np.array([0, 1, -5, 2**40, 123456789], dtype=np.int64)
    rows = spark.createDataFrame([(int(i),) for i in ids], "id long").select("id", F.xxhash64(F.lit(42).cast("long"), F.lit(9).cast("long"), "id").alias("h")).collect()
    assert [r.h for r in sorted(rows, key=lambda r: list(ids).index(r.id))] == random_keys(42, 9, ids).tolist()
