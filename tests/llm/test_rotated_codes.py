import numpy as np
import pytest

from hypernear.llm import rotated_codes as R

SCHEMA = "vec_id long, embedding array<float>, label int"


def scan(V, ids, queries, k=10):
    out = {}
    for q in queries:
        d = np.sqrt(((V - V[list(ids).index(q)]) ** 2).sum(axis=1))
        out[q] = sorted((x, i) for x, i in zip(d, ids) if i != q)[:k]
    return out


def test_recall_against_brute_force(spark):
    random = np.random.default_rng(1)
    V = random.standard_normal((3000, 32)).astype(np.float32)
    df = spark.createDataFrame([(i, v.tolist(), 0) for i, v in enumerate(V)], SCHEMA)
    index, setting = R.build(df)
    assert index.count() == 3000
    queries = index.filter("vec_id % 100 = 0")
    for options in ({}, dict(batch_bytes=2000, block=256)):
        want, hits = scan(V.astype(float), range(3000), range(0, 3000, 100)), 0
        for r in R.search(index, setting, queries, **options).collect():
            hits += any(i == r.vec_id and abs(d - r.score) < 1e-9 for d, i in want[r.query_id])
        assert hits / 300 >= 0.97


def test_bounds_hold_mostly():
    random = np.random.default_rng(2)
    d, n = 64, 2000
    X, Q = random.standard_normal((n, d)), random.standard_normal((20, d))
    setting = {"d": d, "centre": X.mean(axis=0), "rotation": R.rotation(d, 1)}
    offset = X - setting["centre"]
    norm = np.linalg.norm(offset, axis=1)
    turned = (offset / norm[:, None]) @ setting["rotation"].T
    estimate, half = R.bounds(Q, R.packed(turned > 0), norm, np.abs(turned).sum(axis=1) / np.sqrt(d), setting, 3.0)
    true = ((Q[:, None, :] - X[None]) ** 2).sum(axis=2)
    assert (np.abs(estimate - true) <= half).mean() > 0.99


@pytest.mark.parametrize("rows, want", [
    ([], []),
    ([(0, [1.0, 0.0], 1)], []),
    ([(0, [1.0, 0.0], 1), (1, [1.0, 0.0], 1), (2, [1.0, 0.0], 1), (3, None, 1), (4, [0.0, 0.0], 1), (5, [float("nan"), 1.0], 1), (6, [1.0], 1), (7, [None, 1.0], 1), (None, [1.0, 1.0], 1), (8, [float("inf"), 1.0], None)], [(0, 1, 1, 0.0), (0, 2, 2, 0.0)]),
    ([(0, [1.0, 0.0], 1), (1, [4.0, 4.0], 1), (1, [4.0, 4.0], 1)], [(0, 1, 1, 5.0), (0, 2, 1, 5.0)]),
])
def test_edge_cases(spark, rows, want):
    df = spark.createDataFrame(rows, SCHEMA).selectExpr("*", "1 AS score", "'c' AS code")
    index, setting = R.build(df)
    found = R.search(index, setting, index.filter("vec_id % 100 = 0"))
    assert sorted((r.query_id, r["rank"], r.vec_id, r.score) for r in found.collect()) == want


def test_products_are_counted_on_bits():
    """The estimate from packed bits is that of the signs themselves, up to the rounding of the query."""
    random = np.random.default_rng(6)
    d = 100
    X, Q = random.standard_normal((300, d)), random.standard_normal((7, d))
    setting = {"d": d, "centre": np.zeros(d), "rotation": np.eye(d)}
    norm = np.linalg.norm(X, axis=1)
    fit = np.abs(X / norm[:, None]).sum(axis=1) / np.sqrt(d)
    estimate, _ = R.bounds(Q, R.packed(X > 0), norm, fit, setting, 3.0, levels=12)
    length = np.linalg.norm(Q, axis=1)
    product = (Q / length[:, None]) @ np.where(X > 0, 1, -1).T / np.sqrt(d) / fit
    assert np.allclose(estimate, length[:, None] ** 2 + norm**2 - 2 * length[:, None] * norm * product, atol=0.2)


def test_repeated_query_rows_and_double_vectors(spark):
    rows = [(0, [1.0, 0.0])] * 2 + [(i, [1.0, float(i)]) for i in range(1, 13)]
    index, setting = R.build(spark.createDataFrame(rows, "vec_id long, embedding array<double>"))
    found = sorted((r["rank"], r.vec_id, r.score) for r in R.search(index, setting, index.filter("vec_id % 100 = 0")).collect())
    assert found == sorted([(k + 1, k, float(k)) for k in range(10)] * 2)
    near = [(0, [1.0, 1.0]), (1, [1.0, 1.0 + 3e-9]), (2, [1.0, 1.0 + 1e-9])]
    index, setting = R.build(spark.createDataFrame(near, "vec_id long, embedding array<double>"))
    found = sorted((r["rank"], r.vec_id) for r in R.search(index, setting, index.filter("vec_id = 0")).collect())
    assert found == [(1, 2), (2, 1)]
    other = spark.createDataFrame([(7, [1.0, 1.0])], "vec_id long, embedding array<double>")
    assert [(r.vec_id, r.score) for r in R.search(index, setting, other).orderBy("rank").collect()][0] == (0, 0.0)
