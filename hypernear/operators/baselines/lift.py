"""The quadratic lift: products of lifted vectors are squared products, so a hyperplane search becomes one by distance."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def lift(x: Column) -> Column:
    """Squares, and root two times each product of two components: d (d + 1) / 2 numbers."""
    index = F.sequence(F.lit(0), F.size(x) - 1)
    root = F.lit(2.0**0.5)
    return F.flatten(F.transform(index, lambda i: F.transform(F.slice(x, i + 1, F.size(x)), lambda v, j: F.when(j == 0, F.get(x, i) * v).otherwise(root * F.get(x, i) * v))))


def lift_rows(X: np.ndarray) -> np.ndarray:
    i, j = np.triu_indices(X.shape[1])
    return X[:, i] * X[:, j] * np.where(i == j, 1.0, np.sqrt(2.0))


def recipe_pairs(d: int, lam: int) -> list[tuple[int, int]]:
    """lam index pairs by integer arithmetic, which SQL can repeat."""
    return [((7 * t + 3) % d, (11 * t + 5 * (t // d) + 1) % d) for t in range(lam)]


def random_pairs(d: int, lam: int, seed: int) -> list[tuple[int, int]]:
    draw = np.random.default_rng(seed).integers(0, d, (lam, 2))
    return [(int(a), int(b)) for a, b in draw]


def sampled_lift(x: Column, pairs: list[tuple[int, int]], d: int) -> Column:
    """lam sampled products, scaled so that products of sampled lifts are squared products on average."""
    scale = d / len(pairs) ** 0.5
    return F.array(*[F.get(x, F.lit(i)) * F.get(x, F.lit(j)) * scale for i, j in pairs])


def sampled_rows(X: np.ndarray, pairs: list[tuple[int, int]] | None) -> np.ndarray:
    """Sampled lifts of rows; the whole lift without pairs."""
    if pairs is None:
        return lift_rows(X)
    i, j = np.array(pairs).T
    return X[:, i] * X[:, j] * (X.shape[1] / np.sqrt(len(pairs)))


def largest_norm(points: DataFrame, pairs: list[tuple[int, int]] | None) -> float:
    """Greatest norm of the lifted points: one number, by one aggregation."""
    return largest_norms(points, [pairs])[1][0]


def largest_norms(points: DataFrame, pairs: list[list[tuple[int, int]] | None], block: int = 4096) -> tuple[int, list[float]]:
    """The number of points, and the greatest norm of each of their lifts, by one aggregation."""
    import pyarrow as pa

    def run(batches):
        n, most = 0, [0.0] * len(pairs)
        for batch in batches:
            for at in range(0, batch.num_rows, block):
                some = batch.slice(at, block)
                X = np.asarray(some.column(0).flatten()).reshape(some.num_rows, -1)
                n, most = n + len(X), [max(m, float(np.linalg.norm(sampled_rows(X, one), axis=1).max(initial=0.0))) for m, one in zip(most, pairs)]
        yield pa.RecordBatch.from_pydict({"lift": pa.array(np.arange(len(pairs))), "most": pa.array(most, pa.float64()), "n": pa.array([n] * len(pairs), pa.int64())})

    found = points.select("x").mapInArrow(run, "lift long, most double, n long").groupBy("lift").agg(F.max("most").alias("most"), F.sum("n").alias("n")).collect()
    by = {r.lift: r for r in found}
    return (by[0].n, [by[at].most for at in range(len(pairs))]) if by else (0, [0.0] * len(pairs))


def complete(L: np.ndarray, most: np.ndarray | float) -> np.ndarray:
    """Lifted points with the coordinate that gives all of them the norm most."""
    rest = np.sqrt(np.maximum(np.asarray(most) ** 2 - np.einsum("ij,ij->i", L, L), 0.0))
    return np.column_stack([L, rest])


def lifted_query(Q: np.ndarray, pairs: list[tuple[int, int]] | None, near: bool) -> np.ndarray:
    """Planes in the completed space: negated for a nearest search, as they are for a furthest one."""
    L = sampled_rows(Q, pairs)
    return np.column_stack([-L if near else L, np.zeros(len(L))])


def exact_distances(points: DataFrame, planes: DataFrame, near: bool = True) -> DataFrame:
    """(qid, id, distance) in the completed lifted space, of all pairs: for checks on small sets."""
    import pyarrow as pa

    from ...sources.storage import opened, ship
    from ..brute import batches_of

    most, found = largest_norm(points, None), None
    for qids, Q in batches_of(planes):
        shared = ship(points.sparkSession, (qids, lifted_query(Q, None, near), most))

        def run(batches, shared=shared):
            qids, LQ, most = opened(shared)
            for batch in batches:
                ids, X = np.asarray(batch.column(0)), np.asarray(batch.column(1).flatten()).reshape(batch.num_rows, -1)
                L = complete(lift_rows(X), most)
                for qid, q in zip(qids, LQ):
                    yield pa.RecordBatch.from_pydict({"qid": np.full(len(ids), qid), "id": ids, "distance": np.sqrt(((L - q) ** 2).sum(axis=1))})

        part = points.select("id", "x").mapInArrow(run, "qid long, id long, distance double")
        found = part if found is None else found.unionByName(part)
    return found


def distortion(distances: DataFrame) -> DataFrame:
    """(qid, ratio): greatest over least lifted distance; near 1, where a distance search can hardly tell points apart."""
    return distances.groupBy("qid").agg((F.max("distance") / F.min("distance")).alias("ratio"))
