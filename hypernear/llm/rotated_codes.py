"""Approximate nearest neighbours by randomly rotated one-bit codes.

A vector's offset from the mean is made a unit vector, turned by a random rotation, and kept as one sign bit a
dimension, with two correction scalars: the offset's length and the product of the unit vector with its
code. From these the squared distance to a query is estimated by counting bits, with an error that exceeds its bound (``width``
standard errors, that of the query's rounding included) rarely and independently of the data. Of each block of vectors the ten best
estimates are measured exactly; then only vectors whose lower bound is within the tenth exact distance that the task has met so far
are measured (reranked).

The index holds every valid row, the vector beside its code: of 64 numbers one bit each tells a sixth of the rows apart from the ten
nearest at best (see README), so that vectors fetched by id would be moved many times. Queries are a stated set that grows with the data, so
they are broadcast in batches of at most ``batch_bytes``, one at a time; each batch reads the index once and never meets more than a block at a time.

Defined cases: vectors that are null, zero, hold null or non-finite components, or have another length than most
take no part; nor do rows with a null id; repeated ids are one row each, as queries too: each such row gets its own ranks from 1, and may
find the others; equal distances are ordered by the smaller id; fewer candidates than k give fewer rows; an empty table gives an empty result.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import opened, persisted, ship, split

SCHEMA = "row long, vec_id long, embedding array<double>, code binary, norm double, fit double"
NAMES = ["row", "vec_id", "embedding", "code", "norm", "fit"]


def rotation(d: int, seed: int) -> np.ndarray:
    """A random orthogonal matrix (signs fixed, so that it is uniform)."""
    q, r = np.linalg.qr(np.random.default_rng(seed).standard_normal((d, d)))
    return q * np.sign(np.diag(r))


def valid(vectors: DataFrame, column: str = "embedding") -> DataFrame:
    """vec_id and the vector of the rows that take part."""
    v = F.col(column)
    fine = v.isNotNull() & (F.size(v) > 0) & ~F.exists(v, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf"))) & F.exists(v, lambda x: x != 0)
    kept = vectors.filter(F.col("vec_id").isNotNull()).filter(fine).select("vec_id", v.alias("embedding"))
    most = kept.groupBy(F.size("embedding").alias("d")).count().orderBy(F.desc("count"), F.desc("d")).first()
    return kept.filter(F.size("embedding") == (most.d if most else 0))


def matrix(column: pa.Array, d: int) -> np.ndarray:
    return np.asarray(column.flatten(), dtype=np.float64).reshape(-1, d)


def build(vectors: DataFrame, seed: int = 42) -> tuple[DataFrame, dict]:
    """The index, a written table of one row a vector, and what a search needs to read it. ``row`` tells rows of one vec_id apart."""
    kept = valid(vectors)
    first = kept.select(F.size("embedding").alias("d")).first()
    d = first.d if first else 0

    def sums(batches):
        total, n = np.zeros(d), 0
        for batch in batches:
            X = matrix(batch.column(0), d)
            total, n = total + X.sum(axis=0), n + len(X)
        yield pa.RecordBatch.from_pydict({"at": pa.array(range(d), pa.int32()), "total": pa.array(total), "n": pa.array([n] * d, pa.int64())})

    if not d:
        return kept.sparkSession.createDataFrame([], SCHEMA), {"d": 0}
    means = kept.select("embedding").mapInArrow(sums, "at int, total double, n long").groupBy("at").agg((F.sum("total") / F.sum("n")).alias("mean")).orderBy("at").collect()
    setting = {"d": d, "centre": np.array([r.mean for r in means]), "rotation": rotation(d, seed)}
    shared = ship(kept.sparkSession, setting)

    def encode(batches):
        s = opened(shared)
        for batch in batches:
            offset = matrix(batch.column(2), d) - s["centre"]
            norm = np.linalg.norm(offset, axis=1)
            turned = (offset / np.where(norm > 0, norm, 1)[:, None]) @ s["rotation"].T
            bits = packed(turned > 0)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array([b.tobytes() for b in bits], pa.binary()), pa.array(norm), pa.array(np.abs(turned).sum(axis=1) / np.sqrt(d))], names=["row", "vec_id", "embedding", "code", "norm", "fit"])

    rows = kept.select(F.monotonically_increasing_id().alias("row"), F.col("vec_id").cast("long"), F.col("embedding").cast("array<double>"))
    return persisted(rows.mapInArrow(encode, SCHEMA), "rotated-codes"), setting


def packed(bits: np.ndarray) -> np.ndarray:
    """Rows of bits as whole 64-bit words."""
    short = np.packbits(bits, axis=-1)
    return np.concatenate([short, np.zeros((*short.shape[:-1], -short.shape[-1] % 8), np.uint8)], axis=-1).view(np.uint64)


def planes(turned: np.ndarray, levels: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Each row in whole steps above its least component, as ``levels`` bit planes: (planes, least, step, sum of the whole steps)."""
    least = turned.min(axis=1)
    step = np.maximum(turned.max(axis=1) - least, 1e-300) / (2**levels - 1)
    whole = np.rint((turned - least[:, None]) / step[:, None]).astype(np.int64)
    bits = [packed((whole >> k & 1).astype(bool)) for k in range(levels)]
    return np.stack(bits, axis=1), least, step, whole.sum(axis=1)


def bounds(Q: np.ndarray, codes: np.ndarray, norm: np.ndarray, fit: np.ndarray, setting: dict, width: float, levels: int = 6) -> tuple[np.ndarray, np.ndarray]:
    """Estimated squared distances (queries by vectors) and the half-widths of their bounds.

    The product of a query with a code is counted on packed bits: of the query's whole steps, plane by plane, those that the code's bits pick.
    """
    d = setting["d"]
    offset = Q - setting["centre"]
    length = np.linalg.norm(offset, axis=1)
    turned = (offset / np.where(length > 0, length, 1)[:, None]) @ setting["rotation"].T
    bits, least, step, whole = planes(turned, levels)
    ones = np.bitwise_count(codes).sum(axis=1, dtype=np.int64)
    picked = np.zeros((len(Q), len(codes)), dtype=np.int32)
    for word in range(codes.shape[1]):
        for k in range(levels):
            picked += np.left_shift(np.bitwise_count(codes[None, :, word] & bits[:, k, word, None]), k, dtype=np.int32)
    # A set bit stands for +1 and another for -1, over the square root of d.
    signed = least[:, None] * (2 * ones - d)[None, :] + step[:, None] * (2 * picked - whole[:, None])
    fit = np.where(fit > 0, fit, 1.0)
    product = signed / np.sqrt(d) / fit
    error = width * np.sqrt(np.maximum(1 - fit**2, 0)[None, :] / max(d - 1, 1) + step[:, None] ** 2 / 12) / fit
    scale = 2 * length[:, None] * norm[None, :]
    return length[:, None] ** 2 + norm[None, :] ** 2 - scale * product, scale * error


def distances(X: np.ndarray, q: np.ndarray) -> np.ndarray:
    """Euclidean distances, squares added in the order of the components, so that SQL gets the same bits."""
    total = np.zeros(len(X))
    for part in ((X - q) ** 2).T:
        total += part
    return np.sqrt(total)


def nearest_in_block(own, Q, tau, rows, block_ids, X, codes, norm, fit, setting, k, width):
    """(query number, vector number, exact distance) of vectors of a block that may be among the k nearest, each query's own row aside.

    tau holds the k-th least distance that each query has met so far, and is lowered.
    """
    estimate, half = bounds(Q, codes, norm, fit, setting, width)
    estimate[own[:, None] == rows[None, :]] = np.inf
    low, out = estimate - half, []
    for q in range(len(own)):
        row = estimate[q]
        some = np.argpartition(row, min(k, len(row)) - 1)[: min(k, len(row))]
        some = some[np.isfinite(row[some])]
        if not len(some):
            continue
        exact = distances(X[some], Q[q])
        if len(some) == k:
            tau[q] = min(tau[q], exact.max())
        if np.isfinite(tau[q]):
            near = np.flatnonzero((low[q] <= tau[q] ** 2 * (1 + 1e-9) + 1e-12) & np.isfinite(row))
            some = np.union1d(some, near) if len(near) else some
            exact = distances(X[some], Q[q])
        best = np.lexsort((block_ids[some], exact))[:k]
        if len(best) == k:
            tau[q] = min(tau[q], exact[best[-1]])
        best = best[exact[best] <= tau[q]]
        out.append((np.full(len(best), q), some[best], exact[best]))
    return [np.concatenate(x) for x in zip(*out)] if out else [np.empty(0, int)] * 2 + [np.empty(0)]


def search(index: DataFrame, setting: dict, queries: DataFrame, k: int = 10, width: float = 3.0, batch_bytes: int = 32 << 20, block: int = 4096) -> DataFrame:
    """query_id, rank, vec_id and score (Euclidean distance) of the k nearest found of each query row.

    Queries with a ``row``, taken from the index, don't find their own row; others (vec_id, embedding) may find any.
    """
    d, spark = setting["d"], index.sparkSession
    wanted = queries if "row" in queries.columns and "code" in queries.columns and d else valid(queries).withColumn("row", F.lit(-1))
    wanted = wanted.select("row", F.col("vec_id").alias("query_id"), F.col("embedding").cast("array<double>").alias("embedding")).filter(F.size("embedding") == d)
    batches = max(1, -(-wanted.count() * 8 * max(d, 1) // batch_bytes))
    found = None
    for part in range(batches):
        mine = wanted.filter(F.pmod(F.xxhash64("query_id", "row"), F.lit(batches)) == part).collect() if d else []
        shared = ship(spark, (setting, np.array([r.row for r in mine], dtype=np.int64), np.array([r.query_id for r in mine], dtype=np.int64), np.array([r.embedding for r in mine], dtype=np.float64).reshape(-1, max(d, 1))))

        def run(parts, shared=shared):
            s, own, ids, Q = opened(shared)
            tau = np.full(len(ids), np.inf)
            kept: list[list] = [[] for _ in range(3)]  # best so far of this task: query number, vector id, distance
            for batch in parts:
                for piece in split(batch, block):
                    X, rows, block_ids = matrix(piece.column(2), d), np.asarray(piece.column(0)), np.asarray(piece.column(1))
                    codes = np.frombuffer(b"".join(piece.column(3).to_pylist()), np.uint64).reshape(len(X), -1)
                    scalars = np.asarray(piece.column(4)), np.asarray(piece.column(5))
                    for at in range(0, len(ids), 512):
                        q, v, score = nearest_in_block(own[at : at + 512], Q[at : at + 512], tau[at : at + 512], rows, block_ids, X, codes, *scalars, s, k, width)
                        for to, x in zip(kept, (q + at, block_ids[v], score)):
                            to.append(x)
                if sum(map(len, kept[0])) > 1 << 20:
                    kept = [[x] for x in best(*map(np.concatenate, kept), k)]
            if kept[0]:
                q, v, score = best(*map(np.concatenate, kept), k)
                yield pa.RecordBatch.from_pydict({"row": pa.array(own[q]), "query_id": pa.array(ids[q]), "vec_id": pa.array(v), "score": pa.array(score)})

        part_found = index.select(*NAMES).mapInArrow(run, "row long, query_id long, vec_id long, score double")
        if batches > 1:  # written, so that no two batches are held by the cluster at once
            part_found = persisted(part_found, "rotated-codes-found")
            shared.unpersist()
        found = part_found if found is None else found.unionByName(part_found)
    rank = F.row_number().over(Window.partitionBy("query_id", "row").orderBy("score", "vec_id"))
    return found.select("query_id", rank.alias("rank"), "vec_id", "score").filter(F.col("rank") <= k)


def best(q: np.ndarray, v: np.ndarray, score: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The k best rows of each query."""
    order = np.lexsort((v, score, q))
    q, v, score = q[order], v[order], score[order]
    first = np.searchsorted(q, q, side="left")
    keep = np.arange(len(q)) - first < k
    return q[keep], v[keep], score[keep]
