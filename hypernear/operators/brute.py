"""Exhaustive search: every plane against every point."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import exprs as E
from ..sources.storage import opened, ship

BROADCAST_BYTES = 32 << 20


def small_side(planes: DataFrame, most_bytes: int = BROADCAST_BYTES) -> DataFrame:
    """planes marked for broadcast if their measured size allows; else as they are, for Spark to pair by partitions."""
    size = planes.agg(F.sum(F.size("q") * 8).alias("bytes")).first().bytes or 0
    return F.broadcast(planes) if size <= most_bytes else planes


def all_margins(points: DataFrame, planes: DataFrame, d: int | None = None) -> DataFrame:
    """(qid, id, margin) of all pairs, with the points' other columns. The product is evaluated once: the
    generator keeps filters above it."""
    pairs = points.crossJoin(small_side(planes.select("qid", "q")))
    others = [c for c in points.columns if c not in ("x", "id")]
    return pairs.select("qid", "id", *others, F.inline(F.array(F.struct(E.absdot(F.col("x"), F.col("q"), d).alias("margin")))))


def ranked(margins: DataFrame, k: int) -> DataFrame:
    """The k least margins of each plane, ties to the smaller id; Spark keeps k rows a task before the shuffle."""
    place = F.row_number().over(Window.partitionBy("qid").orderBy("margin", "id"))
    return margins.withColumn("rank", place.cast("long")).filter(F.col("rank") <= k).select("qid", "rank", "id", "margin")


def topk(points: DataFrame, planes: DataFrame, k: int = 10, d: int | None = None) -> DataFrame:
    return ranked(all_margins(points, planes, d), k)


def nearest(points: DataFrame, planes: DataFrame, d: int | None = None) -> DataFrame:
    """The nearest point of each plane, by one aggregation."""
    best = all_margins(points, planes, d).groupBy("qid").agg(F.min(F.struct("margin", "id")).alias("best"))
    return best.select("qid", F.col("best.id").alias("id"), F.col("best.margin").alias("margin"))


def single_topk(points: DataFrame, q: list[float], k: int = 10, d: int | None = None) -> DataFrame:
    """The k nearest of one plane, by a top-k without any window."""
    plane = F.array(*[F.lit(float(v)) for v in q])
    return points.select("id", E.absdot(F.col("x"), plane, d).alias("margin")).orderBy("margin", "id").limit(k)


def slab(points: DataFrame, planes: DataFrame, tau: float, d: int | None = None) -> DataFrame:
    """All pairs within tau: the range form of the search."""
    return all_margins(points, planes, d).filter(F.col("margin") <= tau)


def sides(points: DataFrame, planes: DataFrame, d: int | None = None) -> DataFrame:
    """Points on each side of each plane."""
    pairs = points.crossJoin(small_side(planes.select("qid", "q"))).select("qid", F.inline(F.array(F.struct(E.dot(F.col("x"), F.col("q"), d).alias("ip")))))
    return pairs.groupBy("qid").agg(F.count_if(F.col("ip") > 0).alias("above"), F.count_if(F.col("ip") < 0).alias("below"), F.count_if(F.col("ip") == 0).alias("on"))


# --- Arrow form: one matrix product a block, the same bits in the answer ---


def folded(X: np.ndarray, q: np.ndarray) -> np.ndarray:
    """Products as left folds in component order, the bits that expressions and SQL get."""
    return np.add.accumulate(X * q, axis=1)[:, -1]


def block_best(X: np.ndarray, ids: np.ndarray, q: np.ndarray, rough: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """The k least (margin, id) of a block: rough margins choose, with room for rounding, and folds decide."""
    if len(rough) > k:
        cut = np.partition(rough, k - 1)[k - 1]
        near = np.flatnonzero(rough <= cut + 1e-9 * (1 + abs(q).sum()))
    else:
        near = np.arange(len(rough))
    exact = np.abs(folded(X[near], q))
    order = np.lexsort((ids[near], exact))[:k]
    return ids[near][order], exact[order]


def batches_of(planes: DataFrame | list, most_bytes: int = BROADCAST_BYTES):
    """Planes as (qids, matrix) in batches of bounded size, split by a hash. A list of such batches is given back."""
    if isinstance(planes, list):
        yield from planes
        return
    size = planes.agg(F.count("*").alias("n"), F.max(F.size("q")).alias("d")).first()
    if not size.n:
        return
    parts = max(1, -(-size.n * size.d * 8 // most_bytes))
    for part in range(parts):
        rows = sorted((r.qid, r.q) for r in planes.filter(F.pmod(F.xxhash64("qid"), F.lit(parts)) == part).select("qid", "q").collect())
        if rows:
            yield np.array([r[0] for r in rows]), np.array([r[1] for r in rows], dtype=float)


def topk_arrow(points: DataFrame, planes: DataFrame, k: int = 10, block: int = 1024) -> DataFrame:
    """topk() by matrix products in Arrow batches, of blocks whose products stay in a core's cache; each task keeps k rows a plane."""
    found = None
    for qids, Q in batches_of(planes):
        shared = ship(points.sparkSession, (qids, Q))

        def run(batches, shared=shared):
            qids, Q = opened(shared)
            best: list[tuple[np.ndarray, np.ndarray]] = [(np.empty(0, dtype=np.int64), np.empty(0)) for _ in qids]
            worst, slack = np.full(len(qids), np.inf), 1e-9 * (1 + np.abs(Q).sum(axis=1))  # the k-th margin so far
            for batch in batches:
                for at in range(0, batch.num_rows, block):
                    part = batch.slice(at, block)
                    ids = np.asarray(part.column(0))
                    X = np.asarray(part.column(1).flatten()).reshape(len(ids), -1)
                    rough = np.abs(Q @ X.T)
                    near = ~(rough > (worst + slack)[:, None])
                    for n in np.flatnonzero(near.any(axis=1)):
                        some = np.flatnonzero(near[n])
                        new, margins = block_best(X[some], ids[some], Q[n], rough[n, some], k)
                        both, values = np.concatenate([best[n][0], new]), np.concatenate([best[n][1], margins])
                        order = np.lexsort((both, values))[:k]
                        best[n] = both[order], values[order]
                        if len(order) == k:
                            worst[n] = values[order[-1]]
            counts = [len(b[0]) for b in best]
            yield pa.RecordBatch.from_pydict({"qid": pa.array(np.repeat(qids, counts), pa.int64()), "id": pa.array(np.concatenate([b[0] for b in best]), pa.int64()), "margin": pa.array(np.concatenate([b[1] for b in best]), pa.float64())})

        part = points.select("id", "x").mapInArrow(run, "qid long, id long, margin double")
        found = part if found is None else found.unionByName(part)
    if found is None:
        return points.sparkSession.createDataFrame([], "qid long, rank long, id long, margin double")
    return ranked(found, k)


def axis_slab(points: DataFrame, planes: DataFrame, component: int, tau: float) -> DataFrame:
    """Pairs within tau of planes that fix one component at -offset, by a range join: bins of width tau are keys, so that each
    plane meets three bins of points and no others."""
    width = F.lit(float(tau))
    value = F.get("x", F.lit(component))
    binned = points.select("id", value.alias("v"), F.floor(value / width).alias("bin"))
    at = -F.element_at("q", -1)
    wanted = planes.select("qid", at.alias("at"), F.explode(F.sequence(F.floor(at / width) - 1, F.floor(at / width) + 1)).alias("bin"))
    return binned.join(small_side_of(wanted), "bin").select("qid", "id", F.abs(F.col("v") - F.col("at")).alias("margin")).filter(F.col("margin") <= tau)


def small_side_of(rows: DataFrame, most_rows: int = 1_000_000) -> DataFrame:
    """rows marked for broadcast if their counted number allows."""
    return F.broadcast(rows) if rows.count() <= most_rows else rows
