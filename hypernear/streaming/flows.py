"""Streams of points and of planes over the batch operators."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.streaming.stateful_processor import StatefulProcessor, StatefulProcessorHandle

from ..functions import exprs as E
from ..operators import search
from ..operators.brute import batches_of, small_side
from ..operators.build import distance2, grown, written
from ..operators.index import BOTH, Index
from ..sources.storage import fresh_path, opened, persisted, ship


def point_alerts(points: DataFrame, planes: DataFrame, tau: float, d: int | None = None) -> DataFrame:
    """Stateless: each arriving point (id, x) against static planes, with its side, where it lies within tau."""
    met = points.crossJoin(small_side(planes.select("qid", "q")))
    scored = met.select(*[c for c in points.columns if c != "x"], "qid", F.inline(F.array(F.struct(E.dot(F.col("x"), F.col("q"), d).alias("ip")))))
    return scored.filter(F.abs("ip") <= tau).withColumn("margin", F.abs("ip")).withColumn("side", F.signum("ip")).drop("ip")


def search_each(planes: DataFrame, index: Index, sink: Callable[[DataFrame, int], None], k: int = 10, checkpoint: str | None = None):
    """A query that searches every micro-batch of planes on a static index and hands the answers to sink."""

    def step(batch: DataFrame, number: int) -> None:
        sink(search.shard_dfs(index, persisted(batch.select("qid", "q").withColumn("q_norm", E.norm(F.col("q"))), "stream-planes"), k), number)

    writer = planes.writeStream.foreachBatch(step).trigger(availableNow=True)
    return (writer.option("checkpointLocation", checkpoint) if checkpoint else writer).start()


def nearest_shard(index: Index, rows: DataFrame) -> DataFrame:
    """rows (row, id, x) with the shard whose root's centre is nearest, by a look at batches of roots of bounded size."""
    roots = index.packed().filter("n > 0").select("shard", "center")
    best = None
    for shards, centers in batches_of(roots.select(F.col("shard").cast("long").alias("qid"), F.col("center").alias("q"))):
        shared = ship(index.nodes.sparkSession, (shards, centers))

        def run(batches, shared=shared):
            shards, centers = opened(shared)
            for batch in batches:
                X = np.asarray(batch.column(1).flatten()).reshape(batch.num_rows, -1)
                far = ((X[:, None, :] - centers[None]) ** 2).sum(axis=2) if len(shards) * X.size < 1 << 24 else np.stack([((X - c) ** 2).sum(axis=1) for c in centers], axis=1)
                at = far.argmin(axis=1)
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(shards[at].astype(np.int32)), pa.array(far[np.arange(len(X)), at])], names=["row", "shard", "far"])

        part = rows.select("row", "x").mapInArrow(run, "row long, shard int, far double")
        best = part if best is None else best.unionByName(part)
    chosen = best.groupBy("row").agg(F.min(F.struct("far", "shard")).alias("at")).select("row", F.col("at.shard").alias("shard"))
    return rows.join(chosen, "row")


def nearest_leaf(index: Index, rows: DataFrame) -> DataFrame:
    """(row, shard, leaf) of rows (row, x, shard): in each row's shard the leaf whose centre is nearest, by a look at batches of leaves of bounded size."""
    leaves = index.leaves().select((F.shiftleft(F.col("shard").cast("long"), 32) + F.col("leaf")).alias("qid"), F.col("center").alias("q"))
    best = None
    for numbers, centers in batches_of(leaves):
        shared = ship(index.nodes.sparkSession, (numbers >> 32, numbers & 0xFFFFFFFF, centers))

        def run(batches, shared=shared):
            shards, leaves, centers = opened(shared)
            for batch in batches:
                X, mine = np.asarray(batch.column(1).flatten()).reshape(batch.num_rows, -1), np.asarray(batch.column(2))
                for shard in np.intersect1d(mine, shards):
                    near, at = np.flatnonzero(shards == shard), np.flatnonzero(mine == shard)
                    for some in np.array_split(at, -(-len(at) * len(near) // (1 << 21))):
                        far = ((X[some] ** 2).sum(axis=1))[:, None] - 2 * X[some] @ centers[near].T + (centers[near] ** 2).sum(axis=1)[None, :]
                        first = far.argmin(axis=1)
                        yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(some)), pa.array(np.full(len(some), shard, dtype=np.int32)), pa.array(leaves[near[first]]), pa.array(far[np.arange(len(some)), first])], names=["row", "shard", "leaf", "far"])

        part = rows.select("row", "x", "shard").mapInArrow(run, "row long, shard int, leaf long, far double")
        best = part if best is None else best.unionByName(part)
    return best.groupBy("row").agg(F.min(F.struct("far", "shard", "leaf")).alias("at")).select("row", "at.shard", "at.leaf")


def append(index: Index, arrivals: DataFrame) -> Index:
    """A new version of the index with more points, without moving a centre.

    Arrivals go to the shard whose root's centre is nearest, and there to the leaf whose centre is; that centre stays as the leaf's anchor (and
    the weight that siblings are derived with stays too), counts grow, and radii grow to cover. Any anchor with a covering radius
    gives valid bounds, so searches stay exact; leaves over their size are split by compacted(). Repeated arrivals are points each.
    """
    rows = persisted(arrivals.select(F.monotonically_increasing_id().alias("row"), "id", "x"), "arrivals")
    if rows.isEmpty() or index.nodes.isEmpty():
        return index
    met = persisted(nearest_leaf(index, nearest_shard(index, rows)), "append-leaves")
    placed = rows.join(met, "row").join(index.leaves().select("shard", "leaf", "center", "center_norm"), ["shard", "leaf"])
    par = E.dot(F.col("x"), F.col("center")) / F.col("center_norm")
    noted = placed.withColumn("r_x", F.sqrt(distance2("x", "center"))).withColumn("x_par", par)
    noted = noted.withColumn("x_perp", E.norm(F.zip_with("x", "center", lambda a, c: a - F.col("x_par") / F.col("center_norm") * c)))
    more = persisted(noted.select("shard", "leaf", F.lit(None).cast("long").alias("pos"), "id", "r_x", "x_par", "x_perp", "x"), "appended")
    rows = index.points.unionByName(more)
    order = F.row_number().over(Window.partitionBy("shard", "leaf").orderBy(F.desc("r_x"), "id")) - 1
    points = persisted(rows.withColumn("pos", order.cast("long")), "index-points")
    nodes, reach = index.nodes, None
    ancestors = nodes.filter("is_leaf").select("shard", F.col("node").alias("leaf"), "node")  # numbers only: vectors are met once, below
    up = nodes.select("shard", "node", F.col("parent").alias("_parent"))
    for _ in range(200):
        reach = ancestors if reach is None else reach.unionByName(ancestors)
        ancestors = persisted(ancestors.join(up, ["shard", "node"]).filter("_parent is not null").select("shard", "leaf", F.col("_parent").alias("node")), "append-path")
        if ancestors.isEmpty():
            break
    centers = reach.join(nodes.select("shard", "node", "center"), ["shard", "node"])
    cover = more.select("shard", "leaf", "x").join(centers, ["shard", "leaf"]).groupBy("shard", "node").agg(F.max(F.sqrt(distance2("x", "center"))).alias("_far"), F.count("*").alias("_more"))
    wider = nodes.join(cover, ["shard", "node"], "left").withColumn("radius", F.greatest("radius", F.coalesce("_far", F.lit(0.0)))).withColumn("n", F.col("n") + F.coalesce("_more", F.lit(0))).drop("_far", "_more")
    return Index(persisted(wider.select(*nodes.columns), "index-nodes"), points, index.d, index.leaf_size)


def compacted(index: Index, most: float = 2.0, seed: int = 42) -> Index:
    """The index with the shards grown anew that hold a leaf of over ``most`` times the leaf size (and not of equal points alone).

    Other shards keep their rows. A shard that appends made large stays one shard, until the next build deals all points.
    """
    full = index.nodes.filter(F.col("is_leaf") & ~F.col("oversize") & (F.col("n") > most * index.leaf_size)).select("shard").distinct()
    full = persisted(full, "full-shards")
    if full.isEmpty():
        return index
    leaf_size = index.leaf_size

    def run(table: pa.Table) -> pa.Table:
        return grown(table, leaf_size, seed)

    anew = written(index.points.join(full, "shard", "left_semi").select("shard", "id", "x").groupBy("shard").applyInArrow(run, BOTH), index.d, leaf_size)
    kept = lambda rows: rows.join(full, "shard", "left_anti")
    return Index(kept(index.nodes).unionByName(anew.nodes), kept(index.points).unionByName(anew.points), index.d, leaf_size)


def windowed(events: DataFrame, length: str, slide: str | None = None, delay: str = "1 hour") -> DataFrame:
    """Count and least margin of events (ts, margin) in tumbling or sliding windows; rows later than the delay are dropped."""
    window = F.window("ts", length, slide) if slide else F.window("ts", length)
    return events.withWatermark("ts", delay).groupBy(window.alias("w")).agg(F.count("*").alias("n"), F.min("margin").alias("least")).select(F.col("w.start").alias("start"), "n", "least")


def sessions(events: DataFrame, gap: str, delay: str = "1 hour") -> DataFrame:
    per = events.withWatermark("ts", delay).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n"), F.min("margin").alias("least"))
    return per.select("user_id", F.col("w.start").alias("start"), "n", "least")


def matched(points: DataFrame, planes: DataFrame, within: str = "1 hour", delay: str = "1 hour") -> DataFrame:
    """Stream-stream: points (ts, key, x) with the planes (plane_ts, plane_key, q) of their key from at most ``within`` before."""
    left = points.withWatermark("ts", delay)
    right = planes.withWatermark("plane_ts", delay)
    close = (F.col("key") == F.col("plane_key")) & (F.col("plane_ts") <= F.col("ts")) & (F.col("plane_ts") >= F.col("ts") - F.expr(f"INTERVAL {within}"))
    return left.join(right, close).withColumn("margin", E.absdot(F.col("x"), F.col("q")))


class RunningTopK(StatefulProcessor):
    """Keeps the k least (margin, id) of each key and emits them again whenever they change."""

    def __init__(self, k: int):
        self.k = k

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.best = handle.getValueState("best", "margins array<double>, ids array<bigint>")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timers) -> Iterator[pd.DataFrame]:
        held = self.best.get() if self.best.exists() else ([], [])
        old = sorted(zip(held[0], held[1]))
        new = list(old)
        for part in rows:
            new += list(zip(part["margin"].tolist(), part["id"].tolist()))
        new = sorted(set(new))[: self.k]
        if new != old:
            self.best.update(([m for m, _ in new], [i for _, i in new]))
            yield pd.DataFrame({"qid": [key[0]] * len(new), "rank": range(1, len(new) + 1), "id": [i for _, i in new], "margin": [m for m, _ in new]})

    def close(self) -> None:
        pass


def running_topk(scored: DataFrame, k: int = 10) -> DataFrame:
    """Stateful: the k nearest so far of each plane, of a stream of (qid, id, margin)."""
    return scored.groupBy("qid").transformWithStateInPandas(RunningTopK(k), "qid long, rank long, id long, margin double", "Update", "None")


def drained(stream: DataFrame, spark: SparkSession, name: str, mode: str = "append", checkpoint: str | None = None) -> DataFrame:
    """Run a stream over what is there and return its rows: of all batches, or of the last one where each is complete. Batches are
    written as tables, each anew if it is run again, and none comes to the driver."""
    out = fresh_path(spark, name)

    def step(batch: DataFrame, number: int) -> None:
        batch.withColumn("batch", F.lit(number).cast("long")).write.mode("overwrite").parquet(f"{out}/{number}")

    writer = stream.writeStream.foreachBatch(step).outputMode(mode).trigger(availableNow=True).queryName(name)
    (writer.option("checkpointLocation", checkpoint) if checkpoint else writer).start().awaitTermination()
    folders = folders_of(spark, out)
    if not folders:
        return spark.createDataFrame([], stream.schema)
    rows = spark.read.schema(stream.schema).parquet(*([f"{out}/{max(folders)}"] if mode == "complete" else [f"{out}/{n}" for n in folders]))
    return rows


def folders_of(spark: SparkSession, path: str) -> list[int]:
    """The batches that were written below a path."""
    root = spark._jvm.org.apache.hadoop.fs.Path(path)
    fs = root.getFileSystem(spark._jsc.hadoopConfiguration())
    return sorted(int(s.getPath().getName()) for s in fs.listStatus(root)) if fs.exists(root) else []
