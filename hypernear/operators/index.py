"""An index: trees of all shards as two tables, and how to write, read and check it."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.storage import fresh_path, persisted
from .grow import Tree, from_bytes, to_bytes

NODES = "shard int, node long, parent long, depth int, is_leaf boolean, oversize boolean, n long, weight long, center array<double>, center_norm double, radius double, left long, right long, lo long, hi long"
POINTS = "shard int, leaf long, pos long, id long, r_x double, x_par double, x_perp double, x array<double>"
TREES = "shard int, n long, center array<double>, center_norm double, radius double, tree binary"
BOTH = f"kind string, part int, {NODES}, tree binary"
PARTS = 1024  # folders that the packed trees are dealt to, so that shards which no plane can reach are not read


def names(schema: str) -> list[str]:
    return [part.split()[0] for part in schema.split(", ")]


@dataclass
class Index:
    """nodes: one row a node, numbered within its shard (0 is the shard's root). points: one row a point, in leaves by falling distance
    from the leaf's centre. The numbers r_x, x_par, x_perp can be read without the vectors. trees: one row a shard, its whole tree as one value,
    so that a walk needs no shuffle. A builder gives points (``placed``) or trees; the others are made from them when they are first asked for."""

    nodes: DataFrame
    placed: DataFrame | None
    d: int
    leaf_size: int
    trees: DataFrame | None = None
    known: dict = field(default_factory=dict)  # what was counted or fetched once

    @property
    def points(self) -> DataFrame:
        if self.placed is None:
            self.placed = persisted(self.trees.select("shard", "tree").mapInArrow(unpacked, POINTS), "index-points")
        return self.placed

    def roots(self, most_bytes: int = 8 << 20) -> dict[str, np.ndarray] | None:
        """shard, part, center, center_norm and radius of all shards with points, if a count says that they are few enough for the driver."""
        if "roots" not in self.known:
            some = self.packed().filter("n > 0")
            most = most_bytes // (8 * (self.d + 5))
            table = some.select("shard", "part", "center", "center_norm", "radius").limit(most + 1).toArrow()
            table = table if table.num_rows <= most else None
            self.known["roots"] = table and {c: flat(table.column(c), self.d) if c == "center" else table.column(c).to_numpy() for c in table.column_names}
        return self.known["roots"]

    def packed(self) -> DataFrame:
        """Rows (TREES, part), in folders by part."""
        if self.trees is None:
            d = self.d

            def run(nodes: pa.Table, points: pa.Table) -> pa.Table:
                return tree_row(nodes.column("shard")[0].as_py() if nodes.num_rows else 0, tree_of(nodes, points, d))

            made = self.nodes.groupBy("shard").cogroup(self.points.groupBy("shard")).applyInArrow(run, TREES)
            spark = self.nodes.sparkSession
            path = fresh_path(spark, "index-trees")
            made.withColumn("part", F.pmod("shard", F.lit(PARTS)).cast("int")).write.partitionBy("part").parquet(path)
            self.trees = spark.read.schema(f"{TREES}, part int").parquet(path)
        return self.trees

    def shards(self) -> DataFrame:
        """Size, centre and radius of each shard."""
        return self.nodes.filter("node = 0").select("shard", "n", "center", "center_norm", "radius")

    def leaves(self) -> DataFrame:
        return self.nodes.filter("is_leaf").select("shard", F.col("node").alias("leaf"), "n", "center", "center_norm", "radius")

    def wide(self) -> DataFrame:
        """Inner nodes with what a step down needs: the smaller child's centre, and numbers of both children."""
        inner = self.nodes.filter("not is_leaf").select("shard", "node", F.col("weight").alias("n"), "left", "right")
        child = self.nodes.select("shard", F.col("node").alias("child"), F.struct("node", F.col("weight").alias("n"), "center", "center_norm", "radius", "is_leaf").alias("c"))
        with_left = inner.join(child.select("shard", F.col("child").alias("left"), F.col("c").alias("l")), ["shard", "left"])
        both = with_left.join(child.select("shard", F.col("child").alias("right"), F.col("c").alias("r")), ["shard", "right"])
        first = F.col("l.n") <= F.col("r.n")
        return both.select("shard", "node", "n", F.when(first, F.col("l")).otherwise(F.col("r")).alias("small"), F.when(first, F.col("r")).otherwise(F.col("l")).alias("big"))

    def save(self, path: str) -> None:
        self.nodes.write.mode("overwrite").parquet(f"{path}/nodes")
        bucketed = self.points.withColumn("shard_bucket", F.col("shard") % 256)
        bucketed.sortWithinPartitions("shard", "leaf", F.desc("r_x"), "id").write.mode("overwrite").partitionBy("shard_bucket").parquet(f"{path}/points")
        self.nodes.sparkSession.createDataFrame([(self.d, self.leaf_size)], "d int, leaf_size int").coalesce(1).write.mode("overwrite").json(f"{path}/meta")


def dense(column: pa.ChunkedArray) -> np.ndarray:
    """A column of longs with -1 for null."""
    return column.combine_chunks().fill_null(-1).to_numpy(zero_copy_only=False)


def flat(column: pa.ChunkedArray, d: int) -> np.ndarray:
    """A column of vectors as a matrix."""
    return column.combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(-1, d)


def tree_of(nodes: pa.Table, points: pa.Table, d: int) -> Tree:
    """A shard's tree from its rows."""
    nodes = nodes.sort_by("node")
    names, tree = dense(nodes.column("node")), Tree(d)
    place = lambda column: np.where(dense(column) < 0, -1, np.searchsorted(names, dense(column)))
    tree.parent, tree.left, tree.right = (place(nodes.column(c)) for c in ("parent", "left", "right"))
    tree.centers, tree.norms, tree.radii = flat(nodes.column("center"), d), nodes.column("center_norm").to_numpy(), nodes.column("radius").to_numpy()
    tree.weight = dense(nodes.column("weight"))
    leaf = place(points.column("leaf"))
    order = np.lexsort((dense(points.column("pos")), leaf))
    tree.ids, tree.X = points.column("id").to_numpy()[order], flat(points.column("x"), d)[order]
    tree.r_x, tree.x_par, tree.x_perp = (points.column(c).to_numpy()[order] for c in ("r_x", "x_par", "x_perp"))
    lo, hi = (np.searchsorted(leaf[order], np.arange(len(names)), side=side) for side in ("left", "right"))
    inner = tree.left >= 0  # inner nodes keep their counts; only leaves' ranges are read
    tree.lo, tree.hi = np.where(inner, 0, lo), np.where(inner, dense(nodes.column("n")), hi)
    return tree


def tree_row(shard: int, tree: Tree) -> pa.Table:
    """A tree as a row of TREES."""
    center = [tree.centers[0].tolist()] if len(tree.centers) else [[]]
    return pa.table({
        "shard": pa.array([shard], pa.int32()), "n": pa.array([len(tree.ids)], pa.int64()), "center": pa.array(center, pa.list_(pa.float64())),
        "center_norm": pa.array(tree.norms[:1]), "radius": pa.array(tree.radii[:1]), "tree": pa.array([to_bytes(tree)], pa.binary()),
    })


def vectors_of(X: np.ndarray) -> pa.ListArray:
    """A matrix as a column of vectors."""
    return pa.ListArray.from_arrays(pa.array(np.arange(len(X) + 1, dtype=np.int32) * X.shape[1]), pa.array(np.ascontiguousarray(X).ravel()))


def unpacked(batches, rows: int = 8192):
    """Rows POINTS of packed trees (shard, tree)."""
    for batch in batches:
        for row in range(batch.num_rows):
            shard, tree = batch.column(0)[row].as_py(), from_bytes(batch.column(1)[row].as_buffer())
            leaf = np.zeros(len(tree.ids), dtype=np.int64)
            for at in range(len(tree.left)):
                if tree.is_leaf(at):
                    leaf[tree.lo[at] : tree.hi[at]] = at
            for at in range(0, len(leaf), rows):
                some = slice(at, min(at + rows, len(leaf)))
                columns = [np.full(some.stop - at, shard, dtype=np.int32), leaf[some], np.arange(at, some.stop), tree.ids[some], tree.r_x[some], tree.x_par[some], tree.x_perp[some]]
                yield pa.RecordBatch.from_arrays([*map(pa.array, columns), vectors_of(tree.X[some])], names=names(POINTS))


def load(spark: SparkSession, path: str) -> Index:
    meta = spark.read.schema("d int, leaf_size int").json(f"{path}/meta").first()
    return Index(spark.read.parquet(f"{path}/nodes"), spark.read.parquet(f"{path}/points").drop("shard_bucket"), meta.d, meta.leaf_size)


def check_partition(index: Index) -> DataFrame:
    """Violations of the tree's invariants as (rule, n); all are 0 for a sound index."""
    children = index.nodes.filter("parent is not null").groupBy("shard", F.col("parent").alias("node")).agg(F.sum("n").alias("kids"), F.count("*").alias("two"))
    inner = index.nodes.filter("not is_leaf").join(children, ["shard", "node"], "left")
    counts = inner.filter("kids is null or kids <> n or two <> 2").agg(F.count("*").alias("n")).select(F.lit("children add up").alias("rule"), "n")
    placed = index.points.groupBy("shard", "leaf").agg(F.count("*").alias("held"))
    leaves = index.leaves().join(placed, ["shard", "leaf"], "full").filter("held is null or n is null or held <> n").agg(F.count("*").alias("n")).select(F.lit("points in leaves").alias("rule"), "n")
    again = index.points.groupBy("id").count().filter("count > 1").agg(F.count("*").alias("n")).select(F.lit("each point once").alias("rule"), "n")
    large = index.nodes.filter(f"is_leaf and not oversize and n > {index.leaf_size}").agg(F.count("*").alias("n")).select(F.lit("leaf size").alias("rule"), "n")
    gap = F.sqrt(F.aggregate(F.zip_with("x", "center", lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda s, v: s + v))
    near = index.points.join(index.leaves(), ["shard", "leaf"]).withColumn("gap", gap)
    radius = near.filter((F.col("gap") > F.col("radius") * (1 + 1e-9) + 1e-9) | (F.abs(F.col("gap") - F.col("r_x")) > 1e-7)).agg(F.count("*").alias("n")).select(F.lit("points in balls").alias("rule"), "n")
    tight = near.groupBy("shard", "leaf").agg(F.max("gap").alias("most"), F.max("radius").alias("radius")).filter("abs(most - radius) > 1e-7").agg(F.count("*").alias("n")).select(F.lit("radius is reached").alias("rule"), "n")
    return counts.unionByName(leaves).unionByName(again).unionByName(large).unionByName(radius).unionByName(tight)


def sizes(index: Index) -> DataFrame:
    """Bytes of the index beside the data: eight a number of nodes, and three numbers a point."""
    nodes = index.nodes.agg(F.count("*").alias("nodes"), F.sum((F.size("center") + 8) * 8).alias("bytes"))
    points = index.points.agg((F.count("*") * 24).alias("annotations"))
    return nodes.crossJoin(points).select("nodes", F.col("bytes").alias("plain_bytes"), (F.col("bytes") + F.col("annotations")).alias("annotated_bytes"))
