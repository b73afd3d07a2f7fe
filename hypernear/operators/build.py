"""Building an index: sampled router and shard-local trees, or level by level in the DataFrame API."""

from __future__ import annotations

import heapq
from collections.abc import Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions import exprs as E
from ..sources.storage import fresh_path, opened, persisted, ship
from .grow import Tree, grow_all, pivots, squared
from .index import BOTH, NODES, PARTS, TREES, Index, flat, names, tree_row, vectors_of



def dimension(points: DataFrame) -> int:
    first = points.select(F.size("x").alias("d")).first()
    return first.d if first else 0


def as_tables(tree: Tree, shard: int) -> pa.Table:
    """A tree's nodes, and the tree as one value, as rows of one tagged schema."""
    count = len(tree.node)
    optional = lambda values: pa.array([None if v < 0 else v for v in values], pa.int64())
    nulls = lambda size, kind: pa.nulls(size, kind)
    node_part = {
        "kind": pa.array(["node"] * count), "part": pa.array([shard % PARTS] * count, pa.int32()), "shard": pa.array([shard] * count, pa.int32()), "node": pa.array(range(count), pa.int64()), "parent": optional(tree.parent),
        "depth": pa.array(tree.depth, pa.int32()), "is_leaf": pa.array([tree.is_leaf(a) for a in range(count)]), "oversize": pa.array(tree.flat), "n": pa.array([tree.n(a) for a in range(count)], pa.int64()), "weight": pa.array(tree.weight, pa.int64()),
        "center": vectors_of(tree.centers), "center_norm": pa.array(tree.norms), "radius": pa.array(tree.radii), "left": optional(tree.left), "right": optional(tree.right), "lo": pa.array(tree.lo, pa.int64()), "hi": pa.array(tree.hi, pa.int64()),
        "tree": nulls(count, pa.binary()),
    }
    kinds = {k: v.type for k, v in node_part.items()}
    row = tree_row(shard, tree)
    tree_part = {k: nulls(1, kind) for k, kind in kinds.items()} | {"kind": pa.array(["tree"]), "part": pa.array([shard % PARTS], pa.int32())} | {c: row.column(c).combine_chunks() for c in row.column_names}
    return pa.concat_tables([pa.table(node_part), pa.table(tree_part)])


def router(sample: np.ndarray, ids: np.ndarray, shards: int, seed: int) -> list[tuple]:
    """A small tree over a sample: (pivot, other pivot, left, right), where a negative child is shard -1 - child.

    The largest part is split until there are enough.
    """
    steps: list[list] = []
    parts, whole = [(-len(ids), 0, np.arange(len(ids)), None)], []  # a heap, the largest first; and what can't be split
    while parts and len(parts) + len(whole) < shards:
        _, _, rows, place = heapq.heappop(parts)
        a, b, to_a = pivots(sample[rows], ids[rows], seed, len(steps) + 1) if len(rows) > 1 else (0, 0, np.zeros(1))
        if to_a[b] == 0:
            whole.append((rows, place))
            continue
        nearer = to_a <= squared(sample[rows], sample[rows[b]])
        if place:
            steps[place[0]][place[1]] = len(steps)
        steps.append([sample[rows[a]], sample[rows[b]], None, None])
        for side, some in ((2, rows[nearer]), (3, rows[~nearer])):
            heapq.heappush(parts, (-len(some), 2 * len(steps) + side, some, (len(steps) - 1, side)))
    for shard, (_, place) in enumerate([(rows, place) for _, _, rows, place in parts] + whole):
        if place:
            steps[place[0]][place[1]] = -1 - shard
    return [tuple(s) for s in steps]


def routed(X: np.ndarray, steps: tuple | None, cells: int = 1 << 18) -> np.ndarray:
    """The shard of each row: all rows of a block take a step at once, whatever the number of steps."""
    out = np.zeros(len(X), dtype=np.int64)
    if steps is None:
        return out
    first, second, children = steps
    block = max(1, cells // X.shape[1])
    for start in range(0, len(X), block):
        here, at = np.arange(start, min(start + block, len(X))), np.zeros(min(block, len(X) - start), dtype=np.int64)
        while len(here):
            some = X[here]
            at = children[at, np.where(squared(some, first[at]) <= squared(some, second[at]), 0, 1)]
            ended = at < 0
            out[here[ended]] = -1 - at[ended]
            here, at = here[~ended], at[~ended]
    return out


def held_by(points: DataFrame, steps: tuple | None, shards: int) -> np.ndarray:
    """The number of points that each shard would get, summed by task."""
    shared = ship(points.sparkSession, steps)

    def run(batches):
        steps, held = opened(shared), np.zeros(shards, dtype=np.int64)
        for batch in batches:
            held += np.bincount(routed(np.asarray(batch.column(0).flatten()).reshape(batch.num_rows, -1), steps), minlength=shards)
        some = np.flatnonzero(held)
        yield pa.RecordBatch.from_pydict({"shard": pa.array(some.astype(np.int32)), "n": pa.array(held[some])})

    counted = points.select("x").mapInArrow(run, "shard int, n long").groupBy("shard").agg(F.sum("n").alias("n")).toArrow()
    out = np.zeros(shards, dtype=np.int64)
    out[counted.column("shard").to_numpy()] = counted.column("n").to_numpy()
    return out


def route(points: DataFrame, steps: tuple | None, cuts: np.ndarray | None, buffer_bytes: int = 32 << 20, row_bytes: int = 2 << 20) -> DataFrame:
    """Rows (shard, ids, xs) of points dealt to shards. A task holds points up to ``buffer_bytes`` and gives those of one shard as one row, so that few rows are
    shuffled. cuts: how many shards each is cut into by a hash."""
    shared, most_cuts = ship(points.sparkSession, (steps, cuts)), 1 if cuts is None else int(cuts.max(initial=1))

    def rows(ids: np.ndarray, X: np.ndarray, shard: np.ndarray) -> pa.RecordBatch:
        order = np.argsort(shard, kind="stable")
        ids, X, shard = ids[order], X[order], shard[order]
        starts, most = np.flatnonzero(np.diff(shard, prepend=-1)), max(1, row_bytes // (8 * (X.shape[1] + 1)))
        spans = [(at, min(at + most, end)) for start, end in zip(starts, [*starts[1:], len(ids)]) for at in range(start, end, most)]
        return pa.RecordBatch.from_pydict({"shard": pa.array(shard[[a for a, _ in spans]].astype(np.int32)), "ids": pa.array([ids[a:b].tobytes() for a, b in spans], pa.binary()), "xs": pa.array([X[a:b].tobytes() for a, b in spans], pa.binary())})

    def run(batches):
        steps, cuts = opened(shared)
        held, size = [], 0
        for batch in batches:
            if not batch.num_rows:
                continue
            X = np.asarray(batch.column(1).flatten(), dtype=float).reshape(batch.num_rows, -1)
            shard = routed(X, steps)
            if most_cuts > 1:
                shard = shard * most_cuts + np.asarray(batch.column(2)) % cuts[shard]
            held.append((np.asarray(batch.column(0), dtype=np.int64), X, shard))
            size += 8 * X.size
            if size >= buffer_bytes:
                yield rows(*map(np.concatenate, zip(*held)))
                held, size = [], 0
        if held:
            yield rows(*map(np.concatenate, zip(*held)))

    columns = ["id", "x"] + [F.xxhash64("id", F.lit(7)).alias("spread")] * (most_cuts > 1)
    return points.select(*columns).mapInArrow(run, "shard int, ids binary, xs binary")


def hybrid(points: DataFrame, leaf_size: int = 100, seed: int = 42, shard_bytes: int = 8 << 20, shards: int = 1, sample_rows: int = 20_000, sample_bytes: int = 16 << 20, annotate: bool = True) -> Index:
    """Index of points (id, x): see hybrids()."""
    return hybrids(points, [leaf_size], seed, shard_bytes, shards, sample_rows, sample_bytes, annotate)[0]


def hybrids(points: DataFrame, leaf_sizes: Sequence[int], seed: int = 42, shard_bytes: int = 8 << 20, shards: int = 1, sample_rows: int = 20_000, sample_bytes: int = 16 << 20, annotate: bool = True) -> list[Index]:
    """Indexes of points (id, x), one a leaf size: a router from a bounded sample deals points into shards, and each shard grows its own tree, all sizes from
    one series of splits.

    Points move once. There are at least ``shards`` shards, and as many as it takes to hold a shard's rows to ``shard_bytes`` (ids, vectors and three
    numbers each), as a task holds a few copies of a shard. The sample has ``sample_rows`` rows (fewer, where these pass ``sample_bytes``) and eight a shard at
    least. A shard that the sample has made too large is cut further by a hash; any partition gives right answers, as every ball is computed from the points it holds.
    Rows are routed twice, to be counted and to be dealt, so that no copy of them is written; a task deals them in blocks, a row a shard and block.
    """
    d = dimension(points)
    points = points.select("id", "x")
    n = points.count()
    most = max(*leaf_sizes, shard_bytes // (8 * (d + 4)))
    shards = max(shards, -(-n // most))
    steps, cuts = None, None
    if shards > 1:
        sample_rows = max(8 * shards, min(sample_rows, sample_bytes // (8 * d)))
        drawn = points.filter(F.pmod(F.xxhash64("id", F.lit(seed)), F.lit(1_000_003)) < F.lit(min(1.0, sample_rows / n) * 1_000_003)).toArrow()
        ids, order = drawn.column("id").to_numpy(), np.argsort(drawn.column("id").to_numpy(), kind="stable")
        made = router(flat(drawn.column("x"), d)[order], ids[order], shards, seed) if len(ids) else []
        if made:
            steps = np.array([a for a, *_ in made]), np.array([b for _, b, *_ in made]), np.array([children for _, _, *children in made], dtype=np.int64)
        cuts = np.ceil(held_by(points, steps, shards) / (2.0 * most)).astype(np.int64)

    leaf_sizes = list(leaf_sizes)

    def run(table: pa.Table) -> pa.Table:
        ids, X = (np.concatenate([np.frombuffer(part.as_buffer(), kind) for part in table.column(c)]) for c, kind in (("ids", "<i8"), ("xs", "<f8")))
        return grown_of(table.column("shard")[0].as_py(), ids, X.reshape(len(ids), -1), leaf_sizes, seed, annotate)

    return written_all(route(points, steps, cuts).groupBy("shard").applyInArrow(run, f"{BOTH}, leaf_size int"), d, leaf_sizes)


def grown(table: pa.Table, leaf_size: int, seed: int, annotate: bool = True) -> pa.Table:
    """Rows BOTH of a shard's (id, x, shard)."""
    X = np.asarray(table.column("x").combine_chunks().flatten()).reshape(table.num_rows, -1)
    return grown_of(table.column("shard")[0].as_py(), table.column("id").to_numpy(), X, [leaf_size], seed, annotate).drop_columns("leaf_size")


def grown_of(shard: int, ids: np.ndarray, X: np.ndarray, leaf_sizes: list[int], seed: int, annotate: bool) -> pa.Table:
    """Rows (BOTH, leaf_size) of a shard's points, for each leaf size."""
    parts = []
    for leaf_size, tree in zip(leaf_sizes, grow_all(ids, X, leaf_sizes, seed, annotate)):
        part = as_tables(tree, shard)
        parts.append(part.append_column("leaf_size", pa.array(np.full(part.num_rows, leaf_size, dtype=np.int32))))
    return pa.concat_tables(parts)


def written(both: DataFrame, d: int, leaf_size: int) -> Index:
    """The index of tagged rows (BOTH)."""
    return written_all(both.withColumn("leaf_size", F.lit(leaf_size)), d, [leaf_size])[0]


def written_all(both: DataFrame, d: int, leaf_sizes: list[int]) -> list[Index]:
    """The indexes of tagged rows (BOTH, leaf_size), written in folders by leaf size, kind and part. Points are not written beside the trees before they are asked for."""
    spark = both.sparkSession
    path = fresh_path(spark, "index")
    both.write.partitionBy("leaf_size", "kind", "part").parquet(path)
    read, out = spark.read.schema(f"{BOTH}, leaf_size int").parquet(path), []
    for leaf_size in leaf_sizes:
        kind = lambda name, columns, leaf_size=leaf_size: read.filter((F.col("leaf_size") == leaf_size) & (F.col("kind") == name)).select(*columns)
        out.append(Index(kind("node", names(NODES)), None, d, leaf_size, kind("tree", [*names(TREES), "part"])))
    return out


def distance2(x, y):
    return F.aggregate(F.zip_with(x, y, lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda s, v: s + v)


def above(node):
    """Heap number of the parent, by bits: doubles would round numbers below the fifty-third level."""
    return F.shiftright(node, 1)


def deep(node):
    """Level of a heap number: 0 for the root, 1."""
    return F.length(F.bin(node)) - 1


def pick_pivots(placed: DataFrame, seed: int) -> DataFrame:
    """(node, a, b) of nodes: a random point's farthest point, and the farthest from that. Two more sweeps, each one aggregation."""
    start = placed.groupBy("node").agg(F.min_by("x", F.struct(F.xxhash64(F.lit(seed).cast("long"), "node", "id").alias("h"), "id")).alias("v"))
    first = placed.join(start, "node").groupBy("node").agg(F.max_by("x", F.struct(distance2("x", "v").alias("far"), -F.col("id"))).alias("a"))
    return placed.join(first, "node").groupBy("node", "a").agg(F.max_by("x", F.struct(distance2("x", "a").alias("far"), -F.col("id"))).alias("b"))


def exact_levels(points: DataFrame, leaf_size: int = 100, seed: int = 42, most_depth: int = 60) -> Index:
    """The same tree as one local shard, level by level with aggregations only: for data of any size, at a few jobs a level."""
    placed = persisted(points.select("id", "x").withColumn("node", F.lit(1).cast("long")), "levels")
    closed, inner = None, None
    for depth in range(most_depth + 1):
        count = placed.groupBy("node").agg(F.count("*").alias("n"))
        cuts = pick_pivots(placed.join(count.filter(F.col("n") > leaf_size).select("node"), "node", "left_semi"), seed)
        cuts = persisted(cuts.filter(distance2("a", "b") > 0) if depth < most_depth else cuts.limit(0), "levels-cuts")
        done = placed.join(cuts.select("node"), "node", "left_anti")
        closed = done if closed is None else closed.unionByName(done)
        if cuts.isEmpty():
            break
        inner = cuts if inner is None else inner.unionByName(cuts)
        left = distance2("x", "a") <= distance2("x", "b")
        placed = persisted(placed.join(cuts, "node").select("id", "x", (F.col("node") * 2 + F.when(left, 0).otherwise(1)).alias("node")), "levels")
    closed = persisted(closed, "levels-closed")
    leaves = centers(closed).join(closed.groupBy("node").agg(F.count("*").alias("n")), "node")
    nodes = persisted(roll_up_centers(persisted(leaves, "levels-leaves")), "levels-nodes")
    wide = persisted(nodes.join(radii(closed, nodes), "node"), "levels-radii")
    is_inner = wide.select(above(F.col("node")).alias("node")).distinct().withColumn("inner", F.lit(True))
    shaped = wide.join(is_inner, "node", "left").select(
        F.lit(0).alias("shard"), (F.col("node") - 1).alias("node"), F.when(F.col("node") > 1, above(F.col("node")) - 1).alias("parent"), deep(F.col("node")).alias("depth"),
        F.col("inner").isNull().alias("is_leaf"), (F.col("inner").isNull() & (F.col("n") > leaf_size)).alias("oversize"), "n", F.col("n").alias("weight"), "center", E.norm(F.col("center")).alias("center_norm"), "radius",
        F.when(F.col("inner"), F.col("node") * 2 - 1).alias("left"), F.when(F.col("inner"), F.col("node") * 2).alias("right"), F.lit(None).cast("long").alias("lo"), F.lit(None).cast("long").alias("hi"),
    )
    return Index(shaped, annotate_leaves(closed, shaped), dimension(points), leaf_size)


def centers(placed: DataFrame) -> DataFrame:
    """(node, center): means of the points of each node, by component."""
    long = placed.select("node", F.posexplode("x").alias("i", "v")).groupBy("node", "i").agg(F.avg("v").alias("v"))
    return long.groupBy("node").agg(F.transform(F.array_sort(F.collect_list(F.struct("i", "v"))), lambda s: s["v"]).alias("center"))


def roll_up_centers(leaves: DataFrame) -> DataFrame:
    """(node, n, center) of all nodes from those of the leaves, deepest first: a parent's centre is the mean of its children's, weighted by count."""
    leaves = leaves.select("node", "n", "center")
    deepest = leaves.agg(F.max(deep(F.col("node")))).first()[0] or 0
    known, above_it = leaves, None
    for depth in range(deepest, 0, -1):  # a level is made of the one below and its own leaves, so no plan holds another twice
        level = leaves.filter(deep(F.col("node")) == depth)
        level = level if above_it is None else level.unionByName(above_it)
        pairs = level.groupBy(above(F.col("node")).alias("node")).agg(F.sum("n").alias("n"), F.array_sort(F.collect_list(F.struct("node", "n", "center"))).alias("kids"))
        first, second = F.get("kids", F.lit(0)), F.get("kids", F.lit(1))
        mean = F.zip_with(first["center"], second["center"], lambda a, b: (first["n"] * a + second["n"] * b) / (first["n"] + second["n"]))
        above_it = persisted(pairs.select("node", "n", mean.alias("center")), "levels-rolled")
        known = known.unionByName(above_it)
    return known


def radii(placed: DataFrame, nodes: DataFrame) -> DataFrame:
    """(node, radius): the farthest point below each node, a level at a time: each point meets its one ancestor on a level, whose centres
    Spark broadcasts while they are small, and greatest distances are kept by task before they are shuffled."""
    deepest, out = nodes.agg(F.max(deep(F.col("node")))).first()[0] or 0, None
    for depth in range(deepest + 1):
        on = deep(F.col("node")) >= depth
        up = F.call_function("shiftright", F.col("node"), deep(F.col("node")) - F.lit(depth))
        level = nodes.filter(deep(F.col("node")) == depth).select("node", "center")
        met = placed.filter(on).select(up.alias("node"), "x").join(level, "node")
        far = met.groupBy("node").agg(F.sqrt(F.max(distance2("x", "center"))).alias("radius"))
        out = far if out is None else out.unionByName(far)
    return out


def annotate_leaves(closed: DataFrame, nodes: DataFrame) -> DataFrame:
    """Points with their leaf, their distance from its centre, and their parts along and across it."""
    leaf = nodes.filter("is_leaf").select(F.col("node").alias("leaf"), "center", "center_norm")
    joined = closed.select("id", "x", (F.col("node") - 1).alias("leaf")).join(leaf, "leaf")
    par = E.dot(F.col("x"), F.col("center")) / F.col("center_norm")
    with_par = joined.withColumn("r_x", F.sqrt(distance2("x", "center"))).withColumn("x_par", par)
    across = F.zip_with("x", "center", lambda a, c: a - F.col("x_par") / F.col("center_norm") * c)
    full = with_par.withColumn("x_perp", E.norm(across))
    order = F.row_number().over(W.partitionBy("leaf").orderBy(F.desc("r_x"), "id")) - 1
    return full.select(F.lit(0).alias("shard"), "leaf", order.cast("long").alias("pos"), "id", "r_x", "x_par", "x_perp", "x")


