"""Searching an index: depth-first in each shard, or in rounds of joins; the answers are those of the exhaustive scan."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import exprs as E
from ..sources.storage import opened, persisted, ship
from .brute import batches_of, ranked, small_side
from .grow import COUNTERS, Met, Options, from_bytes, walks
from .index import TREES, Index, names

FOUND = "qid long, shard int, id long, margin double, " + ", ".join(f"{c} long" for c in COUNTERS)


def directory(index: Index, planes: DataFrame) -> DataFrame:
    """Every plane against every leaf: product, bound and the counts for ranking. Inner nodes may be skipped, as each leaf has its own ball."""
    pairs = index.leaves().crossJoin(small_side(planes.select("qid", "q", "q_norm")))
    with_ip = pairs.select("qid", "q_norm", "shard", "leaf", "n", "center_norm", "radius", F.inline(F.array(F.struct(E.dot(F.col("center"), F.col("q"), index.d).alias("ip")))))
    return with_ip.withColumn("bound", E.node_bound(F.col("ip"), F.col("q_norm"), F.col("radius")))


def leaf_order(preference: str = "center") -> list:
    """Which leaves come first: those whose centre is nearest, or those whose bound is least."""
    by_center = F.abs("ip")
    return ([by_center] if preference == "center" else [F.col("bound"), by_center]) + [F.col("shard"), F.col("leaf")]


def leaf_scan(index: Index, leaves: DataFrame, planes: DataFrame) -> DataFrame:
    """(qid, id, margin) of all points of the given (qid, shard, leaf)."""
    met = index.points.select("shard", "leaf", "id", "x").join(leaves.select("qid", "shard", "leaf"), ["shard", "leaf"])
    with_q = met.join(small_side(planes.select("qid", "q")), "qid")
    return with_q.select("qid", "id", F.inline(F.array(F.struct(E.absdot(F.col("x"), F.col("q"), index.d).alias("margin")))))


def thresholds(index: Index, planes: DataFrame, k: int, seeds: int = 3, preference: str = "center") -> DataFrame:
    """(qid, lam): an upper bound of the k-th margin, from a walk down each plane's most promising shard that ends after about ``seeds``
    leaves. Planes that meet fewer than k points there have none."""
    options, found = Options(k, preference=preference), None
    for qids, Q in batches_of(planes):
        first = likeliest(index, qids, Q)
        part = walked(index, qids, Q, options, only=first, quota=seeds * index.leaf_size)
        found = part if found is None else found.unionByName(part)
    if found is None:
        return planes.select("qid", F.lit(0.0).alias("lam")).limit(0)
    return ranked(found.filter("id is not null"), k).filter(F.col("rank") == k).select("qid", F.col("margin").alias("lam"))


def likeliest(index: Index, qids: np.ndarray, Q: np.ndarray) -> dict[int, int]:
    """The shard of each plane whose root's centre is nearest to it; found where the roots are, if they are many: one number a plane and task comes back."""
    roots = index.roots()
    if roots is not None:
        order = np.argsort(roots["shard"])
        return dict(zip(qids.tolist(), roots["shard"][order][np.abs(roots["center"][order] @ Q.T).argmin(axis=0)].tolist())) if len(order) else {}
    shared = ship(index.nodes.sparkSession, (qids, Q))

    def run(batches):
        qids, Q = opened(shared)
        for batch in batches:
            if batch.num_rows:
                near = np.abs(np.asarray(batch.column(1).flatten()).reshape(batch.num_rows, -1) @ Q.T)
                at = near.argmin(axis=0)
                yield pa.RecordBatch.from_arrays([pa.array(qids), pa.array(np.asarray(batch.column(0))[at]), pa.array(near[at, np.arange(len(qids))])], names=["qid", "shard", "near"])

    best = index.packed().select("shard", "center").mapInArrow(run, "qid long, shard int, near double").groupBy("qid").agg(F.min(F.struct("near", "shard")).alias("best"))
    return {r.qid: r.best.shard for r in best.collect()}


def reachable_parts(index: Index, Q: np.ndarray, lengths: np.ndarray, lams: np.ndarray) -> list[int] | None:
    """Folders with a shard that some plane's threshold can reach (at most PARTS numbers), or None for all, where no plane has a threshold."""
    if not np.isfinite(lams).all():
        return None
    roots = index.roots()
    if roots is not None:
        return np.unique(roots["part"][reached(Q, lengths, lams, roots["center"], roots["center_norm"], roots["radius"]).any(axis=0)]).tolist()
    shared = ship(index.nodes.sparkSession, (Q, lengths, lams))

    def run(batches):
        Q, lengths, lams = opened(shared)
        for batch in batches:
            if batch.num_rows:
                centers, norms, radii = np.asarray(batch.column(1).flatten()).reshape(batch.num_rows, -1), np.asarray(batch.column(2)), np.asarray(batch.column(3))
                yield pa.RecordBatch.from_arrays([pa.array(np.unique(np.asarray(batch.column(0))[reached(Q, lengths, lams, centers, norms, radii).any(axis=0)]))], names=["part"])

    some = index.packed().filter("n > 0").select("part", "center", "center_norm", "radius").mapInArrow(run, "part int")
    return sorted(r.part for r in some.distinct().collect())


def reached(Q: np.ndarray, lengths: np.ndarray, lams: np.ndarray, centers: np.ndarray, norms: np.ndarray, radii: np.ndarray) -> np.ndarray:
    """Planes by roots: whether the root's ball comes within the plane's threshold, with the walk's room for rounding."""
    least = np.maximum(np.abs(Q @ centers.T) - lengths[:, None] * radii[None, :], 0.0) - 1e-9 * lengths[:, None] * np.maximum(1.0, norms)[None, :]
    return least <= lams[:, None]


def walked(index: Index, qids: np.ndarray, Q: np.ndarray, options: Options | list[Options], lams: np.ndarray | None = None, only: dict[int, int] | None = None, but: dict[int, int] | None = None, budget: float | dict[int, float] | None = None, quota: int | None = None) -> DataFrame:
    """Rows FOUND of a batch of planes over the packed trees, in place: no row is shuffled. A plane walks its shard in ``only``, or all
    shards but its one in ``but``. Shards that no threshold reaches are not unpacked, and folders of such shards are not read; their
    roots' products are counted all the same. Equal planes with budgets of their own are walked once. Where shards are fewer than cores, planes are
    dealt to several tasks, each of which reads the trees. A list of options gives rows (variant, FOUND), by place in the list: each tree is read once for all,
    and walks without a clock share a plane's products."""
    lengths = np.linalg.norm(Q, axis=1)
    lams = np.full(len(qids), np.inf) if lams is None else lams
    alike: dict[tuple, list[int]] = {}
    for at in range(len(qids)):
        alike.setdefault((Q[at].tobytes(), lams[at]) if isinstance(budget, dict) else at, []).append(at)
    groups = list(alike.values())
    roots, cores = index.roots(), index.nodes.sparkSession.sparkContext.defaultParallelism
    slices = 1 if roots is None else max(1, min(-(-2 * cores // max(len(roots["shard"]), 1)), len(groups) // 4))
    several = isinstance(options, list)
    variants = options if several else [options]
    shared = ship(index.nodes.sparkSession, (qids, Q, lengths, lams, variants, only, but, budget, quota, [groups[n::slices] for n in range(slices)]))

    def run(batches, slice):
        qids, Q, lengths, lams, variants, only, but, budget, quota, groups = opened(shared)
        groups, here = groups[slice], np.zeros(len(qids), dtype=bool)
        here[[at for group in groups for at in group]] = True
        at_root = tuple(int(c in ("nodes_visited", "center_products")) for c in COUNTERS)
        together = sum(not options.clock for options in variants) > 1
        for batch in batches:
            for row in range(batch.num_rows):
                shard, n = batch.column(0)[row].as_py(), batch.column(1)[row].as_py()
                if not n:
                    continue
                mine = here & np.array([(only is None or only[q] == shard) and (but is None or but[q] != shard) for q in qids.tolist()])
                center, norm, radius = np.asarray(batch.column(2)[row].values)[None, :], np.asarray(batch.column(3))[row : row + 1], np.asarray(batch.column(4))[row : row + 1]
                near = mine & reached(Q, lengths, lams, center, norm, radius)[:, 0]
                rows = Rows(shard)
                for variant in range(len(variants)):
                    for q in qids[mine & ~near].tolist():
                        rows.add(variant, q, [], at_root)
                if near.any():
                    tree = from_bytes(batch.column(5)[row].as_buffer())
                    for group in groups:
                        group = [at for at in group if near[at]]
                        if not group:
                            continue
                        shares = [budget[int(qids[at])] if isinstance(budget, dict) else budget for at in group]
                        quotas = [quota if share is None else int(np.ceil(share * n)) for share in shares]
                        q, length, lam = Q[group[0]], float(lengths[group[0]]), float(lams[group[0]])
                        met = Met(tree, q, length) if together else None
                        for variant, options in enumerate(variants):
                            for at, (best, done) in zip(group, walks(tree, q, length, options, lam, quotas, None if options.clock else met)):
                                rows.add(variant, int(qids[at]), best, tuple(done.values()))
                        if len(rows.ids) > 1 << 16:
                            yield rows.batch(several)
                            rows = Rows(shard)
                yield rows.batch(several)

    parts = reachable_parts(index, Q, lengths, lams) if but is not None else None
    if parts is not None and roots is not None and len(parts) == len(np.unique(roots["part"])):
        parts = None  # all are read
    trees = index.packed() if parts is None else index.packed().filter(F.col("part").isin(parts))
    found = None
    for n in range(slices):
        part = trees.select(*names(TREES)).mapInArrow(lambda batches, n=n: run(batches, n), f"variant int, {FOUND}" if several else FOUND)
        found = part if found is None else found.unionByName(part)
    if parts is None:
        return found
    zero = [F.lit(int(c in ("nodes_visited", "center_products"))).cast("long").alias(c) for c in COUNTERS]
    skipped = index.packed().filter((F.col("n") > 0) & ~F.col("part").isin(parts)).select("shard")
    planes = index.nodes.sparkSession.createDataFrame([(int(q),) for q in qids], "qid long")
    if several:
        planes = planes.withColumn("variant", F.explode(F.sequence(F.lit(0), F.lit(len(variants) - 1))))
    unread = skipped.crossJoin(F.broadcast(planes)).select(*["variant"] * several, "qid", "shard", F.lit(None).cast("long").alias("id"), F.lit(None).cast("double").alias("margin"), *zero)
    return found.unionByName(unread)


class Rows:
    """Rows FOUND of one shard, with their variant: an answer's first row has its cost."""

    def __init__(self, shard: int):
        self.shard, self.heads, self.counts, self.costs, self.ids, self.margins = shard, [], [], [], [], []

    def add(self, variant: int, qid: int, best: list[tuple[float, int]], cost: tuple) -> None:
        self.heads.append((variant, qid))
        self.counts.append(max(len(best), 1))
        self.costs.append(cost)
        self.margins += [m for m, _ in best] or [None]
        self.ids += [i for _, i in best] or [None]

    def batch(self, several: bool) -> pa.RecordBatch:
        counts = np.array(self.counts, dtype=np.int64)
        variants, qids = (np.repeat(np.array([h[i] for h in self.heads], dtype=np.int64), counts) for i in (0, 1))
        costs = np.zeros((len(COUNTERS), len(self.ids)), dtype=np.int64)
        if len(counts):
            costs[:, np.cumsum(counts) - counts] = np.array(self.costs, dtype=np.int64).T
        shards = pa.array(np.full(len(self.ids), self.shard, dtype=np.int32))
        columns = [pa.array(variants.astype(np.int32))] * several + [pa.array(qids), shards, pa.array(self.ids, pa.int64()), pa.array(self.margins, pa.float64()), *map(pa.array, costs)]
        return pa.RecordBatch.from_arrays(columns, names=["variant"] * several + ["qid", "shard", "id", "margin", *COUNTERS])


def kept_with_thresholds(found: DataFrame, qids: np.ndarray, k: int, most_rows: int = 100_000) -> tuple[DataFrame, np.ndarray]:
    """Rows of a first round, computed once, and each plane's k-th margin: rows of few planes (k a plane) come through the driver, others are written."""
    spark = found.sparkSession
    if len(qids) * k <= most_rows:
        table = found.toArrow()
        rows = table.filter(pc.is_valid(table.column("id"))).select(["qid", "margin"])
        worst = rows.group_by("qid").aggregate([("margin", "max"), ("margin", "count")])
        lam = {q: m for q, m, n in zip(*(worst.column(c).to_pylist() for c in ("qid", "margin_max", "margin_count"))) if n >= k}
        kept = spark.createDataFrame(table, FOUND) if table.num_rows else spark.createDataFrame([], FOUND)
    else:
        kept = persisted(found, "first-shards")
        worst = kept.filter("id is not null").groupBy("qid").agg(F.max("margin").alias("lam"), F.count("*").alias("n"))
        lam = {r.qid: r.lam for r in worst.filter(F.col("n") >= k).collect()}
    return kept, np.array([lam.get(q, np.inf) for q in qids.tolist()])


def shard_dfs(index: Index, planes: DataFrame, k: int = 10, ball: bool = True, cone: bool = True, derive_sibling: bool = True, preference: str = "center", budget: float | dict[int, float] | None = None, eps: float = 0.0, seeds: int = 3, with_counters: bool = False, rederive: int = 8, clock: bool = False) -> DataFrame:
    """Walk every shard's tree for every plane that can reach it.

    An exact search of several shards (with ``seeds``) has two rounds, as running tasks can't tell one another their thresholds: each
    plane walks its most promising shard first, and then, with the k-th margin from there, all others that its threshold reaches. Every walk
    is kept and counted. A batch of planes reads each shard once a round; the merge ranks at most k rows a shard and plane.
    A budget (a share of the points, or one for each qid) is dealt to the shards by size. The plain tree is ball = cone = derive_sibling = False.
    """
    options, found = Options(k, ball, cone, derive_sibling, preference, eps, rederive, clock), None
    roots = index.roots()
    rounds = budget is None and seeds and (roots is None or len(roots["shard"]) > 1)
    for qids, Q in batches_of(planes):
        if rounds:
            first = likeliest(index, qids, Q)
            part, lams = kept_with_thresholds(walked(index, qids, Q, options, only=first), qids, k)
            part = part.unionByName(walked(index, qids, Q, options, lams, but=first))
        else:
            part = walked(index, qids, Q, options, budget=budget)
        found = part if found is None else found.unionByName(part)
    if found is None:
        found = index.nodes.sparkSession.createDataFrame([], FOUND)
    return found if with_counters else ranked(found.filter("id is not null"), k)


def shard_walks(index: Index, planes, options: list[Options], budget: dict[int, float]) -> DataFrame:
    """Rows (variant, FOUND) of budgeted walks with each of several options, in one pass over the trees; see shard_dfs()."""
    found = None
    for qids, Q in batches_of(planes):
        part = walked(index, qids, Q, options, budget=budget)
        found = part if found is None else found.unionByName(part)
    return index.nodes.sparkSession.createDataFrame([], f"variant int, {FOUND}") if found is None else found


def counters(found: DataFrame) -> DataFrame:
    """What each plane cost over all shards, from shard_dfs(.., with_counters=True)."""
    return found.groupBy("qid").agg(*[F.sum(c).alias(c) for c in COUNTERS], F.count_distinct("shard").alias("shards_touched"))


# --- rounds of joins ---


def expand(index_wide: DataFrame, frontier: DataFrame, planes: DataFrame, d: int, derive: bool) -> DataFrame:
    """Both children of each frontier row (qid, shard, node, ip), with their products: the smaller one's by a dot product, the
    other's from parent and sibling (or by its own)."""
    met = frontier.join(index_wide, ["shard", "node"]).join(small_side(planes.select("qid", "q", "q_norm")), "qid")
    first = met.select("qid", "shard", "n", "ip", "q", "q_norm", "small", "big", F.inline(F.array(F.struct(E.dot(F.col("small.center"), F.col("q"), d).alias("ip_small")))))
    other = E.sibling_ip(F.col("ip"), F.col("ip_small"), F.col("n"), F.col("small.n")) if derive else E.dot(F.col("big.center"), F.col("q"), d)
    child = lambda side, ip: F.struct(F.col(f"{side}.node").alias("node"), F.col(f"{side}.n").alias("count"), F.col(f"{side}.is_leaf").alias("is_leaf"), F.col(f"{side}.radius").alias("radius"), F.col(f"{side}.center_norm").alias("center_norm"), ip.alias("ip"))
    return first.select("qid", "shard", "q_norm", F.inline(F.array(child("small", F.col("ip_small")), child("big", other))))


def reachable(rows: DataFrame, lam: DataFrame) -> DataFrame:
    """Rows whose ball may hold a point within the plane's threshold."""
    joined = rows.join(small_threshold(lam), "qid", "left")
    bound = E.node_bound(F.col("ip"), F.col("q_norm"), F.col("radius")) - E.prune_slack(F.col("q_norm"), F.col("center_norm"))
    return joined.filter(F.col("lam").isNull() | (bound <= F.col("lam"))).drop("lam")


def small_threshold(lam: DataFrame) -> DataFrame:
    return lam.select("qid", "lam")


def surviving_leaves(index: Index, planes: DataFrame, lam: DataFrame, derive: bool = True, most_rounds: int = 200) -> DataFrame:
    """(qid, shard, leaf, ip, center_norm, q_norm) of all leaves that no bound on the way down rules out, a level a round."""
    wide = persisted(index.wide(), "frontier-wide")
    roots = index.nodes.filter("node = 0").select("shard", "node", "n", "center", "center_norm", "radius", "is_leaf")
    start = roots.crossJoin(small_side(planes.select("qid", "q", "q_norm"))).select("qid", "shard", "q_norm", "node", F.col("n").alias("count"), "is_leaf", "radius", "center_norm", E.dot(F.col("center"), F.col("q"), index.d).alias("ip"))
    level, leaves = persisted(reachable(start, lam), "frontier"), None
    for _ in range(most_rounds):
        ended = level.filter("is_leaf").select("qid", "shard", F.col("node").alias("leaf"), "ip", "center_norm", "q_norm")
        leaves = ended if leaves is None else leaves.unionByName(ended)
        open_rows = level.filter("not is_leaf")
        if open_rows.isEmpty():
            break
        level = persisted(reachable(expand(wide, open_rows.select("qid", "shard", "node", "ip"), planes, index.d, derive), lam), "frontier")
    return leaves


def theta_leaves(index: Index, planes: DataFrame, lam: DataFrame) -> DataFrame:
    """The same leaves and perhaps more, by one join of planes with the leaf directory."""
    return reachable(directory(index, planes), lam).select("qid", "shard", "leaf", "ip", "center_norm", "q_norm")


def scan_with_bounds(index: Index, leaves: DataFrame, lam: DataFrame, ball: bool = True, cone: bool = True) -> DataFrame:
    """(qid, shard, leaf, id) that the point bounds let through, from the three numbers alone: x is not read."""
    met = index.points.select("shard", "leaf", "id", "r_x", "x_par", "x_perp").join(leaves, ["shard", "leaf"]).join(small_threshold(lam), "qid", "left")
    slack = E.prune_slack(F.col("q_norm"), F.col("center_norm"))
    limit = F.coalesce("lam", F.lit(float("inf"))) + slack
    if ball:
        met = met.filter(E.point_ball_bound(F.col("ip"), F.col("q_norm"), F.col("r_x")) <= limit)
    if cone:
        bound = E.point_cone_bound(F.col("ip"), F.col("center_norm"), F.col("q_norm"), F.col("x_par"), F.col("x_perp")) - E.cone_slack(F.col("q_norm"), F.col("x_par"), F.col("x_perp"))
        met = met.filter(bound <= limit)
    return met.select("qid", "shard", "leaf", "id")


def frontier(index: Index, planes: DataFrame, k: int = 10, annotated: bool = True, seeds: int = 3, one_shot: bool = False) -> DataFrame:
    """Top-k by DataFrame operations only: seed thresholds, pruning down the levels (or in one join), bounds, products."""
    lam = persisted(thresholds(index, planes, k, seeds), "thresholds")
    leaves = theta_leaves(index, planes, lam) if one_shot else surviving_leaves(index, planes, lam, derive=annotated)
    if not annotated:
        return ranked(leaf_scan(index, leaves, planes), k)
    chosen = scan_with_bounds(index, leaves, lam)
    met = index.points.select("shard", "leaf", "id", "x").join(chosen, ["shard", "leaf", "id"]).join(small_side(planes.select("qid", "q")), "qid")
    return ranked(met.select("qid", "id", F.inline(F.array(F.struct(E.absdot(F.col("x"), F.col("q"), index.d).alias("margin"))))), k)


# --- budgets ---


def budget_leaves(index: Index, planes: DataFrame, budget: float, preference: str = "bound", bins: int = 1024, few: int = 100_000) -> DataFrame:
    """The leaves of all shards that a budget buys: each plane takes its leaves in order of preference while the points before
    them are below its share of all points.

    No plane's leaves are sorted in one task if there are more than ``few``: points are counted by bins of the first order key, and only the bin
    in which the share is reached is put in order.
    """
    total = index.nodes.filter("node = 0").agg(F.sum("n").alias("total"))  # one row
    order = leaf_order(preference)
    if index.leaves().limit(few + 1).count() <= few:
        before = F.sum("n").over(Window.partitionBy("qid").orderBy(*order).rowsBetween(Window.unboundedPreceding, -1))
        return directory(index, planes).withColumn("before", F.coalesce(before, F.lit(0))).crossJoin(F.broadcast(total)).filter(F.col("before") < F.ceil(F.col("total") * budget))
    scored = directory(index, planes).withColumn("score", order[0])
    most = scored.groupBy("qid").agg(F.max("score").alias("most"))
    share = F.when(F.col("most") > 0, F.col("score") / F.col("most")).otherwise(0.0)
    binned = scored.join(F.broadcast(most), "qid").withColumn("bin", F.floor(share * (bins - 1)).cast("int"))  # one row a plane
    summed = binned.groupBy("qid", "bin").agg(F.sum("n").alias("held")).crossJoin(F.broadcast(total)).withColumn("quota", F.ceil(F.col("total") * budget))
    earlier = F.sum("held").over(Window.partitionBy("qid").orderBy("bin").rowsBetween(Window.unboundedPreceding, -1))
    bought = summed.withColumn("earlier", F.coalesce(earlier, F.lit(0))).filter("earlier < quota").select("qid", "bin", "earlier", "quota", (F.col("earlier") + F.col("held") <= F.col("quota")).alias("whole"))
    taken = binned.join(bought, ["qid", "bin"]).drop("score", "most")
    before = F.col("earlier") + F.coalesce(F.sum("n").over(Window.partitionBy("qid").orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    edge = taken.filter(~F.col("whole")).withColumn("before", before).filter("before < quota")
    return taken.filter("whole").unionByName(edge.drop("before"))


def budgeted(index: Index, planes: DataFrame, k: int = 10, budget: float = 0.05, preference: str = "bound", order: str = "global") -> DataFrame:
    """Approximate top-k: the best leaves of all shards first (global), or each shard's walk with its share (depth_first)."""
    if order == "depth_first":
        return shard_dfs(index, planes, k, preference=preference, budget=budget, seeds=0)
    return ranked(leaf_scan(index, budget_leaves(index, planes, budget, preference), planes), k)
