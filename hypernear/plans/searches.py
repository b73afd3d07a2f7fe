"""Queries: exhaustive, tree and hash searches."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions import exprs as E
from ..operators import brute, build, index, metrics, search, vectors
from ..operators.baselines import hashing, lift
from ..sources import planes, tables
from ..sources.storage import fresh_path, persisted
from ..streaming import flows
from .registry import CLUSTER, CUSTOMERS, DOC64, EMB, LI4, LI6, ORDERS, PART2, USERS, dot, index_of, norm, planes_for, points_of, query, sql_normals, sql_planes_box, sql_planes_rows, sql_terms, sql_topk

H1 = sql_planes_rows("emb", 100, 64)
BRUTE = {k: sql_topk(EMB, H1, k) for k in (1, 10, 20, 40)}
CLUSTERED = sql_topk(CLUSTER, H1)
LINES = sql_topk(LI4, sql_planes_box(100, 4))
DOCS = sql_topk(DOC64, sql_planes_rows("emb", 100, 64, 0.9, 200))


def emb(spark: SparkSession, d: str, n: int = 100):
    return points_of(spark, d, "emb").select("id", "x"), planes_for(spark, d, "emb", n)


# --- exhaustive ---


@query(f"WITH {EMB}, {sql_planes_rows('emb', 100, 64)} SELECT qid, id, abs({dot('x', 'q')}) AS margin FROM emb CROSS JOIN planes")
def margin_all(spark, d):
    return brute.all_margins(*emb(spark, d), d=65)


@query(BRUTE[1].replace("SELECT qid, rank, id, margin FROM r", "SELECT qid, id, margin FROM r"))
def brute_nearest(spark, d):
    return brute.nearest(*emb(spark, d), d=65)


for _k in (10, 1, 20, 40):
    query(BRUTE[_k], "brute_topk" if _k == 10 else f"brute_topk_k{_k}")(lambda spark, d, k=_k: brute.topk(*emb(spark, d), k, 65))


@query(BRUTE[10])
def arrow_topk(spark, d):
    return brute.topk_arrow(*emb(spark, d))


@query(f"WITH {EMB}, {sql_planes_rows('emb', 8, 64)}, m AS (SELECT id, abs({dot('x', 'q')}) AS margin FROM emb CROSS JOIN planes WHERE qid = 7) SELECT id, margin FROM m ORDER BY margin, id LIMIT 10")
def single_topk(spark, d):
    points, some = emb(spark, d, 8)
    return brute.single_topk(points, some.filter("qid = 7").first().q, 10, 65)


@query(f"SELECT qid, margin AS lam FROM ({BRUTE[10]}) t WHERE rank = 10")
def kth_margin(spark, d):
    """The current threshold of each plane: its tenth margin, as a window value."""
    points, some = emb(spark, d)
    top = brute.topk(points, some, 10, 65)
    lam = F.nth_value("margin", 10).over(W.partitionBy("qid").orderBy("rank").rowsBetween(W.unboundedPreceding, W.unboundedFollowing))
    return top.select("qid", lam.alias("lam")).distinct()


@query(f"WITH {EMB}, {sql_planes_rows('emb', 100, 64)}, m AS (SELECT qid, id, abs({dot('x', 'q')}) AS margin FROM emb CROSS JOIN planes) SELECT qid, id, margin FROM m WHERE margin <= 0.02")
def slab_range(spark, d):
    return brute.slab(*emb(spark, d), tau=0.02, d=65)


@query(f"WITH {EMB}, {H1}, m AS (SELECT qid, {dot('x', 'q')} AS ip FROM emb CROSS JOIN planes) SELECT qid, count(*) FILTER (ip > 0) AS above, count(*) FILTER (ip < 0) AS below, count(*) FILTER (ip = 0) AS \"on\" FROM m GROUP BY qid")
def side_counts(spark, d):
    return brute.sides(*emb(spark, d), d=65)


@query(sql_topk(EMB, H1, 10, "label = 3"))
def filtered_topk(spark, d):
    points = points_of(spark, d, "emb").filter("label = 3").select("id", "x")
    return brute.topk(points, planes_for(spark, d, "emb"), 10, 65)


@query(sql_topk(EMB.replace("CAST(embedding AS DOUBLE[])", "list_transform(CAST(embedding AS DOUBLE[]), lambda v: v * (1 + label))"), H1))
def scaled_topk(spark, d):
    """Off the unit sphere."""
    return brute.topk(points_of(spark, d, "emb_scaled").select("id", "x"), planes_for(spark, d, "emb_scaled"), 10, 65)


@query(f"WITH {EMB}, {sql_planes_rows('emb', 100, 64, 1.0)}, m AS (SELECT qid, min(abs({dot('x', 'q')})) AS least FROM emb CROSS JOIN planes GROUP BY qid) SELECT count(*) AS n FROM m WHERE least < 1e-12")
def zero_margin_planes(spark, d):
    """Planes through a point: all of them have a margin of nothing but rounding."""
    points = points_of(spark, d, "emb").select("id", "x")
    return brute.nearest(points, planes_for(spark, d, "emb", 100, 1.0), 65).agg(F.count_if(F.col("margin") < 1e-12).alias("n"))


# --- preparation ---


@query(f"WITH {PART2} SELECT min(id) AS id, x[1] AS a, x[2] AS b FROM emb GROUP BY x")
def dedup_vectors(spark, d):
    return vectors.dedup(points_of(spark, d, "part2")).select("id", F.get("x", F.lit(0)).alias("a"), F.get("x", F.lit(1)).alias("b"))


@query("SELECT 'emb' AS name, count(*) AS n, 64::BIGINT AS d, (count(*) * 256)::BIGINT AS bytes FROM embeddings UNION ALL SELECT 'li4', count(*), 4, (count(*) * 16)::BIGINT FROM lineitem UNION ALL SELECT 'part2', count(*), 2, (count(*) * 8)::BIGINT FROM part")
def dataset_stats(spark, d):
    stats = [vectors.dataset_stats(points_of(spark, d, name), name) for name in ("emb", "li4", "part2")]
    return stats[0].unionByName(stats[1]).unionByName(stats[2])


@query("SELECT 'other length' AS reason, 0::BIGINT AS n UNION ALL SELECT 'repeated id', 0 UNION ALL SELECT 'unusable vector', 0")
def validation(spark, d):
    return vectors.validate(points_of(spark, d, "emb"))


@query(f"WITH {EMB}, {sql_planes_rows('emb', 100, 64)}, raw AS (SELECT qid, list_transform(q, lambda v: v * (qid + 2)) AS q FROM planes), n AS (SELECT qid, list_transform(q, lambda v: v / {norm('q[1:64]')}) AS q FROM raw) SELECT qid, generate_subscripts(q, 1) - 1 AS pos, unnest(q) AS value FROM n")
def normalized_queries(spark, d):
    """Planes of any length brought back to unit normals."""
    raw = planes_for(spark, d, "emb").select("qid", F.transform("q", lambda v: v * (F.col("qid") + 2)).alias("q"))
    return vectors.normalize_queries(raw)[0].select("qid", F.posexplode("q").alias("pos", "value")).withColumn("pos", F.col("pos").cast("long"))


@query(f"""WITH e AS (SELECT vec_id AS qid, CAST(embedding AS DOUBLE[]) AS w, vec_id % 50 AS turn FROM embeddings),
p AS (SELECT qid, CASE WHEN turn = 1 THEN list_transform(w, lambda v: v * 0) WHEN turn = 3 THEN list_transform(w, lambda v: 'nan'::DOUBLE) WHEN turn <> 2 THEN w END AS w FROM e),
r AS (SELECT qid, CASE WHEN w IS NULL OR len(list_filter(w, lambda v: v IS NULL OR isnan(v) OR isinf(v))) > 0 THEN 'not finite' WHEN {norm('w')} = 0 THEN 'zero normal' END AS reason FROM p)
SELECT qid, reason FROM r WHERE reason IS NOT NULL""")
def invalid_queries(spark, d):
    return vectors.normalize_queries(planes.odd(spark, d))[1]


@query("WITH " + LI4 + ", a AS (SELECT i, id, abs(x[i + 1] - 0.5) AS margin FROM emb CROSS JOIN range(0, 4) t(i)) SELECT i AS qid, arg_min(id, (margin, id)) AS id, min(margin) AS margin FROM a GROUP BY i")
def axis_nearest(spark, d):
    """Axis planes have a closed form: the value nearest to a half."""
    return brute.nearest(points_of(spark, d, "li4").select("id", "x"), planes.axes(spark, 4), 5)


@query(f"WITH {EMB}, {sql_normals(10, 64)}, pq AS (SELECT qid, list_append(w, [1.5, -1.5, 5.0, -5.0][CAST(qid % 4 + 1 AS INT)]::DOUBLE) AS q FROM w), m AS (SELECT qid, id, abs({dot('x', 'q')}) AS margin FROM emb CROSS JOIN pq), r AS (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY margin, id) AS rank FROM m) SELECT qid, rank, id, margin FROM r WHERE rank <= 10")
def far_planes_topk(spark, d):
    """Planes that miss the data: the one-sided cases of the bounds, searched on the tree."""
    return search.shard_dfs(index_of(spark, d, "emb", 50), planes.far_off(spark, 64))


# --- trees: the oracle is a plain scan, as no index may change an answer ---


def tree_query(name: str, oracle: str, points: str, leaf: int, n: int = 100, shards: int = 1, method=search.shard_dfs, annotate: bool = True, **options):
    query(oracle, name)(lambda spark, d: method(index_of(spark, d, points, leaf, shards, annotate), planes_for(spark, d, points, n), **options))


PLAIN = dict(ball=False, cone=False, derive_sibling=False)
tree_query("plain_topk", CLUSTERED, "emb_cluster", 20, annotate=False, **PLAIN)
tree_query("plain_topk_bound_pref", CLUSTERED, "emb_cluster", 20, annotate=False, preference="bound", **PLAIN)
tree_query("annotated_topk", CLUSTERED, "emb_cluster", 20)
tree_query("annotated_topk_bound_pref", CLUSTERED, "emb_cluster", 20, preference="bound")
tree_query("annotated_no_cone", CLUSTERED, "emb_cluster", 20, cone=False)
tree_query("annotated_no_ball", CLUSTERED, "emb_cluster", 20, ball=False)
tree_query("annotated_no_bounds", CLUSTERED, "emb_cluster", 20, ball=False, cone=False)
tree_query("annotated_no_sibling", CLUSTERED, "emb_cluster", 20, derive_sibling=False)
tree_query("annotated_leaf_500", CLUSTERED, "emb_cluster", 500)
tree_query("annotated_k1", sql_topk(CLUSTER, H1, 1), "emb_cluster", 20, k=1)
tree_query("annotated_k40", sql_topk(CLUSTER, H1, 40), "emb_cluster", 20, k=40)
tree_query("sharded_topk", CLUSTERED, "emb_cluster", 20, shards=6)
tree_query("frontier_topk", CLUSTERED, "emb_cluster", 50, method=search.frontier, annotated=False)
tree_query("frontier_annotated_topk", CLUSTERED, "emb_cluster", 50, method=search.frontier)
tree_query("one_shot_topk", CLUSTERED, "emb_cluster", 50, method=search.frontier, one_shot=True)
tree_query("lineitem_annotated_topk", LINES, "li4", 1000, shards=4)
tree_query("doc_annotated_topk", DOCS, "doc_tf", 100)
tree_query("budget_whole_topk", CLUSTERED, "emb_cluster", 20, method=search.budgeted, budget=1.0)
tree_query("budget_depth_first", None, "emb_cluster", 20, method=search.budgeted, budget=0.2, order="depth_first")
tree_query("budget_global", None, "emb_cluster", 20, method=search.budgeted, budget=0.2)


# The other vector sets, each searched on a tree.
tree_query("li6_topk", sql_topk(LI6, sql_planes_box(100, 6)), "li6", 1000, shards=4)
tree_query("orders_topk", sql_topk(ORDERS, sql_planes_box(100, 2)), "order2", 200, shards=2)
tree_query("customers_topk", sql_topk(CUSTOMERS, sql_planes_box(100, 3)), "cust3", 100)
tree_query("parts_topk", sql_topk(PART2, sql_planes_box(100, 2)), "part2", 100)
tree_query("users_topk", sql_topk(USERS, sql_planes_box(100, 10)), "user_rates", 100)
tree_query("doc256_topk", sql_topk(sql_terms("documents", "doc_id", "text", 256), sql_planes_rows("emb", 100, 256, 0.9, 200)), "doc_tf256", 100)
tree_query("doc1024_topk", sql_topk(sql_terms("documents", "doc_id", "text", 1024), sql_planes_rows("emb", 100, 1024, 0.9, 200)), "doc_tf1024", 100)
tree_query("pages_topk", sql_topk(sql_terms("pages", "page_id", "html", 128), sql_planes_box(100, 128)), "page_tf", 100)
tree_query("turns_topk", sql_topk(sql_terms("conversations", "conv_id * 1000 + turn", "text", 128), sql_planes_box(100, 128)), "conv_tf", 100)


@query("SELECT 0::BIGINT AS n")
def amplified_disagreements(spark, d):
    """V9, lines with jittered copies: answers of the tree that a scan doesn't give, or the other way round."""
    points, some = tables.li4(spark, d, 2).select("id", "x"), planes_for(spark, d, "li4")
    found, truth = search.shard_dfs(build.hybrid(points, 1000, shards=4), some), brute.topk_arrow(points, some)
    return found.exceptAll(truth).unionByName(truth.exceptAll(found)).agg(F.count("*").alias("n"))


@query(CLUSTERED)
def leaf_join(spark, d):
    """The leaves that a threshold can reach, joined with their points."""
    built, some = index_of(spark, d, "emb_cluster", 50), planes_for(spark, d, "emb_cluster")
    lam = search.thresholds(built, some, 10)
    return brute.ranked(search.leaf_scan(built, search.theta_leaves(built, some, lam), some), 10)


@query("SELECT 0::BIGINT AS n")
def slack_guarantee(spark, d):
    """With slack 0.5 a found margin is at most half as large again as the true one of its rank."""
    built, some = index_of(spark, d, "emb_cluster", 20), planes_for(spark, d, "emb_cluster")
    truth = brute.topk_arrow(points_of(spark, d, "emb_cluster").select("id", "x"), some).select("qid", "rank", F.col("margin").alias("true"))
    found = search.shard_dfs(built, some, eps=0.5)
    return truth.join(found, ["qid", "rank"], "left").agg(F.count_if(F.col("margin").isNull() | (F.col("margin") > 1.5 * F.col("true") + 1e-9)).alias("n"))


@query("SELECT 0::BIGINT AS n")
def counter_identity(spark, d):
    """Points seen in an exact search are verified or ruled out by a bound, each once."""
    built, some = index_of(spark, d, "emb_cluster", 20, 6), planes_for(spark, d, "emb_cluster")
    cost = search.counters(search.shard_dfs(built, some, with_counters=True))
    shards = built.packed().filter("n > 0").count()
    return cost.agg(F.count_if((F.col("points_seen") != F.col("verified") + F.col("pruned_ball") + F.col("pruned_cone")) | (F.col("shards_touched") != shards)).alias("n"))


@query("SELECT 'depth_first' AS \"order\", 0::BIGINT AS wrong, 0::BIGINT AS short UNION ALL SELECT 'global', 0, 0")
def budget_verified(spark, d):
    """Answers under a budget hold true margins, and k of them a plane."""
    built, some, out = index_of(spark, d, "emb_cluster", 20), planes_for(spark, d, "emb_cluster"), None
    truth = brute.all_margins(points_of(spark, d, "emb_cluster").select("id", "x"), some, 65).select("qid", "id", F.col("margin").alias("true"))
    for order in ("depth_first", "global"):
        found = persisted(search.budgeted(built, some, budget=0.2, order=order), "budget-found")
        wrong = found.join(truth, ["qid", "id"], "left").agg(F.count_if(F.col("true").isNull() | (F.col("true") != F.col("margin"))).alias("wrong"))
        short = found.groupBy("qid").count().agg((F.lit(100) - F.count_if(F.col("count") == 10)).alias("short"))
        row = wrong.crossJoin(short).select(F.lit(order).alias("order"), "wrong", F.col("short").cast("long").alias("short"))
        out = row if out is None else out.unionByName(row)
    return out


@query(CLUSTERED)
def levels_topk(spark, d):
    """An index built level by level with aggregations."""
    return search.shard_dfs(build.exact_levels(points_of(spark, d, "emb_cluster"), 100), planes_for(spark, d, "emb_cluster"))


@query("SELECT * FROM (VALUES ('children add up', 0::BIGINT), ('points in leaves', 0), ('each point once', 0), ('leaf size', 0), ('points in balls', 0), ('radius is reached', 0)) t(rule, n)")
def tree_invariants(spark, d):
    return index.check_partition(index_of(spark, d, "emb_cluster", 20, 6))


@query("SELECT 0::BIGINT AS n")
def rollup_centers(spark, d):
    """Inner centres computed upwards agree with means over all points below."""
    built = index_of(spark, d, "emb_cluster", 20)
    up = built.points.join(built.nodes.select("shard", "node", "lo", "hi", "center"), "shard").filter((F.col("pos") >= F.col("lo")) & (F.col("pos") < F.col("hi")))
    mean = up.select("shard", "node", F.posexplode("x").alias("i", "v"), "center").groupBy("shard", "node", "i").agg(F.avg("v").alias("v"), F.first(F.get("center", F.col("i"))).alias("c"))
    return mean.agg(F.count_if(F.abs(F.col("v") - F.col("c")) > 1e-9).alias("n"))


@query("SELECT 0::BIGINT AS n")
def sibling_identity(spark, d):
    """Products derived from parent and sibling agree with direct ones."""
    built, some = index_of(spark, d, "emb_cluster", 20), planes_for(spark, d, "emb_cluster")
    met = built.wide().join(built.nodes.select("shard", "node", "center"), ["shard", "node"]).crossJoin(F.broadcast(some))
    ip = lambda c: E.dot(c, F.col("q"), 65)
    derived = E.sibling_ip(ip(F.col("center")), ip(F.col("small.center")), F.col("n"), F.col("small.n"))
    return met.agg(F.count_if(F.abs(derived - ip(F.col("big.center"))) > 1e-9).alias("n"))


@query("SELECT 0::BIGINT AS n")
def halving_check(spark, d):
    """With derived siblings C centre products become (C + 1) / 2."""
    built, some = index_of(spark, d, "li4", 1000, 4), planes_for(spark, d, "li4")
    cost = {derive: search.counters(search.shard_dfs(built, some, derive_sibling=derive, with_counters=True, rederive=1 << 30)).select("qid", F.col("center_products").alias(f"c{int(derive)}"), F.col("shards_touched").alias(f"s{int(derive)}")) for derive in (False, True)}
    return cost[False].join(cost[True], "qid").agg(F.count_if(2 * F.col("c1") - F.col("s1") != F.col("c0")).alias("n"))


@query("SELECT 0::BIGINT AS fewer, 0::BIGINT AS same")
def ablation_order(spark, d):
    """Planes where the full tree verifies more than a variant, or more than without the ball, which the cone contains."""
    built, some = index_of(spark, d, "emb_cluster", 20), planes_for(spark, d, "emb_cluster")
    variants = {"full": {}, "ball": dict(cone=False), "cone": dict(ball=False), "none": dict(ball=False, cone=False)}
    cost = [search.counters(search.shard_dfs(built, some, with_counters=True, **v)).select("qid", F.col("verified").alias(k)) for k, v in variants.items()]
    joined = cost[0].join(cost[1], "qid").join(cost[2], "qid").join(cost[3], "qid")
    return joined.agg(F.count_if((F.col("full") > F.col("ball")) | (F.col("ball") > F.col("none"))).alias("fewer"), F.count_if(F.col("full") != F.col("cone")).alias("same"))


@query()
def search_counters(spark, d):
    """What each plane costs on the annotated tree."""
    found = search.shard_dfs(index_of(spark, d, "emb_cluster", 20), planes_for(spark, d, "emb_cluster"), with_counters=True)
    return search.counters(found)


@query()
def index_sizes(spark, d):
    return index.sizes(index_of(spark, d, "emb_cluster", 20))


@query("SELECT count(*) AS n FROM embeddings")
def index_round_trip(spark, d):
    """Points of a saved and loaded index."""
    path = fresh_path(spark, "saved-index")
    index_of(spark, d, "emb_cluster", 20, 6).save(path)
    return index.load(spark, path).points.agg(F.count("*").alias("n"))


# --- hash baselines ---


@query("SELECT 0::BIGINT AS n")
def lift_identity(spark, d):
    """Products of lifts are squared products."""
    points, some = points_of(spark, d, "part2").select("id", "x"), planes_for(spark, d, "part2")
    pairs = points.crossJoin(F.broadcast(some))
    square = F.pow(E.dot(F.col("x"), F.col("q"), 3), F.lit(2.0))
    return pairs.agg(F.count_if(F.abs(E.dot(lift.lift(F.col("x")), lift.lift(F.col("q"))) - square) > 1e-9 * (1 + square)).alias("n"))


def lifted_topk(spark, d, near: bool) -> DataFrame:
    points, some = points_of(spark, d, "emb_cluster").select("id", "x"), planes_for(spark, d, "emb_cluster")
    order = F.asc("distance") if near else F.desc("distance")
    place = F.row_number().over(W.partitionBy("qid").orderBy(order, "id"))
    chosen = lift.exact_distances(points, some, near).withColumn("place", place).filter("place <= 10")
    return hashing.verify(points, chosen, some, 10, 65)


CLUSTERED_20 = sql_topk(CLUSTER, sql_planes_rows("emb", 100, 64))
query(CLUSTERED_20, "near_lift_topk")(lambda spark, d: lifted_topk(spark, d, True))
query(CLUSTERED_20, "far_lift_topk")(lambda spark, d: lifted_topk(spark, d, False))


@query(f"""WITH {PART2}, {sql_planes_box(100, 2)}, f AS (SELECT max({dot('x', 'x')}) AS most FROM emb),
m AS (SELECT qid, sqrt(most * most + pow({dot('q', 'q')}, 2) + 2 * pow({dot('x', 'q')}, 2)) AS distance FROM emb CROSS JOIN planes CROSS JOIN f)
SELECT qid, round(max(distance) / min(distance), 6) AS ratio FROM m GROUP BY qid""")
def distortion_ratio(spark, d):
    points, some = points_of(spark, d, "part2").select("id", "x"), planes_for(spark, d, "part2")
    return lift.distortion(lift.exact_distances(points, some)).select("qid", F.round("ratio", 6).alias("ratio"))


@query("WITH " + PART2 + ", t AS (SELECT t, (7*t + 3) % 3 AS i, (11*t + 5*(t // 3) + 1) % 3 AS j FROM range(0, 6) r(t)) SELECT id, t AS pos, x[CAST(i + 1 AS INT)] * x[CAST(j + 1 AS INT)] * (3 / sqrt(6)) AS value FROM emb CROSS JOIN t")
def sampled_lift(spark, d):
    made = points_of(spark, d, "part2").select("id", F.posexplode(lift.sampled_lift(F.col("x"), lift.recipe_pairs(3, 6), 3)).alias("pos", "value"))
    return made.withColumn("pos", F.col("pos").cast("long"))


def hash_search(spark, d, kind: str) -> tuple[DataFrame, DataFrame, DataFrame]:
    points, some = persisted(points_of(spark, d, "emb_cluster").select("id", "x"), "hash-set"), planes_for(spark, d, "emb_cluster")
    if kind == "near":
        return points, some, hashing.near_search(hashing.near_build(points, m=128, lam=4 * 65), some, budget=0.5)
    if kind == "far":
        return points, some, hashing.far_search(hashing.far_build(points, m=128, lam=4 * 65), some, separation=4, budget=0.5)
    return points, some, hashing.sphere_search(hashing.sphere_build(points, kind, bits=2 if kind == "pair" else 8), some)


def verified_margins(spark, d, kind: str) -> DataFrame:
    """Margins that a hash search found and a scan disagrees with."""
    points, some, found = hash_search(spark, d, kind)
    truth = brute.all_margins(points, some, 65).select("qid", "id", F.col("margin").alias("true"))
    return found.join(truth, ["qid", "id"], "left").agg(F.count_if(F.col("true").isNull() | (F.col("true") != F.col("margin"))).alias("n"))


query(None, "near_hash_topk")(lambda spark, d: hash_search(spark, d, "near")[2])
query(None, "far_hash_topk")(lambda spark, d: hash_search(spark, d, "far")[2])
query(None, "sphere_pair_topk")(lambda spark, d: hash_search(spark, d, "pair")[2])
query(None, "sphere_bilinear_topk")(lambda spark, d: hash_search(spark, d, "bilinear")[2])
query(None, "sphere_lift_topk")(lambda spark, d: hash_search(spark, d, "embedding")[2])
for _kind in ("pair", "bilinear", "embedding"):
    query("SELECT 0::BIGINT AS n", f"sphere_{_kind}_verified")(lambda spark, d, kind=_kind: verified_margins(spark, d, kind))
query("SELECT 0::BIGINT AS n", "near_hash_verified")(lambda spark, d: verified_margins(spark, d, "near"))
query("SELECT 0::BIGINT AS n", "far_hash_verified")(lambda spark, d: verified_margins(spark, d, "far"))


# --- measures ---


@query("SELECT i AS qid, 1.0::DOUBLE AS recall, 10::BIGINT AS returned FROM range(0, 100) t(i)")
def recall_brute_budget1(spark, d):
    points, some = points_of(spark, d, "emb_cluster").select("id", "x"), planes_for(spark, d, "emb_cluster")
    found = search.budgeted(index_of(spark, d, "emb_cluster", 20), some, budget=1.0)
    return metrics.recall(found, brute.topk_arrow(points, some), 10)


@query(f"""WITH {EMB}, {H1}, m AS (SELECT qid, id, label, abs({dot('x', 'q')}) AS margin FROM emb CROSS JOIN planes),
t AS (SELECT qid, id FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY margin, id) AS r FROM m) WHERE r <= 10),
f AS (SELECT qid, id FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY margin, id) AS r FROM m WHERE label < 5) WHERE r <= 10)
SELECT t.qid, count(f.id) / 10.0::DOUBLE AS recall, 10::BIGINT AS returned FROM t LEFT JOIN f ON f.qid = t.qid AND f.id = t.id GROUP BY t.qid""")
def recall_join(spark, d):
    """Recall of a search that sees half the labels."""
    points, some = points_of(spark, d, "emb"), planes_for(spark, d, "emb")
    return metrics.recall(brute.topk_arrow(points.filter("label < 5").select("id", "x"), some), brute.topk_arrow(points.select("id", "x"), some), 10)


@query("WITH runs AS (SELECT p_size / 50.0::DOUBLE AS recall, p_retailprice / 1000.0::DOUBLE AS seconds FROM part) SELECT a.recall, min(b.seconds) AS seconds FROM (SELECT DISTINCT recall FROM runs) a JOIN runs b ON b.recall >= a.recall GROUP BY a.recall")
def pareto_curve(spark, d):
    """Least time at each recall or better, with parts as runs: their size stands for recall, their price for seconds."""
    return metrics.pareto(tables.table(spark, d, "part").select((F.col("p_size") / 50.0).alias("recall"), (F.col("p_retailprice") / 1000.0).alias("seconds")))


@query()
def budget_recall(spark, d):
    """Mean recall of both budget orders, by budget."""
    points, some = points_of(spark, d, "emb_cluster").select("id", "x"), planes_for(spark, d, "emb_cluster")
    built, truth, rows = index_of(spark, d, "emb_cluster", 20), persisted(brute.topk_arrow(points, some), "truth"), None
    for order in ("depth_first", "global"):
        for budget in (0.05, 0.2, 0.5):
            found = search.budgeted(built, some, budget=budget, order=order, preference="center" if order == "depth_first" else "bound")
            row = metrics.recall(found, truth, 10).agg(F.avg("recall").alias("recall")).select(F.lit(order).alias("order"), F.lit(budget).alias("budget"), "recall")
            rows = row if rows is None else rows.unionByName(row)
    return rows




@query(CLUSTERED)
def chosen_topk(spark, d):
    """The mode is chosen by the engine."""
    from .choose import topk

    return topk(index_of(spark, d, "emb_cluster", 20), planes_for(spark, d, "emb_cluster"))


# --- streams: the oracle is the batch form ---


STREAM = "abs(value / 100.0::DOUBLE - 0.5)"


def event_stream(spark, d, schema: str = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double"):
    """The events table as a file stream, with margins from the plane value = 50; times are UTC."""
    stream = spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").parquet(d)
    return stream.select("event_id", F.to_timestamp("ts").alias("ts"), "user_id", F.abs(F.col("value") / 100.0 - 0.5).alias("margin"), (F.col("value") / 100.0).alias("v"))


@query("SELECT event_id AS id, 0::BIGINT AS qid, " + STREAM + " AS margin FROM events WHERE " + STREAM + " <= 0.001")
def stream_alerts(spark, d):
    """Points of a stream within 0.001 of a plane."""
    points = event_stream(spark, d).select(F.col("event_id").alias("id"), F.array("v", F.lit(1.0)).alias("x"))
    plane = spark.createDataFrame([(0, [1.0, -0.5])], "qid long, q array<double>")
    return flows.drained(flows.point_alerts(points, plane, 0.001, 2), spark, "hn_alerts").select("id", "qid", "margin")


@query("SELECT date_trunc('day', ts) AS start, count(*) AS n, min(" + STREAM + ") AS least FROM events GROUP BY ALL")
def stream_tumbling(spark, d):
    return flows.drained(flows.windowed(event_stream(spark, d), "1 day"), spark, "hn_tumbling", "complete").select(F.to_timestamp_ntz(F.date_format("start", "yyyy-MM-dd HH:mm:ss")).alias("start"), "n", "least")


@query("SELECT 0::BIGINT AS qid, row_number() OVER (ORDER BY margin, id) AS rank, id, margin FROM (SELECT event_id AS id, " + STREAM + " AS margin FROM events) ORDER BY margin, id LIMIT 10")
def stream_topk(spark, d):
    """The ten nearest of a stream so far, as its last update shows them."""
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    scored = event_stream(spark, d).select(F.lit(0).cast("long").alias("qid"), F.col("event_id").alias("id"), "margin")
    updates = flows.drained(flows.running_topk(scored), spark, "hn_running", "update")
    return updates.groupBy("qid", "rank").agg(F.min(F.struct("margin", "id")).alias("b")).select("qid", "rank", "b.id", "b.margin")


@query(CLUSTERED_20)
def stream_planes(spark, d):
    """A stream of planes searched on a static index."""
    planes_for(spark, d, "emb_cluster").select("qid", "q").write.parquet(path := fresh_path(spark, "plane-stream"))
    stream, out = spark.readStream.schema("qid long, q array<double>").parquet(path), fresh_path(spark, "plane-answers")
    flows.search_each(stream, index_of(spark, d, "emb_cluster", 20), lambda found, n: found.write.mode("append").parquet(out)).awaitTermination()
    return spark.read.parquet(out)


@query(CLUSTERED_20)
def append_topk(spark, d):
    """An index of half the points, with the other half appended: answers stay exact."""
    points = points_of(spark, d, "emb_cluster").select("id", "x")
    half = build.hybrid(points.filter("id % 2 = 0"), 50)
    return search.shard_dfs(flows.append(half, points.filter("id % 2 = 1")), planes_for(spark, d, "emb_cluster"))


@query("WITH " + LI4 + ", pl AS (SELECT i AS qid, 0.1::DOUBLE + 0.2::DOUBLE * i AS c FROM range(0, 4) t(i)) SELECT qid, id, abs(x[2] - c) AS margin FROM emb CROSS JOIN pl WHERE abs(x[2] - c) <= 0.001")
def axis_range(spark, d):
    """Points within a thousandth of planes that fix one component, by a range join on bins."""
    some = spark.range(4).select(F.col("id").alias("qid"), F.array(F.lit(0.0), F.lit(1.0), F.lit(0.0), F.lit(0.0), -(F.lit(0.1) + F.lit(0.2) * F.col("id"))).alias("q"))
    return brute.axis_slab(points_of(spark, d, "li4").select("id", "x"), some, 1, 0.001)
