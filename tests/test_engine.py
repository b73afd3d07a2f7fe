"""Spark operators against plain scans, with the edge cases of points and planes."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from hypernear.functions import exprs as E
from hypernear.functions import sql as sqlfns
from hypernear.operators import brute, build, index, metrics, search, vectors
from hypernear.operators.baselines import hashing, lift
from hypernear.plans import choose
from hypernear.sources import datasource, tables
from hypernear.streaming import flows


def points_of(spark, P):
    return spark.createDataFrame([(i, [float(v) for v in p] + [1.0]) for i, p in enumerate(P)], "id long, x array<double>")


def planes_of(spark, Q):
    rows = [(i, [float(v) for v in q], float(np.linalg.norm(q))) for i, q in enumerate(Q)]
    return spark.createDataFrame(rows, "qid long, q array<double>, q_norm double")


def unit(Q):
    Q = np.array(Q, dtype=float)
    return Q / np.linalg.norm(Q[:, :-1], axis=1)[:, None]


def rows(df):
    return sorted((r.qid, r["rank"], r.id, r.margin) for r in df.collect())


@pytest.fixture(scope="module")
def clustered():
    random = np.random.default_rng(5)
    P = np.concatenate([random.standard_normal((80, 3)) * 0.1 + c for c in random.standard_normal((5, 3)) * 3])
    Q = unit(np.column_stack([random.standard_normal((12, 3)), random.uniform(-3, 3, 12)]))
    return P, Q


def test_all_searches_agree(spark, clustered):
    points, planes = points_of(spark, clustered[0]), planes_of(spark, clustered[1])
    truth = rows(brute.topk(points, planes, 7, 4))
    assert rows(brute.topk_arrow(points, planes, 7, block=64)) == truth
    assert rows(brute.topk(points, planes, 7)) == truth
    built = build.hybrid(points, 16, shards=3)
    assert all(r.n == 0 for r in index.check_partition(built).collect())
    assert built.nodes.select("shard").distinct().count() == 3
    for found in (search.shard_dfs(built, planes, 7), search.shard_dfs(built, planes, 7, seeds=0, preference="bound"), search.frontier(built, planes, 7), search.frontier(built, planes, 7, annotated=False), search.frontier(built, planes, 7, one_shot=True), search.budgeted(built, planes, 7, budget=1.0)):
        assert rows(found) == truth
    for forced in ("brute", "frontier", "shard_dfs"):
        assert rows(choose.topk(built, planes, 7, force=forced)) == truth


def test_two_builders_give_one_tree(spark, clustered):
    points = points_of(spark, clustered[0])
    local, levels = build.hybrid(points, 25, shards=1), build.exact_levels(points, 25)
    assert all(r.n == 0 for r in index.check_partition(levels).collect())
    members = lambda built: {frozenset(r.ids) for r in built.points.groupBy("shard", "leaf").agg(F.collect_list("id").alias("ids")).collect()}
    assert members(local) == members(levels)


def test_oversize_shards_are_cut(spark):
    points = points_of(spark, np.tile([[1.0, 2.0]], (300, 1)))
    built = build.hybrid(points, 10, shards=4, shard_bytes=10 * 8 * 3)
    assert all(r.n == 0 for r in index.check_partition(built).collect())
    assert rows(search.shard_dfs(built, planes_of(spark, [[1, 0, -1]]), 3)) == [(0, 1, 0, 0.0), (0, 2, 1, 0.0), (0, 3, 2, 0.0)]


@pytest.mark.parametrize("P", [np.zeros((0, 2)), np.ones((1, 2)), np.ones((30, 2)), np.arange(12.0).reshape(6, 2)])
def test_small_and_degenerate_sets(spark, P):
    points, planes = points_of(spark, P), planes_of(spark, [[1, 0, -1], [0, 1, 0.5]])
    truth = rows(brute.topk(points, planes, 10))
    assert rows(brute.topk_arrow(points, planes, 10)) == truth
    if len(P):
        assert rows(search.shard_dfs(build.hybrid(points, 4), planes, 10)) == truth


def test_margin_and_rescaling(spark):
    df = spark.createDataFrame([([3.0, 4.0], [3.0, 4.0, 5.0])], "p array<double>, q array<double>")
    row = df.select(E.margin(F.col("p"), F.col("q")).alias("m"), E.absdot(E.augment(F.col("p")), E.rescale(F.col("q"))).alias("s"), E.absdot(E.augment(F.col("p")), E.rescale(F.transform("q", lambda v: v * -7))).alias("t")).first()
    assert row.m == pytest.approx(6.0) and row.s == pytest.approx(6.0) and row.t == pytest.approx(6.0)


def test_validation_and_odd_planes(spark):
    df = spark.createDataFrame([(1, [1.0, 2.0]), (1, [1.0, 2.0]), (2, [1.0]), (3, None), (4, [float("nan"), 1.0]), (5, [])], "id long, x array<double>")
    assert {r.reason: r.n for r in vectors.validate(df).collect()} == {"unusable vector": 3, "other length": 1, "repeated id": 1}
    assert [r.id for r in vectors.dedup(df.filter("id < 2")).collect()] == [1]
    planes = spark.createDataFrame([(0, [0.0, 2.0, 4.0]), (1, [0.0, 0.0, 1.0]), (2, None), (3, [float("inf"), 0.0, 0.0]), (4, [1.0])], "qid long, q array<double>")
    good, bad = vectors.normalize_queries(planes)
    assert [(r.qid, r.q) for r in good.collect()] == [(0, [0.0, 1.0, 2.0])]
    assert {r.qid: r.reason for r in bad.collect()} == {1: "zero normal", 2: "not finite", 3: "not finite", 4: "not finite"}


def test_margin_is_not_a_metric(spark):
    """A point on a plane has margin 0 without equalling it, and two planes through it meet points the sum of margins can't reach."""
    points, planes = points_of(spark, [[0, 0], [5, 0]]), planes_of(spark, [[0, 1, 0], [1, 0, 0]])
    m = {(r.qid, r.id): r.margin for r in brute.all_margins(points, planes).collect()}
    assert m[0, 0] == m[0, 1] == m[1, 0] == 0 and m[1, 1] == 5


def test_lift_identities(spark, clustered):
    P, Q = clustered
    X = np.column_stack([P, np.ones(len(P))])
    ip = X @ Q.T
    assert np.allclose(lift.lift_rows(X) @ lift.lift_rows(Q).T, ip**2)
    most = np.linalg.norm(lift.lift_rows(X), axis=1).max()
    done = lift.complete(lift.lift_rows(X), most)
    for near, sign in ((True, 1), (False, -1)):
        gap = ((done[:, None, :] - lift.lifted_query(Q, None, near)[None]) ** 2).sum(axis=2)
        assert np.allclose(gap, most**2 + np.linalg.norm(Q, axis=1) ** 4 + sign * 2 * ip**2)
    assert lift.largest_norm(points_of(spark, P), None) == pytest.approx(most)


def test_sampled_lift_is_unbiased():
    random = np.random.default_rng(0)
    x, q = random.standard_normal((1, 6)), random.standard_normal((1, 6))
    values = [(lift.sampled_rows(x, p) @ lift.sampled_rows(q, p).T).item() for p in (lift.random_pairs(6, 12, s) for s in range(600))]
    assert abs(np.mean(values) - (x @ q.T).item() ** 2) < 4 * np.std(values) / np.sqrt(600)


def test_hash_searches_verify_and_recall_grows(spark, clustered):
    points, planes = points_of(spark, clustered[0]), planes_of(spark, clustered[1])
    truth = brute.topk(points, planes, 10)
    exact = {(r.qid, r.id): r.margin for r in brute.all_margins(points, planes).collect()}
    recall = lambda found: metrics.recall(found, truth, 10).agg({"recall": "avg"}).first()[0]
    near, far = hashing.near_build(points, m=16), hashing.far_build(points, m=16)
    got = [recall(hashing.near_search(near, planes, budget=b)) for b in (0.05, 0.5, 1.0)]
    assert got == sorted(got) and got[0] < got[-1]
    got = [recall(hashing.far_search(far, planes, separation=2, budget=b)) for b in (0.05, 0.5, 1.0)]
    assert got == sorted(got) and got[-1] == 1
    sphere = [hashing.sphere_build(points, kind, bits=2) for kind in ("pair", "bilinear", "embedding")]
    assert all(hashing.sphere_search(built, planes, 7).count() == 7 * 12 for built in sphere)  # no plane gets fewer than k
    budgets = {q: 0.05 if q < 6 else 1.0 for q in range(12)}
    mixed = {r.qid: r.recall for r in metrics.recall(hashing.near_search(near, planes, budget=budgets), truth, 10).collect()}
    assert all(mixed[q] == 1 for q in range(6, 12)) and min(mixed.values()) < 1
    for found in (hashing.near_search(near, planes), hashing.far_search(far, planes), hashing.sphere_search(hashing.sphere_build(points, "pair", bits=2), planes)):
        assert all(exact[r.qid, r.id] == r.margin for r in found.collect())


def test_index_is_saved_loaded_and_read_by_the_data_source(spark, clustered, tmp_path):
    points, planes = points_of(spark, clustered[0]), planes_of(spark, clustered[1])
    build.hybrid(points, 16, shards=2).save(str(tmp_path / "index"))
    loaded = index.load(spark, str(tmp_path / "index"))
    assert rows(search.shard_dfs(loaded, planes, 5)) == rows(brute.topk(points, planes, 5))
    spark.dataSource.register(datasource.IndexSource)
    assert spark.read.format("hypernear_index").load(str(tmp_path / "index")).count() == len(clustered[0])


def test_plans_are_as_meant(spark, clustered):
    points, planes = points_of(spark, clustered[0]), planes_of(spark, clustered[1])
    plan = brute.topk(points, planes, 5, 4)._jdf.queryExecution().executedPlan().toString()
    assert "WindowGroupLimit" in plan and "BroadcastNestedLoopJoin" in plan
    built = build.hybrid(points, 16)
    lam = search.thresholds(built, planes, 5)
    bounds = search.scan_with_bounds(built, search.theta_leaves(built, planes, lam), lam)
    scans = [line for line in bounds._jdf.queryExecution().toString().split("\n") if "ReadSchema" in line and "r_x" in line]
    assert scans and all("x:array" not in line.split("ReadSchema")[1] for line in scans)


def test_readers(spark, tmp_path):
    (tmp_path / "v.csv").write_text("1,0.5,2\n2,1,3\n")
    (tmp_path / "v.txt").write_text("1 0.5 2\n2 1 3\n")
    (tmp_path / "v.json").write_text('{"id":1,"p":[0.5,2]}\n{"id":2,"p":[1,3]}\n')
    records = b"".join(np.int32(2).tobytes() + np.array(p, "<f4").tobytes() for p in ([0.5, 2], [1, 3]))
    (tmp_path / "v.fvecs").write_bytes(records)
    want = [[0.5, 2.0], [1.0, 3.0]]
    for kind in ("csv", "text", "json", "fvecs"):
        path = str(tmp_path / {"text": "v.txt"}.get(kind, f"v.{kind}"))
        assert [r.p for r in sorted(tables.read_vectors(spark, path, kind, 2).collect())] == want
    spark.createDataFrame([(1, want[0]), (2, want[1])], "id long, p array<double>").write.orc(str(tmp_path / "orc"))
    assert [r.p for r in sorted(tables.read_vectors(spark, str(tmp_path / "orc"), "orc").collect())] == want
    sparse = spark.createDataFrame([({"0": 1.5, "2": 2.5},)], "m map<string, double>")
    assert tables.from_sparse(sparse, "m", 3).first().x == [1.5, 0.0, 2.5, 1.0]


def test_sql_functions(spark):
    sqlfns.register(spark)
    row = spark.sql("SELECT hn_margin(array(3D, 4D), array(3D, 4D, 5D)) AS m, hn_normalize(array(0D, 2D, 4D)) AS n, hn_augment(array(1D)) AS a, hn_cone_bound(2D, 1D, 3D, 1D) AS c, hn_ball_bound(-5D, 2D, 1D) AS b").first()
    assert (row.m, row.n, row.a, row.c, row.b) == (6.0, [0.0, 1.0, 2.0], [1.0, 1.0], 5.0, 3.0)
    assert spark.sql("SELECT vec_mean(v) AS m, vec_sum(v) AS s FROM VALUES (array(1D, 2D)), (array(3D, 6D)) t(v)").first() == ([2.0, 4.0], [4.0, 8.0])
    assert [r.value for r in spark.sql("SELECT value FROM hn_lift(array(2D, 3D)) ORDER BY i, j").collect()] == [4.0, pytest.approx(6 * 2**0.5), 9.0]


def test_measures(spark):
    found = spark.createDataFrame([(0, 1, 1.0), (0, 2, 2.0)], "qid long, id long, margin double")
    truth = spark.createDataFrame([(0, 1, 1.0), (0, 3, 1.0), (1, 4, 1.0)], "qid long, id long, margin double")
    assert {r.qid: (r.recall, r.returned) for r in metrics.recall(found, truth, 10).collect()} == {0: (0.5, 2), 1: (0.0, 0)}
    assert metrics.margin_ratio(found, truth).first().ratio == 1.5
    runs = spark.createDataFrame([("a", 0.5, 1.0), ("a", 0.9, 3.0), ("b", 0.95, 2.0)], "method string, recall double, seconds double")
    assert {r.recall: r.seconds for r in metrics.pareto(runs).collect()} == {0.5: 1.0, 0.9: 2.0, 0.95: 2.0}
    assert {r.method: r.seconds for r in metrics.at_recall(runs, 0.8).collect()} == {"a": 3.0, "b": 2.0}
    assert metrics.timed(lambda: None, 2) >= 0


def test_appends_keep_searches_exact_and_are_compacted(spark):
    """Arrivals all on one side of a shard, so that counts and means come apart; repeated arrivals are points each."""
    random = np.random.default_rng(12)
    P = np.concatenate([random.standard_normal((300, 3)), random.standard_normal((400, 3)) * 0.2 + [4, 4, 4]])
    points, planes = points_of(spark, P), planes_of(spark, unit(np.column_stack([random.standard_normal((15, 3)), random.uniform(-7, 7, 15)])))
    truth = rows(brute.topk(points, planes, 5))
    for shards in (1, 3):
        grown = flows.append(build.hybrid(points.filter("id < 300"), 20, shards=shards), points.filter("id >= 300"))
        assert rows(search.shard_dfs(grown, planes, 5)) == truth and rows(search.frontier(grown, planes, 5)) == truth
        assert grown.nodes.filter("is_leaf").agg(F.max("n")).first()[0] > 40
        new = flows.compacted(grown)
        assert new.nodes.filter("is_leaf").agg(F.max("n")).first()[0] <= 40 and new.points.count() == 700
        assert rows(search.shard_dfs(new, planes, 5)) == truth and all(r.n == 0 for r in index.check_partition(new).collect())
    twice = points.filter("id = 300").unionByName(points.filter("id = 300"))
    assert flows.append(build.hybrid(points.filter("id < 300"), 20), twice).points.count() == 302


def test_walks_shuffle_nothing_and_skip_unreached_shards(spark):
    """Packed trees are read in place, folders of shards out of reach are not read, and their roots' products are counted."""
    random = np.random.default_rng(13)
    P = np.concatenate([random.standard_normal((100, 2)) * 0.1 + [10 * c, 0] for c in range(6)])
    points, planes = points_of(spark, P), planes_of(spark, [[1.0, 0.0, 0.0], [1.0, 0.0, -50.0]])
    built = build.hybrid(points, 10, shards=6)
    qids, Q = np.array([0, 1]), np.array([[1.0, 0.0, 0.0], [1.0, 0.0, -50.0]])
    plan = search.walked(built, qids, Q, search.Options(3))._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and "MapInArrow" in plan
    assert len(search.reachable_parts(built, Q, np.linalg.norm(Q, axis=1), np.array([1.0, 1.0]))) < 6
    cost = {r.qid: r for r in search.counters(search.shard_dfs(built, planes, 3, with_counters=True)).collect()}
    assert all(r.shards_touched == 6 and r.verified < 400 for r in cost.values()), cost
    assert rows(search.shard_dfs(built, planes, 3)) == rows(brute.topk(points, planes, 3))


def test_heap_numbers_are_exact_far_below_the_root(spark):
    deep = [(1 << 56) + 7, (1 << 56) - 1, 1, 2, 3]
    found = spark.createDataFrame([(v,) for v in deep], "node long").select("node", build.above(F.col("node")).alias("up"), build.deep(F.col("node")).alias("deep")).collect()
    assert all(r.up == r.node // 2 and r.deep == r.node.bit_length() - 1 for r in found)


def test_budgets_buy_leaves_in_order(spark, clustered):
    """Counting by bins buys the leaves that sorting all of them would."""
    points, planes = points_of(spark, clustered[0]), planes_of(spark, clustered[1])
    built = build.hybrid(points, 16, shards=3)
    for preference in ("bound", "center"):
        every = search.directory(built, planes).select("qid", "shard", "leaf", "n", *[c.alias(f"k{i}") for i, c in enumerate(map(lambda c: F.col(c) if isinstance(c, str) else c, search.leaf_order(preference)[:-2]))]).collect()
        for budget in (0.01, 0.2, 0.55, 1.0):
            want = set()
            for q in {r.qid for r in every}:
                held = 0
                for r in sorted((r for r in every if r.qid == q), key=lambda r: (*r[4:], r.shard, r.leaf)):
                    if held < np.ceil(400 * budget):
                        want.add((q, r.shard, r.leaf))
                    held += r.n
            for bins, few in ((4, 0), (1024, 0), (1024, 100)):
                found = search.budget_leaves(built, planes, budget, preference, bins, few).collect()
                assert {(r.qid, r.shard, r.leaf) for r in found} == want and len(found) == len(want)
