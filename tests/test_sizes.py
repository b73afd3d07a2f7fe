"""What must hold as tables grow: shards bounded in bytes, plans bounded by the levels, walks and scores shared by budgets."""

import inspect

import numpy as np
import pytest
from pyspark.sql import functions as F

from hypernear.operators import brute, build, index, metrics, search
from hypernear.operators.baselines import hashing
from hypernear.operators.grow import Met, Options, grow, grow_all, walk, walks
from hypernear.plans import experiments
from hypernear.sources import tables
from hypernear.streaming import flows
from test_engine import planes_of, points_of, rows, unit


@pytest.fixture(scope="module")
def some():
    random = np.random.default_rng(21)
    P = random.standard_normal((600, 3))
    return P, unit(np.column_stack([random.standard_normal((16, 3)), random.uniform(-2, 2, 16)]))


def test_a_number_of_shards_is_no_upper_bound(spark, some):
    """Shards are held to shard_bytes, however few were asked for, and nothing is left out."""
    points, planes = points_of(spark, some[0]), planes_of(spark, some[1])
    for asked in (1, 2):
        built = build.hybrid(points, 10, shards=asked, shard_bytes=100 * 8 * 8)
        assert built.packed().agg(F.max("n")).first()[0] <= 200 and built.packed().count() >= 6
        assert all(r.n == 0 for r in index.check_partition(built).collect())
        assert rows(search.shard_dfs(built, planes, 5)) == rows(brute.topk(points, planes, 5))


def test_points_are_written_only_when_asked_for(spark, some):
    built = build.hybrid(points_of(spark, some[0]), 10)
    search.shard_dfs(built, planes_of(spark, some[1]), 5).collect()
    assert built.placed is None and built.points.count() == 600


def test_levels_are_not_planned_twice(spark):
    """A plan that held each level twice would read the leaves 2 ** depth times."""
    leaves = spark.createDataFrame([((1 << n) + 1, 1, [float(n)]) for n in range(1, 12)] + [(1 << 11, 1, [0.0])], "node long, n long, center array<double>")
    known = build.roll_up_centers(leaves)
    assert {r.node: r.n for r in known.collect()}[1] == 12
    assert known._jdf.queryExecution().optimizedPlan().toString().count("\n") < 100


def test_one_walk_serves_all_quotas(some):
    P, Q = some
    X, ids = np.column_stack([P, np.ones(len(P))]), np.arange(len(P))
    tree = grow(ids, X, 25, 7)
    quotas = [40, 0, None, 3, 1, 600, 40, 333]
    for flags in ({}, dict(ball=False, cone=False, derive_sibling=False), dict(preference="bound")):
        for q in Q:
            args = tree, q, float(np.linalg.norm(q)), Options(5, **flags), np.inf
            assert walks(*args, quotas) == [walk(*args, quota) for quota in quotas]


def test_slices_of_planes_give_one_answer(spark, some):
    """One shard, so planes are dealt to several tasks; copies of a plane have budgets of their own."""
    points, planes = points_of(spark, some[0]), planes_of(spark, np.concatenate([some[1]] * 3))
    built = build.hybrid(points, 10)
    shares = {q: (0.05, 0.3, 1.0)[q // 16] for q in range(48)}
    found = search.shard_dfs(built, planes, 5, budget=shares, seeds=0, with_counters=True)
    assert found._jdf.queryExecution().executedPlan().toString().count("MapInArrow") > 1
    together = search.counters(found).select("qid", "verified", "nodes_visited").collect()
    alone = [search.counters(search.shard_dfs(built, planes.filter(F.col("qid").between(16 * n, 16 * n + 15)), 5, budget=share, seeds=0, with_counters=True)).select("qid", "verified", "nodes_visited").collect() for n, share in enumerate((0.05, 0.3, 1.0))]
    assert sorted(together) == sorted(r for part in alone for r in part) and len(together) == 48
    assert rows(search.shard_dfs(built, planes, 5)) == rows(brute.topk(points, planes, 5))


def test_percentiles_are_sparks(spark):
    """Exact with ties, few bins and few rows a list, against F.percentile."""
    random = np.random.default_rng(3)
    values = [float(v) for v in np.concatenate([np.round(random.standard_normal(700), 2), np.zeros(200), random.exponential(size=300) * 1e6])]
    df = spark.createDataFrame([(v,) for v in values] + [(None,)], "v double")
    shares = (0.0, 0.08, 0.1, 0.5, 0.9, 0.999, 1.0)
    want = list(df.agg(*[F.percentile("v", p) for p in shares]).first())
    for bins, few in ((4096, 50_000), (3, 5), (2, 0)):
        assert metrics.percentiles(df, "v", shares, bins, few) == want
    assert metrics.percentiles(df.filter("v is null"), "v", (0.5,)) == [None]
    assert metrics.percentiles(df.filter("v = 0"), "v", (0.1, 0.5)) == [0.0, 0.0]


def test_term_shares_are_counted_in_place(spark):
    texts = spark.createDataFrame([(1, "a b a"), (2, None), (3, "7 !"), (4, "B c " * 40)], "id long, t string")
    made = tables.term_frequencies(texts, "id", "t", 16)
    found = {r.id: r.x for r in made.collect()}
    assert sorted(found) == [1, 2, 3, 4] and all(len(x) == 17 and x[16] == 1.0 for x in found.values())
    assert found[2] == found[3] == [0.0] * 16 + [1.0] and sum(found[1]) == 2 and max(found[1][:16]) == 2 / 3
    assert "Exchange" not in made._jdf.queryExecution().executedPlan().toString()


def test_arrivals_meet_no_leaf_as_rows(spark, some):
    """An append writes each arrival a few times, whatever the number of leaves and levels."""
    points = points_of(spark, some[0])
    built = build.hybrid(points.filter("id < 300"), 2, shards=2)
    grown, before = flows.append(built, points.filter("id >= 300")), built.nodes.count()
    assert grown.nodes.count() == before and grown.points.count() == 600
    assert rows(search.shard_dfs(grown, planes_of(spark, some[1]), 5)) == rows(brute.topk(points, planes_of(spark, some[1]), 5))
    arrived = points.filter("id >= 300").select(F.col("id").alias("row"), "id", "x")
    placed = flows.nearest_leaf(built, flows.nearest_shard(built, arrived))
    assert placed.count() == 300 and "NestedLoop" not in placed._jdf.queryExecution().executedPlan().toString()


def test_a_pareto_window_sees_a_row_a_recall(spark):
    runs = spark.range(1000).select((F.col("id") % 5 / 4).alias("recall"), (F.col("id") % 7 + F.col("id") % 5).cast("double").alias("seconds"))
    assert {r.recall: r.seconds for r in metrics.pareto(runs).collect()} == {0.0: 0.0, 0.25: 1.0, 0.5: 2.0, 0.75: 3.0, 1.0: 4.0}
    assert "HashAggregate" in metrics.pareto(runs)._jdf.queryExecution().executedPlan().toString().split("Window")[-1]


def test_wide_products_are_left_folds():
    """Bit for bit what adding component by component gives, without a step of Python a component."""
    random = np.random.default_rng(9)
    X, q = random.standard_normal((50, 1025)) * 10.0 ** random.integers(-8, 8, (50, 1025)), random.standard_normal(1025)
    total = X[:, 0] * q[0]
    for j in range(1, 1025):
        total = total + X[:, j] * q[j]
    assert brute.folded(X, q).tolist() == total.tolist()
    assert inspect.signature(build.hybrid).parameters["shard_bytes"].default <= 8 << 20


def test_leaf_sizes_share_one_growth(spark, some, monkeypatch):
    """Trees of several leaf sizes are those that each size grows alone, from points that are dealt once; no points give no trees."""
    P, Q = some
    P = np.concatenate([P, np.ones((40, 3))])
    X, ids = np.column_stack([P, np.ones(len(P))]), np.arange(len(P))[::-1].copy()
    sizes = [50, 5, 90, 20]
    for size, tree in zip(sizes, grow_all(ids, X, sizes, 7)):
        alone = grow(ids, X, size, 7)
        assert all(getattr(tree, name) == getattr(alone, name) for name in ("node", "parent", "left", "right", "depth", "lo", "hi", "flat", "weight"))
        assert all(np.array_equal(getattr(tree, name), getattr(alone, name)) for name in ("centers", "norms", "radii", "ids", "X", "r_x", "x_par", "x_perp"))
    points, planes = points_of(spark, some[0]), planes_of(spark, Q)
    dealt, route = [], build.route
    monkeypatch.setattr(build, "route", lambda *args: dealt.append(1) or route(*args))
    built = build.hybrids(points, sizes, shard_bytes=100 * 8 * 8)
    assert len(dealt) == 1
    alone = build.hybrid(points, 5, shard_bytes=100 * 8 * 8)
    assert [one.leaf_size for one in built] == sizes and sorted(map(str, built[1].nodes.collect())) == sorted(map(str, alone.nodes.collect()))
    for one in built:
        assert rows(search.shard_dfs(one, planes, 5)) == rows(brute.topk(points, planes, 5))
        assert all(r.n == 0 for r in index.check_partition(one).collect())
    assert build.hybrids(points.limit(0), sizes)[0].nodes.count() == 0


def test_a_leaf_is_verified_in_place():
    """Points of a leaf that no bound rules out are read as one slice, and single numbers as Python's: a step costs microseconds."""
    random = np.random.default_rng(4)
    X = np.column_stack([random.standard_normal((20_000, 4)), np.ones(20_000)])
    tree, q = grow(np.arange(20_000), X, 20, 3).ready(), random.standard_normal(5)
    assert all(isinstance(part, list) for part in (*tree.plain, tree.closer))
    found, cost = walk(tree, q, float(np.linalg.norm(q)), Options(10, ball=False, cone=False))
    margins = np.abs(brute.folded(X, q))
    assert [i for _, i in found] == np.lexsort((np.arange(20_000), margins))[:10].tolist() and cost["verified"] == cost["points_seen"]


def test_scores_take_all_rows_at_once():
    """Scores are those of sorting each point's own gaps, and of comparing its own keys, bit for bit at the edges of scores; a block is not scored row by row."""
    random = np.random.default_rng(8)
    for m, separation in ((8, 1), (33, 4), (128, 6), (3, 5)):
        s = {"m": m, "bins": 512, "parts": 48, "ratio": 0.9, "most": 2.0}
        part = random.integers(0, 48, 3000).astype(np.int32)
        keys = random.standard_normal((3000, m)) * 3 * 0.9 ** part[:, None]
        look = np.append(random.standard_normal(m), 1.0)
        edge = 5.0 * (2.0 * 0.9 ** part[:600].astype(float) + 1.0) * (np.arange(600) % 512) / 512
        keys[:600] = look[:-1] + edge[:, None]  # gaps at the edges of scores, within rounding
        gap, nth = np.abs(keys - look[:-1]), min(separation, m)
        far = np.sort(gap, axis=1)[:, m - nth]
        want = np.minimum(far / (5.0 * (2.0 * 0.9 ** part.astype(float) + 1.0)) * 512, 512).astype(np.int64)
        score = hashing.Seen(separation)
        assert np.array_equal(score(score.view(keys, part, s), look, s), want)
        for wide in (1, 100, 10_000, 10**6):
            whole = random.integers(-3, 3, (3000, m)).astype(np.int32) * wide
            key = whole[7].copy()
            key[0] = 2**31 - 1
            view = hashing.collisions.view(whole, part, s)
            assert view.shape == (m, 3000) and np.array_equal(hashing.collisions(view, key, s), (whole == key).sum(axis=1))


def test_budgets_of_a_plane_are_verified_together(spark, some):
    """Stored keys or not, each budget gives what it gives alone, and a block's products are made once for all budgets of a plane."""
    points, planes = points_of(spark, some[0]), planes_of(spark, np.concatenate([some[1]] * 3))
    shares = {q: (0.05, 0.3, 1.0)[q // 16] for q in range(48)}
    for search_by, make in ((hashing.near_search, hashing.near_build), (lambda *a, **b: hashing.far_search(*a, separation=2, **b), hashing.far_build)):
        found = [rows(search_by(make(points, 8, 4, stored=stored), planes, 5, budget=shares)) for stored in (True, False)]
        assert found[0] == found[1]
        alone = [r for n, share in enumerate((0.05, 0.3, 1.0)) for r in rows(search_by(make(points, 8, 4), planes.filter(F.col("qid").between(16 * n, 16 * n + 15)), 5, budget=share))]
        assert sorted(alone) == sorted(found[0])
        assert [r for r in found[0] if r[0] >= 32] == [r for r in rows(brute.topk(points, planes, 5)) if r[0] >= 32]
    unstored = hashing.near_build(points, 8, 4, stored=False)
    assert unstored.read("id", "x", "part", "keys").columns == ["id", "x"]  # keys are made where they are used


def test_points_of_an_experiment_are_spread(spark, sf_dir, monkeypatch):
    """One file of one row group is not one task's work."""
    spread = lambda df: "Exchange" in df._jdf.queryExecution().executedPlan().toString().replace("BroadcastExchange", "")
    assert spread(tables.li4(spark, sf_dir, 2)) and not spread(tables.li4(spark, sf_dir))
    kept, written = [], experiments.persisted
    monkeypatch.setattr(experiments, "persisted", lambda df, label: kept.append(df) or written(df, label))
    assert experiments.bench_of(spark, sf_dir, "li4", 2).points.count() == tables.li4(spark, sf_dir).count() and spread(kept[0])


def test_walks_with_several_options_share_products(spark, some):
    """Answers and counters are those of walks on their own, and a tree is read once for all options."""
    P, Q = some
    X, ids = np.column_stack([np.concatenate([P, np.ones((40, 3))]), np.ones(len(P) + 40)]), np.arange(len(P) + 40)
    options = [Options(k, preference=p, **flags) for k in (1, 10) for p in ("center", "bound") for flags in (*experiments.VARIANTS.values(), experiments.METHODS["plain"])]
    for tree in (grow(ids, X, 25, 7), grow(ids, np.concatenate([X[:, :3] * 0 + 1, X[:, 3:]], axis=1), 25, 7)):
        for q in Q:
            length, quotas = float(np.linalg.norm(q)), [3, 40, 333, None]
            met = Met(tree, q, length)
            for one in options:
                assert walks(tree, q, length, one, np.inf, quotas, met) == walks(tree, q, length, one, np.inf, quotas)
    points, planes = points_of(spark, P), planes_of(spark, Q)
    built = build.hybrid(points, 10, shard_bytes=100 * 8 * 8)
    found = search.shard_walks(built, planes, options, {q: 0.3 for q in range(16)})
    for at in (0, 4, 13):
        flags = {name: getattr(options[at], name) for name in ("k", "ball", "cone", "derive_sibling", "preference")}
        alone = search.shard_dfs(built, planes, budget=0.3, seeds=0, with_counters=True, **flags)
        assert sorted(map(str, found.filter(F.col("variant") == at).drop("variant").collect())) == sorted(map(str, alone.collect()))


def test_an_experiment_walks_once(spark, some, monkeypatch):
    """All settings of the trees are one job a run, whatever their number, with the recalls of each on its own."""
    bench = experiments.Bench(spark, "some", points_of(spark, some[0]), planes_of(spark, some[1]), 1, clock=False)
    built, written, kept = build.hybrids(bench.points, [10, 50]), experiments.persisted, []
    monkeypatch.setattr(experiments, "persisted", lambda df, label: kept.append(label) or written(df, label))
    bench.trees([w for one in built for k in (1, 5) for w in experiments.walks_of(one, k, setting=str(one.leaf_size))], (0.1, 1.0))
    assert kept.count("experiment-found") == 1 and len(bench.rows) == 16
    for name, method, setting, k, budget, recall, seconds, *_ in bench.rows:
        truth = {(r.qid, r.id) for r in brute.topk(bench.points, bench.planes, k).collect()}
        one = search.shard_dfs(built[setting == "50"], bench.planes, k, budget=budget, seeds=0, **experiments.METHODS[method])
        assert seconds is None and recall == pytest.approx(len(truth & {(r.qid, r.id) for r in one.collect()}) / len(truth)) and (budget < 1 or recall == 1)


def test_separations_share_one_scoring(spark, some):
    """Scores of several separations are those of each alone, and all hash searches of an experiment give what each gives."""
    random = np.random.default_rng(8)
    s = {"m": 33, "bins": 512, "parts": 48, "ratio": 0.9, "most": 2.0}
    part, keys, look = random.integers(0, 48, 500).astype(np.int32), random.standard_normal((500, 33)), np.append(random.standard_normal(33), 1.0)
    three = hashing.Seen(2, 40, 4)
    view = three.view(keys, part, s)
    assert all(np.array_equal(level, one(view, look, s)) for level, one in zip(three.all(view, look, s), three.alone())) and three.kinds == 3
    assert hashing.charges(three, view, np.array([look]), s).shape == (3,)
    points, planes = points_of(spark, some[0]), planes_of(spark, some[1])
    known = hashing.measures(points, [4, 8])
    assert known[:2] == (4, 600)
    near, far = (make(points, 8, 4, stored=False, known=known) for make in (hashing.near_build, hashing.far_build))
    found = hashing.searched([(near, hashing.near_look, hashing.collisions), (far, hashing.far_look, hashing.Seen(2, 4))], planes, 5, 0.2)
    alone = [hashing.near_search(hashing.near_build(points, 8, 4), planes, 5, 0.2), *(hashing.far_search(hashing.far_build(points, 8, 4), planes, 5, n, 0.2) for n in (2, 4))]
    for variant, one in enumerate(alone):
        some_rows = found.filter(F.col("variant") == variant)
        assert rows(brute.ranked(some_rows.filter("id is not null"), 5)) == rows(one)
        assert some_rows.filter("id is null").agg(F.min("qid"), F.count_distinct("qid"), F.sum("look_ns") > 0).first() == (0, 16, True)


def test_a_query_about_trees_runs_no_hashes(spark, sf_dir, monkeypatch):
    def refused(*args):
        raise AssertionError("hashes were searched")

    monkeypatch.setattr(hashing, "searched", refused)
    experiments._runs.cache_clear()
    assert experiments.trend_budget(spark, sf_dir).first().n == 0
    runs = experiments.runs_of(spark, sf_dir, "tree_recall")
    assert runs.count() == 2 * len(experiments.SMALL_LEAVES) * len(experiments.BUDGETS) and {r.method for r in runs.collect()} == set(experiments.METHODS)


def test_cuts_are_tested_without_whole_scores(spark):
    """Gaps of 16 bits, and of 24 for planes out of their reach, give the scores of 53; a cut lets through all points that reach it, and few others."""
    random = np.random.default_rng(5)
    s = {"m": 32, "bins": 512, "parts": 48, "ratio": 0.9, "most": 2.0}
    part = random.integers(0, 20, 4000).astype(np.int32)
    keys = random.standard_normal((4000, 32)) * 2 * 0.9 ** part[:, None]
    seen = hashing.Seen(4, 2)
    for far, reach in ((1.0, {}), (1.0, {"furthest": 300.0}), (100.0, {})):
        look = np.append(random.standard_normal(32) * far, 1.5)
        edge = 5.0 * (2.0 * 0.9 ** part[:600].astype(float) + 1.5) * (np.arange(600) % 200) / 512
        keys[:600] = look[:-1] + edge[:, None]
        view = seen.view(keys, part, s | reach)
        longest = 5.0 * (2.0 * 0.9 ** part.astype(float) + 1.5)
        near = seen.nearing(view, look, part, s)
        for kind, (nth, level) in enumerate(zip((4, 2), seen.all(view, look, s))):
            want = np.minimum(np.sort(np.abs(keys - look[:-1]), axis=1)[:, -nth] / longest * 512, 512).astype(np.int64)
            assert np.array_equal(level, want) and np.array_equal(near.levels(kind, np.arange(4000)), want) and np.array_equal(near.levels(kind, np.arange(50)), want[:50])
            cut = np.full(48, int(np.median(want)))
            at = near.reaching(kind, cut, None)
            assert np.isin((want >= cut[0]).nonzero()[0], at).all() and (want[at] >= cut[0] - 4).all()
            assert np.array_equal(near.reached(kind, np.arange(4000), cut[part]).nonzero()[0], at)


def test_hash_searches_read_their_points_once(spark, some):
    """Searches that make keys on the spot share a pass, while their counts fit in a task; answers are those of each alone."""
    points, planes = points_of(spark, some[0]), planes_of(spark, some[1])
    known = hashing.measures(points, [4])
    searches = [(hashing.near_build(points, 8, 4, stored=False, known=known), hashing.near_look, hashing.collisions), (hashing.far_build(points, 8, 4, stored=False, known=known), hashing.far_look, hashing.Seen(2))]
    found = hashing.searched(searches, planes, 5, 0.2)
    assert found._jdf.queryExecution().executedPlan().toString().count("MapInArrow") == 1
    assert hashing.passes(searches, 16, 0) == [[0], [1]] and hashing.passes([searches[0], (hashing.near_build(points, 8, 4), *searches[0][1:])], 16) == [[0], [1]]
    for variant, alone in enumerate((hashing.near_search(hashing.near_build(points, 8, 4), planes, 5, 0.2), hashing.far_search(hashing.far_build(points, 8, 4), planes, 5, 2, 0.2))):
        assert rows(brute.ranked(found.filter(F.col("variant") == variant).filter("id is not null"), 5)) == rows(alone)


def test_points_are_dealt_in_blocks(spark, some):
    """A task shuffles a row a shard and block of points, not a row a point, and no point is lost where shards are cut by a hash."""
    X = np.column_stack([some[0], np.ones(600)])
    steps = build.router(X, np.arange(600), 6, 42)
    arrays = np.array([a for a, *_ in steps]), np.array([b for _, b, *_ in steps]), np.array([children for _, _, *children in steps], dtype=np.int64)
    want = []
    for x in X:
        at = 0
        while at >= 0:
            at = steps[at][2 if ((x - steps[at][0]) ** 2).sum() <= ((x - steps[at][1]) ** 2).sum() else 3]
        want.append(-1 - at)
    assert build.routed(X, arrays, 40).tolist() == build.routed(X, arrays).tolist() == want
    points = points_of(spark, some[0]).repartition(3)
    assert build.held_by(points, arrays, 6).tolist() == np.bincount(want, minlength=6).tolist()
    for cuts, most in ((None, 6), (np.array([1, 2, 3, 1, 1, 2]), 10)):
        dealt = build.route(points, arrays, cuts).collect()
        ids = [i for r in dealt for i in np.frombuffer(r.ids, "<i8").tolist()]
        assert sorted(ids) == list(range(600)) and len(dealt) <= 3 * most
        assert all(np.array_equal(np.frombuffer(r.xs, "<f8").reshape(-1, 4), X[np.frombuffer(r.ids, "<i8")]) for r in dealt)
        assert len(build.route(points, arrays, cuts, 1, 80).collect()) > 3 * most


def test_the_largest_experiment_needs_no_clock():
    """Its query returns no seconds, so that walks of both trees share a plane's products."""
    assert inspect.signature(experiments.large).parameters["clock"].default is False
