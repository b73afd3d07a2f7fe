"""Headline queries, timed: prints one JSON line. BENCH_SF_DIR and BENCH_CPUS choose data and cores."""

from __future__ import annotations

import json
import os
import sys
import time

from pyspark.sql import SparkSession

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

from hypernear.operators import brute, build, search  # noqa: E402
from hypernear.operators.baselines import hashing  # noqa: E402
from hypernear.operators.metrics import drain, recall  # noqa: E402
from hypernear.plans.registry import planes_for, points_of  # noqa: E402
from hypernear.sources.storage import persisted  # noqa: E402

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")


def main() -> None:
    builder = SparkSession.builder.master(f"local[{CPUS}]").config("spark.sql.shuffle.partitions", CPUS).config("spark.driver.memory", "8g")
    spark = builder.config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    seconds: dict[str, float] = {}
    facts: dict[str, float] = {}

    def timed(name, action):
        begun = time.perf_counter()
        out = action()
        seconds[name] = round(time.perf_counter() - begun, 3)
        return out

    drain(spark.range(1000).selectExpr("sum(id)"))  # start the engine
    for name, leaf, n in (("emb_cluster", 100, 100), ("li4", 1000, 100)):
        points = persisted(points_of(spark, SF_DIR, name).select("id", "x"), "bench")
        planes = persisted(planes_for(spark, SF_DIR, name, n), "bench")
        index = timed(f"{name}_build", lambda: build.hybrid(points, leaf, shards=1 if name == "emb_cluster" else 8))
        truth = persisted(brute.topk_arrow(points, planes), "bench")
        if name == "emb_cluster":  # the expression form sorts all pairs of a task; at scale the Arrow form is the one to use
            timed(f"{name}_brute_expr", lambda: drain(brute.topk(points, planes, 10, 65)))
        timed(f"{name}_brute_arrow", lambda: drain(brute.topk_arrow(points, planes)))
        timed(f"{name}_plain_dfs", lambda: drain(search.shard_dfs(index, planes, ball=False, cone=False, derive_sibling=False)))
        timed(f"{name}_annotated_dfs", lambda: drain(search.shard_dfs(index, planes)))
        timed(f"{name}_one_shot", lambda: drain(search.frontier(index, planes, one_shot=True)))
        found = timed(f"{name}_budget_5pct", lambda: persisted(search.budgeted(index, planes, budget=0.05), "bench"))
        facts[f"{name}_budget_5pct_recall"] = round(recall(found, truth, 10).agg({"recall": "avg"}).first()[0], 4)
        cost = search.counters(search.shard_dfs(index, planes, with_counters=True)).agg({"verified": "avg", "center_products": "avg"}).first()
        facts[f"{name}_verified_share"] = round(cost["avg(verified)"] / max(points.count(), 1), 4)
    points = persisted(points_of(spark, SF_DIR, "emb_cluster").select("id", "x"), "bench")
    planes = persisted(planes_for(spark, SF_DIR, "emb_cluster", 100), "bench")
    truth = persisted(brute.topk_arrow(points, planes), "bench")
    near = timed("near_hash_build", lambda: hashing.near_build(points, m=128, lam=4 * 65))
    far = timed("far_hash_build", lambda: hashing.far_build(points, m=128, lam=4 * 65))
    for name, make in (("near_hash_search", lambda: hashing.near_search(near, planes, budget=0.5)), ("far_hash_search", lambda: hashing.far_search(far, planes, separation=4, budget=0.5))):
        found = timed(name, lambda make=make: persisted(make(), "bench"))
        facts[f"{name}_recall"] = round(recall(found, truth, 10).agg({"recall": "avg"}).first()[0], 4)
    print(json.dumps({"metric": "headline queries, total", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "facts": facts, "sf": os.path.basename(SF_DIR.rstrip("/")).removeprefix("sf")}))


if __name__ == "__main__":
    main()
