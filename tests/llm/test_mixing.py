from collections import defaultdict

from pyspark.sql import functions as F

from hypernear.llm import mixing


def fill(sizes, weights, total):
    """Targets by resharing the excess until none is above its cap."""
    caps, done = {s: 2.0 * n for s, n in sizes.items()}, {}
    while True:
        left, free = total - sum(done.values()), [s for s in sizes if s not in done]
        share = {s: left * weights[s] / sum(weights[f] for f in free) for s in free}
        over = [s for s in free if share[s] > caps[s]]
        if not over:
            return done | share
        done |= {s: caps[s] for s in over}


def test_targets_follow_the_weights(spark):
    sizes = {"b": 1000, "a": 100, "c": 400, "é": 50, "Z": 10_000, None: 70}
    order = sorted((s for s in sizes if s is not None), key=lambda s: s.encode()) + [None]
    want = fill(sizes, {s: (5, 2, 1)[k % 3] for k, s in enumerate(order)}, 1.5 * sum(sizes.values()))
    found = {r.source: r.target for r in mixing.targets(spark.createDataFrame(list(sizes.items()), "source string, source_size long")).collect()}
    assert all(abs(found[s] - want[s]) < 1e-6 for s in sizes) and abs(sum(found.values()) - 1.5 * sum(sizes.values())) < 1e-6


def test_edge_cases(documents, no_documents):
    rows = mixing.copies(documents).collect()
    assert len(rows) == 12
    by_source = defaultdict(int)
    for r in rows:
        assert 0 <= r.copies <= 2 and r.size * r.copies <= 2 * r.size
        assert (r.size == 0) <= (r.copies == 0)
        by_source[r.source] += r.size
    assert all(r.source_size == by_source[r.source] for r in rows)
    mixed = mixing.mix(documents)
    assert mixed.columns == documents.columns and mixed.count() == sum(r.copies for r in rows)
    assert mixing.copies(no_documents).count() == 0 and mixing.mix(no_documents).count() == 0


def test_taken_words_come_near_and_reruns_agree(spark):
    docs = spark.range(3000).select(F.col("id").alias("doc_id"), F.expr("repeat('w ', cast(1 + id * 7 % 23 as int))").alias("text"), F.when(F.col("id") % 3 == 0, "hot").otherwise(F.concat(F.lit("s"), F.col("id") % 5)).alias("source"))
    once, again = ({r.doc_id: (r.size, r.source, r.target, r.copies) for r in mixing.copies(docs.repartition(n)).collect()} for n in (3, 7))
    assert once == again
    taken, target = defaultdict(int), {}
    for size, source, goal, copies in once.values():
        taken[source] += size * copies
        target[source] = goal
    assert all(abs(taken[s] - target[s]) <= 23 for s in target)


def test_no_python_in_the_plan(documents):
    plan = mixing.copies(documents)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan and "Cartesian" not in plan


def test_inclusion_odds_differ_by_document(spark):
    """Documents that are likelier in the plan are taken oftener: the share of extra copies of each weight is near its probability."""
    docs = spark.range(40_000).select(F.col("id").alias("doc_id"), F.expr("repeat('w ', case id % 3 when 0 then 2 when 1 then 20 else 120 end)").alias("text"), F.lit("s").alias("source"))
    rates = {weight: rate for weight, rate in mixing.plan_mix(docs, percent=70).first().rates.items()}
    assert len(set(rates.values())) == 3 and rates[2] < rates[5] < rates[7]
    rows = mixing.copies(docs, percent=70).groupBy("size").agg(F.avg("copies").alias("share")).collect()
    assert all(abs(r.share - rates[len(bin(r.size)) - 2]) < 0.02 for r in rows)


def test_equal_rows_are_split_at_the_target(spark):
    """Rows that agree in id and text, and null ids: no more and no fewer than the target asks for."""
    rows = [(7, "one two three four", "a", k) for k in range(50)] + [(None, "null id text here", "a", 0)] * 40 + [(None, f"other text {k}", "b", k) for k in range(40)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string, extra long")
    found = mixing.copies(docs, percent=60).collect()
    for source in "ab":
        mine = [r for r in found if r.source == source]
        assert abs(sum(r.size * r.copies for r in mine) - mine[0].target) <= 4 and len(mine) == sum(r[2] == source for r in rows)
    assert len({r.copies for r in found if r.doc_id is None and r.source == "b"}) > 1


def test_many_sources(spark):
    """Targets of thousands of sources, numbered by ranges."""
    sizes = {f"host{i * 7919 % 5000:05d}": 1 + i * i % 977 for i in range(5000)}
    want = fill(sizes, {s: (5, 2, 1)[k % 3] for k, s in enumerate(sorted(sizes))}, 1.5 * sum(sizes.values()))
    found = {r.source: r.target for r in mixing.targets(spark.createDataFrame(list(sizes.items()), "source string, source_size long").repartition(7)).collect()}
    assert all(abs(found[s] - want[s]) < 1e-6 for s in sizes)
