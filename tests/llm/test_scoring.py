"""Toxicity, urls and the small models behind them."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from hypernear.llm import toxicity, url_filter
from hypernear.llm.boosting import BoostedTrees, Isotonic


def test_trees_learn_and_isotonic_is_monotone():
    random = np.random.default_rng(0)
    X = random.uniform(-1, 1, (2000, 3))
    y = ((X[:, 0] > 0) ^ (X[:, 1] > 0.3)).astype(float)
    model = BoostedTrees(depth=3).fit(X[:1500], y[:1500])
    assert ((model.predict(X[1500:]) > 0.5) == y[1500:]).mean() > 0.95
    score = random.uniform(0, 1, 500)
    truth = (random.uniform(0, 1, 500) < score**2).astype(float)
    fitted = Isotonic().fit(score, truth).predict(np.linspace(0, 1, 50))
    assert (np.diff(fitted) >= 0).all() and abs(fitted[25] - 0.25) < 0.12
    assert BoostedTrees().fit(np.zeros((0, 2)), np.zeros(0)).predict(np.zeros((1, 2)))[0] == pytest.approx(0.5)
    assert BoostedTrees().fit(np.zeros((9, 2)), np.zeros(9)).predict(np.zeros((1, 2)))[0] < 0.1


def test_held_out_accuracy(spark):
    """On the tables of the next scale: no clean document is rejected, most toxic ones are."""
    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.01/{t}.parquet") for t in ("documents", "labels"))
    scored = toxicity.score(docs, toxicity.fit(docs, labels.filter(~toxicity.held_out())))
    rows = scored.join(labels, "doc_id").filter(toxicity.held_out()).select("toxic", "score").collect()
    toxic, clean = [r.score >= 0.7 for r in rows if r.toxic], [r.score >= 0.7 for r in rows if not r.toxic]
    assert np.mean(toxic) > 0.6 and np.mean(clean) < 0.02


def test_toxicity_edge_cases(spark, documents, no_documents):
    labels = spark.createDataFrame([(1, 1), (1, 0), (None, 1), (3, None), (9, 0), (77, 1)], "doc_id long, toxic int")
    scored = toxicity.score(documents, toxicity.fit(documents, labels))
    assert scored.count() == 12 and set(scored.columns) == set(documents.columns)
    assert all(0 <= r.score <= 1 for r in scored.collect())
    none = toxicity.fit(documents, labels.limit(0))
    assert {round(r.score, 6) for r in toxicity.score(documents, none).collect()} == {0.5}
    assert toxicity.score(no_documents, none).count() == 0
    assert toxicity.score(documents, toxicity.fit(no_documents, labels)).count() == 12


def test_features_see_masked_words():
    rows = toxicity.featurise(["you are an i.d.i.o.t and st*pid", "s t u p i d", "HEY!! soooooo", None, ""], {"stupid": 1.0}, {})
    assert rows[0][16] >= 1 and rows[1][16] == 1 and rows[2][18] > 0 and not rows[3][:18].any() and (rows[3] == rows[4]).all()


def test_rules(spark):
    rows = [
        (1, "http://X.ORG", "x.org", "", None), (2, "https://a.example.org/en/12?x", "a.example.org", "/en/12", "example.org/en/1"), (3, "http://example.org/es/", "example.org", "/es/", "example.org/es/"),
        (4, "http://b.org/es/", "b.org", "/es/", "org/"), (5, "http://badexample.org/es/x", "badexample.org", "/es/x", "org/"), (6, "http://c.com/fr/1#t", "c.com", "/fr/1", "com/fr/"), (7, "http://c.com/de/", "c.com", "/de/", "com/de/"),
        (8, None, "", "", None), (9, "no scheme.org/x", "", "", None), (10, "a://b://c/d", "b:", "//c/d", None), (11, "http://É.org/?q=/", "É.org", "/", "org/"), (12, "", "", "", None), (12, "", "", "", None),
    ]
    pages = spark.createDataFrame([r[:2] for r in rows], "page_id long, url string").withColumn("host", F.lit("clash"))
    found = url_filter.judge(pages, url_filter.fit(url_filter.seeded(pages))).collect()
    assert sorted((r.page_id, r.host, r.path, r.rule or "") for r in found) == sorted((r[0], r[2], r[3], r[4] or "") for r in rows)
    verdicts = dict(url_filter.RULES)
    assert all(r.verdict in ("allow", "block") and (r.rule is None or r.verdict == verdicts[r.rule]) for r in found)
    none = pages.limit(0)
    assert url_filter.judge(none, url_filter.fit(url_filter.seeded(none))).count() == 0


def test_all_suffixes_have_statistics(spark):
    """Rare suffixes too, in a table of more than 2,000 of them."""
    pages = spark.range(3000).selectExpr("concat('www.', if(id % 3 = 0, 'spam.', ''), 'name', id, '.net') AS host", "int(id % 3 = 0) AS y")
    pages = pages.unionByName(spark.range(50).selectExpr("'often.com' AS host", "0 AS y"))
    statistics = url_filter.suffix_statistics(pages)
    found = {r.host: (round(np.expm1(r.often_one)), r.share_one, round(np.expm1(r.often_two)), r.share_two) for r in url_filter.host_statistics(pages, statistics).collect()}
    assert len(found) == 3001 and found["often.com"] == (50, 1 / 52, 50, 1 / 52)
    assert all(found[f"www.{'' if i % 3 else 'spam.'}name{i}.net"] == (3000, 1001 / 3002, 1, 1 / 3 if i % 3 else 2 / 3) for i in range(3000))
    new = spark.createDataFrame([("a.b.new",)], "host string")
    assert tuple(url_filter.host_statistics(new, statistics).first())[1:] == (0.0, 0.5, 0.0, 0.5)


def test_held_out_hosts(spark):
    """Labelled urls whose label shows in their looks alone: hosts that the model has not met are judged right."""
    random, rows = np.random.default_rng(8), []
    letters = lambda n: "".join(random.choice(list("abcdeilnorstu"), n))
    for i in range(400):
        bad = i % 4 == 0
        host = "-".join(letters(4) + str(random.integers(10, 999)) for _ in range(3)) + random.choice([".top", ".com"]) if bad else f"www.{letters(random.integers(5, 12))}" + random.choice([".com", ".net"])
        for k in range(5):
            rows.append((f"http://{host}/" + (f"p?id={random.integers(10**6)}&s={k}&r={letters(6)}" if bad and k % 2 else f"{letters(5)}/{k}"), int(bad), i))
    urls = spark.createDataFrame(rows, "url string, y int, i int")
    model = url_filter.fit(urls.filter("i % 3 <> 0").unionByName(spark.createDataFrame([(None, 1, 0), ("http://x.com/", None, 0)], urls.schema)))
    held = urls.filter("i % 3 = 0").selectExpr("monotonically_increasing_id() AS page_id", "url", "y")
    held = spark.createDataFrame(held.collect(), held.schema)
    found = url_filter.judge(held, model, rules=()).join(held, "page_id").collect()
    assert np.mean([(r.verdict == "block") == bool(r.y) for r in found]) > 0.95


def test_unwanted_hosts_are_blocked(spark):
    """The trees see no words, and still tell unwanted hosts apart."""
    pages = spark.read.parquet("/root/testdata/sf0.1/pages.parquet")
    found = url_filter.judge(pages, url_filter.fit(url_filter.seeded(pages))).filter("rule is null").select("host", "verdict").collect()
    seeds = set(url_filter.SEEDS.split())
    right = [(r.verdict == "block") == bool(seeds & set(r.host.replace(".", "-").split("-"))) for r in found]
    assert np.mean(right) > 0.99
