import random

from pyspark.sql import functions as F

from hypernear.llm import order_minhash as O
from hypernear.llm.alignment import banded_distance
from hypernear.llm.common import words
from hypernear.llm.components import components


def grouped(rows):
    out = {}
    for doc, cls in rows:
        out.setdefault(cls, set()).add(doc)
    return {frozenset(g) for g in out.values()}


def test_edge_cases(documents, no_documents):
    rows = {(r.doc_id, r.class_id) for r in O.near_duplicates(documents).collect()}
    assert {(1, 1), (2, 1), (3, 1), (4, 4), (5, 5), (6, 6), (7, 7), (8, 8), (9, 9), (10, 10), (None, None)} == rows
    kept = O.deduplicated(documents)
    assert kept.columns == documents.columns
    assert sorted(r.doc_id or 0 for r in kept.collect()) == [0, 1, 4, 5, 6, 7, 8, 9, 10]
    assert O.near_duplicates(no_documents).count() == 0 and O.deduplicated(no_documents).count() == 0


def test_classes_equal_brute_force(spark, real):
    docs = real("documents").select("doc_id", "text")
    rows = docs.collect()
    texts = {r.doc_id: words(r.text) for r in rows}
    parent = {d: d for d in texts}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    ids = sorted(texts)
    for n, a in enumerate(ids):
        for b in ids[:n]:
            if texts[a] and texts[b] and banded_distance(texts[a], texts[b], int(0.2 * max(len(texts[a]), len(texts[b])) + 1e-9)) is not None:
                parent[root(a)] = root(b)
    want = grouped((d, root(d)) for d in ids)
    assert grouped((r.doc_id, r.class_id) for r in O.near_duplicates(docs).collect()) == want


def test_a_large_group_and_a_shared_passage(spark):
    """Hundreds of near copies are one class; texts that share a third of their words in one passage stay apart."""
    r = random.Random(4)
    fresh = lambda n: [f"w{r.randrange(10**6)}" for _ in range(n)]
    base, passage = fresh(120), fresh(60)
    rows = []
    for i in range(300):
        copy = list(base)
        for _ in range(4):
            copy[r.randrange(len(copy))] = f"n{r.randrange(10**6)}"
        rows.append((i, " ".join(copy)))
        rows.append((1000 + i, " ".join(fresh(60) + passage + fresh(60))))
    classes = grouped((x.doc_id, x.class_id) for x in O.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect())
    assert frozenset(range(300)) in classes and len(classes) == 301


def test_a_star_of_unlike_variants(spark):
    """Variants of one text that are unlike each other: all links between texts of one bucket are found, as by brute force."""
    r = random.Random(7)
    base = [f"w{i}" for i in range(120)]
    texts = []
    for i in range(400):
        copy = list(base)
        for at in r.sample(range(120), 15):
            copy[at] = f"n{i}x{at}"
        texts.append(copy)
    texts.append(base)
    docs = spark.createDataFrame([(i, " ".join(t)) for i, t in enumerate(texts)], "doc_id long, text string").coalesce(1)
    keys = {x.doc_id: x["keys"] for x in O.sketched(docs, 80, 5, 2, 42).collect()}
    parent = list(range(len(texts)))

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a in range(len(texts)):
        for b in range(a):
            if root(a) != root(b) and any(x == y for x, y in zip(keys[a], keys[b])) and banded_distance(texts[a], texts[b], 24) is not None:
                parent[root(a)] = root(b)
    want = grouped((d, root(d)) for d in range(len(texts)))
    assert max(map(len, want)) > 300
    for options in ({}, {"few": 0, "block": 50}):
        assert grouped((x.doc_id, x.class_id) for x in O.near_duplicates(docs, **options).collect()) == want


def test_scattered_edits_are_found(spark):
    """Pairs whose edits (two substitutions of three, else insertions and deletions) are scattered evenly: the recall stated for each edit similarity."""
    r = random.Random(11)
    rows, n = [], 150
    for level, share in enumerate((0.10, 0.15, 0.18, 0.20)):
        for i in range(n):
            base = [f"w{r.randrange(10**6)}" for _ in range(200)]
            copy = list(base)
            for at in sorted(r.sample(range(200), int(200 * share)), reverse=True):
                kind = r.randrange(6)
                copy[at : at + (kind != 0)] = [] if kind == 1 else [f"n{r.randrange(10**6)}"]
            if banded_distance(base, copy, int(0.2 * max(len(base), len(copy)) + 1e-9)) is not None:
                rows += [(level * 10_000 + 2 * i, " ".join(base)), (level * 10_000 + 2 * i + 1, " ".join(copy))]
    found = {x.doc_id: x.class_id for x in O.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    for level, least in enumerate((0.99, 0.97, 0.93, 0.9)):
        pairs = [d for d in found if d // 10_000 == level and d % 2]
        assert len(pairs) > n / 3 and sum(found[d] == found[d - 1] for d in pairs) >= least * len(pairs), level
    assert all(c in (d, d - 1) for d, c in found.items())


def test_a_large_group_beside_a_few_others(spark, monkeypatch):
    """A bucket with nearly all texts in one group is dealt in rows that grow with its size, not with its square, and stays exact."""
    r = random.Random(5)
    fresh = lambda n: [f"w{r.randrange(10**6)}" for _ in range(n)]
    base, rows, seen = fresh(100), [], []
    for i in range(400):
        copy = list(base)
        copy[r.randrange(100)] = f"n{i}"
        rows.append((i, " ".join(copy)))
    rows += [(1000 + i, " ".join(base[:70] + fresh(30))) for i in range(3)]
    whole = O.dealt
    monkeypatch.setattr(O, "dealt", lambda *args: seen.append(whole(*args)) or seen[-1])
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    found = {x.doc_id: x.class_id for x in O.near_duplicates(docs, block=32).collect()}
    assert {found[i] for i in range(400)} == {0} and all(found[1000 + i] == 1000 + i for i in range(3))
    cells = seen[0].groupBy("key").agg(F.min("j").alias("j"), F.count("*").alias("dealt"), F.count_distinct("node").alias("n")).collect()
    assert any(c.j == -1 for c in cells) and all(c.dealt <= 1.5 * c.n for c in cells if c.n > 300)


def test_order_matters(spark):
    a = [f"w{i}" for i in range(100)]
    rows = [(1, " ".join(a)), (2, " ".join(a[50:] + a[:50]))]
    assert len({r.class_id for r in O.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()}) == 2


def test_components(spark):
    path = [(i, i + 1) for i in range(30)] + [(100, 101), (102, 101), (200, 200)]
    found = {r.node: r.component for r in components(spark.createDataFrame(path, "u long, v long")).collect()}
    assert all(found[i] == 0 for i in range(31)) and {found[i] for i in (100, 101, 102)} == {100}
    spread = components(spark.createDataFrame(path, "u long, v long"), few=0)
    assert {r.node: r.component for r in spread.collect()} == found
    assert components(spark.createDataFrame([], "u long, v long")).agg(F.count("*")).first()[0] == 0
