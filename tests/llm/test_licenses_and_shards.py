import pytest

from hypernear.llm import licenses, shards

FILES = "path string, text string, similarity string"


def test_licences(spark):
    mit, gpl = "Released under the MIT License.", "This work is licensed under the GNU General Public License, version 3."
    rows = [
        ("r/LICENSE", mit, ""), ("r/a/b/x.py", "code", ""), ("r/a/LICENSE.txt", "intro\n" + gpl + "\nmore", ""), ("r/a/c/y.py", "# " + mit + "\ncode", ""), ("r/z.py", None, ""), ("other/q.py", "", ""),
        (None, mit.upper(), ""), ("top.py", "code", ""), ("r/a/b/x.py", "code", ""), ("r/w/copying", "no notice here", ""), ("r/w/v.py", "the licence of the mit building is version 3 of a work", ""),
    ]
    found = licenses.licences(spark.createDataFrame(rows, FILES)).collect()
    got = sorted(((r.path or "", r.own_licence, r.inherited_licence, r.inherited_from, r.licence) for r in found), key=lambda r: tuple(map(str, r)))
    assert got == sorted([
        ("r/LICENSE", "MIT", "MIT", "r", "MIT"), ("r/a/b/x.py", None, "GPL-3.0", "r/a", "GPL-3.0"), ("r/a/LICENSE.txt", "GPL-3.0", "GPL-3.0", "r/a", "GPL-3.0"), ("r/a/c/y.py", "MIT", "GPL-3.0", "r/a", "MIT"), ("r/z.py", None, "MIT", "r", "MIT"), ("other/q.py", None, None, None, None),
        ("", "MIT", None, None, "MIT"), ("top.py", None, None, None, None), ("r/a/b/x.py", None, "GPL-3.0", "r/a", "GPL-3.0"), ("r/w/copying", None, "MIT", "r", "MIT"), ("r/w/v.py", None, "MIT", "r", "MIT"),
    ], key=lambda r: tuple(map(str, r)))
    assert licenses.licences(spark.createDataFrame([], FILES)).count() == 0


def test_wrapped_notices(spark):
    """Notices as they stand in files: wrapped, behind comment signs, followed by more of the sentence."""
    gpl = ["This program is free software: you can redistribute it and/or modify", "it under the terms of the GNU General Public License as published by", "the Free Software Foundation, either version 3 of the License, or", "(at your option) any later version."]
    bsd = ["Redistribution and use in source and binary forms, with or without", "modification, are permitted provided that the following conditions", "are met:", "1. Redistributions of source code must retain the above copyright"]
    mit = ["Permission is hereby granted, free of charge, to any person obtaining a", 'copy of this software and associated documentation files (the "Software"),', "to deal in the Software without restriction, including without limitation"]
    rows = [(f"{name}{k}/LICENSE", "Copyright 2020 A. Person\n\n" + "\n".join(sign + line for line in notice), "") for name, notice in (("GPL-3.0", gpl), ("BSD-3-Clause", bsd), ("MIT", mit)) for k, sign in enumerate(("", "# ", " * ", "dnl "))]
    rows += [(r[0].replace("LICENSE", "src/x.c"), "int main", "") for r in rows]
    rows += [(f"prose{i}.txt", f"the person may modify number {i} and use the work of the building under the terms of a free house", "") for i in range(50)]
    for r in licenses.licences(spark.createDataFrame(rows, FILES)).collect():
        assert r.licence == (None if r.path.startswith("prose") else r.path.split("/")[0][:-1])


def test_scan_equals_brute_force(real):
    docs = licenses.document_paths(real("documents"))
    matcher = licenses.fit(docs)
    want = {}
    for r in docs.collect():
        best = (0.0, None)
        for sentence in licenses.SENTENCE.split(r.text or ""):
            count = licenses.Counter(licenses.words(sentence))
            weights = {t: c * matcher.idf.get(t, matcher.unseen) for t, c in count.items()}
            norm = sum(w * w for w in weights.values()) ** 0.5
            for name, vector in matcher.vectors:
                cosine = sum(w * vector.get(t, 0) for t, w in weights.items()) / norm if norm else 0
                best = max(best, (cosine, name)) if cosine > best[0] + 1e-12 else best
        want[r.doc_id] = best[1] if best[0] >= matcher.least else None
    assert {r.doc_id: r.own_licence for r in licenses.scan(docs, matcher).collect()} == want and any(want.values())


def test_inheritance_equals_brute_force(spark):
    """Random trees of directories, climbed file by file."""
    import random

    r, rows = random.Random(2), []
    for i in range(600):
        folder = "/".join(f"d{r.randrange(3)}" for _ in range(r.randrange(5)))
        name = r.choice(["LICENSE", "COPYING.txt", "a.py", "b.py", "licence.md", "notice"])
        rows.append((f"{folder}/{name}" if folder else name, r.choice([None, "MIT", "GPL-3.0", "ISC"]), r.randrange(80, 100) / 100, i))
    rows += [(None, "MIT", 0.9, 700), rows[0]]
    given: dict = {}
    for path, own, similarity, _ in rows:
        folder, slash, name = (path or "").rpartition("/")
        if slash and own and name.lower().split(".")[0] in ("license", "licence", "copying", "notice"):
            given[folder] = min(given.get(folder, (0, "~", "")), (-similarity, own, path))
    want = []
    for path, own, _, i in rows:
        folder, near = (path or "").rpartition("/")[0], None
        while folder and near is None:
            near = given.get(folder, (None, None))[1]
            folder = folder.rpartition("/")[0]
        want.append((i, own or near))
    found = licenses.inherit(spark.createDataFrame(rows, "path string, own_licence string, similarity double, i int"))
    assert sorted(((x.i, x.licence) for x in found.collect()), key=str) == sorted(want, key=str)


@pytest.fixture
def store(spark, tmp_path):
    return shards.ShardStore(spark, str(tmp_path / "store"), target_bytes=60_000)


def test_appends_merges_and_versions(store, documents, no_documents, real):
    docs = real("documents")
    assert store.version() == 0 and store.shards() == [] and store.read().count() == 0
    for part in shards.arrivals(docs.repartition(6), "doc_id"):
        store.append(part)
    before = len(store.shards())
    assert store.version() == 5 and store.read().count() == docs.count()
    version = store.compact()
    assert version > 5 and len(store.shards()) < before and not store.plan(store.shards())
    assert store.read().exceptAll(docs).isEmpty() and docs.exceptAll(store.read()).isEmpty()
    assert store.read(1).count() < docs.count()  # older versions stay readable
    store.append(no_documents)
    assert store.version() == version + 1 and store.read().count() == docs.count()
    assert store.vacuum() > 0 and store.read().count() == docs.count()


def test_repeated_and_null_rows_survive(store, documents):
    store.append(documents)
    store.append(documents)
    store.compact()
    assert store.read().count() == 24 and store.read().filter("text is null").count() == 2


def test_one_of_two_writers_wins(store, documents):
    store.append(documents)
    now = store.shards()
    assert store._publish(2, now, documents.schema.json()) and not store._publish(2, [], documents.schema.json())
    assert store.version() == 2 and len(store.shards()) == len(now)
    store.append(documents)
    assert store.version() == 3


def test_vacuum_spares_what_is_not_committed_yet(store, documents):
    store.append(documents)
    name, files = store._write(documents)  # another writer, between its files and its commit
    assert store.vacuum() == 0
    store._claim(name)
    assert store.vacuum(patience=-10) == 0
    assert store._publish(2, store.shards() + [shards.Shard(p, b, 2) for p, b in files], documents.schema.json())
    store._done(name)
    assert store.vacuum(patience=-10) == 0 and store.read().count() == 24
    late, files = store._write(documents)
    assert store.vacuum(patience=-10) == len(files)  # given up: its writer can't commit any more
    with pytest.raises(RuntimeError):
        store._claim(late)
    assert store.read().count() == 24


def test_arrivals_of_another_schema_are_refused(store, documents):
    store.append(documents.select("doc_id", "text"))
    for other in (documents.select("doc_id", "text", "lang"), documents.select("doc_id"), documents.selectExpr("string(doc_id) AS doc_id", "text")):
        with pytest.raises(ValueError):
            store.append(other)
    store.append(documents.select("text", "doc_id"))
    assert store.read().columns == ["doc_id", "text"] and store.read().count() == 24
    assert {r.doc_id for r in store.read().collect()} == {r.doc_id for r in documents.collect()}


def test_compaction_of_very_many_files_ends(spark, tmp_path):
    store = shards.ShardStore(spark, str(tmp_path / "many"), target_bytes=1 << 20, fan_in=2)
    store.append(spark.range(400).repartition(100))
    store.compact()
    assert not store.plan(store.shards()) and len(store.shards()) <= 2 and store.read().count() == 400
