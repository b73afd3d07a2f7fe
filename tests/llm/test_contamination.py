import re

import numpy as np
import pytest

from hypernear.llm import contamination as C
from hypernear.llm.common import words

ITEMS = "item_id long, text string"


def brute(docs, items):
    """By plain text search, without the operator's functions: four fifths of the five-word runs of question and answer each."""
    out = set()
    clean = lambda t: " ".join(re.findall(r"\w+", t.lower()))
    for d, text in docs:
        whole = f" {clean(text or '')} "
        for i, item in items:
            sentences = [clean(x) for x in re.split(r"(?<=[.!?])\s+", (item or "").strip()) if clean(x)]
            if not sentences:
                continue
            met = []
            for part in ([" ".join(sentences[:-1]), sentences[-1]] if len(sentences) > 1 else sentences):
                w = part.split()
                runs = [" ".join(w[k : k + 5]) for k in range(max(1, len(w) - 4))]
                met.append(sum(f" {r} " in whole for r in runs) >= 0.8 * len(runs))
            if all(met):
                out.add((d, i))
    return out


@pytest.mark.parametrize("options", [{}, {"shard_bytes": 3000, "pass_bytes": 6000}, {"shard_bytes": 1500, "pass_bytes": 1}])
def test_equals_brute_force(spark, real, options):
    docs, items = real("documents").select("doc_id", "text"), real("benchmark")
    want = brute([tuple(r) for r in docs.collect()], [tuple(r) for r in items.collect()])
    found = C.leaks(docs, items, **options).collect()
    assert {(r.doc_id, r.item_id) for r in found} == want and len(found) == len(want) > 0
    clean = C.clean(docs, items, **options)
    assert {r.doc_id for r in clean.collect()} == {r.doc_id for r in docs.collect()} - {d for d, _ in want}


def test_a_wrong_answer_is_no_leak(spark):
    question = "Which of the seven wizards of the northern valley was the first one to mix a potion of pure silver by the old mill stream?"
    items = spark.createDataFrame([(1, f"{question} It was old Barnaby with his crooked copper ladle.")], ITEMS)
    docs = spark.createDataFrame([(1, f"Well. {question} Nobody in the town could remember any such thing at all."), (2, f"Ah. {question} It was old Barnaby with his crooked copper ladle. So there.")], "doc_id long, text string")
    assert [r.doc_id for r in C.leaks(docs, items).collect()] == [2]


def test_a_question_alone_is_no_leak():
    question, answer = "Which river flows past the old stone mill of the northern valley town?", "The narrow Esk."
    index = C.ItemIndex([(1, f"{question} {answer}"), (2, question)], 2, 15.0, {w: 1 for w in words(f"{question} {answer}")})
    hits = {(at, item) for at, item, *_ in index.matches([words(question), words(f"so {question} {answer} indeed")], 0.6, 5, 0.8)}
    assert hits == {(0, 2), (1, 1), (1, 2)}


def test_edge_cases(spark, documents, no_documents):
    fox = "The quick brown fox jumps over the lazy dog, while seven wizards quietly mix potions. For the evening feast and nobody complains about it at all!"
    items = spark.createDataFrame([(1, fox), (1, fox), (2, None), (3, ""), (None, fox), (4, "?!")], ITEMS)
    found = sorted((r.doc_id, r.item_id) for r in C.leaks(documents, items).collect())
    assert (1, 1) in found and {d for d, _ in found} <= {1, 2, 3}
    assert C.clean(documents, items).columns == documents.columns
    none = spark.createDataFrame([], ITEMS)
    assert C.leaks(documents, none).count() == 0 and C.clean(documents, none).count() == documents.count()
    assert C.leaks(no_documents, items).count() == 0 and C.clean(no_documents, items).count() == 0


def test_walk_finds_all_above_the_threshold():
    """Block bounds and the pivot walk lose no item that a full scoring puts at the threshold, for items of all lengths, and skip blocks."""
    random = np.random.default_rng(3)
    vocabulary = [f"t{i}" for i in range(400)]
    texts = [" ".join(random.choice(vocabulary, random.integers(3, 12) * (1 + 29 * (i % 7 == 0)))) for i in range(300)]
    frequency = {t: sum(t in words(x) for x in texts) for t in vocabulary}
    index = C.ItemIndex(list(enumerate(texts)), 300, np.mean([len(words(t)) for t in texts]), frequency, coarse=16, common=0.03)
    assert len(index.classes) > 1 and len({g.stride for g in index.classes}) > 1
    passages = [random.choice(vocabulary, 40).tolist() + words(texts[k]) + random.choice(vocabulary, 90).tolist() for k in range(40)]
    ids = [np.array([index.vocabulary.get(w, -1) for w in p]) for p in passages]
    got = {}
    for at, a, e, item, score in index.retrieve(ids, 0.6):
        got[at, a, e, item] = score
    want = {}
    for group in index.classes:
        s = group.stride
        for at, x in enumerate(ids):
            for w in range(-(-len(x) // s) + 1):
                terms = np.unique(x[max((w - 1) * s, 0) : (w + 1) * s])
                scores = np.zeros(len(group.places))
                for t in terms[terms >= 0]:
                    mine = slice(group.start[t], group.start[t + 1])
                    np.add.at(scores, group.item[mine], group.impact[mine])
                for k in np.flatnonzero(scores >= 0.6):
                    want[at, max((w - 1) * s, 0), (w + 1) * s, group.places[k]] = scores[k]
    assert set(got) == set(want) and len(want) >= 40 and all(abs(got[k] - want[k]) < 1e-9 for k in want)


def test_blocks_are_skipped():
    """A passage that holds one item looks at few of its terms' fine posting blocks."""
    random = np.random.default_rng(5)
    vocabulary = [f"t{i}" for i in range(1500)]
    texts = [" ".join(random.choice(vocabulary, 10)) for _ in range(2000)]
    frequency = {t: sum(t in x for x in map(set, map(words, texts))) for t in vocabulary}
    (group,) = (index := C.ItemIndex(list(enumerate(texts)), 2000, 10.0, frequency, coarse=16)).classes
    term = np.unique([index.vocabulary[w] for w in words(texts[7]) + random.choice(vocabulary, 40).tolist()])
    window, block, looked = group.promising(np.zeros(len(term), np.int64), term, 1, 0.6)
    _, _, start = group.levels[1]
    assert 7 // 4 in block.tolist() and looked[1] < sum(start[t + 1] - start[t] for t in term) * 0.6, (looked, sum(start[t + 1] - start[t] for t in term), block)
