"""Benchmark decontamination: passages as queries to a BM25 index of the test items, by block-max WAND.

Items are indexed with impacts: a term's BM25 weight over the weight of the whole item, so that a passage's
score is the share of an item that it covers, and one threshold serves all items. Items are put in classes by length, and for each class
documents are cut into windows of twice its longest item, half overlapping, so that any copy of an item lies whole in one. Postings
stand in item order, with maxima over coarse and fine blocks of items. A batch of windows is bounded at once: maxima of coarse blocks first;
posting blocks inside coarse blocks that can't reach the threshold are skipped, the others are bounded by their own maxima (frequent terms
add a constant a block), and only in fine blocks that can reach it does the pivot walk score items. All items at or above the threshold are
retrieved and verified: the item's last sentence is its answer, what stands before is its question (an item of one sentence is all
question), and of each part the share ``least`` of the word runs of ``gram`` must occur in the passage.

Indexes of ``shard_bytes`` of item text are built and broadcast, as many as make ``pass_bytes`` for one pass over the documents; larger
benchmarks mean more passes, with term statistics over all items. Documents are never shuffled.

Defined cases: null and empty texts and items hold no terms and match nothing; repeated items are found each under its
id; repeated documents are reported each; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import math
import re
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import opened, persisted, ship, words

SENTENCE = re.compile(r"(?<=[.!?])\s+")
SCHEMA = "doc_id long, item_id long, score double, question_overlap double, answer_overlap double"


def parts(text: str) -> tuple[list[str], list[str]]:
    """Words of the question and of the answer."""
    sentences = [s for s in SENTENCE.split(text.strip()) if words(s)]
    if len(sentences) < 2:
        return words(text), []
    return words(" ".join(sentences[:-1])), words(sentences[-1])


def overlap(part: list[str], passage: list[str], gram: int) -> float:
    """Share of the part's word runs that the passage has; runs are as long as the part, if that is shorter."""
    n = min(gram, len(part))
    if not n:
        return 1.0
    have = set(zip(*(passage[k:] for k in range(n))))
    runs = list(zip(*(part[k:] for k in range(n))))
    return sum(r in have for r in runs) / len(runs)


class LengthClass:
    """Postings of the items of one class of lengths, in item order, with maxima over blocks of items at two levels.

    ``stride`` is the longest item's number of words: a copy of an item lies whole in some window of two strides, half overlapping.
    """

    def __init__(self, places: list[int], lengths: list[int], impacts: list[dict[int, float]], rare: np.ndarray, fine: int, coarse: int):
        self.places, self.stride, self.sizes = places, max(max(lengths), 64), (coarse, fine)
        term = np.array([t for each in impacts for t in each], dtype=np.int64)
        item = np.repeat(np.arange(len(impacts)), [len(each) for each in impacts])
        impact = np.array([w for each in impacts for w in each.values()])
        order = np.lexsort((item, term))
        self.item, self.impact = item[order], impact[order]
        self.start = np.searchsorted(term[order], np.arange(len(rare) + 1))  # of each term's postings
        self.present = rare & (np.diff(self.start) > 0)
        frequent = np.bincount(item, impact * ~rare[term], len(impacts))  # what frequent terms can add to an item
        self.floor, self.levels = [], []
        for size in self.sizes:
            self.floor.append(np.maximum.reduceat(frequent, np.arange(0, len(impacts), size)))
            cell = term[order] * len(self.floor[-1]) + self.item // size
            cells, first = np.unique(cell, return_index=True)
            tops = np.maximum.reduceat(self.impact, first)
            of = cells // len(self.floor[-1])
            self.levels.append((cells % len(self.floor[-1]), tops, np.searchsorted(of, np.arange(len(rare) + 1))))
        self.cells, self.first = cells, np.append(first, len(self.item))  # term and fine block of each fine posting block, rising, and its postings

    def promising(self, window: np.ndarray, term: np.ndarray, windows: int, threshold: float) -> tuple[np.ndarray, np.ndarray, list[int]]:
        """(window, fine block) pairs whose block maxima can reach the threshold, from different (window, term) pairs, and how many
        posting blocks were looked at on each level. The fine blocks of a coarse block that can't reach it are skipped."""
        wanted = self.present[term]
        window, term = window[wanted], term[wanted]
        blocks, tops, start = self.levels[0]
        count = start[term + 1] - start[term]
        spread = expand(start[term], count)
        looked = [len(spread)]
        coarse, bound = summed(np.repeat(window, count) * len(self.floor[0]) + blocks[spread], tops[spread])
        coarse = coarse[bound + self.floor[0][coarse % len(self.floor[0])] >= threshold - 1e-9]
        always = np.flatnonzero(self.floor[0] >= threshold - 1e-9)  # frequent terms alone may fill these, wherever they are
        coarse = np.unique(np.concatenate([coarse, (np.arange(windows)[:, None] * len(self.floor[0]) + always).ravel()]))
        # The terms of a window against its surviving coarse blocks, and there their fine blocks.
        w, c = coarse // len(self.floor[0]), coarse % len(self.floor[0])
        order = np.argsort(window, kind="stable")
        window, term = window[order], term[order]
        low, high = np.searchsorted(window, w), np.searchsorted(window, w, side="right")
        at = expand(low, high - low)
        w, c, t = np.repeat(w, high - low), np.repeat(c, high - low), term[at]
        blocks, tops, _ = self.levels[1]
        span, fines = self.sizes[0] // self.sizes[1], len(self.floor[1])
        low = np.searchsorted(self.cells, t * fines + c * span)
        high = np.searchsorted(self.cells, t * fines + np.minimum((c + 1) * span, fines))
        spread = expand(low, high - low)
        looked.append(len(spread))
        fine, bound = summed(np.repeat(w, high - low) * len(self.floor[1]) + blocks[spread], tops[spread])
        fine = fine[bound + self.floor[1][fine % len(self.floor[1])] >= threshold - 1e-9]
        always = np.flatnonzero(self.floor[1] >= threshold - 1e-9)
        fine = np.unique(np.concatenate([fine, (np.arange(windows)[:, None] * len(self.floor[1]) + always).ravel()]))
        return fine // len(self.floor[1]), fine % len(self.floor[1]), looked

    def walk(self, terms: np.ndarray, block: int, threshold: float) -> list[tuple[int, float]]:
        """Items of a fine block that score at least threshold: lists move to the pivot, where the maxima of the lists before it add up
        to the threshold, so that items which can't reach it are not scored."""
        out, low = [], threshold - 1e-9
        key = terms * len(self.floor[1]) + block
        at = np.searchsorted(self.cells, key)
        at = at[self.cells[np.minimum(at, len(self.cells) - 1)] == key]
        # [current item, place, end, maximum]
        lists = [[int(self.item[self.first[c]]), int(self.first[c]), int(self.first[c + 1]), float(self.levels[1][1][c])] for c in at.tolist()]
        while lists:
            lists.sort()
            total, pivot = 0.0, None
            for c in lists:
                total += c[3]
                if total >= low:
                    pivot = c[0]
                    break
            if pivot is None:
                break
            if lists[0][0] == pivot:
                score = sum(float(self.impact[c[1]]) for c in lists if c[0] == pivot)
                if score >= low:
                    out.append((pivot, score))
                pivot += 1
            for c in lists:
                if c[0] < pivot:
                    c[1] += int(np.searchsorted(self.item[c[1] : c[2]], pivot))
                    c[0] = int(self.item[c[1]]) if c[1] < c[2] else -1
            lists = [c for c in lists if c[0] >= 0]
        return out


def expand(start: np.ndarray, count: np.ndarray) -> np.ndarray:
    """start, start + 1, ... of each range of count numbers, one after another."""
    return np.repeat(start - np.concatenate([[0], np.cumsum(count)[:-1]]).astype(np.int64), count) + np.arange(count.sum())


def summed(cell: np.ndarray, value: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Different cells and the sum of their values."""
    cells, inverse = np.unique(cell, return_inverse=True)
    return cells, np.bincount(inverse, value, len(cells))


class ItemIndex:
    """Items by classes of length (powers of ``ratio``, from 64 words up), with impacts normalised to 1 an item."""

    def __init__(self, items: list[tuple[int, str]], n_items: int, mean_length: float, frequency: dict[str, int], fine: int = 4, coarse: int = 64, ratio: float = 4.0, k1: float = 1.2, b: float = 0.75, common: float = 0.05):
        self.ids, self.parts = [i for i, _ in items], [parts(t) for _, t in items]
        self.vocabulary: dict[str, int] = {}
        classes: dict[int, list[tuple[int, int, dict[int, float]]]] = {}
        for at, (question, answer) in enumerate(self.parts):
            count = Counter(question + answer)
            length, impacts = len(question) + len(answer), {}
            for term, tf in count.items():
                df = frequency[term]
                impacts[self.vocabulary.setdefault(term, len(self.vocabulary))] = np.log(1 + (n_items - df + 0.5) / (df + 0.5)) * tf * (k1 + 1) / (tf + k1 * (1 - b + b * length / mean_length))
            whole = sum(impacts.values())
            classes.setdefault(math.ceil(math.log(max(length, 64), ratio) - 1e-9), []).append((at, length, {t: w / whole for t, w in impacts.items()}))
        limit = max(8, common * n_items)
        rare = np.array([frequency[t] <= limit for t in self.vocabulary], dtype=bool)
        self.classes = [LengthClass(*map(list, zip(*found)), rare, fine, coarse) for _, found in sorted(classes.items())]

    def retrieve(self, ids: list[np.ndarray], threshold: float):
        """(text number, words from, words to, item number, score) of every item at or above the threshold in a window."""
        for group in self.classes:
            s = group.stride
            windows = np.array([-(-len(x) // s) + 1 for x in ids], dtype=np.int64)  # window v of a text begins at word (v - 1) * s
            first = np.concatenate([[0], np.cumsum(windows)])
            key, term = [np.empty(0, np.int64)], [np.empty(0, np.int64)]
            for at, x in enumerate(ids):
                place = np.flatnonzero(x >= 0)
                place = place[group.present[x[place]]]
                for later in (0, 1):  # each word is in two windows
                    key.append(first[at] + place // s + later)
                    term.append(x[place])
            total = len(self.vocabulary)
            both = np.unique(np.concatenate(key) * total + np.concatenate(term))
            found, block, _ = group.promising(both // total, both % total, int(first[-1]), threshold)
            last, terms = -1, None
            for w, k in zip(found.tolist(), block.tolist()):
                at = int(np.searchsorted(first, w, side="right")) - 1
                a = (w - int(first[at]) - 1) * s
                if w != last:
                    inside = ids[at][max(a, 0) : a + 2 * s]
                    last, terms = w, np.unique(inside[inside >= 0])
                for item, score in group.walk(terms, k, threshold):
                    yield at, max(a, 0), a + 2 * s, group.places[item], score

    def matches(self, tokens: list[list[str]], threshold: float, gram: int, least: float) -> list[tuple[int, int, float, float, float]]:
        """(text number, item id, score, question overlap, answer overlap) of the verified items; the best window of each."""
        get = self.vocabulary.get
        ids = [np.fromiter((get(w, -1) for w in t), dtype=np.int64, count=len(t)) for t in tokens]
        best: dict[tuple[int, int], tuple[float, float, float, float]] = {}
        for at, a, e, item, score in self.retrieve(ids, threshold):
            question, answer = (overlap(p, tokens[at][a:e], gram) for p in self.parts[item])
            if question >= least and answer >= least:
                found = (question + answer, score, question, answer)
                best[at, item] = max(best.get((at, item), found), found)
        return [(at, self.ids[item], *v[1:]) for (at, item), v in sorted(best.items())]


def indexes(items: DataFrame, shard_bytes: int, pass_bytes: int) -> list[list[Broadcast]]:
    """Broadcast indexes over all items, of about shard_bytes of text each, with common term statistics; those of one pass stand together."""
    spark = items.sparkSession
    named = items.filter(F.col("item_id").isNotNull() & F.col("text").isNotNull()).select(F.col("item_id").cast("long").alias("item_id"), "text")

    def tokenise(batches):
        for batch in batches:
            rows = [words(t) for t in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_pydict({"item_id": batch.column(0), "text": batch.column(1), "words": pa.array(rows, pa.list_(pa.string()))})

    termed = persisted(named.mapInArrow(tokenise, "item_id long, text string, words array<string>").filter(F.size("words") > 0), "benchmark-words")
    size = termed.agg(F.count("*").alias("n"), F.avg(F.size("words")).alias("mean"), F.sum(F.octet_length("text")).alias("bytes")).first()
    if not size.n:
        return []
    shards = -(-size.bytes // shard_bytes)
    termed = termed.withColumn("shard", F.pmod(F.xxhash64("item_id", "text"), F.lit(shards)))
    each = termed.select("shard", F.explode(F.array_distinct("words")).alias("term"))
    frequency = persisted(each.groupBy("term").agg(F.count("*").alias("df")), "benchmark-terms")
    made = []
    for shard in range(shards):
        rows = termed.filter(F.col("shard") == shard).select("item_id", "text").collect()
        mine = each.filter(F.col("shard") == shard).select("term").distinct().join(frequency, "term")
        if rows:
            made.append(ship(spark, ItemIndex(sorted((r.item_id, r.text) for r in rows), size.n, size.mean, {r.term: r.df for r in mine.collect()})))
    together = max(1, pass_bytes // shard_bytes)
    return [made[k : k + together] for k in range(0, len(made), together)]


def hits(texts: list[str | None], indexes: list[ItemIndex], *options) -> list[tuple]:
    """The matches of all indexes; each text is cut into words once."""
    tokens = [words(t) for t in texts]
    return [found for index in indexes for found in index.matches(tokens, *options)]


def leaks(docs: DataFrame, items: DataFrame, threshold: float = 0.6, gram: int = 5, least: float = 0.8, shard_bytes: int = 8 << 20, pass_bytes: int = 64 << 20) -> DataFrame:
    """One row for each document and each test item that it holds."""
    found = None
    for shared in indexes(items, shard_bytes, pass_bytes):

        def run(batches, shared=shared):
            own = [opened(s) for s in shared]
            for batch in batches:
                ids = batch.column(0).to_pylist()
                made = [(ids[at], *rest) for at, *rest in hits(batch.column(1).to_pylist(), own, threshold, gram, least)]
                if made:
                    kinds = (pa.int64(), pa.int64(), pa.float64(), pa.float64(), pa.float64())
                    yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*made), kinds)], names=["doc_id", "item_id", "score", "question_overlap", "answer_overlap"])

        part = docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, SCHEMA)
        found = part if found is None else found.unionByName(part)
    return found if found is not None else docs.sparkSession.createDataFrame([], SCHEMA)


def clean(docs: DataFrame, items: DataFrame, threshold: float = 0.6, gram: int = 5, least: float = 0.8, shard_bytes: int = 8 << 20, pass_bytes: int = 64 << 20) -> DataFrame:
    """The rows of docs that hold no test item: one narrow pass for each group of indexes."""
    at = docs.columns.index("text")
    for shared in indexes(items, shard_bytes, pass_bytes):

        def run(batches, shared=shared):
            own = [opened(s) for s in shared]
            for batch in batches:
                hit = {found[0] for found in hits(batch.column(at).to_pylist(), own, threshold, gram, least)}
                yield batch.filter(pa.array([k not in hit for k in range(batch.num_rows)], pa.bool_()))

        docs = docs.mapInArrow(run, docs.schema)
    return docs
