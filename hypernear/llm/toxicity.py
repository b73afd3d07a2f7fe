"""Toxicity: boosted trees over dense features of the text, isotonically calibrated.

The features are densities of a lexicon (a general word list plus words and word stems that the
labelled sample shows to be toxic), nearness of second-person pronouns to them, capitals, punctuation
and obfuscation rates. A model is fitted on at most ``sample_rows`` labelled rows (drawn by a hash of the
id over all labels) and scores every whole text in one narrow pass.

Defined cases: null and empty texts get the score of their (all zero) features; null or repeated labels are
dropped or joined by their maximum; of several texts of one labelled id the least is learnt from; no labels at all give the constant base rate; repeated rows are scored
each; extra columns pass through, and a result column replaces an input column of the same name.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .boosting import BoostedTrees, Isotonic, out_of_fold
from .common import WORD, opened, persisted, ship

# General insults, and second-person pronouns, of four languages.
INSULTS = "idiot moron stupid loser scum trash worthless pathetic disgusting clown dumb fool jerk bastard bitch idiota estúpido imbécil basura asqueroso idiote imbécile stupide ordure dégoûtant trottel dummkopf abschaum widerlich arschloch"
YOU = "you your yours yourself u ur tú tu usted ustedes vosotros te ti vous votre vos toi du dich dir dein deine ihr euch sie"
LEET = str.maketrans("013457@$!", "oieastasi")
STEMS = (4, 5, 6, 7, 8)
FEATURES = 20


@dataclass
class Scorer:
    """What scoring needs: learnt weights of words and stems, trees and calibration."""

    weights: dict[str, float] = field(default_factory=dict)
    stems: dict[str, float] = field(default_factory=dict)
    trees: BoostedTrees = field(default_factory=BoostedTrees)
    calibration: Isotonic = field(default_factory=Isotonic)

    def score(self, texts: list[str | None], *prepared) -> np.ndarray:
        return self.calibration.predict(self.trees.predict(featurise(texts, self.weights, self.stems, *prepared)))


def weigh(word: str, weights: dict[str, float], stems: dict[str, float]) -> float:
    best = weights.get(word, 0.0)
    for n in STEMS:
        if len(word) >= n:
            best = max(best, stems.get(word[:n], 0.0))
    return best


class Kinds(dict):
    """What a word says, worked out once: 0 for most, else its weight and whether it is a general insult, a pronoun, shouted."""

    def __init__(self, weights: dict[str, float], stems: dict[str, float]):
        super().__init__()
        self.weights, self.stems, self.insults, self.you = weights, stems, frozenset(INSULTS.split()), frozenset(YOU.split())

    def __missing__(self, word: str):
        if len(self) > 500_000:
            self.clear()
        low = word.lower()
        weight, insult, you, shouted = weigh(low, self.weights, self.stems), low in self.insults, low in self.you, len(word) > 1 and word.isupper()
        self[word] = kind = (weight, insult, you, shouted) if weight or insult or you or shouted else 0
        return kind

    def bad(self, word: str) -> bool:
        return word in self.insults or weigh(word, self.weights, self.stems) > 0


OTHER, LETTER, CAPITAL, DIGIT, SPACE, POINT = range(6)


def character_classes(limit: int = 0x3000) -> np.ndarray:
    """Class of each code point below limit; the rest (mostly other scripts) count as letters."""
    kinds = np.full(limit + 1, LETTER, dtype=np.uint8)
    for code in range(limit):
        c = chr(code)
        kinds[code] = CAPITAL if c.isupper() else LETTER if c.isalpha() else DIGIT if c.isdigit() else SPACE if c.isspace() else OTHER if c == "_" else POINT
    return kinds


def featurise(texts: list[str | None], weights: dict[str, float], stems: dict[str, float], kinds: Kinds | None = None, classes: np.ndarray | None = None) -> np.ndarray:
    """One row of dense features a text."""
    kinds = Kinds(weights, stems) if kinds is None else kinds
    classes = character_classes() if classes is None else classes
    rows = []
    for text in texts:
        text = text or ""
        found = WORD.findall(text)
        telling = [(at, kind) for at, kind in enumerate(map(kinds.__getitem__, found)) if kind]
        spots = [at for at, k in telling if k[0] or k[1]]
        you_at = [at for at, k in telling if k[2]]
        hits, total, general = len(spots), sum(k[0] for _, k in telling), sum(k[1] for _, k in telling)
        near = 0
        if spots and you_at:
            right = np.searchsorted(you_at, spots)
            beside = np.stack([right - 1, right]).clip(0, len(you_at) - 1)
            near = int((np.abs(np.array(you_at)[beside] - np.array(spots)).min(axis=0) <= 5).sum())
        codes = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), dtype=np.uint32)
        kind = classes[np.minimum(codes, len(classes) - 1)]
        count = np.bincount(kind, minlength=6)
        masked, spelt, runs = oddities(codes, kind)
        unmasked = sum(kinds.bad(w) for at in masked for w in around(text, int(at))) + sum(kinds.bad(w) for w in spelt_out(text, spelt))
        n, chars, letters = max(len(found), 1), max(len(text), 1), max(int(count[LETTER] + count[CAPITAL]), 1)
        rows.append((
            math.log1p(len(found)), general / n, math.log1p(general), hits / n, math.log1p(hits), total / n, math.log1p(total), len({found[at].lower() for at in spots}),
            near / max(hits, 1), len(you_at) / n, count[CAPITAL] / letters, sum(k[3] for _, k in telling) / n, count[POINT] / chars, text.count("!") / n, text.count("?") / n,
            (len(masked) + len(spelt)) / n, unmasked, unmasked / n, runs / n, letters / chars,
        ))
    return np.array(rows, dtype=float).reshape(len(texts), FEATURES)


def oddities(codes: np.ndarray, kind: np.ndarray) -> tuple[np.ndarray, np.ndarray, int]:
    """Where a digit or one of * @ $ ! # stands between letters, where four lone letters begin, and how many fourfold letters there are."""
    letter = (kind == LETTER) | (kind == CAPITAL)
    if len(codes) < 3:
        return np.empty(0, int), np.empty(0, int), 0
    sign = (kind == DIGIT) | np.isin(codes, np.frombuffer("*@$!#".encode("utf-32-le"), dtype=np.uint32)) if (kind >= DIGIT).any() else np.zeros(len(kind), bool)
    masked = np.flatnonzero(sign[1:-1] & letter[:-2] & letter[2:]) + 1
    edge = np.concatenate([[False], letter, [False]])
    lone = letter & ~edge[:-2] & ~edge[2:]
    spelt = np.flatnonzero(lone[:-6] & lone[2:-4] & lone[4:-2] & lone[6:]) if len(lone) > 6 else np.empty(0, int)
    same = letter[1:] & (codes[1:] == codes[:-1])
    runs = int((same[:-2] & same[1:-1] & same[2:]).sum()) if len(same) > 2 else 0
    return masked, spelt, runs


def around(text: str, at: int) -> list[str]:
    """The masked word at a place, read as letters: signs undone, and signs left out."""
    a = max(text.rfind(" ", 0, at), text.rfind("\n", 0, at)) + 1
    b = re.compile(r"\s|$").search(text, at).start()
    word = text[a:b].lower()[:80]
    return [re.sub(r"[\W\d_]", "", word.translate(LEET)), re.sub(r"[\W\d_]", "", word)]


def spelt_out(text: str, starts: np.ndarray) -> list[str]:
    """Words written as lone letters; each run of starts two apart is one word."""
    words, begun = [], None
    for k, at in enumerate(starts):
        begun = at if begun is None else begun
        if k + 1 == len(starts) or starts[k + 1] != at + 2:
            words.append(text[begun : at + 7 : 2].lower())
            begun = None
    return words


def signature(found: list[str]) -> int:
    """Least hash of the three-word runs: near copies mostly share it."""
    return min((hash_of(" ".join(found[i : i + 3])) for i in range(max(1, len(found) - 2))), default=0)


def hash_of(text: str) -> int:
    import xxhash

    return xxhash.xxh64_intdigest(text) >> 1


def one_each(sample: DataFrame) -> DataFrame:
    """(text, y) of one text, that of the least doc_id, of each group of near copies, whatever tasks they stand in."""

    def run(batches):
        for batch in batches:
            marks = [signature(WORD.findall((t or "").lower())) for t in batch.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in ("doc_id", "text", "y")), pa.array(marks, pa.int64())], names=["doc_id", "text", "y", "mark"])

    marked = sample.select("doc_id", "text", "y").mapInArrow(run, "doc_id long, text string, y int, mark long")
    return marked.groupBy("mark").agg(F.min_by(F.struct("text", "y"), "doc_id").alias("one")).select("one.*")


def learn_terms(sample: DataFrame, least_evidence: float) -> tuple[dict[str, float], dict[str, float]]:
    """Words and stems that mark label 1, by a likelihood ratio over documents: as many as a bounded sample gives evidence for.

    Each near-copy group of the sample counts once. Terms are counted inside each task and summed by Spark.
    """

    def count(batches):
        pairs: Counter = Counter()
        for batch in batches:
            for text, y in zip(batch.column("text").to_pylist(), batch.column("y").to_pylist()):
                terms = set(WORD.findall((text or "").lower()))
                terms = {f"w{t}" for t in terms} | {f"s{t[:n]}" for t in terms for n in STEMS if len(t) > n} | {""}
                pairs.update((t, y) for t in terms)
        kept = sorted({t for t, y in pairs if len(t) < 40})
        yield pa.RecordBatch.from_pydict({"term": pa.array(kept, pa.string()), "pos": pa.array([pairs[t, 1] for t in kept], pa.int64()), "neg": pa.array([pairs[t, 0] for t in kept], pa.int64())})

    counts = one_each(sample).mapInArrow(count, "term string, pos long, neg long").groupBy("term").agg(F.sum("pos").alias("pos"), F.sum("neg").alias("neg"))
    counts = persisted(counts, "toxicity-terms")
    whole = counts.filter("term = ''").first()
    if whole is None or not whole.pos or not whole.neg:
        return {}, {}
    P, N = float(whole.pos), float(whole.neg)
    share = F.lit(P / (P + N))
    ends = lambda a, e: F.when(a > 0, a * F.log(a / e)).otherwise(0.0)
    pos, neg, both = F.col("pos"), F.col("neg"), F.col("pos") + F.col("neg")
    evidence = 2 * (ends(pos, both * share) + ends(neg, both * (1 - share)))
    purity = (pos + 0.1) / (both + 0.2)
    top = counts.filter((F.col("term") != "") & (pos >= 3) & (purity >= 0.6)).select("term", purity.alias("purity"), evidence.alias("evidence")).filter(F.col("evidence") >= least_evidence).collect()
    return {r.term[1:]: r.purity for r in top if r.term[0] == "w"}, {r.term[1:]: r.purity for r in top if r.term[0] == "s"}


def fit(docs: DataFrame, labels: DataFrame, label: str = "toxic", sample_rows: int = 24_000, least_evidence: float = 12.0, least_positive: int = 20) -> Scorer:
    """Model from at most about sample_rows of the given labelled rows.

    Half of the sample shows which terms are toxic; the trees and the calibration see the other half only, so
    that the terms they find there are as reliable as in new texts. With few positive rows both use all of it.
    """
    marks = labels.filter(F.col(label).isNotNull() & F.col("doc_id").isNotNull()).groupBy("doc_id").agg(F.max((F.col(label) != 0).cast("int")).alias("y"))
    known = marks.agg(F.count("*").alias("n"), F.coalesce(F.sum("y"), F.lit(0)).alias("pos")).first()
    rate = min(1.0, sample_rows / max(known.n, 1))
    drawn = marks.filter(F.pmod(F.xxhash64("doc_id", F.lit(17)), F.lit(1_000_003)) < F.lit(rate * 1_000_003))
    texts = docs.select(F.col("doc_id").cast("long"), "text").join(F.broadcast(drawn), "doc_id")  # at most sample_rows rows are broadcast
    texts = persisted(texts.groupBy("doc_id", "y").agg(F.min("text").alias("text")), "toxicity-sample")  # and kept: one row an id
    halved = known.pos * rate >= 4 * least_positive
    side = F.pmod(F.xxhash64("doc_id", F.lit(5)), F.lit(2))
    weights, stems = learn_terms(texts.filter(side == 0) if halved else texts, least_evidence)
    shared = ship(docs.sparkSession, (weights, stems))

    def features(batches):
        terms = opened(shared)
        prepared = Kinds(*terms), character_classes()
        for batch in batches:
            X = featurise(batch.column("text").to_pylist(), *terms, *prepared)
            yield pa.RecordBatch.from_pydict({"doc_id": batch.column("doc_id"), "y": batch.column("y"), "x": pa.array(list(X), pa.list_(pa.float64()))})

    rest = (texts.filter(side == 1) if halved else texts).mapInArrow(features, "doc_id long, y int, x array<double>")
    rows = sorted((hash_of(str(r.doc_id)), r.y, r.x) for r in rest.collect())
    X, y = np.array([r[2] for r in rows], dtype=float).reshape(len(rows), FEATURES), np.array([r[1] for r in rows], dtype=float)
    scorer = Scorer(weights, stems, BoostedTrees(rounds=40).fit(X, y))
    if len(y) and 0 < y.sum() < len(y):
        scorer.calibration = Isotonic().fit(out_of_fold(X, y, rounds=40), y)
    return scorer


def score(docs: DataFrame, scorer: Scorer, column: str = "score") -> DataFrame:
    """docs with the calibrated probability of toxicity of the whole text."""
    shared = ship(docs.sparkSession, scorer)
    kept = [c for c in docs.columns if c != column]
    schema = docs.select(*kept).schema.add(column, "double")
    at = docs.select(*kept).columns.index("text")

    def run(batches):
        model = opened(shared)
        prepared = Kinds(model.weights, model.stems), character_classes()
        for batch in batches:
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(model.score(batch.column(at).to_pylist(), *prepared), pa.float64())], names=[*batch.schema.names, column])

    return docs.select(*kept).mapInArrow(run, schema)


def held_out(column: str = "doc_id"):
    """Rows whose label no model may see: crc32 of the id's digits, modulo 3, is 1."""
    return F.coalesce(F.crc32(F.col(column).cast("string")) % 3 == 1, F.lit(False))
