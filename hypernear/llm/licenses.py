"""Licence scan: sparse TF-IDF cosine to licence templates, then inheritance from the nearest directory.

Every sentence of a whole text, and every window of a template's number of words, is compared with every template; a text's licence
is that of its most similar sentence or window, from ``least`` upwards. Windows run over the words of the whole text, whatever
its line breaks, comment signs and punctuation, so that wrapped notices are met. Inverse document frequencies of the templates' words are counted over all texts; other words
weigh as unseen ones. A sentence or window can only reach ``least`` if it shares one of a template's heavy words, as the Cauchy bound
shows, so most are passed over by one set look-up.

Files named LICENSE, LICENCE, COPYING or NOTICE give their licence to their directory. A file without a licence of its own
inherits that of its nearest ancestor directory that has one: directories, not files, are joined with their ancestors.

Defined cases: null and empty texts have no licence of their own; a null path has no directory and inherits nothing; of several licence
files in a directory the most similar wins, ties to the smaller licence name, and the smaller path; repeated rows are scanned each; an empty table
gives an empty result; extra columns pass through unless a result column has their name.
"""

from __future__ import annotations

import math
import re
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import opened, persisted, ship, words
from .licence_texts import TEMPLATES

COMMENT = re.compile(r"^[^\S\n]*(?:dnl|rem)\b", re.I | re.M)  # comment signs that would be read as words
SENTENCE = re.compile(r"[\r\n]+|(?<=[.!?;:])\s+")
LICENCE_FILE = r"(?i)(^|/)(licen[sc]e|copying|notice)(\.[^/]*)?$"


class Matcher:
    """Templates as unit vectors of TF-IDF weights, and the words without which none is reached."""

    def __init__(self, templates, n: int, df: dict[str, int], least: float):
        self.unseen, self.least = math.log(1 + n) + 1, least
        self.idf = {t: math.log((1 + n) / (1 + df.get(t, 0))) + 1 for _, text in templates for t in words(text)}
        self.vectors, self.heavy = [], set()
        for name, text in templates:
            vector = {t: c * self.idf[t] for t, c in Counter(words(text)).items()}
            norm = math.sqrt(sum(w * w for w in vector.values()))
            vector = {t: w / norm for t, w in vector.items()}
            self.vectors.append((name, vector))
            left = 0.0
            for t in sorted(vector, key=vector.get):  # light words may stay out while together they can't reach least
                left += vector[t] ** 2
                if left >= least**2:
                    self.heavy.add(t)

        self.place = {t: k for k, t in enumerate(self.idf, 1)}  # 0 stands for all other words
        self.weight = np.array([self.unseen, *self.idf.values()])
        self.lengths = [len(words(text)) for _, text in templates]
        self.parts = np.array([[0.0, *(vector.get(t, 0.0) * w for t, w in self.idf.items())] for _, vector in self.vectors])

    def windows(self, terms: list[str], least: float):
        """(name, similarity) of windows of the templates' lengths, of those at or above least and better than the ones before.

        A word that occurs c times adds c to the square of the norm's bound and c * c to the square itself, so the bound from running
        sums is never under the similarity; only windows whose bound reaches least are counted out.
        """
        at = np.fromiter((self.place.get(t, 0) for t in terms), dtype=np.int64, count=len(terms))
        squares = np.concatenate([[0.0], np.cumsum(self.weight[at] ** 2)])
        for (name, vector), part, length in zip(self.vectors, self.parts, self.lengths):
            length, enough = min(length, len(at)), least
            dots = np.concatenate([[0.0], np.cumsum(part[at])])
            bound = (dots[length:] - dots[:-length]) / np.sqrt(squares[length:] - squares[:-length])
            for k in np.flatnonzero(bound >= least - 1e-6).tolist():
                if bound[k] >= enough - 1e-6:
                    cosine = self.cosine(Counter(terms[k : k + length]), vector)
                    if cosine >= enough:
                        enough = cosine
                        yield name, cosine

    def cosine(self, count: Counter, vector: dict[str, float]) -> float:
        weights = {t: c * self.idf.get(t, self.unseen) for t, c in count.items()}
        return sum(w * vector[t] for t, w in weights.items() if t in vector) / math.sqrt(sum(w * w for w in weights.values()))

    def best(self, text: str | None) -> tuple[str | None, float]:
        """Name and similarity of the nearest template; ties go to the smaller name."""
        found = (0.0, None)
        terms = words(text)
        if self.heavy.isdisjoint(terms):
            return None, 0.0

        def offer(name: str, cosine: float) -> None:
            nonlocal found
            if cosine > found[0] + 1e-12 or (abs(cosine - found[0]) <= 1e-12 and found[1] is not None and name < found[1]):
                found = (cosine, name)

        for sentence in SENTENCE.split(text):
            terms = words(sentence)
            if not self.heavy.isdisjoint(terms):
                count = Counter(terms)
                for name, vector in self.vectors:
                    offer(name, self.cosine(count, vector))
        for name, cosine in self.windows(words(COMMENT.sub(" ", text)), max(self.least, found[0])):
            offer(name, cosine)
        return (found[1], found[0]) if found[0] >= self.least else (None, 0.0)


def fit(docs: DataFrame, templates=TEMPLATES, least: float = 0.8) -> Matcher:
    """Count the templates' words over all texts."""
    terms = sorted({t for _, text in templates for t in words(text)})
    wanted = frozenset(terms)

    def count(batches):
        total: Counter = Counter()
        for batch in batches:
            for text in batch.column(0).to_pylist():
                total.update(wanted.intersection(words(text)))
                total[""] += 1
        yield pa.RecordBatch.from_pydict({"term": pa.array(list(total), pa.string()), "n": pa.array(list(total.values()), pa.int64())})

    counted = {r.term: r.n for r in docs.select("text").mapInArrow(count, "term string, n long").groupBy("term").agg(F.sum("n").alias("n")).collect()}
    return Matcher(templates, counted.pop("", 0), counted, least)


def scan(files: DataFrame, matcher: Matcher) -> DataFrame:
    """files (path, text and others) with own_licence and similarity; the text goes."""
    shared = ship(files.sparkSession, matcher)
    kept = [c for c in files.columns if c not in ("text", "own_licence", "similarity")]
    schema = files.select(*kept).schema.add("own_licence", "string").add("similarity", "double")

    def run(batches):
        matcher = opened(shared)
        for batch in batches:
            found = [matcher.best(t) for t in batch.column(0).to_pylist()]
            yield pa.RecordBatch.from_arrays([*batch.columns[1:], pa.array([f[0] for f in found], pa.string()), pa.array([f[1] for f in found], pa.float64())], names=[*batch.schema.names[1:], "own_licence", "similarity"])

    return files.select("text", *kept).mapInArrow(run, schema)


def directory(path):
    """What stands before the last slash; null at the top and for null."""
    return F.when(F.instr(path, "/") > 0, F.regexp_extract(path, "^(.*)/[^/]*$", 1))


def inherit(scanned: DataFrame) -> DataFrame:
    """scanned with inherited_licence, inherited_from and the resulting licence."""
    placed = scanned.drop("inherited_licence", "inherited_from", "licence").withColumn("_dir", directory(F.col("path")))
    named = placed.filter(F.col("_dir").isNotNull() & F.col("own_licence").isNotNull() & F.col("path").rlike(LICENCE_FILE))
    order = F.struct((-F.col("similarity")).alias("far"), F.col("own_licence").alias("name"), F.col("path"))
    given = named.groupBy(F.col("_dir").alias("ancestor")).agg(F.min(order).alias("best")).select("ancestor", F.col("best.name").alias("name"))
    parts = F.split("_dir", "/")
    ancestors = F.transform(F.sequence(F.lit(1), F.size(parts)), lambda k: F.struct(k.alias("depth"), F.array_join(F.slice(parts, 1, k), "/").alias("ancestor")))
    directories = placed.filter(F.col("_dir").isNotNull()).select("_dir").distinct()
    climbed = directories.select(F.col("_dir").alias("_of"), F.inline(ancestors)).join(given, "ancestor")
    nearest = climbed.groupBy("_of").agg(F.max(F.struct("depth", "ancestor", "name")).alias("_near"))
    joined = placed.join(nearest, F.col("_dir") == F.col("_of"), "left")
    return joined.withColumns({"inherited_licence": F.col("_near.name"), "inherited_from": F.col("_near.ancestor"), "licence": F.coalesce("own_licence", "_near.name")}).drop("_dir", "_of", "_near")


def licences(files: DataFrame, templates=TEMPLATES, least: float = 0.8) -> DataFrame:
    """Own, inherited and resulting licence of every file; the scan, which reads the texts, is written once for the joins of inherit()."""
    return inherit(persisted(scan(files, fit(files, templates, least)), "licence-scan"))


def document_paths(docs: DataFrame) -> DataFrame:
    """Paths for a table of documents: a tree of thousands and hundreds below each source, where ids divisible by 10 name the licence
    file of a directory, the higher up the rounder they are."""
    d = F.col("doc_id")
    top, sub = F.concat(F.lit("t"), F.floor(d / 1000)), F.concat(F.lit("s"), F.floor(d / 100) % 10)
    place = F.when(d % 1000 == 0, F.concat_ws("/", "source", F.lit("LICENSE"))).when(d % 100 == 0, F.concat_ws("/", "source", top, F.lit("LICENSE")))
    place = place.when(d % 10 == 0, F.concat_ws("/", "source", top, sub, F.concat(F.lit("LICENSE."), d))).otherwise(F.concat_ws("/", "source", top, sub, F.concat(d, F.lit(".txt"))))
    return docs.withColumn("path", place)
