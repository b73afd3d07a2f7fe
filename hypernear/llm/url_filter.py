"""URL filter: prefix rules first, then boosted trees on lexical features of the url.

The longest rule that fits a url decides. Other urls are judged by trees over lengths, depth, digit ratio, entropy,
parameter counts and suffix statistics, learnt from labelled urls: ``fit`` takes a table of them and draws at most ``sample_rows`` by a hash. Suffix
statistics (how often a host's last one and two labels occur, and their share of label 1) are counted over labelled rows of other hosts than those
that the trees learn from; they stay a table of all suffixes, joined to the different hosts of what is judged. Where a table has
no labels, ``seeded`` gives weak ones: hosts on the seed list of unwanted words are labelled 1, all others 0. The words themselves are no
feature, so that what the trees can learn from them is how such hosts and urls look; with true labels nothing else changes.

Defined cases: a null url or one without :// has an empty host and path, fits no rule, and is judged like any other; repeated rows are judged each;
no labelled url at all gives the smoothed base rate; null labels are left out; an empty table gives an empty result; extra columns are dropped.
"""

from __future__ import annotations

import math
import re
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .boosting import BoostedTrees
from .common import opened, persisted, ship
from .html_text import after_scheme, host_of

# Verdicts by url prefix, and words of unwanted hosts.
RULES = (("org/", "allow"), ("example.org/es/", "block"), ("example.org/en/1", "block"), ("com/fr/", "allow"), ("com/de/", "block"))
SEEDS = "ads adult bet bets casino cheap escort free gambling loan lottery payday phish pills poker porn replica sex slots spam track viagra warez xxx"


def path_of(url: Column) -> Column:
    """What follows the host, up to ?, # or the end."""
    rest = F.regexp_extract(after_scheme(url), r"^[^/?#]*([^?#]*)", 1)
    return F.when(F.instr(url, "://") > 0, rest).otherwise("")


def rule_of(host: Column, path: Column, rules=RULES) -> Column:
    """The longest rule whose host is the url's or a parent of it and whose path begins the url's; null if none."""
    chosen = F.lit(None).cast("string")
    for rule, _ in sorted(rules, key=lambda r: len(r[0])):
        name, slash, rest = rule.partition("/")
        fits = ((host == name) | F.endswith(host, F.lit(f".{name}"))) & F.startswith(path, F.lit(slash + rest))
        chosen = F.when(fits, rule).otherwise(chosen)
    return chosen


FEATURES = 27
STATISTICS = ["often_one", "share_one", "often_two", "share_two"]  # of the last label, and of the last two


def entropy(text: str) -> float:
    n = len(text)
    return -sum(c / n * math.log2(c / n) for c in Counter(text).values()) if n else 0.0


def featurise(urls: list[str | None], statistics: np.ndarray) -> np.ndarray:
    """Features of urls; statistics holds the STATISTICS of their hosts, one row a url."""
    rows = []
    for url, known in zip(urls, statistics.tolist()):
        url = url or ""
        rest = url.partition("://")[2]
        host, path = (re.match(r"([^/?#]*)([^?#]*)", rest).groups()) if rest else ("", "")
        host, query = host.lower(), url.partition("?")[2].partition("#")[0]
        parts, names = host.split("."), re.split(r"[.\-]", host)
        digits = sum(map(str.isdigit, url))
        longest = max(names, key=len)
        rows.append((
            len(url), len(host), len(path), len(query), path.strip("/").count("/") + bool(path.strip("/")), len(parts), host.count("-"), path.count("-"),
            digits / max(len(url), 1), sum(map(str.isdigit, host)) / max(len(host), 1), entropy(url), entropy(host), entropy(path), entropy(longest),
            query.count("&") + bool(query), query.count("%"), "#" in url, url.startswith("https:"), "@" in host or ":" in host, host.startswith("www."),
            len(longest), sum(c in "aeiou" for c in host) / max(len(host), 1), len(set(host)) / max(len(host), 1), *known,
        ))
    return np.array(rows, dtype=float).reshape(len(urls), FEATURES)


def label_of(host: Column, seeds: str = SEEDS) -> Column:
    """1 where a part of the host between dots and hyphens is a seed word."""
    return F.arrays_overlap(F.split(host, r"[.\-]"), F.array(*map(F.lit, seeds.split()))).cast("int")


def suffixes(host: Column) -> dict[str, Column]:
    """A host's last label, and its last two."""
    return {"one": F.element_at(F.split(host, r"\."), -1), "two": F.substring_index(host, ".", -2)}


def suffix_statistics(labelled: DataFrame) -> DataFrame:
    """(suffix, often, share) of every suffix of labelled rows (host, y): how often it occurs, and its smoothed share of label 1."""
    hosts = labelled.groupBy("host").agg(F.count("*").alias("n"), F.sum("y").alias("pos"))  # hot hosts are summed before their suffixes are
    each = hosts.select("n", "pos", F.explode(F.array_distinct(F.array(*suffixes(F.col("host")).values()))).alias("suffix"))
    counted = each.groupBy("suffix").agg(F.sum("n").alias("n"), F.sum("pos").alias("pos"))
    return persisted(counted.select("suffix", F.log1p("n").alias("often"), ((F.col("pos") + 1) / (F.col("n") + 2)).alias("share")), "url-suffixes")


def host_statistics(hosts: DataFrame, statistics: DataFrame) -> DataFrame:
    """(host and STATISTICS) of every different host; a suffix that was not met is rare and as likely 1 as 0."""
    found = hosts.select("host").distinct()
    for name, end in suffixes(F.col("host")).items():
        mine = statistics.select(F.col("suffix").alias(f"_{name}"), F.col("often").alias(f"often_{name}"), F.col("share").alias(f"share_{name}"))
        found = found.join(mine, end == F.col(f"_{name}"), "left").drop(f"_{name}")
    return persisted(found.na.fill({"often_one": 0.0, "share_one": 0.5, "often_two": 0.0, "share_two": 0.5}), "url-hosts")  # a table of measured size: Spark broadcasts it while it is small, and splits hot hosts if not


def seeded(urls: DataFrame, seeds: str = SEEDS) -> DataFrame:
    """(url, y) for urls without labels: 1 where the host has a seed word, else 0."""
    return urls.select("url", label_of(host_of(F.col("url")), seeds).alias("y"))


def fit(labelled: DataFrame, sample_rows: int = 20_000, least_positive: int = 20) -> tuple[DataFrame, BoostedTrees]:
    """Suffix statistics and trees from labelled urls (url, y).

    Hosts are halved by a hash: the rows of one half make the statistics, at most about sample_rows of the other the trees, so that no row
    that the trees learn from is counted in its own statistics. With few positive rows in a half both use all rows.
    """
    side = F.pmod(F.xxhash64("host", F.lit(23)), F.lit(2))
    known = labelled.select("url", "y", host_of(F.col("url")).alias("host")).filter("host <> '' and y is not null").withColumn("side", side)
    counts = {r.side: (r.n, r.pos) for r in known.groupBy("side").agg(F.count("*").alias("n"), F.sum("y").alias("pos")).collect()}
    halved = all(min(counts.get(k, (0, 0))[1], counts.get(k, (0, 0))[0] - counts.get(k, (0, 0))[1]) >= least_positive for k in (0, 1))
    statistics = suffix_statistics(known.filter("side = 0") if halved else known)
    rest = known.filter("side = 1") if halved else known
    n = sum(counts[k][0] for k in counts if k == 1 or not halved)
    drawn = rest.filter(F.pmod(F.xxhash64("url", F.lit(11)), F.lit(1_000_003)) < F.lit(min(1.0, sample_rows / max(n, 1)) * 1_000_003)).select("url", "y", "host").distinct()
    rows = sorted(map(tuple, drawn.join(host_statistics(drawn, statistics), "host").select("url", "y", *STATISTICS).collect()))
    y = np.array([r[1] for r in rows], dtype=float)
    met = np.array([r[2:] for r in rows], dtype=float).reshape(len(rows), len(STATISTICS))
    return statistics, BoostedTrees(rounds=40, depth=4).fit(featurise([r[0] for r in rows], met), y)


def judge(pages: DataFrame, model: tuple[DataFrame, BoostedTrees], rules=RULES, least: float = 0.5) -> DataFrame:
    """page_id, host, path, rule, verdict and the trees' score of every row."""
    statistics, trees = model
    shared = ship(pages.sparkSession, trees)

    def run(batches):
        trees = opened(shared)
        for batch in batches:
            known = np.stack([batch.column(k).to_numpy(zero_copy_only=False) for k in range(2, 2 + len(STATISTICS))], axis=1)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(trees.predict(featurise(batch.column(1).to_pylist(), known)), pa.float64())], names=["page_id", "url", "score"])

    hosted = pages.select("page_id", "url", host_of(F.col("url")).alias("_host"))
    hosts = host_statistics(hosted.filter("_host <> ''").select(F.col("_host").alias("host")), statistics)
    placed = hosted.join(hosts, F.col("_host") == F.col("host"), "left")
    scored = placed.select("page_id", "url", *(F.coalesce(c, F.lit(0.0)).alias(c) for c in STATISTICS)).mapInArrow(run, "page_id long, url string, score double")
    parted = scored.select("page_id", host_of(F.col("url")).alias("host"), path_of(F.col("url")).alias("path"), "score")
    ruled = parted.withColumn("rule", rule_of(F.col("host"), F.col("path"), rules))
    by_rule = F.element_at(F.create_map(*[F.lit(x) for rule in rules for x in rule]), F.col("rule"))
    verdict = F.when(F.col("rule").isNotNull(), by_rule).when(F.col("score") >= least, "block").otherwise("allow")
    return ruled.select("page_id", "host", "path", "rule", verdict.alias("verdict"), "score")
