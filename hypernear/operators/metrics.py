"""Accuracy and cost measures."""

from __future__ import annotations

import statistics
import time
from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def timed(action: Callable[[], object], runs: int = 5) -> float:
    """Mean wall-clock seconds of an action over several runs."""
    seconds = []
    for _ in range(runs):
        begun = time.perf_counter()
        action()
        seconds.append(time.perf_counter() - begun)
    return statistics.mean(seconds)


def drain(df: DataFrame) -> None:
    """Compute all rows and keep none."""
    df.write.format("noop").mode("overwrite").save()


def recall(found: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    """(qid, recall, returned): the share of the true k (or all points, if fewer) that was found."""
    hits = truth.select("qid", "id").join(found.select("qid", "id", F.lit(1).alias("hit")), ["qid", "id"], "left")
    by_plane = hits.groupBy("qid").agg((F.count("hit") / F.least(F.lit(k), F.count("*"))).alias("recall"))
    returned = found.groupBy("qid").agg(F.count("*").alias("returned"))
    return by_plane.join(returned, "qid", "left").select("qid", "recall", F.coalesce("returned", F.lit(0)).alias("returned"))


def margin_ratio(found: DataFrame, truth: DataFrame) -> DataFrame:
    """(qid, ratio): sum of found over sum of true margins; 1 is exact."""
    total = lambda df, name: df.groupBy("qid").agg(F.sum("margin").alias(name))
    return total(found, "found").join(total(truth, "true"), "qid").select("qid", F.when(F.col("true") > 0, F.col("found") / F.col("true")).otherwise(F.lit(1.0)).alias("ratio"))


def pareto(runs: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """Of (recall, seconds) rows, the least time at each recall or better; by: for each value of these columns."""
    window = Window.partitionBy(*by).orderBy(F.desc("recall")).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    least = runs.groupBy(*by, "recall").agg(F.min("seconds").alias("least"))  # a row a recall is all that the window sees
    return least.select(*by, "recall", F.min("least").over(window).alias("seconds"))


def percentiles(values: DataFrame, column: str, shares: tuple[float, ...], bins: int = 4096, few: int = 50_000) -> list[float | None]:
    """The exact percentiles of a column of numbers, as F.percentile interpolates them, without all values in one task.

    Values are counted by bins; a bin that holds a wanted place is cut into bins again, until it holds at most ``few`` different values' worth of
    rows or one value. Only those bins' values come to the driver. Each round is one pass.
    """
    v = F.col(column)
    values = values.filter(v.isNotNull()).select(v.cast("double").alias(column))
    total = values.agg(F.count("*").alias("n"), F.min(column).alias("low"), F.max(column).alias("high")).first()
    if not total.n:
        return [None for _ in shares]
    places = [(total.n - 1) * p for p in shares]
    wanted = sorted({int(r) for p in places for r in (np.floor(p), np.ceil(p))})
    found: dict[int, float] = {}
    cut, listed = [(total.low, total.high, 0, total.n)], []  # (low, high, rows before, rows)
    while cut:
        which, at = F.lit(None).cast("int"), F.lit(None).cast("int")
        for n, (low, high, _, _) in enumerate(cut):
            inside = v.between(low, high)
            which = F.when(inside, F.lit(n)).otherwise(which)
            at = F.when(inside, F.least(F.floor((v / bins - low / bins) / (high / bins - low / bins) * bins), F.lit(bins - 1)).cast("int") if high > low else F.lit(0)).otherwise(at)
        counted = values.select(column, which.alias("which"), at.alias("at")).filter("which is not null").groupBy("which", "at").agg(F.min(column).alias("low"), F.max(column).alias("high"), F.count("*").alias("n"))
        rows, again = sorted((r.which, r.at, r.low, r.high, r.n) for r in counted.collect()), []
        for n, (_, _, before, _) in enumerate(cut):
            for _, _, low, high, held in (r for r in rows if r[0] == n):
                mine = [r for r in wanted if before <= r < before + held]
                if mine and low == high:
                    found |= dict.fromkeys(mine, low)
                elif mine:
                    (listed if held <= few or (low, high) == cut[n][:2] else again).append((low, high, before, held))  # a range that can't be cut is listed
                before += held
        cut = again
    if listed:
        inside = F.lit(False)
        for low, high, _, _ in listed:
            inside = inside | v.between(low, high)
        counts = sorted((r[0], r[1]) for r in values.filter(inside).groupBy(column).count().collect())
        for low, high, before, _ in listed:
            for value, held in ((x, n) for x, n in counts if low <= x <= high):
                found |= dict.fromkeys([r for r in wanted if before <= r < before + held], value)
                before += held
    out = []
    for p in places:
        low, high = int(np.floor(p)), int(np.ceil(p))
        a, b = found[low], found[high]
        out.append(a if low == high or a == b else (high - p) * a + (p - low) * b)
    return out


def at_recall(runs: DataFrame, target: float, *by: str) -> DataFrame:
    """The cheapest run of each method (or of each value of by) that reaches the target."""
    return runs.filter(F.col("recall") >= target).groupBy(*(by or ("method",))).agg(F.min("seconds").alias("seconds"), F.min_by("recall", "seconds").alias("recall"))


def ratios(runs: DataFrame, value: str, by: str = "method") -> DataFrame:
    """Each method's value over each other's."""
    a, b = runs.select(F.col(by).alias("a"), F.col(value).alias("va")), runs.select(F.col(by).alias("b"), F.col(value).alias("vb"))
    return a.join(b, F.col("a") != F.col("b")).select("a", "b", (F.col("va") / F.col("vb")).alias("ratio"))


def tightness(bounds: DataFrame) -> DataFrame:
    """Of rows (margin, ball, cone): how much the cone adds and how near the bounds come."""
    return bounds.agg(F.avg(F.col("cone") - F.col("ball")).alias("cone_gain"), F.avg(F.when(F.col("margin") > 0, F.col("ball") / F.col("margin"))).alias("ball_share"), F.avg(F.when(F.col("margin") > 0, F.col("cone") / F.col("margin"))).alias("cone_share"))


def profile(counters: DataFrame, d: int) -> DataFrame:
    """Where the work of a search goes, in multiplications: verification, centre products, and constant-time bounds."""
    return counters.agg((F.sum("verified") * d).alias("verification"), (F.sum("center_products") * d).alias("centres"), (F.sum("nodes_visited") + F.sum("cone_evals")).alias("bounds"))


def time_profile(counters: DataFrame) -> DataFrame:
    """Where the seconds of walks go: verification, and bounds with centre products."""
    return counters.agg((F.sum("verify_ns") / 1e9).alias("verification"), ((F.sum("walk_ns") - F.sum("verify_ns")) / 1e9).alias("lookup"))
