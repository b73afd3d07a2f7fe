"""Choosing how to search: by the work of a scan, and by how much a sample of leaves survives."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import brute, search
from ..operators.index import Index


def survival(index: Index, planes: DataFrame, k: int, sample_planes: int = 10) -> float:
    """Share of points in leaves that a few planes' seed thresholds can't rule out."""
    some = planes.orderBy("qid").limit(sample_planes)
    lam = search.thresholds(index, some, k)
    left = search.reachable(search.directory(index, some), lam).agg(F.sum("n")).first()[0] or 0
    total = index.nodes.filter("node = 0").agg(F.sum("n")).first()[0] or 1
    return left / (total * max(some.count(), 1))


def mode(index: Index, planes: DataFrame, k: int, budget: float | None = None, scan_work: float = 1e9, least_gain: float = 0.1) -> str:
    """brute, where a scan is cheap or bounds rule out under least_gain of the points; frontier for few planes with few survivors; else shard_dfs."""
    if budget is not None:
        return "shard_dfs"
    points, count = index.nodes.filter("node = 0").agg(F.sum("n")).first()[0] or 0, planes.count()
    if points * count * index.d < scan_work:
        return "brute"
    share = survival(index, planes, k)
    if share > 1 - least_gain:
        return "brute"
    return "frontier" if count <= 16 and share < 0.3 else "shard_dfs"


def topk(index: Index, planes: DataFrame, k: int = 10, budget: float | None = None, force: str | None = None) -> DataFrame:
    """The k nearest points of each plane, in the mode that suits index and planes."""
    chosen = force or mode(index, planes, k, budget)
    if chosen == "brute":
        return brute.topk_arrow(index.points.select("id", "x"), planes, k)
    if chosen == "frontier":
        return search.frontier(index, planes, k)
    return search.budgeted(index, planes, k, budget) if budget is not None else search.shard_dfs(index, planes, k)
