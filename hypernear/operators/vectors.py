"""Checks and preparation of vector sets and planes."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import exprs as E


def finite(v) -> F.Column:
    """Whether an array is there, not empty, and holds only finite numbers."""
    return F.coalesce(v.isNotNull() & (F.size(v) > 0) & ~F.exists(v, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf"))), F.lit(False))


def validate(df: DataFrame, column: str = "x") -> DataFrame:
    """Violations as (reason, n): unusable vectors, lengths other than the commonest, and repeated ids."""
    good = df.filter(finite(F.col(column)))
    lengths = good.groupBy(F.size(column).alias("d")).count()
    most = F.broadcast(lengths.agg(F.max_by("d", F.struct("count", "d")).alias("usual")))  # one row
    bad = df.filter(~finite(F.col(column))).agg(F.count("*").alias("n")).select(F.lit("unusable vector").alias("reason"), "n")
    odd = lengths.join(most, F.col("d") != F.col("usual")).agg(F.coalesce(F.sum("count"), F.lit(0)).alias("n")).select(F.lit("other length").alias("reason"), "n")
    again = df.groupBy("id").count().filter("count > 1").agg(F.coalesce(F.sum(F.col("count") - 1), F.lit(0)).alias("n")).select(F.lit("repeated id").alias("reason"), "n")
    return bad.unionByName(odd).unionByName(again)


def dedup(df: DataFrame, column: str = "x") -> DataFrame:
    """One row a vector, with its least id: grouped by a hash first, so that rows shuffle on 8 bytes."""
    return df.groupBy(F.xxhash64(column).alias("_hash"), column).agg(F.min("id").alias("id")).select("id", column)


def normalize_queries(planes: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Planes with unit normals and q_norm, and the rejected rows with a reason."""
    usable = finite(F.col("q")) & (F.size("q") > 1)
    marked = planes.withColumn("reason", F.when(~F.coalesce(usable, F.lit(False)), "not finite").when(E.norm(E.normal_of(F.col("q"))) == 0, "zero normal"))
    good = marked.filter("reason is null").drop("reason").withColumn("q", E.rescale(F.col("q"))).withColumn("q_norm", E.norm(F.col("q")))
    return good, marked.filter("reason is not null").select("qid", "reason")


def dataset_stats(df: DataFrame, name: str, column: str = "x") -> DataFrame:
    """Points, raw dimension and bytes at four a component."""
    d = F.size(column) - 1
    return df.agg(F.count("*").alias("n"), F.max(d).cast("long").alias("d"), F.sum((d * 4).cast("long")).alias("bytes")).select(F.lit(name).alias("name"), "n", "d", "bytes")
