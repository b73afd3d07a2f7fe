"""Query planes (qid, q, q_norm): q holds a unit normal and the offset."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import exprs as E
from . import tables

def finished(raw: DataFrame) -> DataFrame:
    return raw.withColumn("q", E.rescale(F.col("q"))).withColumn("q_norm", E.norm(F.col("q")))


def normals(spark: SparkSession, n: int, d: int) -> DataFrame:
    """(qid, w): unit normals by integer arithmetic, the same in any SQL engine."""
    raw = spark.range(n).select(F.col("id").alias("qid"), F.transform(F.sequence(F.lit(0).cast("long"), F.lit(d - 1).cast("long")), lambda j: coefficient(F.col("id"), j)).alias("w"))
    return raw.withColumn("w", F.transform("w", lambda v: v / E.norm(F.col("w"))))


def coefficient(i: F.Column, j: F.Column) -> F.Column:
    return ((31 * i * i + 17 * j * j + 101 * i * j + 7 * i + 13 * j + 5) % 2003 - 1001) / F.lit(1001.0)


def unit_anchor(i: F.Column, j: F.Column) -> F.Column:
    return ((13 * i + 29 * j + 3) % 97) / F.lit(97.0)


def anchored(planes: DataFrame, share: float) -> DataFrame:
    """Offsets that put the plane near (share < 1) or through (share 1) the anchor column."""
    offset = -F.lit(share) * E.dot(F.col("w"), F.col("anchor"))
    q = F.concat("w", F.array(offset))
    return planes.select("qid", q.alias("q")).withColumn("q_norm", E.norm(F.col("q")))


def through_rows(spark: SparkSession, points: DataFrame, n: int, d: int, share: float = 0.9, modulus: int = 500) -> DataFrame:
    """H1 (share 0.9) and H1x (share 1): planes anchored at the points with id (37 i) mod modulus."""
    rows = points.select(F.col("id").alias("anchor_id"), F.slice("x", 1, d).alias("anchor"))
    planes = normals(spark, n, d).withColumn("anchor_id", (37 * F.col("qid")) % modulus).join(rows, "anchor_id")
    return anchored(planes, share)


def through_box(spark: SparkSession, n: int, d: int, share: float = 0.9) -> DataFrame:
    """H1 for sets without small ids: anchors in the unit box, by integer arithmetic."""
    anchor = F.transform(F.sequence(F.lit(0).cast("long"), F.lit(d - 1).cast("long")), lambda j: unit_anchor(F.col("qid"), j))
    return anchored(normals(spark, n, d).withColumn("anchor", anchor), share)


def bisectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """H2: the planes half-way between each two label means; qid is 10 a + b."""
    means = tables.label_means(spark, sf_dir)
    a, b = means.select(F.col("label").alias("la"), F.col("mean").alias("a")), means.select(F.col("label").alias("lb"), F.col("mean").alias("b"))
    pairs = a.join(b, F.col("la") < F.col("lb"))
    half = F.zip_with("a", "b", lambda x, y: (x + y) / 2)
    normal = F.zip_with("a", "b", lambda x, y: x - y)
    raw = pairs.select((10 * F.col("la") + F.col("lb")).cast("long").alias("qid"), F.concat(normal, F.array(-E.dot(normal, half))).alias("q"))
    return finished(raw)


def axes(spark: SparkSession, d: int, at: float = 0.5) -> DataFrame:
    """H4: one plane a component, where it equals ``at``."""
    unit = F.transform(F.sequence(F.lit(0), F.lit(d - 1)), lambda j: F.when(j == F.col("qid"), 1.0).otherwise(0.0))
    return spark.range(d).select(F.col("id").alias("qid")).withColumn("q", F.concat(unit, F.array(F.lit(-at)))).withColumn("q_norm", E.norm(F.col("q")))


def far_off(spark: SparkSession, d: int) -> DataFrame:
    """H5: planes that miss the data, at offsets of 1.5 and 5 to either side."""
    offsets = F.array(*[F.lit(v) for v in (1.5, -1.5, 5.0, -5.0)])
    raw = normals(spark, 10, d).select("qid", F.concat("w", F.array(F.get(offsets, (F.col("qid") % 4).cast("int")))).alias("q"))
    return raw.withColumn("q_norm", E.norm(F.col("q")))


def odd(spark: SparkSession, sf_dir: str) -> DataFrame:
    """H6: the embeddings as normals, of each fifty one zero, one null and one NaN."""
    turn, w = F.col("vec_id") % 50, tables.doubles("embedding")
    normal = F.when(turn == 1, F.transform(w, lambda v: v * 0.0)).when(turn == 3, F.transform(w, lambda v: F.lit(float("nan")))).when(turn != 2, w)
    return tables.table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("qid"), F.concat(normal, F.array(F.lit(-0.5))).alias("q"))
