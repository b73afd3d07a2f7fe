"""SQL names for the expressions, and Python table and aggregate functions."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

VECTOR = T.ArrayType(T.DoubleType())
DOT = "aggregate(zip_with({a}, {b}, (x, y) -> x * y), 0D, (s, v) -> s + v)"

SCALARS = {
    "hn_absdot(x ARRAY<DOUBLE>, q ARRAY<DOUBLE>) RETURNS DOUBLE": f"abs({DOT.format(a='x', b='q')})",
    "hn_margin(p ARRAY<DOUBLE>, q ARRAY<DOUBLE>) RETURNS DOUBLE": f"abs({DOT.format(a='p', b='slice(q, 1, size(p))')} + get(q, size(p))) / sqrt({DOT.format(a='slice(q, 1, size(p))', b='slice(q, 1, size(p))')})",
    "hn_augment(p ARRAY<DOUBLE>) RETURNS ARRAY<DOUBLE>": "concat(p, array(1D))",
    "hn_normalize(q ARRAY<DOUBLE>) RETURNS ARRAY<DOUBLE>": f"transform(q, w -> w / sqrt({DOT.format(a='slice(q, 1, size(q) - 1)', b='slice(q, 1, size(q) - 1)')}))",
    "hn_node_bound(ip DOUBLE, q_norm DOUBLE, radius DOUBLE) RETURNS DOUBLE": "greatest(abs(ip) - q_norm * radius, 0D)",
    "hn_ball_bound(ip DOUBLE, q_norm DOUBLE, r_x DOUBLE) RETURNS DOUBLE": "greatest(abs(ip) - q_norm * r_x, 0D)",
    "hn_cone_bound(along DOUBLE, across DOUBLE, x_par DOUBLE, x_perp DOUBLE) RETURNS DOUBLE": "CASE WHEN along * x_par - across * x_perp > 0 THEN along * x_par - across * x_perp WHEN along * x_par + across * x_perp < 0 THEN -(along * x_par + across * x_perp) ELSE 0D END",
}


def register(spark: SparkSession) -> None:
    """Create the temporary SQL functions; the analyzer inlines their bodies into the plan."""
    for head, body in SCALARS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURN {body}")
    spark.udf.register("vec_sum", vec_sum)
    spark.udf.register("vec_mean", vec_mean)
    spark.udf.register("vec_radius", vec_radius)
    spark.udf.register("absdot_batch", absdot_batch)
    spark.udtf.register("hn_lift", Lift)
    spark.udtf.register("hn_topk", TopK)


@F.pandas_udf(VECTOR)
def vec_sum(vectors: pd.Series) -> list:
    """Componentwise sum of a group's vectors."""
    return np.sum(np.stack(vectors.to_numpy()), axis=0).tolist()


@F.pandas_udf(VECTOR)
def vec_mean(vectors: pd.Series) -> list:
    return np.mean(np.stack(vectors.to_numpy()), axis=0).tolist()


@F.pandas_udf(T.DoubleType())
def vec_radius(vectors: pd.Series, centers: pd.Series) -> float:
    """Greatest distance of a group's vectors from the group's centre."""
    return float(np.sqrt(((np.stack(vectors.to_numpy()) - centers.iloc[0]) ** 2).sum(axis=1).max()))


@F.pandas_udf(T.DoubleType())
def absdot_batch(x: pd.Series, q: pd.Series) -> pd.Series:
    """Margins of whole Arrow batches; products are added as expressions and SQL add them."""
    X, Q = np.stack(x.to_numpy()), np.stack(q.to_numpy())
    total = X[:, 0] * Q[:, 0]
    for j in range(1, X.shape[1]):
        total = total + X[:, j] * Q[:, j]
    return pd.Series(np.abs(total))


@F.udtf(returnType=T.StructType([T.StructField("i", T.IntegerType()), T.StructField("j", T.IntegerType()), T.StructField("value", T.DoubleType())]))
class Lift:
    """The components of a vector's quadratic lift."""

    def eval(self, x: list):
        for i, a in enumerate(x):
            yield i, i, a * a
            for j in range(i + 1, len(x)):
                yield i, j, a * x[j] * 2**0.5


@F.udtf(returnType=T.StructType([T.StructField("id", T.LongType()), T.StructField("margin", T.DoubleType())]))
class TopK:
    """The k points of a partition nearest to one plane: hn_topk(TABLE(points) PARTITION BY .., q, k)."""

    def __init__(self):
        self.best: list = []
        self.k = 0

    def eval(self, row, q: list, k: int):
        self.k = k
        total = 0.0
        for a, b in zip(row["x"], q):  # a left fold: sum() would compensate for rounding
            total += a * b
        self.best.append((abs(total), row["id"]))
        if len(self.best) > 4096:
            self.best = sorted(self.best)[:k]

    def terminate(self):
        for margin, id_ in sorted(self.best)[: self.k]:
            yield id_, margin
