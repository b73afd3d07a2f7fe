"""The given tables as vector sets (id, x): x is the vector with a one appended.

All recipes use arithmetic that SQL engines evaluate alike, so that oracles can repeat them.
"""

from __future__ import annotations

import struct

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import exprs as E


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def doubles(column) -> F.Column:
    return F.col(column).cast("array<double>")


def emb(spark: SparkSession, sf_dir: str) -> DataFrame:
    """V1: the embeddings as they are."""
    return table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), E.augment(doubles("embedding")).alias("x"), F.col("label").cast("long").alias("label"))


def emb_scaled(spark: SparkSession, sf_dir: str) -> DataFrame:
    """V2: off the unit sphere, by one plus the label."""
    scaled = F.transform(doubles("embedding"), lambda v: v * (1 + F.col("label")))
    return table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), E.augment(scaled).alias("x"), F.col("label").cast("long").alias("label"))


def label_means(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mean vector of each label, rounded so that the order of addition can't show."""
    long = table(spark, sf_dir, "embeddings").select("label", F.posexplode(doubles("embedding")).alias("pos", "v"))
    means = long.groupBy("label", "pos").agg(F.round(F.avg("v"), 9).alias("v"))
    return means.groupBy("label").agg(F.transform(F.array_sort(F.collect_list(F.struct("pos", "v"))), lambda s: s["v"]).alias("mean"))


def emb_cluster(spark: SparkSession, sf_dir: str, factor: float = 0.1) -> DataFrame:
    """V3: unit label mean plus a share of the own vector."""
    means = label_means(spark, sf_dir).select("label", F.transform("mean", lambda v: v / E.norm(F.col("mean"))).alias("centre"))
    moved = F.zip_with("centre", doubles("embedding"), lambda c, v: c + v * factor)
    joined = table(spark, sf_dir, "embeddings").join(F.broadcast(means), "label")  # ten labels
    return joined.select(F.col("vec_id").alias("id"), E.augment(moved).alias("x"), F.col("label").cast("long").alias("label"))


def line_id() -> F.Column:
    """60 bits of an md5 of the columns that tell lines apart."""
    days, cents = F.datediff(F.col("l_shipdate").cast("date"), F.lit("1970-01-01").cast("date")), F.round(F.col("l_extendedprice") * 100).cast("long")
    key = F.concat_ws("-", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", cents, days)
    return F.conv(F.substring(F.md5(key), 1, 15), 16, 10).cast("long")


def li4(spark: SparkSession, sf_dir: str, copies: int = 1) -> DataFrame:
    """V4: four scaled measures of each line. V9: copies > 1 adds jittered copies."""
    values = [F.col("l_quantity") / 50.0, F.col("l_extendedprice") / 105000.0, F.col("l_discount") * 10.0, F.col("l_tax") * 12.5]
    lines = table(spark, sf_dir, "lineitem").select(line_id().alias("id"), *[v.alias(f"p{i}") for i, v in enumerate(values)], "l_orderkey", "l_returnflag", "l_linestatus")
    numbers = [F.col(f"p{i}") for i in range(len(values))]
    if copies > 1:
        lines = lines.repartition("id").withColumn("copy", F.explode(F.array(*[F.lit(n).cast("long") for n in range(copies)]))).withColumn("id", F.xxhash64("id", "copy"))
        numbers = [F.when(F.col("copy") == 0, v).otherwise(v + F.pmod(F.xxhash64("id", F.lit(i)), F.lit(1000)) / 1e6) for i, v in enumerate(numbers)]
    return lines.select("id", F.array(*numbers, F.lit(1.0)).alias("x"), "l_orderkey", "l_returnflag", "l_linestatus")


def li6(spark: SparkSession, sf_dir: str) -> DataFrame:
    days = F.datediff(F.col("l_shipdate").cast("date"), F.lit("1970-01-01").cast("date"))
    values = [F.col("l_quantity") / 50.0, F.col("l_extendedprice") / 105000.0, F.col("l_discount") * 10.0, F.col("l_tax") * 12.5, days / 3000.0, F.col("l_linenumber") / 7.0]
    return table(spark, sf_dir, "lineitem").select(line_id().alias("id"), E.augment(F.array(*[v.cast("double") for v in values])).alias("x"))


def user_rates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """V5: mean value and count of each event type, by user."""
    kinds = ("click", "error", "login", "purchase", "view")
    events = table(spark, sf_dir, "events")
    is_kind = lambda k: F.col("event_type") == k
    aggregates = [F.round(F.coalesce(F.avg(F.when(is_kind(k), F.col("value"))), F.lit(0.0)) / 100, 9).alias(f"m{i}") for i, k in enumerate(kinds)] + [(F.count_if(is_kind(k)) / 100.0).alias(f"c{i}") for i, k in enumerate(kinds)]
    names = [f"m{i}" for i in range(5)] + [f"c{i}" for i in range(5)]
    return events.groupBy(F.col("user_id").alias("id")).agg(*aggregates).select("id", E.augment(F.array(*names)).alias("x"))


def term_frequencies(texts: DataFrame, key: str, text: str, d: int) -> DataFrame:
    """Shares of a text's words in d buckets, by 32 bits of the word's md5; texts without letters give a zero vector."""
    words = F.filter(F.split(F.lower(F.col(text)), "[^a-z]+"), lambda w: w != "")
    bucket = F.transform(words, lambda w: F.pmod(F.conv(F.substring(F.md5(w), 1, 8), 16, 10).cast("long"), F.lit(d)).cast("int"))
    hashed = texts.select(F.col(key).cast("long").alias("id"), bucket.alias("b"))
    most = max(1, (1 << 20) // d)  # rows of a batch of results

    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, most):
                some = batch.slice(at, most)
                n, sizes = some.num_rows, pc.fill_null(pc.list_value_length(some.column(1)), 0).to_numpy()
                counts = np.bincount(np.repeat(np.arange(n), sizes) * d + some.column(1).flatten().to_numpy(), minlength=n * d).reshape(n, d)
                x = np.column_stack([counts / np.maximum(sizes, 1)[:, None], np.ones(n)])
                lists = pa.ListArray.from_arrays(pa.array(np.arange(n + 1, dtype=np.int32) * (d + 1)), pa.array(x.ravel()))
                yield pa.RecordBatch.from_arrays([some.column(0), lists], names=["id", "x"])

    return hashed.mapInArrow(run, "id long, x array<double>")


def doc_tf(spark: SparkSession, sf_dir: str, d: int = 64, below: int | None = None) -> DataFrame:
    """V6; below: only documents with ids below that."""
    texts = table(spark, sf_dir, "documents")
    return term_frequencies(texts if below is None else texts.filter(F.col("doc_id") < below), "doc_id", "text", d)


def page_tf(spark: SparkSession, sf_dir: str, d: int = 128) -> DataFrame:
    """V7, pages."""
    return term_frequencies(table(spark, sf_dir, "pages"), "page_id", "html", d)


def conv_tf(spark: SparkSession, sf_dir: str, d: int = 128) -> DataFrame:
    """V7, conversation turns."""
    turns = table(spark, sf_dir, "conversations").withColumn("turn_id", F.col("conv_id") * 1000 + F.col("turn"))
    return term_frequencies(turns, "turn_id", "text", d)


def part2(spark: SparkSession, sf_dir: str) -> DataFrame:
    """V8: size and price of parts; holds duplicates."""
    return table(spark, sf_dir, "part").select(F.col("p_partkey").alias("id"), E.augment(F.array(F.col("p_size") / 50.0, F.col("p_retailprice") / 1000.0)).alias("x"))


def order2(spark: SparkSession, sf_dir: str) -> DataFrame:
    days = F.datediff(F.col("o_orderdate").cast("date"), F.lit("1970-01-01").cast("date"))
    return table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("id"), E.augment(F.array(F.col("o_totalprice") / 5e5, (days / 3000.0).cast("double"))).alias("x"))


def cust3(spark: SparkSession, sf_dir: str) -> DataFrame:
    segment = F.length("c_mktsegment") / 5.0
    return table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("id"), E.augment(F.array(F.col("c_acctbal") / 1e4, F.col("c_nationkey") / 25.0, segment)).alias("x"))


def from_sparse(df: DataFrame, column: str, d: int) -> DataFrame:
    """MAP<STRING, DOUBLE> or MAP<INT, DOUBLE> vectors made dense."""
    kind = df.schema[column].dataType.keyType.simpleString()
    dense = F.transform(F.sequence(F.lit(0), F.lit(d - 1)), lambda i: F.coalesce(F.try_element_at(column, i.cast(kind)), F.lit(0.0)))
    return df.withColumn("x", E.augment(dense))


# --- files ---


def read_vectors(spark: SparkSession, path: str, kind: str = "parquet", d: int | None = None) -> DataFrame:
    """(id, p) from Parquet, ORC, JSON, CSV (id, then one column a component) or text (id, then components, by blanks)."""
    if kind in ("parquet", "orc"):
        return spark.read.format(kind).load(path).select(F.col("id").cast("long"), doubles("p").alias("p"))
    if kind == "json":
        return spark.read.schema("id long, p array<double>").json(path)
    if kind == "csv":
        names = [f"c{i}" for i in range(d)]
        return spark.read.schema("id long, " + ", ".join(f"{n} double" for n in names)).csv(path).select("id", F.array(*names).alias("p"))
    if kind == "text":
        parts = F.split(F.trim("value"), r"\s+")
        return spark.read.text(path).select(F.get(parts, F.lit(0)).cast("long").alias("id"), F.slice(parts, F.lit(2), F.size(parts) - 1).cast("array<double>").alias("p"))
    if kind == "fvecs":
        return read_records(spark, path)
    raise ValueError(f"no reader for {kind}")


def read_records(spark: SparkSession, path: str) -> DataFrame:
    """Binary records of a 4-byte dimension and as many 4-byte floats; ids count from 0 in each file."""

    def run(batches):
        for batch in batches:
            for content in batch.column(0).to_pylist():
                d = struct.unpack_from("<i", content)[0]
                rows = np.frombuffer(content, dtype="<f4").reshape(-1, d + 1)[:, 1:].astype(float)
                yield pa.RecordBatch.from_pydict({"id": pa.array(range(len(rows)), pa.int64()), "p": pa.array(list(rows), pa.list_(pa.float64()))})

    return spark.read.format("binaryFile").load(path).select("content").mapInArrow(run, "id long, p array<double>")
