"""Tables in the folder that driver and executors share."""

from __future__ import annotations

import pickle
import re
import uuid

from pyspark import Broadcast, cloudpickle
from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """spark.checkpoint.dir as the session has it. Where it is unset, a default in local mode only: a cluster has to name its shared folder."""
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not root and not re.match(r"local($|\[)", spark.sparkContext.master):
        raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
    return (root or "/tmp/checkpoints").rstrip("/")


def fresh_path(spark: SparkSession, label: str) -> str:
    return f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"


def persisted(df: DataFrame, label: str) -> DataFrame:
    """df as a Parquet table: cuts lineage, survives lost executors, and has a known size."""
    path = fresh_path(df.sparkSession, label)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def ship(spark: SparkSession, thing) -> Broadcast:
    """Broadcast of a small object as bytes that open without this package; see opened()."""
    return spark.sparkContext.broadcast(cloudpickle.dumps(thing))


def opened(shipped: Broadcast):
    return pickle.loads(shipped.value)
