"""The given tables with the columns that a query needs."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def scratch(spark: SparkSession) -> str:
    """A new path in the shared folder that the session names. Where it names none, a temporary one serves a local session; on a cluster it is an error."""
    base = spark.sparkContext.getCheckpointDir() or spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        base = tempfile.mkdtemp(prefix="aclvec-")
    return f"{base.rstrip('/')}/{uuid.uuid4().hex}"


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """vec_id, doc_id, embedding, label of `embeddings`: each vector is its own document."""
    return read(spark, sf_dir, "embeddings").select("vec_id", F.col("vec_id").alias("doc_id"), "embedding", "label")


def bucketed(df: DataFrame, name: str, keys: list[str], n_buckets: int) -> DataFrame:
    """`df` as a table named `name` (one of that name is replaced), in the shared folder, dealt and sorted by `keys`.

    Tables with the same number of buckets join on their keys without a shuffle.
    """
    spark = df.sparkSession
    spark.sql(f"DROP TABLE IF EXISTS {name}")
    rows = df.repartition(n_buckets, *keys)  # one file a bucket
    rows.write.bucketBy(n_buckets, *keys).sortBy(*keys).option("path", scratch(spark)).saveAsTable(name)
    return spark.table(name)
