"""Versioned policies: a directory for each version; readers see a version once its manifest row is written."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from aclvec.operators.policy import Policy
from aclvec.schemas import checked

TABLES = ("docs", "users", "ua", "pa")


def commit(p: Policy, path: str, version: int) -> None:
    """Writes the tables of a version, then its manifest row; a failed commit leaves the older versions as they are."""
    for name in TABLES:
        df = getattr(p, name)
        (checked(df, name) if name in ("ua", "pa") else df).write.mode("overwrite").parquet(f"{path}/v{version}/{name}")
    p.docs.sparkSession.createDataFrame([(version,)], "version int").coalesce(1).write.mode("append").parquet(f"{path}/manifest")


def latest(spark: SparkSession, path: str) -> int:
    return spark.read.schema("version int").parquet(f"{path}/manifest").agg(F.max("version")).first()[0]


def load(spark: SparkSession, path: str, version: int | None = None) -> Policy:
    version = latest(spark, path) if version is None else version
    return Policy(*(spark.read.parquet(f"{path}/v{version}/{name}") for name in TABLES))


def write_rows(df: DataFrame, path: str, kind: str) -> None:
    """Edge tables exported as csv, json, orc or parquet."""
    w = df.write.mode("overwrite")
    (w.option("header", True).csv(path) if kind == "csv" else w.format(kind).save(path))


def read_rows(spark: SparkSession, path: str, kind: str, schema: str) -> DataFrame:
    r = spark.read.schema(schema)
    return r.option("header", True).csv(path) if kind == "csv" else r.format(kind).load(path)
