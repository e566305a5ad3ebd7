"""Readers with explicit schemas and writers for public tables and released sets."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from ..schemas import struct


def load(spark: SparkSession, path: str, kind: str = "parquet", spec: str | None = None) -> DataFrame:
    """Parquet and ORC carry their schema; CSV and JSON catalogs must name a contract."""
    if kind in ("csv", "json"):
        if spec is None:
            raise ValueError("csv and json need a contract")
        reader = spark.read.schema(struct(spec))
        return reader.option("header", True).csv(path) if kind == "csv" else reader.json(path)
    return getattr(spark.read, kind)(path)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def save(df: DataFrame, path: str, by: list[str] | None = None, kind: str = "parquet") -> None:
    """Write a table, partitioned if asked; kind 'noop' only runs the plan."""
    if kind == "noop":
        df.write.format("noop").mode("overwrite").save()
        return
    writer = df.write.mode("overwrite")
    (writer.partitionBy(*by) if by else writer).format(kind).save(path)


def save_bucketed(df: DataFrame, name: str, key: str = "traj_id", buckets: int = 64) -> None:
    """A bucketed table, so that joins of real and released sets on the key need no shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).format("parquet").saveAsTable(name)


def staged(df: DataFrame) -> DataFrame:
    """Cut lineage: write a table below spark.checkpoint.dir (the local temp folder where unset) and read it back."""
    import tempfile
    import uuid

    spark = df.sparkSession
    root = spark.conf.get("spark.checkpoint.dir", None) or tempfile.gettempdir() + "/pointveil-stage"
    path = f"{root.rstrip('/')}/{spark.sparkContext.applicationId}/{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)
