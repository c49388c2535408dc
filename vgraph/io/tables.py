"""Readers and writers around Spark's own sources."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def read_table(spark: SparkSession, sf_dir: str, name: str, columns: list[str] | None = None) -> DataFrame:
    t = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return t.select(*columns) if columns else t


def read_csv_vectors(spark: SparkSession, path: str, sep: str = ",") -> DataFrame:
    """(id, vec) of text lines ``id,x1,x2,...``."""
    p = F.split("value", sep)
    return spark.read.text(path).where("length(trim(value)) > 0").select(F.get(p, 0).cast("long").alias("id"), F.slice(p, 2, 1 << 20).cast("array<double>").alias("vec"))


def read_json_vectors(spark: SparkSession, path: str) -> DataFrame:
    """(id, vec) of JSON lines {"id": ..., "vec": [...]}."""
    return spark.read.schema("id long, vec array<double>").json(path)


def read_orc(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.orc(path)


def read_text(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.text(path)


def save_truth(truth: DataFrame, path: str) -> None:
    truth.write.mode("overwrite").parquet(path)


def save_index(edges: DataFrame, path: str, by: str | None = None) -> None:
    """Edges as Parquet, one folder a shard where ``by`` names its column: routed readers prune the others."""
    w = edges.write.mode("overwrite")
    (w.partitionBy(by) if by else w).parquet(path)


def read_changes(spark: SparkSession, path: str, schema) -> DataFrame:
    return spark.readStream.schema(schema).parquet(path)
