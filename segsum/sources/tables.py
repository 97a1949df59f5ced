"""Readers of the given tables and of raw record files."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

TABLES = (
    "region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations",
)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def records(spark: SparkSession, path: str, kind: str, schema: StructType | str | None = None) -> DataFrame:
    """Raw records from parquet, csv (with header), json or orc. With a schema nothing is inferred."""
    reader = spark.read.format(kind)
    if kind == "csv":
        reader = reader.option("header", True)
    if schema is not None:
        reader = reader.schema(schema)
    return reader.load(path)


def record_stream(spark: SparkSession, path: str, kind: str, schema: StructType | str, files_per_trigger: int | None = None) -> DataFrame:
    reader = spark.readStream.format(kind).schema(schema)
    if files_per_trigger:
        reader = reader.option("maxFilesPerTrigger", files_per_trigger)
    return reader.load(path)


def rate_stream(spark: SparkSession, rows_per_second: int) -> DataFrame:
    return spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load()


def word_items(documents: DataFrame, *more: str) -> DataFrame:
    """(doc_id, more, pos, item): one row per word."""
    return documents.select("doc_id", *more, F.posexplode(F.split("text", " ")).alias("pos", "item")).where(F.col("item") != "")
