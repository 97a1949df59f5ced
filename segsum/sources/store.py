"""Where summaries are kept: Parquet by block, sorted by segment and item."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.segment import block_of


def write_summary(summary: DataFrame, path: str, k_t: int, mode: str = "overwrite", kind: str = "parquet") -> None:
    """One folder per block; inside, row groups have narrow ranges of seg, so a range of segments prunes both. Also writes json, csv and orc."""
    df = summary if "block" in summary.columns else summary.withColumn("block", block_of(F.col("seg"), k_t))
    df.repartition("block").sortWithinPartitions("block", "seg", "item").write.mode(mode).partitionBy("block").format(kind).save(path)


def read_summary(spark: SparkSession, path: str, lo: int | None = None, hi: int | None = None, k_t: int | None = None) -> DataFrame:
    """The pairs of segments [lo, hi): partition pruning by block, pushed filter on seg."""
    df = spark.read.parquet(path)
    if lo is not None and hi is not None:
        df = df.where((F.col("seg") >= lo) & (F.col("seg") < hi))
        if k_t:
            df = df.where((F.col("block") >= lo // k_t) & (F.col("block") <= (hi - 1) // k_t))
    return df


def save_bucketed(summary: DataFrame, name: str, buckets: int = 64) -> None:
    """A table bucketed by seg, so that joins on seg need no exchange."""
    summary.write.mode("overwrite").bucketBy(buckets, "seg").sortBy("seg", "item").saveAsTable(name)


def pack_summary(summary: DataFrame) -> DataFrame:
    """(seg, pairs): one row a segment, pairs sorted by item; a segment has at most s of them."""
    return summary.groupBy("seg").agg(F.sort_array(F.collect_list(F.struct("item", "w"))).alias("pairs"))


def unpack_summary(packed: DataFrame) -> DataFrame:
    return packed.select("seg", F.explode("pairs").alias("p")).select("seg", "p.item", "p.w")
