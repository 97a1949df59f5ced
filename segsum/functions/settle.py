"""Tables that two branches of a plan must see alike, written once to the shared checkpoint folder."""

from __future__ import annotations

import tempfile

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def settled(df: DataFrame) -> DataFrame:
    """`df` as a checkpoint, in the session's folder; a local one only where none is named and the master is local."""
    sc = df.sparkSession.sparkContext
    if sc.getCheckpointDir() is None:
        named = df.sparkSession.conf.get("spark.checkpoint.dir", "")
        if not named and not sc.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="segsum-checkpoint-"))
    return df.checkpoint()


def small(df: DataFrame, most: int = 200_000) -> DataFrame:
    """`df`, marked for broadcast if it has at most so many (narrow) rows; else joins go by the engine's choice. Counted here, so it should be cached or settled."""
    return F.broadcast(df) if df.limit(most + 1).count() <= most else df


def _ranges(df: DataFrame, order: list[Column]) -> DataFrame:
    """Rows in ranges of `order`, the range's number as __part; fixed, so that sums and rows agree on the ranges."""
    return settled(df.repartitionByRange(*order).withColumn("__part", F.spark_partition_id()))


def _before(sizes: DataFrame) -> DataFrame:
    """(__part, __base, __all): what lies before each range, and in all. One row a range."""
    by = Window.orderBy("__part")
    upto = F.sum("__size").over(by.rowsBetween(Window.unboundedPreceding, -1))
    return sizes.select("__part", F.coalesce(upto, F.lit(0)).alias("__base"), F.sum("__size").over(by.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).alias("__all"))


def numbered(df: DataFrame, order: list[Column], name: str) -> DataFrame:
    """Add `name`: 0, 1, 2, ... in the given total order, without one task holding all rows."""
    parts = _ranges(df, order)
    before = _before(parts.groupBy("__part").agg(F.count(F.lit(1)).alias("__size")))
    inside = Window.partitionBy("__part").orderBy(*order)
    rows = parts.join(F.broadcast(before.drop("__all")), "__part")
    return rows.withColumn(name, (F.row_number().over(inside) - 1 + F.col("__base")).cast("long")).drop("__part", "__base")


def running_total(df: DataFrame, order: list[Column], weight: str) -> DataFrame:
    """Add upto, the sum of `weight` up to each row of the given total order, and size, the sum over all."""
    parts = _ranges(df, order)
    before = _before(parts.groupBy("__part").agg(F.sum(weight).alias("__size")))
    inside = Window.partitionBy("__part").orderBy(*order).rowsBetween(Window.unboundedPreceding, 0)
    rows = parts.join(F.broadcast(before), "__part")
    return rows.withColumn("upto", F.sum(weight).over(inside) + F.col("__base")).withColumnRenamed("__all", "size").drop("__part", "__base")
