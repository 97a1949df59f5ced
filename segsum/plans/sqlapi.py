"""Summaries for SQL users: table functions over packed and registered summaries."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

from ..operators.estimate import acc_quantiles, accumulate


@udtf(returnType="item string, w double")
class SummaryItems:
    """summary_items(pairs): the pairs of a packed summary as rows."""

    def eval(self, pairs: list) -> Iterator[tuple[str, float]]:
        for p in pairs or ():
            yield str(p[0]), float(p[1])


def register(spark: SparkSession, name: str, summary: DataFrame, header: DataFrame) -> None:
    """Views <name> (seg, item, w) and <name>_header (seg, n), the function summary_items, and two functions that the engine plans inline: the table <name>_interval(lo, hi) of accumulated pairs and <name>_rank(lo, hi, x)."""
    summary.createOrReplaceTempView(name)
    header.createOrReplaceTempView(f"{name}_header")
    kind = summary.schema["item"].dataType.simpleString()
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}_interval(lo BIGINT, hi BIGINT) RETURNS TABLE(item {kind}, w DOUBLE) RETURN SELECT item, sum(w) FROM {name} WHERE seg >= lo AND seg < hi GROUP BY item")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}_rank(lo BIGINT, hi BIGINT, x {kind}) RETURNS DOUBLE RETURN SELECT coalesce(sum(w), 0) FROM {name} WHERE seg >= lo AND seg < hi AND item <= x")
    spark.udtf.register("summary_items", SummaryItems)


def estimate_interval(spark: SparkSession, name: str, lo: int, hi: int, phi: float | None = None, k: int = 10) -> DataFrame:
    """From registered views: the phi-quantile of a range of segments, or its top k items."""
    if phi is None:
        return spark.sql(f"SELECT item, sum(w) AS w FROM {name} WHERE seg >= {int(lo)} AND seg < {int(hi)} GROUP BY item ORDER BY w DESC, item LIMIT {int(k)}")
    return acc_quantiles(accumulate(spark.table(name), (F.col("seg") >= lo) & (F.col("seg") < hi)), [phi])
