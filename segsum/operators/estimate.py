"""Answers from stored summaries."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.hashing import uniform
from ..functions.kernels import SpaceSaving, VarOptReservoir
from ..functions.settle import running_total, settled
from .segment import probe_array, probe_grid, quantiles


def estimate_freq(summary: DataFrame, where: Column, items: DataFrame) -> DataFrame:
    """(item, est) for a bounded list of items; what is not stored counts zero."""
    got = summary.where(where).join(F.broadcast(items), "item").groupBy("item").agg(F.sum("w").alias("est"))
    return items.join(got, "item", "left").select("item", F.coalesce("est", F.lit(0.0)).alias("est"))


def estimate_rank(summary: DataFrame, where: Column, probes: list[float]) -> DataFrame:
    """(probe, est): stored weight at or below each probe. Each pair is counted from the first probe it reaches."""

    gaps = summary.where(where).select(F.size(F.filter(probe_array(probes), lambda p: p < F.col("item"))).alias("g"), "w").groupBy("g").agg(F.sum("w").alias("w"))
    upto = Window.orderBy("g").rowsBetween(Window.unboundedPreceding, 0)
    return probe_grid(summary, probes).join(gaps, "g", "left").select("probe", F.sum(F.coalesce("w", F.lit(0.0))).over(upto).alias("est"))


def estimate_batch(summary: DataFrame, queries: DataFrame, items: DataFrame) -> DataFrame:
    """(qid, item, est) for interval queries (qid, lo, hi) and a bounded list of items: a range join with the query list, which is broadcast."""
    hit = summary.join(F.broadcast(items), "item").join(F.broadcast(queries), (F.col("seg") >= F.col("lo")) & (F.col("seg") < F.col("hi")))
    return hit.groupBy("qid", "item").agg(F.sum("w").alias("est"))


def estimate_cells(summary: DataFrame, matches: DataFrame, items: DataFrame) -> DataFrame:
    """(qid, item, est) for cube queries given as (qid, seg)."""
    return summary.join(F.broadcast(items), "item").join(matches.select("qid", "seg"), "seg").groupBy("qid", "item").agg(F.sum("w").alias("est"))


def estimate_groupby(summary: DataFrame, header: DataFrame, by: list[str], where: Column | None = None) -> DataFrame:
    """(by, item, est): drill-down over the cells that the filter keeps."""
    cells = header if where is None else header.where(where)
    return summary.join(cells.select("seg", *by), "seg").groupBy(*by, "item").agg(F.sum("w").alias("est"))


def accumulate(summary: DataFrame, where: Column) -> DataFrame:
    """(item, w): all stored pairs of the range added by value; spills, so it has no size limit."""
    return summary.where(where).groupBy("item").agg(F.sum("w").alias("w"))


def accumulate_items(summary: DataFrame, where: Column, size: int) -> DataFrame:
    """(item, w) in bounded counters: one set per task, merged. Overcounts by at most the weight over the size."""
    rows = summary.where(where).select("item", "w")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        acc = SpaceSaving(size)
        for pdf in batches:
            acc.merge(zip(pdf["item"].tolist(), pdf["w"].tolist(), strict=True))
        yield pd.DataFrame(acc.pairs(), columns=["item", "w"])

    kind = rows.schema["item"].dataType.simpleString()
    schema = f"item {kind}, w double"
    return rows.mapInPandas(run, schema).repartition(1).sortWithinPartitions(F.desc("w"), "item").mapInPandas(run, schema)


def accumulate_values(summary: DataFrame, where: Column, size: int, seed: int = 7) -> DataFrame:
    """(item, w) in a bounded weighted sample that keeps the total."""
    rows = summary.where(where).select("item", "w")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        acc = VarOptReservoir(size, seed)
        for pdf in batches:
            acc.update(pdf["item"].tolist(), pdf["w"].tolist())
        yield pd.DataFrame(acc.pairs(), columns=["item", "w"])

    kind = rows.schema["item"].dataType.simpleString()
    schema = f"item {kind}, w double"
    return rows.mapInPandas(run, schema).repartition(1).sortWithinPartitions("item", "w").mapInPandas(run, schema).groupBy("item").agg(F.sum("w").alias("w"))


def accumulate_sampled(summary: DataFrame, where: Column, size: int, seed: int = 7) -> DataFrame:
    """The same bound in SQL: one systematic sample over the accumulated pairs, by ranges of items. Heavy items are among the `size` largest, all that one task sees."""
    acc = settled(accumulate(summary, where))
    total = acc.agg(F.sum("w").alias("total"))
    order = Window.orderBy(F.desc("w"), "item")
    largest = acc.orderBy(F.desc("w"), "item").limit(size).crossJoin(F.broadcast(total))  # one row
    ahead = F.coalesce(F.sum("w").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0))
    slots = F.lit(size) - F.row_number().over(order) + 1
    heavy = largest.select("item", "w", "total", (F.col("w") * slots >= F.col("total") - ahead - 1e-9).alias("heavy")).where("heavy")
    rest = heavy.agg(F.coalesce(F.sum("w"), F.lit(0.0)).alias("taken"), F.count(F.lit(1)).alias("n")).crossJoin(F.broadcast(total))  # one row each
    level = rest.select(F.coalesce(F.try_divide(F.col("total") - F.col("taken"), F.lit(size) - F.col("n")), F.lit(0.0)).alias("h"))
    light = acc.join(F.broadcast(heavy.select("item")), "item", "left_anti").crossJoin(F.broadcast(level)).where("h > 0").withColumn("p", F.col("w") / F.col("h"))
    u = uniform(seed, F.lit(0))
    run = running_total(light, [F.col("item")], "p")
    drawn = run.where(F.floor(F.round(F.col("upto") + u, 9)) > F.floor(F.round(F.col("upto") - F.col("p") + u, 9)))
    return heavy.select("item", "w").unionByName(drawn.select("item", F.col("h").alias("w")))


def top_k(acc: DataFrame, k: int) -> DataFrame:
    return acc.orderBy(F.desc("w"), "item").limit(k)


def heavy_hitters(acc: DataFrame, phi: float, size: float) -> DataFrame:
    """`size` is the exact number of rows, known from the headers."""
    return acc.where(F.col("w") >= F.lit(phi) * F.lit(float(size)))


def acc_quantiles(acc: DataFrame, phis: list[float], size: float | None = None) -> DataFrame:
    """(phi, value); with `size`, against the exact number of rows."""
    return quantiles(acc, phis, "w", size)


def with_bound(est: DataFrame, header: DataFrame, where: Column, s: int, r: float = 1.0) -> DataFrame:
    """Add what any estimate over the range may be off by: the summed local bounds, and the rows of the range."""
    size = header.where(where).agg(F.sum("n").alias("n_rows"), (F.sum("n") * F.lit(r / s)).alias("err_bound"))
    return est.crossJoin(F.broadcast(size))  # one row


def header_totals(header: DataFrame, where: Column) -> DataFrame:
    """Exact count, sum and mean of a range without its rows; `header` has n and total."""
    return header.where(where).agg(F.sum("n").alias("n"), F.sum("total").alias("total"), (F.sum("total") / F.sum("n")).alias("mean"))


def rank_of(packed: Column, x: Column | float) -> Column:
    """Rank from a packed summary array<struct<item,w>>, as an expression."""
    v = F.lit(x) if not isinstance(x, Column) else x
    return F.aggregate(F.filter(packed, lambda p: p["item"] <= v), F.lit(0.0), lambda a, p: a + p["w"])


def freq_of(packed: Column, x: Column | object) -> Column:
    v = F.lit(x) if not isinstance(x, Column) else x
    return F.aggregate(F.filter(packed, lambda p: p["item"] == v), F.lit(0.0), lambda a, p: a + p["w"])


def space_saving_udaf(size: int, item_type: str = "long") -> object:
    """A grouped aggregate: bounded counters as array<struct<item,w>>."""

    @F.pandas_udf(f"array<struct<item:{item_type},w:double>>")
    def run(item: pd.Series, w: pd.Series) -> list:
        acc = SpaceSaving(size)
        acc.merge(zip(item.tolist(), w.tolist(), strict=True))
        return [{"item": i, "w": float(x)} for i, x in acc.pairs()]

    return run


def probes_of_rank(counts: DataFrame, n: int = 200, spacing: str = "rank") -> list[float]:
    """Equally spaced values of the global distribution, by rank or by value."""
    if spacing == "value":
        lo, hi = counts.agg(F.min("item"), F.max("item")).first()
        return [float(x) for x in np.linspace(lo, hi, n)]
    phis = [(i + 0.5) / n for i in range(n)]
    return sorted({float(r["value"]) for r in quantiles(counts, phis, "cnt").collect()})
