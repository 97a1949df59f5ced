"""Cutting data into segments, value counts, and exact answers."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.settle import numbered, running_total, small


def segment_interval(df: DataFrame, t_col: str, seconds: int, origin: str, k_t: int | None = None) -> DataFrame:
    """Add seg (aligned windows of `seconds` since `origin`) and, with `k_t`, block. Narrow: no shuffle."""
    micros = F.expr(f"timestampdiff(MICROSECOND, timestamp_ntz'{origin}', `{t_col}`)")
    out = df.withColumn("seg", F.floor(micros / F.lit(seconds * 1_000_000)).cast("long"))
    return out if k_t is None else out.withColumn("block", block_of(F.col("seg"), k_t))


def segment_sequence(df: DataFrame, order_col: str, width: int, k_t: int | None = None) -> DataFrame:
    """Segments of `width` consecutive values of a dense sequence column."""
    out = df.withColumn("seg", F.floor(F.col(order_col) / F.lit(width)).cast("long"))
    return out if k_t is None else out.withColumn("block", block_of(F.col("seg"), k_t))


def block_of(seg: Column, k_t: int) -> Column:
    return F.floor(seg / F.lit(k_t)).cast("long")


def segment_cube(df: DataFrame, dims: list[str]) -> tuple[DataFrame, DataFrame]:
    """(rows with seg, cells with seg and dims). Cells are numbered in the order of their dims, range by range; the cell table is far smaller than the rows and joins back on all dims."""
    cells = df.groupBy(*dims).agg(F.count(F.lit(1)).alias("n"))
    cells = numbered(cells, [F.col(d) for d in dims], "seg")
    match = [df[d].eqNullSafe(cells[d]) for d in dims]
    cond = match[0]
    for m in match[1:]:
        cond = cond & m
    rows = df.join(small(cells).select("seg", *dims), cond).select(df["*"], "seg")
    return rows, cells.select("seg", *dims, "n")


def value_counts(df: DataFrame, item: str = "item", keys: tuple[str, ...] = ("seg",)) -> DataFrame:
    """(keys, item, cnt) by partial and final aggregation; null and NaN items are left out here and counted in the header."""
    some = F.col(item).isNotNull()
    if dict(df.dtypes)[item] in ("double", "float"):
        some = some & ~F.isnan(item)
    return df.where(some).groupBy(*keys, F.col(item).alias("item")).agg(F.count(F.lit(1)).alias("cnt"))


def segment_header(counts: DataFrame, keys: tuple[str, ...] = ("seg",)) -> DataFrame:
    return counts.groupBy(*keys).agg(F.sum("cnt").cast("long").alias("n"), F.count(F.lit(1)).alias("n_distinct"))


def in_range(lo: int, hi: int) -> Column:
    """Half-open range of segments; reaches the scan as a pushed filter when seg is stored."""
    return (F.col("seg") >= lo) & (F.col("seg") < hi)


def exact_freq(counts: DataFrame, where: Column, items: DataFrame | None = None) -> DataFrame:
    """(item, f); with `items` (a bounded probe list), also those that don't occur."""
    f = counts.where(where).groupBy("item").agg(F.sum("cnt").cast("long").alias("f"))
    return f if items is None else items.join(f, "item", "left").select("item", F.coalesce("f", F.lit(0)).alias("f"))


def exact_rank(counts: DataFrame, where: Column, probes: list[float]) -> DataFrame:
    """(probe, r): records at or below each probe. Values fall into the gaps between probes first, so only the gaps are accumulated."""
    gaps = counts.where(where).select(F.size(F.filter(probe_array(probes), lambda p: p < F.col("item"))).alias("g"), "cnt").groupBy("g").agg(F.sum("cnt").alias("cnt"))
    grid = probe_grid(counts, probes)
    upto = Window.orderBy("g").rowsBetween(Window.unboundedPreceding, 0)
    return grid.join(gaps, "g", "left").select("probe", F.sum(F.coalesce("cnt", F.lit(0))).over(upto).cast("long").alias("r"))


def probe_array(probes: list[float]) -> Column:
    return F.array(*[F.lit(float(p)) for p in sorted(probes)])


def probe_grid(df: DataFrame, probes: list[float]) -> DataFrame:
    return df.sparkSession.createDataFrame([(i, float(p)) for i, p in enumerate(sorted(probes))], "g int, probe double")


def cumulative(counts: DataFrame, weight: str = "cnt") -> DataFrame:
    """(item, weight, upto, size): item totals with the total up to each in order of item and that of all, without one task holding all."""
    return running_total(counts.groupBy("item").agg(F.sum(weight).alias(weight)), [F.col("item")], weight)


def exact_quantile(counts: DataFrame, where: Column, phis: list[float]) -> DataFrame:
    """(phi, value): the smallest value whose rank reaches phi of all."""
    return quantiles(counts.where(where), phis, "cnt")


def quantiles(acc: DataFrame, phis: list[float], weight: str = "w", total: float | None = None) -> DataFrame:
    """(phi, value): the smallest item up to which the weights reach phi of all."""
    return crossings(acc, phis, weight, total).groupBy("phi").agg(F.min("item").alias("value"))


def crossings(acc: DataFrame, phis: list[float], weight: str = "w", total: float | None = None) -> DataFrame:
    """(phi, item): the items at which the weights come to phi of all, the smallest that reaches it among them.

    Only an item whose own weight crosses a share can be its answer, so it meets runs of shares first, then the shares of
    the run that it falls into. Sums are rounded, so items a little beyond are let through; the least is taken in the end.
    """
    cum = cumulative(acc, weight)
    size = F.col("size") if total is None else F.lit(float(total))
    reached = lambda phi: F.col("upto") >= phi * F.col("size") - 1e-9
    before = lambda phi: F.col("upto") - F.col(weight) <= phi * F.col("size") + 1e-6 * (F.col("size") + 1)
    many = sorted(float(p) for p in phis)
    runs = [many[i:i + 16] for i in range(0, len(many), 16)]
    run = F.array(*[F.struct(F.lit(r[0]).alias("least"), F.lit(r[-1]).alias("most"), F.array(*[F.lit(p) for p in r]).alias("phis")) for r in runs])
    near = cum.withColumn("size", size).withColumn("run", F.explode(run)).where(reached(F.col("run.least")) & before(F.col("run.most")))
    return near.withColumn("phi", F.explode("run.phis")).where(reached(F.col("phi")) & before(F.col("phi"))).select("phi", "item")


def exact_topk(counts: DataFrame, where: Column, k: int) -> DataFrame:
    return exact_freq(counts, where).orderBy(F.desc("f"), "item").limit(k)


def exact_heavy(counts: DataFrame, where: Column, phi: float) -> DataFrame:
    """Items with at least phi of the records."""
    f = exact_freq(counts, where)
    size = counts.where(where).agg(F.sum("cnt").alias("size"))
    return f.join(F.broadcast(size), F.col("f") >= F.lit(phi) * F.col("size")).select("item", "f")
