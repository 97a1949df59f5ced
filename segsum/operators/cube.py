"""Planning a cube: roll-up sizes, importance of cells, space allocation, bias, and the whole build."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.settle import numbered, running_total, settled
from .pps import pps

MOST_DIMS = 12


@dataclass(frozen=True)
class IndependentFilters:
    """Every dimension filters with probability p, its value uniform over the domain."""

    p: float = 0.2


def mask_key(dims: list[str], mask: int | Column) -> Column:
    """Text that names a query: '=value' for dimensions that filter (bits of mask, first dimension lowest), '*' for the others. Nulls filter as a value of their own."""
    parts = []
    for j, d in enumerate(dims):
        on = F.lit(bool(mask >> j & 1)) if isinstance(mask, int) else mask.bitwiseAND(F.lit(1 << j)) != 0
        parts.append(F.when(on, F.concat(F.lit("="), F.coalesce(F.col(d).cast("string"), F.lit("\\N")))).otherwise("*"))
    return F.concat_ws("|", *parts)


def masked(cells: DataFrame, dims: list[str]) -> DataFrame:
    """Each cell once per mask, with the key of the query that covers it there."""
    if len(dims) > MOST_DIMS:
        raise ValueError("too many dimensions for all masks; give an explicit workload")
    out = cells.withColumn("mask", F.explode(F.sequence(F.lit(0), F.lit((1 << len(dims)) - 1))))
    return out.withColumn("qkey", mask_key(dims, F.col("mask")))


def rollup_sizes(cells: DataFrame, dims: list[str]) -> DataFrame:
    """(gid, dims, size): rows under every query, from the cell table."""
    return cells.cube(*dims).agg(F.grouping_id().alias("gid"), F.sum("n").cast("long").alias("size"))


def query_weights(cells: DataFrame, dims: list[str], workload: IndependentFilters | DataFrame) -> DataFrame:
    """(qkey, size, q): queries with rows, and their probability. A DataFrame workload gives (qkey, q)."""
    sizes = masked(cells, dims).groupBy("mask", "qkey").agg(F.sum("n").alias("size"))
    if isinstance(workload, DataFrame):
        return sizes.join(workload, "qkey").select("qkey", "size", "q")
    domain = cells.agg(*[F.count_distinct(F.coalesce(F.col(d).cast("string"), F.lit("\\N"))).alias(f"v{j}") for j, d in enumerate(dims)])
    q: Column = F.lit(1.0)
    for j in range(len(dims)):
        q = q * F.when(F.col("mask").bitwiseAND(F.lit(1 << j)) != 0, F.lit(workload.p) / F.col(f"v{j}")).otherwise(1 - workload.p)
    return sizes.crossJoin(F.broadcast(domain)).select("qkey", "size", q.alias("q"))  # one row of domain sizes


def cell_importance(cells: DataFrame, dims: list[str], workload: IndependentFilters | DataFrame) -> DataFrame:
    """(seg, n, alpha): squared size times the summed q / size^2 of the queries over the cell."""
    per = masked(cells, dims).join(query_weights(cells, dims, workload), "qkey")
    return per.groupBy("seg", "n").agg((F.col("n").cast("double") ** 2 * F.sum(F.col("q") / F.col("size").cast("double") ** 2)).alias("alpha"))


POWERS = {"workload_cuberoot": ("alpha", 1 / 3), "workload_sqrt": ("alpha", 1 / 2), "proportional": ("n", 1.0), "equal": ("n", 0.0)}


def allocate(cells: DataFrame, budget: int, method: str = "workload_cuberoot", s_min: int = 0) -> DataFrame:
    """(seg, share): real-valued space that adds up to the budget. `cells` has seg, n and, for workload methods, alpha. Cells under the floor get it; the others share the rest."""
    column, power = POWERS[method]
    w = cells.select("seg", F.pow(F.col(column).cast("double"), F.lit(power)).alias("wt"))
    n = w.agg(F.count(F.lit(1)), F.sum("wt")).first()
    if not n[0]:
        return w.select("seg", F.lit(0.0).alias("share"))
    if s_min * n[0] > budget:
        raise ValueError("the floor takes more than the budget")
    rate, poor = budget / n[1], -1
    while s_min:
        got = w.where(F.col("wt") * F.lit(rate) < s_min).agg(F.count(F.lit(1)), F.sum("wt")).first()
        if got[0] == poor:
            break
        poor = got[0]
        rate = (budget - s_min * got[0]) / (n[1] - (got[1] or 0.0)) if got[0] < n[0] else 0.0
    return w.select("seg", F.greatest(F.lit(float(s_min)), F.col("wt") * F.lit(rate)).alias("share"))


def round_sizes(shares: DataFrame, budget: int) -> DataFrame:
    """(seg, s): whole parts, and one more for the largest remainders until the budget is met."""
    whole = shares.select("seg", F.floor(F.round("share", 9)).cast("long").alias("s"), F.round(F.round("share", 9) - F.floor(F.round("share", 9)), 9).alias("rest"))
    whole = numbered(whole, [F.desc("rest"), F.col("seg")], "rank")
    left = whole.agg((F.lit(budget) - F.sum("s")).alias("left"))  # one row
    return whole.crossJoin(F.broadcast(left)).select("seg", (F.col("s") + (F.col("rank") < F.col("left")).cast("long")).alias("s"))


def cap_shares(shares: DataFrame, caps: DataFrame) -> DataFrame:
    """(seg, share): no cell gets more space than `caps` (seg, most; its distinct values), the excess goes to the others in proportion. What no cell can use is left over."""
    both = settled(shares.join(caps.select("seg", F.col("most").cast("double").alias("most")), "seg"))
    rate, full = 1.0, -1
    while True:
        over = F.col("share") * F.lit(rate) >= F.col("most")
        got = both.agg(F.count_if(over), F.sum(F.when(over, F.col("most"))), F.sum(F.when(~over, F.col("share"))), F.sum("share")).first()
        if got[0] == full or not got[2]:
            break
        full = got[0]
        rate = (got[3] - (got[1] or 0.0)) / got[2]
    return both.select("seg", F.least("most", F.col("share") * F.lit(rate)).alias("share"))


def msre_bound(cells: DataFrame, dims: list[str], workload: IndependentFilters | DataFrame) -> DataFrame:
    """(msre): bound on the workload's mean squared relative error. `cells` has seg, dims, n, s, b and n_eff."""
    terms = masked(cells, dims).groupBy("qkey").agg(F.sum("b").alias("bias"), F.sum((F.col("n_eff") / F.col("s")) ** 2).alias("spread"))
    q = query_weights(cells, dims, workload)
    each = F.col("q") * (F.col("bias") ** 2 + F.col("spread") / 4) / F.col("size").cast("double") ** 2
    return terms.join(q, "qkey").agg(F.sum(each).alias("msre"))


def bias_pieces(counts: DataFrame, sizes: DataFrame) -> DataFrame:
    """(seg, s, a, a2, c, rest): between neighbouring counts a and a2 of a segment, c items and `rest` of their weight lie above. One row per distinct count, zero included."""
    levels = counts.groupBy("seg", F.col("cnt").cast("double").alias("a")).agg(F.count(F.lit(1)).alias("k"))
    levels = levels.unionByName(counts.select("seg", F.lit(0.0).alias("a"), F.lit(0).cast("long").alias("k")).distinct())
    above = Window.partitionBy("seg").orderBy(F.desc("a")).rowsBetween(Window.unboundedPreceding, -1)
    up = Window.partitionBy("seg").orderBy("a")
    return levels.select(
        "seg", "a", F.lead("a").over(up).alias("a2"), F.coalesce(F.sum("k").over(above), F.lit(0)).alias("c"),
        F.coalesce(F.sum(F.col("k") * F.col("a")).over(above), F.lit(0.0)).alias("rest"),
    ).join(sizes.select("seg", "s"), "seg")


def bias_at(pieces: DataFrame, lam: Column) -> DataFrame:
    """(seg, lam, b): the smallest bias whose pull n[b] c(b) is at most lam * s^2."""
    room = lam * F.col("s").cast("double") ** 2
    at_start = (F.col("rest") - F.col("c") * F.col("a")) * F.col("c") <= room
    at_end = (F.col("rest") - F.col("c") * F.coalesce("a2", "a")) * F.col("c") <= room
    inside = F.try_divide(F.col("rest") - F.try_divide(room, F.col("c")), F.col("c"))
    return pieces.groupBy("seg", lam.alias("lam")).agg(F.min(F.when(at_start, F.col("a")).when(at_end, inside)).alias("b"))


def bias_multiplier(pieces: DataFrame) -> float:
    """The multiplier that equals four times the summed bias at it.

    As a function of the multiplier a cell's bias is made of straight pieces:
    falling inside a gap between counts, flat where it rests on a count. Where
    the pieces begin and end, the sum over all cells changes its straight line;
    its running sums over these points show the line that holds the answer.
    """
    s2 = F.col("s").cast("double") ** 2
    by = Window.partitionBy("seg").orderBy("a")
    c, c2 = F.col("c").cast("double"), F.lag("c").over(by).cast("double")
    ends = pieces.select(
        "seg", "a", s2.alias("s2"), c.alias("c"), "rest", ((F.col("rest") - c * F.col("a")) * c).alias("start"),
        F.greatest((F.col("rest") - c * F.coalesce("a2", "a")) * c, F.lit(0.0)).alias("end"),
        ((F.lag("rest").over(by) - c2 * F.col("a")) * c2).alias("was"),
    )
    part = lambda lo, hi, level, slope: F.struct(lo.alias("lo"), hi.alias("hi"), level.alias("level"), slope.alias("slope"))
    spaced = ends.where("s2 > 0")
    gaps = spaced.where("c > 0").select(part(F.col("end") / F.col("s2"), F.col("start") / F.col("s2"), F.col("rest") / F.col("c"), -F.col("s2") / F.col("c") ** 2).alias("p"))
    rests = spaced.where("a > 0").select(part(F.col("start") / F.col("s2"), F.col("was") / F.col("s2"), F.col("a"), F.lit(0.0)).alias("p"))
    spaceless = ends.where("s2 = 0 AND c = 0").select(part(F.lit(0.0), F.lit(None).cast("double"), F.col("a"), F.lit(0.0)).alias("p"))  # a cell that stores nothing gives up all
    lines = gaps.unionByName(rests).unionByName(spaceless).select("p.*").where("hi IS NULL OR hi > lo")
    turns = (
        lines.select(F.col("lo").alias("at"), "level", "slope")
        .unionByName(lines.where("hi IS NOT NULL").select(F.col("hi").alias("at"), (-F.col("level")).alias("level"), (-F.col("slope")).alias("slope")))
        .groupBy("at").agg(F.sum("level").alias("level"), F.sum("slope").alias("slope"))
    )
    level = running_total(turns, [F.col("at")], "level").withColumnRenamed("upto", "levels").drop("size")
    both = running_total(level, [F.col("at")], "slope").withColumnRenamed("upto", "slopes")
    above = both.where(4 * (F.col("levels") + F.col("slopes") * F.col("at")) >= F.col("at"))
    at = above.agg(F.max_by(F.struct("levels", "slopes"), "at").alias("line")).first()
    return max(0.0, 4 * at["line"]["levels"] / (1 - 4 * at["line"]["slopes"])) if at["line"] is not None else 0.0


def fit_bias(counts: DataFrame, sizes: DataFrame) -> DataFrame:
    """(seg, b) that minimise (sum b)^2 + sum (n[b] / s)^2 / 4, the bound of the query over the whole cube.

    Each cell's bias falls with one shared multiplier, four times the summed
    bias, which is found in one pass over the table of distinct counts.
    """
    pieces = settled(bias_pieces(counts, sizes))
    return bias_at(pieces, F.lit(bias_multiplier(pieces))).select("seg", "b")


def bias_objective(counts: DataFrame, sizes: DataFrame, bias: DataFrame) -> float:
    eff = counts.join(bias, "seg").groupBy("seg", "b").agg(F.sum(F.greatest(F.col("cnt") - F.col("b"), F.lit(0.0))).alias("e")).join(sizes, "seg")
    r = eff.agg(F.sum("b"), F.sum(F.when(F.col("s") > 0, (F.col("e") / F.col("s")) ** 2).otherwise(F.when(F.col("e") > 0, float("inf")).otherwise(0.0)))).first()
    return r[0] ** 2 + r[1] / 4


@dataclass(frozen=True)
class CubePlan:
    """A built cube: (seg, item, w), and per cell its dims, n, s and b."""

    summary: DataFrame
    header: DataFrame
    dims: list[str]


def build_cube(
    counts: DataFrame, cells: DataFrame, dims: list[str], budget: int, workload: IndependentFilters | DataFrame, goal: str = "freq",
    size: str = "workload_cuberoot", bias: bool = True, draw: str = "systematic", s_min: int = 0, seed: int = 1,
) -> CubePlan:
    """Sizes, then biases (frequencies only), then samples."""
    base = cell_importance(cells, dims, workload) if size.startswith("workload") else cells.select("seg", "n")
    sizes = round_sizes(allocate(base, budget, size, s_min), budget)
    biased = bias and goal == "freq"
    b = fit_bias(counts, sizes) if biased else sizes.select("seg", F.lit(0.0).alias("b"))
    header = cells.join(sizes, "seg").join(b, "seg")
    own = counts.join(header.select("seg", F.col("s").alias("s"), "b"), "seg")
    return CubePlan(pps(own, "s", draw, seed, "b" if biased else 0.0, goal), header, dims)


def random_queries(cells: DataFrame, dims: list[str], p: float, n: int, seed: int = 5) -> DataFrame:
    """(qid, n_filters, qkey) of n queries of the independent workload."""
    rng = np.random.default_rng(seed)
    domains = [sorted(r[0] for r in cells.select(F.coalesce(F.col(d).cast("string"), F.lit("\\N"))).distinct().collect()) for d in dims]
    rows = []
    for i in range(n):
        parts = [f"={dom[rng.integers(len(dom))]}" if rng.random() < p else "*" for dom in domains]
        rows.append((i, sum(x != "*" for x in parts), "|".join(parts)))
    return cells.sparkSession.createDataFrame(rows, "qid long, n_filters int, qkey string")


def cells_of(queries: DataFrame, cells: DataFrame, dims: list[str]) -> DataFrame:
    """(qid, seg) by an equality join on the masked dims."""
    return masked(cells, dims).select("seg", "n", "qkey").join(F.broadcast(queries.select("qid", "qkey")), "qkey").select("qid", "seg", "n")
