"""Inclusion thresholds and samples with probability proportional to size."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.hashing import uniform
from ..functions.kernels import pairwise_draw, peel_threshold


def _size(s: int | str) -> Column:
    return F.lit(s) if isinstance(s, int) else F.col(s)


def _levels(counts: DataFrame, s: int | str, weight: str) -> DataFrame:
    """(seg, h, n_heavy, least): the threshold, the number of heavy items, and the least weight that is heavy (null if none is).

    Ranked by weight, an item is heavy while it holds its share of the remaining
    weight over the remaining slots; the condition is monotone, so no loop is
    needed. Items of one weight share its outcome (each takes its weight off both
    sides), so segments meet as tables of their distinct weights, not of items.
    """
    same = counts.groupBy("seg", F.col(weight).alias("__w")).agg(F.count(F.lit(1)).alias("__k"), F.max(_size(s)).alias("__slots"))
    w, k, slots = F.col("__w"), F.col("__k"), F.col("__slots")
    upto = Window.partitionBy("seg").orderBy("__w").rowsBetween(Window.unboundedPreceding, 0)  # a frame that ends open would be summed anew for each row
    ahead = F.sum("__k").over(Window.partitionBy("seg")) - F.sum("__k").over(upto)
    ranked = same.withColumn("__ahead", ahead).withColumn("__rest", F.sum(w * k).over(upto))
    met = ranked.withColumn("__heavy", (F.col("__ahead") < slots) & (w * (slots - F.col("__ahead")) >= F.col("__rest")))
    heavy = F.col("__heavy")
    sums = met.groupBy("seg").agg(
        F.sum(F.when(~heavy, w * k).otherwise(0)).alias("__light"), F.sum(F.when(heavy, k).otherwise(0)).alias("n_heavy"),
        F.min(F.when(heavy, w)).alias("least"), F.max("__slots").alias("__slots"),
    )
    return sums.select("seg", F.coalesce(F.try_divide("__light", slots - F.col("n_heavy")), F.lit(0)).cast("double").alias("h"), "n_heavy", "least")


def with_threshold(counts: DataFrame, s: int | str, weight: str = "cnt") -> DataFrame:
    """Add heavy and h, by the segment's threshold."""
    levels = _levels(counts, s, weight).select(F.col("seg").alias("__seg"), "h", "least")
    both = counts.join(levels, counts["seg"].eqNullSafe(F.col("__seg")))
    return both.select(*counts.columns, F.coalesce(F.col(weight) >= F.col("least"), F.lit(False)).alias("heavy"), "h")


def inclusion_threshold(counts: DataFrame, s: int | str) -> DataFrame:
    """(seg, h, n_heavy)."""
    return _levels(counts, s, "cnt").select("seg", "h", "n_heavy")


def simple_threshold(counts: DataFrame, s: int) -> DataFrame:
    """(seg, h): the conservative n / s."""
    return counts.groupBy("seg").agg((F.sum("cnt") / F.lit(s)).alias("h"))


def pps_probabilities(counts: DataFrame, s: int | str, weight: str = "cnt") -> DataFrame:
    """Add p, the chance to be stored, and v, the weight stored then."""
    t = with_threshold(counts, s, weight)
    return t.withColumn("p", F.when(F.col("heavy"), 1.0).otherwise(F.col(weight) / F.col("h"))).withColumn(
        "v", F.when(F.col("heavy"), F.col(weight).cast("double")).otherwise(F.col("h"))
    )


def effective_weight(counts: DataFrame, bias: float | str = 0.0) -> DataFrame:
    """(seg, n_eff): weight that is left when every item gives up the bias."""
    b = F.lit(float(bias)) if not isinstance(bias, str) else F.col(bias)
    return counts.groupBy("seg").agg(F.sum(F.greatest(F.col("cnt") - b, F.lit(0.0))).alias("n_eff"))


def pps(counts: DataFrame, s: int | str, draw: str = "systematic", seed: int = 1, bias: str | float = 0.0, goal: str = "freq") -> DataFrame:
    """(seg, item, w). `s` and `bias` may name columns of `counts` that are constant in a segment.

    independent: each item by itself, expected size s. systematic: fixed size and
    prefix error at most h, in SQL. pairwise: neighbours in item order settle
    their chances between them, s or s - 1 items, prefix error at most h.
    """
    if goal == "rank" and (isinstance(bias, str) or bias):
        raise ValueError("biased samples answer frequencies only")
    b = F.lit(float(bias)) if not isinstance(bias, str) else F.col(bias)
    own = counts.where(_size(s) > 0).select(
        "seg", "item", (F.col("cnt") - b).cast("double").alias("cnt"), b.alias("__b"), _size(s).alias("__s")
    ).where(F.col("cnt") > 0)
    t = pps_probabilities(own, "__s")
    if draw == "independent":
        kept = t.where(F.col("heavy") | (uniform(seed, F.col("seg"), F.col("item")) < F.col("p")))
    elif draw == "systematic":
        run = Window.partitionBy("seg").orderBy("item").rowsBetween(Window.unboundedPreceding, 0)
        upto = F.sum(F.when(F.col("heavy"), 0.0).otherwise(F.col("p"))).over(run)
        u = uniform(seed, F.col("seg"))
        at = t.withColumn("__at", F.floor(F.round(upto + u, 9)))
        before = F.lag("__at", 1).over(Window.partitionBy("seg").orderBy("item"))
        kept = at.withColumn("__was", F.coalesce(before, F.lit(0))).where(F.col("heavy") | (F.col("__at") > F.col("__was")))
    elif draw == "pairwise":
        t = t.withColumn("__u", uniform(seed, F.col("seg"), F.col("item")))
        kept = _pairwise(t)
    else:
        raise ValueError(f"no draw {draw!r}")
    return kept.select("seg", "item", (F.col("v") + F.col("__b")).alias("w"))


def pps_sizes(counts: DataFrame, sizes: list[int], seed: int = 1) -> DataFrame:
    """(variant, seg, item, w): pairwise samples of several sizes in one pass, each what `pps` draws at that size; `variant` is the size's place in the list."""
    return pps_draws(counts, [(s, "pairwise") for s in sizes], seed)


def pps_draws(counts: DataFrame, variants: list[tuple[int, str]], seed: int = 1) -> DataFrame:
    """(variant, seg, item, w): samples of several sizes and draws ('pairwise', 'systematic') in one pass, each what `pps` draws; a task holds a segment. Numbers are sorted there, all else before."""
    if any(draw not in ("pairwise", "systematic") for _, draw in variants):
        raise ValueError("draws in one pass are pairwise or systematic")
    kind = counts.schema["item"].dataType.simpleString()
    plain = kind in ("int", "bigint", "double")
    each = uniform(seed, F.col("seg"), F.col("item")) if any(draw == "pairwise" for _, draw in variants) else F.lit(0.0)
    rows = counts.select("seg", "item", "cnt", each.alias("u"), uniform(seed, F.col("seg")).alias("start")).repartition("seg")
    if not plain:
        rows = rows.sortWithinPartitions("seg", "item")

    def drawn(pdf: pd.DataFrame) -> pd.DataFrame:
        items, cnt, u = pdf["item"].to_numpy(), pdf["cnt"].to_numpy().astype(float), pdf["u"].to_numpy()
        if plain:
            order = np.argsort(items, kind="stable")
            items, cnt, u = items[order], cnt[order], u[order]
        at, weights = [], []
        for s, draw in variants:
            h, n_heavy = peel_threshold(cnt, s)
            least = np.partition(cnt, len(cnt) - n_heavy)[len(cnt) - n_heavy] if n_heavy else np.inf
            heavy = cnt >= least
            p = cnt / h if h > 0 else np.ones(len(cnt))
            if draw == "pairwise":
                keep = pairwise_draw(np.where(heavy, 1.0, p), u)
            else:
                steps = np.floor(np.round(np.cumsum(np.where(heavy, 0.0, p)) + pdf["start"].iloc[0], 9))
                keep = heavy | (np.diff(steps, prepend=0.0) > 0)
            at.append(np.flatnonzero(keep))
            weights.append(np.where(heavy, cnt, h)[keep])
        variant = np.repeat(np.arange(len(variants)), [len(x) for x in at])
        return pd.DataFrame({"variant": variant, "seg": pdf["seg"].iloc[0], "item": items[np.concatenate(at)], "w": np.concatenate(weights)})

    return rows.groupBy("seg").applyInPandas(drawn, f"variant int, seg long, item {kind}, w double")


def _pairwise(t: DataFrame) -> DataFrame:
    """Many segments share a task: rows come sorted and are cut where the segment changes."""
    rows = t.select("seg", "item", "p", "v", "__b", "__u").repartition("seg").sortWithinPartitions("seg", "item")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held: list[pd.DataFrame] = []

        def settle(parts: list[pd.DataFrame]) -> pd.DataFrame:
            pdf = pd.concat(parts) if len(parts) > 1 else parts[0]
            keep = np.zeros(len(pdf), bool)
            seg, p, u = (pdf[c].to_numpy() for c in ("seg", "p", "__u"))
            cuts = np.concatenate(([0], np.flatnonzero(np.diff(seg)) + 1, [len(seg)]))
            for a, b in zip(cuts[:-1], cuts[1:], strict=True):
                keep[a:b] = pairwise_draw(p[a:b], u[a:b])
            return pdf[keep]

        for pdf in batches:
            if not len(pdf):
                continue
            last = pdf.seg.to_numpy() == pdf.seg.iloc[-1]
            if last.all() and (not held or held[-1].seg.iloc[-1] == pdf.seg.iloc[-1]):
                held.append(pdf)
                continue
            yield settle([*held, pdf[~last]]) if (~last).any() else settle(held)
            held = [pdf[last]]
        if held:
            yield settle(held)

    return rows.mapInPandas(run, rows.schema)


