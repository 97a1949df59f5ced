"""Mix sources to target weights by entropy balancing, in DataFrame functions only.

Each document gets a rate, exponentially tilted by its size, that is as close as
can be (in relative entropy, between 0 and `cap`) to taking every document once
while the words of each source meet the source's target. The dual is convex and
separates by source: one multiplier each, found by Newton steps that a bracket
safeguards. A rate depends on source and size alone, so the steps run on the
table (source, size, count), distributed and materialised; multipliers stay in
a DataFrame. Rates are rounded to whole copies by systematic rounding in order
of size, and the few words still missing are made up by largest-fit changes.

Defined cases: null and empty texts have size zero and are taken zero times;
a null source is a source of its own, ranked last; repeated rows are documents
of their own; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import cut, dense_positions, key_of, shards_for, word_count

WEIGHTS = (3, 1, 2)
SHARE = 1.5
CAP = 2
STEPS, ROUNDS = 5, 6
FIXES = 8


def source_targets(base: DataFrame, weights: tuple[int, ...] = WEIGHTS, share: float = SHARE, cap: float = CAP) -> DataFrame:
    """(key, source, source_size, target) from rows (key, source, size): weights repeat by code point order; a target stops at `cap` times the source's size and what is over is shared again."""
    sizes = base.groupBy("key", "source").agg(F.sum("size").alias("source_size"))
    rank = F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last()))
    weigh = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (F.pmod(rank - 1, F.lit(len(weights))) + 1).cast("int"))
    w = sizes.withColumn("weight", weigh).withColumn("most", F.col("source_size") * F.lit(float(cap)))
    by_level = Window.orderBy(F.col("most") / F.col("weight"), "key")
    before = by_level.rowsBetween(Window.unboundedPreceding, -1)
    after = by_level.rowsBetween(0, Window.unboundedFollowing)
    whole = Window.partitionBy()
    levels = w.withColumn(
        "level",
        (F.sum("source_size").over(whole) * F.lit(share) - F.coalesce(F.sum("most").over(before), F.lit(0.0)))
        / F.sum("weight").over(after),
    )
    # the first source, in the order in which caps are reached, that its level doesn't bring to its cap
    level = F.min(F.when(F.col("level") * F.col("weight") <= F.col("most"), F.struct(F.col("most") / F.col("weight"), "key", "level"))).over(whole)
    target = F.least(F.col("most"), F.col("weight") * F.coalesce(level["level"], F.lit(math.inf)))
    return levels.select("key", "source", "source_size", target.alias("target"))


def _newton(cells: DataFrame, state: DataFrame, cap: float) -> DataFrame:
    """One safeguarded step of every source's multiplier."""
    x, lam = F.col("x"), F.col("lam")
    tilt = F.exp(lam * x)
    words = F.col("n") * F.col("size")
    lo = F.when(F.col("f") < F.col("target"), lam).otherwise(F.col("lo"))
    hi = F.when(F.col("f") < F.col("target"), F.col("hi")).otherwise(lam)
    step = lam - F.try_divide(F.col("f") - F.col("target"), F.col("slope"))
    met = F.abs(F.col("f") - F.col("target")) <= 1e-9 * F.col("target")
    good = F.coalesce((F.col("slope") > 0) & (step > lo) & (step < hi), F.lit(False))
    return (
        cells.join(state, "key")
        .groupBy("key", "target", "lam", "lo", "hi")
        .agg(
            F.sum(words * F.least(F.lit(float(cap)), tilt)).alias("f"),
            F.sum(F.when(tilt < cap, words * x * tilt).otherwise(0.0)).alias("slope"),
        )
        .select("key", "target", F.when(met, lam).when(good, step).otherwise((lo + hi) / 2).alias("lam"), lo.alias("lo"), hi.alias("hi"), "f", lam.alias("at"))
    )


def tilted_rates(cells: DataFrame, targets: DataFrame, cap: float = CAP) -> DataFrame:
    """(key, target, lam): rate of a document of scaled size x is min(cap, exp(lam * x))."""
    bounds = cells.groupBy("key").agg(F.min("x").alias("x0"), F.sum(F.col("n") * F.col("size") * F.col("x")).alias("wx"), F.sum(F.col("n") * F.col("size")).alias("words"))
    t = F.greatest(F.col("target"), F.col("words") * 1e-9)
    ratio = F.log(t / F.col("words"))
    lo = F.least(F.lit(-1e-6), ratio * 1.001) / F.col("x0")
    hi = F.lit(math.log(cap) * 1.000001) / F.col("x0")
    full = t >= F.col("words") * F.lit(cap * (1 - 1e-9))
    start = F.greatest(lo * 0.999, F.least(ratio * F.col("words") / F.col("wx"), hi * 0.999))
    state = cut(
        targets.join(bounds, "key").select(
            "key", t.alias("target"), F.when(full, hi).otherwise(start).alias("lam"), F.when(full, hi).otherwise(lo).alias("lo"), hi.alias("hi"), F.lit(None).cast("double").alias("f")
        )
    )
    for _ in range(ROUNDS):
        for _ in range(STEPS):
            state = _newton(cells, state.drop("f", "at"), cap)
        state = cut(state)
        off = state.agg(F.max(F.abs(F.col("f") / F.col("target") - 1))).first()[0]
        if off is None or off < 1e-6:
            break
    return state.select("key", "target", F.col("at").alias("lam"))  # the multiplier whose words were counted


def _fix(cells: DataFrame, state: DataFrame) -> DataFrame:
    """Give (or take) as many copies as fit of the largest size, below the last one used, that the missing words can hold."""
    room = F.when(F.col("gap") > 0, F.col("most") - F.col("copies")).otherwise(F.col("copies"))
    fits = (F.col("size") < F.col("last")) & (F.col("size") <= F.abs("gap")) & (room > 0)
    best = F.max(F.when(fits, F.struct(F.col("size").alias("size"), room.alias("room")))).alias("best")
    some = F.least(F.col("best.room"), F.floor(F.abs("gap") / F.col("best.size"))).cast("long")
    change = F.when(F.col("gap") > 0, some).otherwise(-some)
    found = state.join(cells.select("key", "size", "most", "copies"), "key").groupBy("key", "gap", "last").agg(best, F.first("picks").alias("picks"))
    none = F.col("best").isNull()
    return found.select(
        "key",
        F.when(none, F.col("gap")).otherwise(F.col("gap") - change * F.col("best.size")).alias("gap"),
        F.when(none, F.col("last")).otherwise(F.col("best.size")).alias("last"),
        F.when(none, F.col("picks")).otherwise(F.concat("picks", F.array(F.struct(F.col("best.size").alias("size"), change.alias("change"))))).alias("picks"),
    )


def mix(
    docs: DataFrame, id_col: str = "doc_id", source: str = "source", text: str = "text",
    weights: tuple[int, ...] = WEIGHTS, share: float = SHARE, cap: int = CAP,
) -> DataFrame:
    """(doc_id, size, source_size, target, taken, copies) for every row."""
    base = cut(docs.select(F.col(id_col).alias("doc_id"), key_of(source).alias("key"), F.col(source).alias("source"), word_count(text).alias("size")))
    rows = base.count()
    targets = cut(source_targets(base, weights, share, cap))
    hist = base.where(F.col("size") > 0).groupBy("key", "size").agg(F.count(F.lit(1)).alias("n"))
    mean = base.where(F.col("size") > 0).groupBy("key").agg(F.avg("size").alias("mean"))
    cells = cut(hist.join(mean, "key").select("key", "size", "n", (F.col("size") / F.col("mean")).alias("x")))
    rates = tilted_rates(cells, targets.select("key", "target"), cap)

    run = Window.partitionBy("key").orderBy(F.desc("size")).rowsBetween(Window.unboundedPreceding, 0)
    copies = F.col("n") * F.least(F.lit(float(cap)), F.exp(F.col("lam") * F.col("x")))
    upto = F.round(F.sum("want").over(run), 6)
    rounded = (
        cells.join(rates.drop("target"), "key")
        .withColumn("want", copies)
        .withColumn("upto", F.floor(upto + 0.5).cast("long"))
        .withColumn("copies", F.col("upto") - F.coalesce(F.lag("upto").over(Window.partitionBy("key").orderBy(F.desc("size"))), F.lit(0)))
        .select("key", "size", "n", (F.col("n") * cap).alias("most"), F.greatest(F.lit(0), F.least(F.col("copies"), F.col("n") * cap)).alias("copies"))
    )
    rounded = cut(rounded)
    got = rounded.groupBy("key").agg(F.sum(F.col("copies") * F.col("size")).alias("got"))
    state = targets.join(got, "key").select(
        "key", F.round(F.col("target") - F.col("got")).cast("long").alias("gap"), F.lit((1 << 62)).cast("long").alias("last"),
        F.array().cast("array<struct<size:bigint,change:bigint>>").alias("picks"),
    )
    for _ in range(FIXES):
        state = _fix(rounded, state)
    picks = state.select("key", F.explode("picks").alias("p")).select("key", "p.size", "p.change")
    settled = rounded.join(picks, ["key", "size"], "left").select(
        "key", "size", "n", (F.col("copies") + F.coalesce("change", F.lit(0))).alias("copies")
    )
    numbered = dense_positions(base.where(F.col("size") > 0), ["key", "size"], [F.xxhash64("doc_id"), F.col("doc_id")], shards_for(rows), "pos", settled)
    each = F.floor(F.col("copies") / F.col("n")).cast("long")
    own = (each + (F.col("pos") < F.col("copies") - each * F.col("n")).cast("long")).alias("copies")
    placed = numbered.select("doc_id", "key", "size", own)
    empty = base.where(F.col("size") == 0).select("doc_id", "key", "size", F.lit(0).cast("long").alias("copies"))
    return (
        placed.union(empty)
        .join(targets.select("key", "source_size", "target"), "key")
        .select("doc_id", "size", "source_size", "target", (F.col("copies") * F.col("size")).alias("taken"), "copies")
    )


def take_copies(docs: DataFrame, id_col: str = "doc_id", source: str = "source", text: str = "text") -> DataFrame:
    """`docs` with every row repeated as often as the mix takes it; empty texts weigh nothing and are not taken."""
    copies = mix(docs, id_col, source, text).groupBy(F.col("doc_id").alias("__id")).agg(
        F.sum("copies").alias("__copies"), F.count(F.lit(1)).alias("__rows")
    ).where(F.col("__copies") > 0)
    own = docs.join(copies, docs[id_col].eqNullSafe(F.col("__id")))
    # rows that share an id share its copies, the earlier by hash of the text taking the odd ones
    nth = F.row_number().over(Window.partitionBy("__id").orderBy(F.xxhash64(F.col(text)))) - 1
    base = F.floor(F.col("__copies") / F.col("__rows"))
    times = (base + (nth < F.col("__copies") - base * F.col("__rows")).cast("long")).cast("int")
    return (
        own.withColumn("__times", times)
        .where(F.col("__times") > 0)
        .withColumn("__copy", F.explode(F.sequence(F.lit(1), F.col("__times"))))
        .select(*docs.columns)
    )
