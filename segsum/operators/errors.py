"""Errors of estimates over many queries, against exact counts at a bounded list of probes."""

from __future__ import annotations

import hashlib

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.hashing import md5_int
from .baselines import dyadic_cover


def item_probes(counts: DataFrame, n: int = 200, seed: int = 3, mode: str = "record") -> DataFrame:
    """(g, item): distinct items of n records drawn at random ('record'), or n distinct items ('distinct')."""
    totals = counts.groupBy("item").agg(F.sum("cnt").alias("cnt"))
    u = (md5_int(str(seed), F.col("item")) + F.lit(1)) / F.lit(float(1 << 32))
    order = F.log(u) / F.col("cnt") if mode == "record" else u  # largest log(u) / weight: a weighted draw without replacement
    drawn = totals.orderBy(F.desc(order), "item").limit(n)
    return drawn.select((F.row_number().over(Window.orderBy("item")) - 1).alias("g"), "item")


def interval_queries(spark: SparkSession, segments: int, lengths: list[int], per_length: int, seed: int = 11) -> DataFrame:
    """(qid, k, lo, hi): random aligned starts from an md5 of length and number."""
    rows = []
    for k in (k for k in lengths if k <= segments):
        for i in range(per_length):
            lo = int(hashlib.md5(f"{seed}|{k}|{i}".encode()).hexdigest()[:8], 16) % (segments - k + 1)
            rows.append((len(rows), k, lo, lo + k))
    return spark.createDataFrame(rows, "qid long, k int, lo long, hi long")


def contributions(pairs: DataFrame, probes: DataFrame, goal: str, keys: tuple[str, ...] = ("seg",), weight: str = "w") -> DataFrame:
    """(keys, g, w): what each segment's pairs add at each probe; for ranks, only from the first probe on that a pair reaches."""
    if goal == "freq":
        return pairs.join(F.broadcast(probes), "item").groupBy(*keys, "g").agg(F.sum(weight).cast("double").alias("w"))
    values = probes.agg(F.sort_array(F.collect_list("item")).alias("ps"))
    g = first_reached(F.col("ps"), F.col("item"), probes.count())
    return pairs.join(F.broadcast(values)).withColumn("g", g).where(F.col("g") < F.size("ps")).groupBy(*keys, "g").agg(F.sum(weight).cast("double").alias("w"))


def first_reached(ps: Column, item: Column, n: int) -> Column:
    """How many of the `n` ascending values are smaller than the item, by halving: a comparison per binary digit of n, not one per value."""
    steps = F.array(*[F.lit(1 << j) for j in reversed(range(n.bit_length()))])
    return F.aggregate(steps, F.lit(0), lambda g, step: F.when(F.try_element_at(ps, g + step) < item, g + step).otherwise(g))


def over_intervals(parts: DataFrame, queries: DataFrame, probes: DataFrame, running: bool = False) -> DataFrame:
    """(qid, g, w): sums over each interval as differences of running sums that are read at the intervals' ends only; with `running`, then summed over g."""
    ends = queries.select(F.col("lo").alias("t")).union(queries.select("hi")).distinct()
    marks = ends.crossJoin(F.broadcast(probes.select("g"))).select("g", "t", F.lit(0).alias("kind"), F.lit(0.0).alias("w"))  # queries times probes, both bounded
    rows = marks.unionByName(parts.select("g", F.col("seg").alias("t"), F.lit(1).alias("kind"), "w"))
    run = Window.partitionBy("g").orderBy("t", "kind").rowsBetween(Window.unboundedPreceding, 0)
    at = rows.withColumn("upto", F.sum("w").over(run)).where(F.col("kind") == 0).select("g", "t", "upto")
    ends_of = F.broadcast(queries.select("qid", F.explode(F.array(F.struct(F.col("lo").alias("t"), F.lit(-1.0).alias("sign")), F.struct(F.col("hi").alias("t"), F.lit(1.0).alias("sign")))).alias("e")).select("qid", "e.t", "e.sign"))
    out = at.join(ends_of, "t").groupBy("qid", "g").agg(F.sum(F.col("upto") * F.col("sign")).alias("w"))
    return _running(out) if running else out


def _running(out: DataFrame) -> DataFrame:
    return out.withColumn("w", F.sum("w").over(Window.partitionBy("qid").orderBy("g")))


def over_nodes(parts: DataFrame, queries: DataFrame, probes: DataFrame, layers: int, base: int, running: bool = False) -> DataFrame:
    """The same for a hierarchy: `parts` has layer, node, g and w; the cover of each query is found on the driver, which holds the query list."""
    rows = [(q["qid"], i, j) for q in queries.select("qid", "lo", "hi").collect() for i, j in dyadic_cover(q["lo"], q["hi"], layers, base)]
    cover = parts.sparkSession.createDataFrame(rows, "qid long, layer int, node long")
    got = parts.join(F.broadcast(cover), ["layer", "node"]).groupBy("qid", "g").agg(F.sum("w").alias("w"))
    grid = queries.select("qid").crossJoin(F.broadcast(probes.select("g")))
    out = grid.join(got, ["qid", "g"], "left").select("qid", "g", F.coalesce("w", F.lit(0.0)).alias("w"))
    return _running(out) if running else out


def over_cells(parts: DataFrame, matches: DataFrame, probes: DataFrame, running: bool = False) -> DataFrame:
    """The same for cube queries given as (qid, seg)."""
    got = parts.join(matches.select("qid", "seg"), "seg").groupBy("qid", "g").agg(F.sum("w").alias("w"))
    grid = matches.select("qid").distinct().crossJoin(F.broadcast(probes.select("g")))
    out = grid.join(got, ["qid", "g"], "left").select("qid", "g", F.coalesce("w", F.lit(0.0)).alias("w"))
    return _running(out) if running else out


def max_errors(truth: DataFrame, est: DataFrame, sizes: DataFrame) -> DataFrame:
    """(qid, err): the largest absolute error over the probes by the number of rows; queries without rows are left out."""
    both = truth.select("qid", "g", F.col("w").alias("t")).join(est, ["qid", "g"], "left")
    worst = both.groupBy("qid").agg(F.max(F.abs(F.col("t") - F.coalesce("w", F.lit(0.0)))).alias("e"))
    return worst.join(sizes, "qid").where(F.col("n") > 0).select("qid", (F.col("e") / F.col("n")).alias("err"))


def summarise(errors: DataFrame, queries: DataFrame, by: str, method: str) -> DataFrame:
    """(method, x, mean_err, std_err, n_queries)."""
    return (
        errors.join(F.broadcast(queries.select("qid", F.col(by).alias("x"))), "qid").groupBy("x")
        .agg(F.avg("err").alias("mean_err"), F.coalesce(F.stddev_samp("err"), F.lit(0.0)).alias("std_err"), F.count(F.lit(1)).alias("n_queries"))
        .select(F.lit(method).alias("method"), F.col("x").cast("double").alias("x"), "mean_err", "std_err", "n_queries")
    )


def quantile_rank_errors(answers: DataFrame, counts: DataFrame, where: Column) -> DataFrame:
    """(phi, value, err): by how much phi misses the ranks that `value` covers, as a share of the rows. `answers` (phi, value) is a bounded list."""
    near = counts.where(where).crossJoin(F.broadcast(answers))  # counts times the listed answers, aggregated at once
    got = near.groupBy("phi", "value").agg(
        F.sum("cnt").alias("n"), F.sum(F.when(F.col("item") < F.col("value"), F.col("cnt")).otherwise(0)).alias("below"), F.sum(F.when(F.col("item") <= F.col("value"), F.col("cnt")).otherwise(0)).alias("upto"),
    )
    return got.select("phi", "value", F.greatest(F.lit(0.0), F.col("below") / F.col("n") - F.col("phi"), F.col("phi") - F.col("upto") / F.col("n")).alias("err"))


def measured_msre(truth: DataFrame, est: DataFrame, memberships: DataFrame, weights: DataFrame) -> DataFrame:
    """(msre): squared error by squared size, averaged over the workload, at the probe where it is largest. `truth` and `est` are contributions (seg, g, w); `memberships` (seg, qkey) are the cells of all queries, `weights` (qkey, size, q)."""
    off = truth.unionByName(est.withColumn("w", -F.col("w"))).groupBy("seg", "g").agg(F.sum("w").alias("d")).where("d <> 0")
    per = off.join(memberships.select("seg", "qkey"), "seg").groupBy("qkey", "g").agg(F.sum("d").alias("d"))
    return per.join(weights, "qkey").groupBy("g").agg(F.sum(F.col("q") * (F.col("d") / F.col("size")) ** 2).alias("m")).agg(F.max("m").alias("msre"))


def space_report(summary: DataFrame) -> DataFrame:
    """(n_segments, n_pairs, max_pairs, bytes) at sixteen bytes a pair."""
    per = summary.groupBy("seg").agg(F.count(F.lit(1)).alias("k"))
    return per.agg(F.count(F.lit(1)).alias("n_segments"), F.sum("k").cast("long").alias("n_pairs"), F.max("k").alias("max_pairs"), (F.sum("k") * 16).cast("long").alias("bytes"))


def recall_of_top(estimated: DataFrame, exact: DataFrame) -> DataFrame:
    """(recall) of a list of items against the exact one."""
    hits = exact.select("item").join(estimated.select("item"), "item", "left_semi").agg(F.count(F.lit(1)).alias("hits"))
    return hits.crossJoin(F.broadcast(exact.agg(F.count(F.lit(1)).alias("size")))).select((F.col("hits") / F.col("size")).alias("recall"))
