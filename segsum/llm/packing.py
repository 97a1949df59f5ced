"""Pack documents into batches of a token budget with optimal length buckets.

One pass counts lengths into a grid (exact up to a limit, then a fixed number of
steps per doubling), merged over the whole table; a dynamic program over that
bounded histogram picks the bucket bounds with the least padding. Inside a bucket
rows are numbered densely, part by part, so that no bucket meets in one task, and
every `budget // bucket length` rows form a batch.

Defined cases: null and empty texts have length zero and go to the first bucket;
a text over the budget is a batch of its own; repeated rows are rows of their
own; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import cut, dense_positions, shards_for, word_count

BUCKETS = 16
BUDGET = 32_768
EXACT = 256
STEPS = 64


def grid_cell(length: Column) -> Column:
    """Lengths up to EXACT each have a cell; above, STEPS cells per doubling."""
    octave = F.log2(F.greatest(length, F.lit(1)) / F.lit(float(EXACT)))
    return F.when(length <= EXACT, length).otherwise(EXACT + F.ceil(octave * STEPS)).cast("long")


def optimal_bounds(top: np.ndarray, count: np.ndarray, words: np.ndarray, buckets: int) -> list[int]:
    """Ends (index into the cells, inclusive) of the buckets with the least padding.

    `top` is the largest length seen in each cell; a bucket pads all its rows to the top of its last cell.
    """
    n = len(top)
    c = np.concatenate(([0.0], np.cumsum(count, dtype=float)))
    w = np.concatenate(([0.0], np.cumsum(words, dtype=float)))
    best = np.full(n + 1, np.inf)
    best[0] = 0.0
    choice = []
    for _ in range(min(buckets, n)):
        nxt, back = np.full(n + 1, np.inf), np.zeros(n + 1, np.int64)
        for j in range(1, n + 1):
            cost = best[:j] + top[j - 1] * (c[j] - c[:j]) - (w[j] - w[:j])
            k = int(np.argmin(cost))
            nxt[j], back[j] = cost[k], k
        choice.append(back)
        best = np.minimum(nxt, np.inf)
        best[0] = 0.0 if n == 0 else np.inf
    ends, j = [], n
    for back in reversed(choice):
        if j == 0:
            break
        ends.append(j - 1)
        j = int(back[j])
    return ends[::-1]


def bucket_lengths(lengths: DataFrame, buckets: int = BUCKETS) -> list[int]:
    """Upper length of each bucket, ascending, from the histogram of all rows (a column `n_tokens`)."""
    cells = (
        lengths.groupBy(grid_cell(F.col("n_tokens")).alias("cell"))
        .agg(F.max("n_tokens").alias("top"), F.count(F.lit(1)).alias("n"), F.sum("n_tokens").alias("words"))
        .collect()  # at most EXACT + STEPS per doubling of the longest text
    )
    cells.sort(key=lambda r: r["cell"])
    top, n, words = (np.array([r[k] for r in cells], dtype=np.int64) for k in ("top", "n", "words"))
    return [int(top[i]) for i in optimal_bounds(top, n, words, buckets)] if len(cells) else []


def pack(
    docs: DataFrame, id_col: str = "doc_id", text: str = "text", budget: int = BUDGET, buckets: int = BUCKETS, n_tokens: Column | None = None,
) -> DataFrame:
    """(doc_id, n_tokens, bucket, bucket_len, batch, n_pad) for every row; `n_tokens` may name another length than words."""
    lengths = cut(docs.select(F.col(id_col).alias("doc_id"), (word_count(text) if n_tokens is None else n_tokens).alias("n_tokens")))
    bounds = bucket_lengths(lengths, buckets)
    ends = F.array(*[F.lit(b).cast("long") for b in bounds]) if bounds else F.array(F.lit(0).cast("long"))
    bucket = F.size(F.filter(ends, lambda e: e < F.col("n_tokens")))
    placed = lengths.withColumn("bucket", bucket)
    numbered = dense_positions(placed, ["bucket"], [F.xxhash64("doc_id"), F.col("doc_id"), F.col("n_tokens")], shards_for(lengths.count(), least=64), "pos")
    length = F.element_at(ends, F.col("bucket") + 1)
    fits = F.greatest(F.lit(1), F.floor(F.lit(budget) / F.greatest(length, F.lit(1)))).cast("long")
    return numbered.select(
        "doc_id", "n_tokens", "bucket", length.alias("bucket_len"),
        F.floor(F.col("pos") / fits).cast("long").alias("batch"), (length - F.col("n_tokens")).alias("n_pad"),
    )
