"""Maximum inner product search: score-aware anisotropic product quantisation, four-bit table scans, exact reranking, bounds that close the gap.

Codebooks of sixteen words per two dimensions are fitted on a bounded sample so
that the part of the residual parallel to the vector, which moves large inner
products, weighs more than the part across it. Every row is encoded (two codes a
byte). A query turns the codebooks into tables of partial products; a shard is
scanned by summing table entries, and the best of it are scored again on the
original vectors in double precision. Their k-th score is a threshold: a row's
residual, split into the parts along and across the row, says how far its scanned
product can be from the true one, and every row that may still reach the
threshold is scored too. So nothing is missed, whatever the codes are worth: where
they tell little (crowds of near copies, norms of many magnitudes), more rows are
scored. Shards and query blocks have bounded size, so any number of them runs
side by side; a query's shard winners are merged by a window over the query.

Defined cases: vectors that are null, zero, of another length or hold null or
non-finite components take no part, as query or candidate; a null id takes no
part; of repeated ids one row queries; equal scores go to the smaller id; with
fewer candidates than `k`, all are returned; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import cut
from .vectors import common_size, matrix, stacked, usable

K = 20
FIT_ROWS = 8_192
ETA = 4.0
SUB = 2
SHARD = 16_384
BLOCK = 4_096
POOL = 200


def _cost_parts(x: np.ndarray, unit: np.ndarray, books: np.ndarray, codes: np.ndarray) -> np.ndarray:
    """Parallel residual of each row and subspace, (n, m)."""
    n, m = codes.shape
    res = x.reshape(n, m, -1) - books[np.arange(m), codes]
    return np.einsum("nmd,nmd->nm", res, unit.reshape(n, m, -1))


def encode(x: np.ndarray, books: np.ndarray, eta: float = ETA, sweeps: int = 2) -> np.ndarray:
    """Codes (n, m) by coordinate descent on |residual|^2 + (eta - 1) * (parallel residual)^2."""
    m, _, d = books.shape
    n = len(x)
    xs, norm = x.reshape(n, m, d), np.linalg.norm(x, axis=1, keepdims=True)
    us = (x / norm).reshape(n, m, d)
    dist = np.stack([((xs[:, j, None, :] - books[j][None]) ** 2).sum(-1) for j in range(m)], axis=1)
    along = np.stack([((xs[:, j, None, :] - books[j][None]) * us[:, j, None, :]).sum(-1) for j in range(m)], axis=1)
    codes = dist.argmin(-1)
    rows = np.arange(n)
    total = along[rows[:, None], np.arange(m)[None], codes].sum(1)
    for _ in range(sweeps):
        for j in range(m):
            others = total - along[rows, j, codes[:, j]]
            codes[:, j] = (dist[:, j] + (eta - 1) * (others[:, None] + along[:, j]) ** 2).argmin(-1)
            total = others + along[rows, j, codes[:, j]]
    return codes


def fit_codebooks(x: np.ndarray, sub: int = SUB, eta: float = ETA, rounds: int = 6) -> np.ndarray:
    """(m, 16, sub) codebooks: alternate encoding and the least-squares update of every word."""
    n, dim = x.shape
    m = dim // sub
    rng = np.random.default_rng(7)
    pick = rng.choice(n, size=16, replace=n < 16)
    books = np.ascontiguousarray(x.reshape(n, m, sub)[pick].transpose(1, 0, 2)) + rng.normal(0, 1e-6, (m, 16, sub))
    unit = x / np.linalg.norm(x, axis=1, keepdims=True)
    xs, us = x.reshape(n, m, sub), unit.reshape(n, m, sub)
    for _ in range(rounds):
        codes = encode(x, books, eta, 1)
        along = _cost_parts(x, unit, books, codes)
        total = along.sum(1)
        for j in range(m):
            others = total - along[:, j]
            aim = xs[:, j] + (eta - 1) * (others + (xs[:, j] * us[:, j]).sum(1))[:, None] * us[:, j]
            outer = np.eye(sub)[None] + (eta - 1) * us[:, j, :, None] * us[:, j, None, :]
            for c in range(16):
                mine = codes[:, j] == c
                if mine.any():
                    books[j, c] = np.linalg.solve(outer[mine].sum(0), aim[mine].sum(0))
            along[:, j] = ((xs[:, j] - books[j, codes[:, j]]) * us[:, j]).sum(1)
            total = others + along[:, j]
    return books


def packed(codes: np.ndarray) -> np.ndarray:
    """Two four-bit codes a byte."""
    if codes.shape[1] % 2:
        codes = np.hstack([codes, np.zeros((len(codes), 1), codes.dtype)])
    return (codes[:, ::2] | codes[:, 1::2] << 4).astype(np.uint8)


def unpacked(codes: np.ndarray, m: int) -> np.ndarray:
    """(n, m): the inverse of `packed`."""
    return np.stack([codes & 15, codes >> 4], axis=2).reshape(len(codes), -1)[:, :m]


class Reach:
    """How far the true products of a shard's rows may be from the scanned ones. Queries have length one."""

    def __init__(self, x: np.ndarray, books: np.ndarray, codes: np.ndarray):
        m = len(books)
        coded = books[np.arange(m), unpacked(codes, m)].reshape(len(x), -1)
        self.norm = np.linalg.norm(x, axis=1)
        unit, rest = x / self.norm[:, None], x - coded
        along = np.einsum("nd,nd->n", rest, unit)
        self.across = np.linalg.norm(rest - along[:, None] * unit, axis=1)
        self.keep = 1 - along / self.norm
        # single precision in the tables and their sums; products too small for it count as absolute error
        self.slack = (codes.shape[1] + 4) * 2.0**-23 * (np.linalg.norm(coded, axis=1) + self.norm) + 1e-30

        self.longest, self.sure = float(self.norm.max()), bool((self.keep > 0).all())

    def may_reach(self, near: np.ndarray, least: float) -> np.ndarray:
        """Places of rows whose product with the query may be `least` or more, given the scanned products. Undefined bounds count as may.

        The part across the row meets only what the query has across it: at a
        product of `least` or more, sqrt(1 - (least / norm)^2) at most.
        """
        cosine = max(0.0, least) / self.longest
        share = float(np.sqrt(max(0.0, 1 - cosine * cosine)))
        with np.errstate(invalid="ignore", over="ignore"):
            out = near < least * self.keep - share * self.across - self.slack
        return np.flatnonzero(~out if self.sure else ~(out & (self.keep > 0)))

    def at_least(self, x: np.ndarray, query: np.ndarray, at: np.ndarray, least: float, length: float, scale: float) -> np.ndarray:
        """Those of the places whose true product is `least` or more, up to rounding."""
        close = (x @ query)[at] if 8 * len(at) > len(x) else x[at] @ query
        margin = x.shape[1] * 2.0**-50 * length * scale * self.norm[at]
        with np.errstate(invalid="ignore", over="ignore"):
            return at[~(close < least - margin)]


def scores(x: np.ndarray, query: np.ndarray) -> np.ndarray:
    """Row by row alike wherever a row stands, so that copies tie."""
    return np.einsum("nd,d->n", x, query)


def scan_tables(queries: np.ndarray, books: np.ndarray) -> np.ndarray:
    """(queries, bytes, 256): the partial product that each byte of codes stands for."""
    m, _, d = books.shape
    lut = np.einsum("qmd,mcd->qmc", queries.reshape(len(queries), m, d), books)
    if m % 2:
        lut = np.concatenate([lut, np.zeros((len(queries), 1, 16))], axis=1)
    both = lut[:, 1::2, :, None] + lut[:, ::2, None, :]
    return both.reshape(len(queries), -1, 256).astype(np.float32)


def nearest(
    vectors: DataFrame, queries: Column, id_col: str = "vec_id", vector: str = "embedding", k: int = K, fit_rows: int = FIT_ROWS, pool: int = POOL,
    shard_rows: int = SHARD, block_rows: int = BLOCK,
) -> DataFrame:
    """(query_id, rank, vec_id, score): the `k` largest inner products of each row that the condition `queries` picks, against every other row."""
    out = "query_id long, rank int, vec_id long, score double"
    own = vectors.select(F.col(id_col).cast("long").alias("vec_id"), F.col(vector).alias("embedding"), F.coalesce(queries, F.lit(False)).alias("asks"))
    dim = common_size(own.where(F.col("vec_id").isNotNull()), "embedding")
    if dim <= 0:
        return own.sparkSession.createDataFrame([], out)
    own = own.where(F.col("vec_id").isNotNull() & usable("embedding", dim))
    sample = own.orderBy(F.xxhash64("vec_id"), "vec_id").limit(fit_rows).select("embedding").toPandas()
    if not len(sample):
        return own.sparkSession.createDataFrame([], out)
    sub = next(s for s in (SUB, 1) if dim % s == 0)
    fitted = stacked(sample.embedding.tolist(), dim)
    scale = float(np.abs(fitted).max())
    books = fit_codebooks(fitted / scale, sub)

    def index(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            codes = packed(encode(matrix(batch.column(1), dim) / scale, books))
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array([c.tobytes() for c in codes], pa.binary())], ["vec_id", "embedding", "asks", "codes"])

    item = own.schema["embedding"].dataType.simpleString()
    indexed = cut(own.mapInArrow(index, f"vec_id long, embedding {item}, asks boolean, codes binary"))
    size = indexed.agg(F.count(F.lit(1)), F.count(F.when(F.col("asks"), 1))).first()
    shards, blocks = max(1, -(-size[0] // shard_rows)), max(1, -(-size[1] // block_rows))
    deal = lambda n: F.pmod(F.xxhash64("vec_id"), F.lit(n)).cast("int")
    every = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    found = indexed.select("vec_id", "embedding", "codes", F.lit(False).alias("asks"), deal(shards).alias("shard"), every(blocks).alias("block"))
    asked = indexed.where("asks").dropDuplicates(["vec_id"]).select(
        "vec_id", "embedding", F.lit(None).cast("binary").alias("codes"), F.lit(True).alias("asks"), every(shards).alias("shard"), deal(blocks).alias("block")
    )

    def search(pdf: pd.DataFrame) -> pd.DataFrame:
        q, c = pdf[pdf.asks], pdf[~pdf.asks].sort_values("vec_id")
        if not len(q) or not len(c):
            return pd.DataFrame({"query_id": [], "vec_id": [], "score": []})
        ids, x = c.vec_id.to_numpy(), stacked(c.embedding.tolist(), dim)
        rows_of_codes = np.frombuffer(b"".join(c.codes), np.uint8).reshape(len(c), -1)
        codes, reach = rows_of_codes.T.copy(), Reach(x / scale, books, rows_of_codes)
        asks, qx = q.vec_id.to_numpy(), stacked(q.embedding.tolist(), dim)
        size = np.linalg.norm(qx / scale, axis=1) * scale
        rows = []
        for s in range(0, len(q), 64):
            tables = scan_tables(qx[s:s + 64] / size[s:s + 64, None], books)
            for t, (qid, qv, length) in enumerate(zip(asks[s:s + 64], qx[s:s + 64], size[s:s + 64], strict=True)):
                near = tables[t, 0][codes[0]]
                for b in range(1, len(codes)):
                    near += tables[t, b][codes[b]]
                if len(near) > pool + 1:
                    at = np.argpartition(near, len(near) - pool - 1)[len(near) - pool - 1:]
                    first = scores(x[at[ids[at] != qid]], qv)
                    if len(first) >= k:
                        least = np.partition(first, len(first) - k)[len(first) - k]
                        at = reach.at_least(x, qv, reach.may_reach(near, float(least) / length / scale), float(least), length, scale)
                    else:
                        at = np.arange(len(near))
                else:
                    at = np.arange(len(near))
                at = at[ids[at] != qid]
                score = scores(x[at], qv)
                best = np.lexsort((ids[at], -score))[:k]
                rows.append((np.full(len(best), qid), ids[at][best], score[best]))
        return pd.DataFrame({n: np.concatenate([r[i] for r in rows]) for i, n in enumerate(("query_id", "vec_id", "score"))})

    hits = found.unionByName(asked).groupBy("shard", "block").applyInPandas(search, "query_id long, vec_id long, score double")
    by_query = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return hits.withColumn("rank", F.row_number().over(by_query)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
