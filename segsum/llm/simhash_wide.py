"""Near copies at a stated similarity: wide SimHash fingerprints in a forest of vantage-point trees.

A pair of shingle multisets with Jaccard similarity J has a cosine of about
2 J / (1 + J), and each majority bit differs with probability arccos(cosine) / pi
(15 % of the bits at .8). BITS bits estimate that share to about .026 of
similarity; a pair is linked within `reach` bits, what is expected at the
threshold and one standard error more, so that pairs just at it are found. Pairs
a little below may be linked too; no pair is confirmed otherwise.

Bits that differ by 15 % are too many for the triangle bound of one tree to
prune (distances of unrelated texts crowd around half the bits), so the forest
has many trees. An inner node measures the Hamming distance to its vantage point
on a stretch of one bit, drawn anew for every level, and a pair stays together in
a tree of depth d with probability (1 - reach / BITS)^d; the number of trees
follows from the depth so that a pair just at the threshold is missed by all of
them with probability MISS. That number grows as n^.23 with the rows.

Inside a leaf the triangle bound does work: a point becomes the vantage point of
the points not yet taken, those within reach join it, and only points within
twice the reach are compared with its members; no copy meets all other copies.
A leaf with more than `tile` points is dealt to parts by hash, and every two parts
meet in a task of their own, so no link of a leaf is lost by its size.

Defined cases: words are those of the 64-bit fingerprints, ASCII letters lowered;
a text of fewer than five words is one shingle; null and empty texts are copies
of each other; repeated rows are copies; rows without an id stay; an empty table
gives an empty result; other columns are carried along.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .bytehash import mix, owners, text_buffer, text_slices, window_hashes, word_hashes, word_spans
from .common import connected_components, cut

WIDTH = 5
SIMILARITY = 0.8
BITS = 1024
MISS = 1e-3
LEAF = 512
TILE = 8192
#: Bytes of fingerprints that a worker gathers before it hands them on; all trees of a batch at once would take some thirty times the batch.
GATHERED = 1 << 21

_ODD_BYTES = np.uint64(0x0101010101010101)


def reach_of(similarity: float, bits: int = BITS) -> int:
    """Differing bits expected at a Jaccard similarity, and one standard error of them."""
    share = math.acos(2 * similarity / (1 + similarity)) / math.pi
    return int(bits * share + math.sqrt(bits * share * (1 - share)))


def trees_for(depth: int, reach: int, bits: int = BITS, miss: float = MISS) -> int:
    """Trees by which a pair just at the threshold is missed with probability `miss`."""
    together = (1 - reach / bits) ** depth
    return 1 if together >= 1 else math.ceil(math.log(miss) / math.log(1 - together))


def shingle_hashes(column: pa.Array, width: int = WIDTH) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all shingles of all texts in order, and how many each text has."""
    raw, at = text_buffer(column)
    starts, ends = word_spans(raw, at)
    words, owner = word_hashes(raw, starts, ends, lower=True), owners(at, starts)
    n = np.bincount(owner, minlength=len(column))
    first = np.concatenate(([0], np.cumsum(n)[:-1])).astype(np.int64)
    whole = window_hashes(words, width)
    inside = owner[:len(whole)] == owner[width - 1:] if len(whole) else np.empty(0, bool)
    hashes, place = [whole[inside]], [owner[:len(whole)][inside]]
    for short in range(1, width):  # a text of fewer words is one shingle
        own = np.flatnonzero(n == short)
        if len(own):
            hashes.append(mix(window_hashes(words, short)[first[own]] + np.uint64(short)))
            place.append(own)
    order = np.argsort(np.concatenate(place), kind="stable")
    return np.concatenate(hashes)[order], np.maximum(n - width + 1, (n > 0).astype(n.dtype))


def majority_bits(hashes: np.ndarray, n: np.ndarray, words: int = BITS // 64) -> np.ndarray:
    """(texts, words) unsigned: bit by bit, whether over half of a text's shingles have it set; zero without shingles."""
    out = np.zeros((len(n), words), np.uint64)
    some = np.flatnonzero(n)
    if not len(some):
        return out
    n = n[some]
    first = np.concatenate(([0], np.cumsum(n)[:-1]))
    parts = -(-n // 255)  # a byte holds the counts of 255 shingles
    part_at = np.concatenate(([0], np.cumsum(parts)[:-1]))
    begin = np.repeat(first, parts) + 255 * (np.arange(parts.sum()) - np.repeat(part_at, parts))
    for w in range(words):
        x = mix(hashes + np.uint64((w + 1) * 0x9E3779B97F4A7C15 & (1 << 64) - 1))
        bytes_ = np.zeros((len(n), 8), np.uint8)
        for k in range(8):
            lanes = np.add.reduceat((x >> np.uint64(k)) & _ODD_BYTES, begin).view(np.uint8).reshape(-1, 8)
            counts = np.add.reduceat(lanes.astype(np.int64), part_at, axis=0)
            bytes_ |= (counts * 2 > n[:, None]).astype(np.uint8) << np.uint8(k)
        out[some, w] = bytes_.view(np.uint64)[:, 0]
    return out


def wide_fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = WIDTH) -> DataFrame:
    """(doc_id, t, node, fp) per row: t tells rows of one id apart, fp is the fingerprint, node its hash."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i, size in text_slices(batch.column(2)):
                part = batch.slice(i, size)
                fps = majority_bits(*shingle_hashes(part.column(2), width))
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array([f.tobytes() for f in fps], pa.binary())], ["doc_id", "t", "fp"])

    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.xxhash64(text_col).alias("t"), F.col(text_col).alias("text"))
    return rows.mapInArrow(run, "doc_id long, t long, fp binary").select("doc_id", "t", F.xxhash64("fp").alias("node"), "fp")


class StretchForest:
    """Trees whose levels measure the distance to a vantage point on one bit each."""

    def __init__(self, rows: int, reach: int, bits: int = BITS, leaf: int = LEAF, miss: float = MISS):
        self.depth = max(0, math.ceil(math.log2(max(1, rows) / leaf)))
        self.trees = trees_for(self.depth, reach, bits, miss)
        rng = np.random.default_rng(20_240_117)
        self.stretches = [rng.choice(bits, self.depth, replace=False) for _ in range(self.trees)]

    def sides(self, fps: np.ndarray, tree: int, level: int) -> np.ndarray:
        at = int(self.stretches[tree][level])
        return ((fps[:, at >> 6] >> np.uint64(at & 63)) & np.uint64(1)).astype(np.int64)

    def leaves(self, fps: np.ndarray, tree: int) -> np.ndarray:
        code = np.full(len(fps), tree, np.int64)
        for level in range(self.depth):
            code = code << 1 | self.sides(fps, tree, level)
        return code


def leaf_links(nodes: np.ndarray, fps: np.ndarray, reach: int) -> tuple[np.ndarray, np.ndarray]:
    """Links that join all points within `reach` of each other, by vantage points and the triangle bound."""
    planes = np.ascontiguousarray(fps.T)
    active = np.arange(len(nodes))
    a, b = [nodes[:0]], [nodes[:0]]

    def distances(point: int, others: np.ndarray) -> np.ndarray:
        return np.bitwise_count(planes[:, others] ^ planes[:, point, None]).sum(axis=0, dtype=np.int32)

    while len(active) > 1:
        point, rest = active[0], active[1:]
        d = distances(point, rest)
        near = d <= reach
        members = rest[near]
        if len(members):
            a.append(np.full(len(members), nodes[point])), b.append(nodes[members])
            for other in rest[(d > reach) & (d <= 2 * reach)].tolist():
                met = members[distances(other, members) <= reach]
                if len(met):
                    a.append(nodes[met[:1]]), b.append(nodes[[other]])
        active = rest[~near]
    return np.concatenate(a), np.concatenate(b)


def dealt(forest: StretchForest, nodes: np.ndarray, fps: np.ndarray, parts: dict[int, int], most: int = GATHERED) -> Iterator[pa.RecordBatch]:
    """(leaf, sub, nodes, fps): the points of each leaf as one row of bytes, handed on as soon as `most` bytes are gathered. `parts` tells the overfull leaves."""
    keys: list[tuple[int, int]] = []
    blobs: list[tuple[bytes, bytes]] = []
    size = 0

    def gathered() -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays(
            [pa.array([k[i] for k in keys], pa.int64()) for i in (0, 1)] + [pa.array([x[i] for x in blobs], pa.binary()) for i in (0, 1)], ["leaf", "sub", "nodes", "fps"],
        )

    for tree in range(forest.trees):
        code = forest.leaves(fps, tree)
        sub = np.zeros(len(code), np.int64)
        for full in np.intersect1d(code, list(parts)) if parts else ():
            own = code == full
            sub[own] = nodes[own] % parts[int(full)]
        order = np.lexsort((sub, code))
        code, sub = code[order], sub[order]
        cuts = np.flatnonzero((np.diff(code) != 0) | (np.diff(sub) != 0)) + 1
        for s, e in zip([0, *cuts.tolist()], [*cuts.tolist(), len(code)], strict=True):
            if e > s:
                at, part = int(code[s]), int(sub[s])
                n = parts.get(at, 1)
                blob = (nodes[order[s:e]].tobytes(), fps[order[s:e]].tobytes())
                for other in range(n):  # a part meets each other part, and its own points there
                    if n == 1 or other != part:
                        keys.append((at, min(part, other) * n + max(part, other)))
                        blobs.append(blob)
                        size += len(blob[0]) + len(blob[1])
                        if size >= most:
                            yield gathered()
                            keys, blobs, size = [], [], 0
    if keys:
        yield gathered()


def wide_links(points: DataFrame, rows: int, reach: int, leaf: int = LEAF, tile: int = TILE, bits: int = BITS, miss: float = MISS) -> DataFrame:
    """(a, b): links between nodes of `points` (node, fp; distinct) whose fingerprints lie within `reach` bits."""
    forest = StretchForest(rows, reach, bits, leaf, miss)
    points = points.select("node", "fp")
    words = bits // 64

    def opened(batch: pa.RecordBatch) -> np.ndarray:
        return np.frombuffer(b"".join(batch.column(1).to_pylist()), np.uint64).reshape(-1, words)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            fps = opened(batch)
            code, n = np.unique(np.concatenate([forest.leaves(fps, t) for t in range(forest.trees)]), return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array(code), pa.array(n)], ["leaf", "n"])

    sizes = points.mapInArrow(count, "leaf long, n long").groupBy("leaf").agg(F.sum("n").alias("n")).where(F.col("n") > tile)
    # at most trees * rows / tile leaves are overfull, far fewer unless texts crowd
    parts = {r["leaf"]: max(2, -(-r["n"] // tile)) for r in sizes.collect()}

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield from dealt(forest, batch.column(0).to_numpy(zero_copy_only=False), opened(batch), parts)

    def compare(pdf: pd.DataFrame) -> pd.DataFrame:
        nodes = np.frombuffer(b"".join(pdf.nodes), np.int64)
        order = np.argsort(nodes, kind="stable")  # the same vantage points whatever way the rows come
        a, b = leaf_links(nodes[order], np.frombuffer(b"".join(pdf.fps), np.uint64).reshape(-1, words)[order], reach)
        n = parts.get(int(pdf.leaf.iloc[0]), 1)
        if n > 1:  # what joins points of one part is told by that part's first task only
            lower, upper = divmod(int(pdf["sub"].iloc[0]), n)
            first = np.where(a % n == 0, upper == 1, lower == 0)
            a, b = a[(a % n != b % n) | first], b[(a % n != b % n) | first]
        return pd.DataFrame({"a": a, "b": b})

    return points.mapInArrow(deal, "leaf long, sub long, nodes binary, fps binary").groupBy("leaf", "sub").applyInPandas(compare, "a long, b long")


def near_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", similarity: float = SIMILARITY, width: int = WIDTH) -> DataFrame:
    """(doc_id, t, root) per row; rows of one root are linked by fingerprints at `similarity` or more."""
    own = cut(wide_fingerprints(docs, id_col, text_col, width))
    points = own.groupBy("node").agg(F.min("fp").alias("fp"))
    links = cut(wide_links(points, own.agg(F.approx_count_distinct("node")).first()[0], reach_of(similarity)))
    parts = connected_components(links)
    return own.join(parts, "node", "left").select("doc_id", "t", F.coalesce("root", "node").alias("root"))


def drop_near_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", similarity: float = SIMILARITY) -> DataFrame:
    """One row of each group stays, with all its columns: that of the least id, then of the least hash of its text."""
    found = near_copies(docs.where(F.col(id_col).isNotNull()), id_col, text_col, similarity)
    keep = found.groupBy("root").agg(F.min(F.struct("doc_id", "t")).alias("row")).select(F.col("row.doc_id").alias("__kept_id"), F.col("row.t").alias("__kept_t"))
    at = (F.col(id_col).cast("long") == F.col("__kept_id")) & (F.xxhash64(text_col) == F.col("__kept_t"))
    kept = docs.join(keep, at).dropDuplicates(["__kept_id", "__kept_t"]).drop("__kept_id", "__kept_t")
    return kept.unionByName(docs.where(F.col(id_col).isNull()))
