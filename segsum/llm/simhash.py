"""Near-duplicate documents: 64-bit SimHash fingerprints joined by vantage-point trees.

Two fingerprints within `radius` bits differ in at most radius // blocks bits of
at least one of `blocks` bit blocks. Each block has a vantage-point tree: an
inner node splits by Hamming distance to its vantage point, a fingerprint lives
in one leaf (shard), and it visits as a query every leaf that the triangle
inequality doesn't rule out. Leaves then compare residents with visitors over
all 64 bits, so the links are exact. Leaves report spanning links only, and
residents of an overfull leaf are dealt to tiles that all its visitors see.

Defined cases: null and empty texts have fingerprint zero and link like any
other; repeated rows share a component; a null doc_id gets its group's smallest
id; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import component_least, connected_components, cut

BITS = 64
SHINGLE = 4
RADIUS = 4
BLOCKS = 3
LEAF = 1024
TILE = 32_768


def fingerprint(text: str | None, width: int = SHINGLE) -> int:
    """Majority bits of the XXH64 (seed 42) of all shingles, repeats included; signed."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return 0
    joined = b" ".join(words)
    ends = np.cumsum([len(w) + 1 for w in words]) - 1
    starts = np.concatenate(([0], ends[:-1] + 1))
    if len(words) > width:
        spans = zip(starts[: 1 - width].tolist(), ends[width - 1:].tolist(), strict=True)
    else:
        spans = [(0, len(joined))]
    digest = xxhash.xxh64_intdigest
    counts, n = np.zeros(BITS, np.int64), 0
    hashes: list[int] = []
    for s, e in spans:
        hashes.append(digest(joined[s:e], 42))
        if len(hashes) == 65_536:
            counts += _bit_counts(hashes)
            n += len(hashes)
            hashes = []
    if hashes:
        counts += _bit_counts(hashes)
        n += len(hashes)
    bits = counts * 2 > n
    return int(np.packbits(bits, bitorder="little").view("<i8")[0])


def _bit_counts(hashes: list[int]) -> np.ndarray:
    raw = np.array(hashes, dtype="<u8").view(np.uint8).reshape(-1, 8)
    return np.unpackbits(raw, axis=1, bitorder="little").sum(axis=0, dtype=np.int64)


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = SHINGLE) -> DataFrame:
    """(doc_id, fp): one signed 64-bit fingerprint per row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch.column(1)
            fps = [fingerprint(texts[i].as_py(), width) for i in range(len(texts))]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(fps, pa.int64())], ["doc_id", "fp"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(
        run, "doc_id long, fp long"
    )


class VantageForest:
    """One tree per bit block. Vantage points come from a fixed seed; the radius that splits is the block's median distance."""

    def __init__(self, depth: int, radius: int = RADIUS, blocks: int = BLOCKS):
        edges = [round(i * BITS / blocks) for i in range(blocks + 1)]
        self.depth, self.blocks, self.reach = depth, blocks, radius // blocks
        self.low = edges[:-1]
        self.width = [b - a for a, b in zip(edges[:-1], edges[1:], strict=True)]
        rng = np.random.default_rng(20_240_117)
        self.points = [rng.integers(0, 1 << w, size=1 << max(depth, 1), dtype=np.uint64) for w in self.width]

    def block(self, fps: np.ndarray, k: int) -> np.ndarray:
        return (fps >> np.uint64(self.low[k])) & np.uint64((1 << self.width[k]) - 1)

    def homes(self, fps: np.ndarray, k: int) -> np.ndarray:
        x, node = self.block(fps, k), np.ones(len(fps), np.int64)
        for _ in range(self.depth):
            far = np.bitwise_count(x ^ self.points[k][node]) > self.width[k] // 2
            node = 2 * node + far
        return (node - (1 << self.depth)) * self.blocks + k

    def visits(self, fps: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
        """Rows and leaves: every leaf that may hold a point within reach of the row's block."""
        x, split = self.block(fps, k), self.width[k] // 2
        row, node = np.arange(len(fps)), np.ones(len(fps), np.int64)
        for _ in range(self.depth):
            d = np.bitwise_count(x[row] ^ self.points[k][node]).astype(np.int64)
            near, far = d <= split + self.reach, d + self.reach > split
            row, node = np.concatenate((row[near], row[far])), np.concatenate((2 * node[near], 2 * node[far] + 1))
        return row, (node - (1 << self.depth)) * self.blocks + k


def spanning_links(homes: np.ndarray, visitors: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """Nodes and their local roots, for all pairs of a home and a visitor within `radius` bits."""
    nodes = np.unique(np.concatenate((homes, visitors)))
    parent = np.arange(len(nodes))
    h_at = np.searchsorted(nodes, homes)
    v_at = np.searchsorted(nodes, visitors)
    step = max(1, (1 << 22) // max(1, len(homes)))
    for i in range(0, len(visitors), step):
        close = np.bitwise_count(visitors[i:i + step, None] ^ homes[None, :]) <= radius
        r, c = np.nonzero(close)
        a, b = v_at[i + r], h_at[c]
        keep = a != b
        a, b = a[keep], b[keep]
        while len(a):
            a, b = _roots(parent, a), _roots(parent, b)
            keep = a != b
            a, b = a[keep], b[keep]
            if len(a):
                np.minimum.at(parent, np.maximum(a, b), np.minimum(a, b))
    root = _roots(parent, np.arange(len(nodes)))
    linked = root != np.arange(len(nodes))
    return nodes[linked], nodes[root[linked]]


def _roots(parent: np.ndarray, x: np.ndarray) -> np.ndarray:
    x = parent[x]
    while True:
        y = parent[x]
        if np.array_equal(x, y):
            return x
        x = y


def hamming_links(fps: DataFrame, rows: int, radius: int = RADIUS, blocks: int = BLOCKS, leaf: int = LEAF, tile: int = TILE) -> DataFrame:
    """(a, b): links that join all of `fps` (one distinct long column) lying within `radius` bits of each other."""
    forest = VantageForest(max(0, math.ceil(math.log2(max(1, rows) / leaf))), radius, blocks)

    def pieces(leaves: np.ndarray, values: np.ndarray) -> Iterator[tuple[int, bytes]]:
        order = np.argsort(leaves, kind="stable")
        leaves, values = leaves[order], values[order]
        cuts = np.flatnonzero(np.diff(leaves)) + 1
        for s, e in zip(np.concatenate(([0], cuts)), np.concatenate((cuts, [len(leaves)])), strict=True):
            if e > s:
                yield int(leaves[s]), values[s:e].tobytes()

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen = np.zeros(blocks << forest.depth, np.int64)
        for batch in batches:
            x = batch.column(0).to_numpy(zero_copy_only=False).view(np.uint64)
            for k in range(blocks):
                seen += np.bincount(forest.homes(x, k), minlength=len(seen))
        some = np.flatnonzero(seen)
        yield pa.RecordBatch.from_arrays([pa.array(some), pa.array(seen[some])], ["leaf", "n"])

    full = (
        fps.mapInArrow(count, "leaf long, n long").groupBy("leaf").agg(F.sum("n").alias("n")).where(F.col("n") > tile)
    )
    tiles = {r["leaf"]: -(-r["n"] // tile) for r in full.collect()}  # at most blocks * rows / tile of them

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = batch.column(0).to_numpy(zero_copy_only=False).view(np.uint64)
            keys: list[int] = []
            parts: list[int] = []
            home: list[bool] = []
            blobs: list[bytes] = []
            for k in range(blocks):
                for at, blob in pieces(forest.homes(x, k), x):
                    if at in tiles:
                        own = np.frombuffer(blob, np.uint64)
                        part = (own * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(33)) % np.uint64(tiles[at])
                        split = [(p, own[part == p].tobytes()) for p in range(tiles[at])]
                    else:
                        split = [(0, blob)]
                    for p, b in split:
                        keys.append(at), parts.append(p), home.append(True), blobs.append(b)
                row, leaves = forest.visits(x, k)
                for at, blob in pieces(leaves, x[row]):
                    for p in range(tiles.get(at, 1)):
                        keys.append(at), parts.append(p), home.append(False), blobs.append(blob)
            yield pa.RecordBatch.from_arrays(
                [pa.array(keys, pa.int64()), pa.array(parts, pa.int32()), pa.array(home, pa.bool_()), pa.array(blobs, pa.binary())],
                ["leaf", "tile", "home", "fps"],
            )

    def compare(pdf: pd.DataFrame) -> pd.DataFrame:
        def joined(mask: pd.Series) -> np.ndarray:
            return np.frombuffer(b"".join(pdf.fps[mask]), np.uint64)

        a, b = spanning_links(joined(pdf.home), joined(~pdf.home), radius)
        return pd.DataFrame({"a": a.view(np.int64), "b": b.view(np.int64)})

    return (
        fps.mapInArrow(deal, "leaf long, tile int, home boolean, fps binary")
        .groupBy("leaf", "tile")
        .applyInPandas(compare, "a long, b long")
    )


def near_duplicates(
    docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = SHINGLE, radius: int = RADIUS,
) -> DataFrame:
    """(doc_id, fingerprint, component_id) for every row of `docs`."""
    own = cut(fingerprints(docs, id_col, text_col, width))
    distinct = cut(own.groupBy("fp").agg(F.min("doc_id").alias("least_id")))
    links = hamming_links(distinct.select("fp"), distinct.count(), radius)
    found = component_least(connected_components(links), distinct.select(F.col("fp").alias("node"), F.col("least_id").alias("least")))
    named = distinct.join(found, distinct.fp == found.node, "left").select("fp", F.when(F.col("node").isNull(), F.col("least_id")).otherwise(F.col("least")).alias("component_id"))
    return own.join(named, "fp").select(
        "doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id"
    )
