"""Near-duplicate embeddings: exact cosine links inside a label by PCA-ordered tiles.

Vectors are scaled to length one and rotated to principal axes (largest first),
which keeps every dot product. Two vectors whose cosine reaches the threshold
lie within sqrt(2 - 2 t) of each other, so along any axis only equal or
neighbouring bands of that width can link. The bands of the leading axes make
cells: as many axes as it takes until a point's cell holds a tile of points on
average, up to `AXES`, as long as each at least halves that number. Inside a tile the leading axes are
multiplied first; what the rest can add is at most the product of the suffix
norms, and pairs that can't reach the threshold stop there. Pairs that remain
are decided by the cosine of the original vectors in double precision.

Equal vectors of a label are one point with a count; tiles report counts and
spanning links per point, never pairs. Cells are cut into tiles of bounded size,
each of which meets all points of its own and of half of the neighbouring cells,
so that any two cells meet once. How many axes are taken changes no result.

Defined cases: rows with a null label or id, and vectors that are null, zero,
of another length or hold null or non-finite components, link with nothing and
are their own component; repeated rows link with each other; an empty table
gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import itertools
import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import connected_components, cut
from .simhash import _roots
from .vectors import common_size, matrix, stacked, usable

THRESHOLD = 0.98
TILE = 4096
LEAD = 16
#: Most axes that make cells.
AXES = 4


def principal_axes(points: DataFrame, dim: int) -> np.ndarray:
    """Columns: eigenvectors of the second moments of the unit vectors, largest first. Only dim * dim sums reach the driver."""

    def moments(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((dim, dim))
        for batch in batches:
            x = matrix(batch.column(0), dim)
            x /= np.linalg.norm(x, axis=1, keepdims=True)
            total += x.T @ x
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(dim * dim)), pa.array(total.ravel())], ["i", "v"])

    sums = points.select("embedding").mapInArrow(moments, "i long, v double").groupBy("i").agg(F.sum("v").alias("v")).collect()
    m = np.zeros(dim * dim)
    for r in sums:
        m[r["i"]] = r["v"]
    _, axes = np.linalg.eigh(m.reshape(dim, dim))
    return np.ascontiguousarray(axes[:, ::-1])


def close_pairs(x: np.ndarray, px: np.ndarray, y: np.ndarray, py: np.ndarray, threshold: float, lead: int) -> tuple[np.ndarray, np.ndarray]:
    """Rows of x and of y whose cosine reaches the threshold; px and py are the same points, scaled and rotated."""
    head = px[:, :lead] @ py[:, :lead].T
    rest = np.linalg.norm(px[:, lead:], axis=1)[:, None] * np.linalg.norm(py[:, lead:], axis=1)[None, :]
    i, j = np.nonzero(head + rest >= threshold - 1e-9)
    part, at = head[i, j], lead
    while at < px.shape[1] and len(i):
        upto = min(at * 2, px.shape[1])
        sx, sy = np.linalg.norm(px[:, upto:], axis=1), np.linalg.norm(py[:, upto:], axis=1)
        ok = np.empty(len(i), bool)
        for s in range(0, len(i), 1 << 17):
            e = s + (1 << 17)
            part[s:e] += np.einsum("ij,ij->i", px[i[s:e], at:upto], py[j[s:e], at:upto])
            ok[s:e] = part[s:e] + sx[i[s:e]] * sy[j[s:e]] >= threshold - 1e-9
        i, j, part, at = i[ok], j[ok], part[ok], upto
    nx, ny = np.linalg.norm(x, axis=1), np.linalg.norm(y, axis=1)
    keep = np.empty(len(i), bool)
    for s in range(0, len(i), 1 << 17):
        e = s + (1 << 17)
        keep[s:e] = np.einsum("ij,ij->i", x[i[s:e]], y[j[s:e]]) / (nx[i[s:e]] * ny[j[s:e]]) >= threshold
    return i[keep], j[keep]


def _cell_axes(banded: DataFrame, most: int, tile: int) -> int:
    """How many leading axes make cells, from the sums of squared cell sizes (one row each)."""
    met = None
    for axes in range(1, most + 1):
        cells = banded.groupBy("label", F.slice("bands", 1, axes)).agg(F.count(F.lit(1)).cast("double").alias("n"))
        got = cells.agg(F.sum(F.col("n") ** 2) / F.sum("n")).first()[0] or 0.0
        if met is not None and got > met / 2:
            return axes - 1
        met = got
        if got <= tile:
            return axes
    return most


def near_duplicates(
    vectors: DataFrame, id_col: str = "vec_id", vector: str = "embedding", label: str = "label", threshold: float = THRESHOLD, tile: int = TILE, axes_taken: int | None = None,
) -> DataFrame:
    """(vec_id, n_links, component_id, kept) for every row. `axes_taken` fixes the number of axes that make cells."""
    own = vectors.select(F.col(id_col).cast("long").alias("vec_id"), F.col(vector).alias("embedding"), F.col(label).alias("label"))
    dim = common_size(own.where(F.col("label").isNotNull() & F.col("vec_id").isNotNull()), "embedding")
    fit = usable("embedding", dim) & F.col("label").isNotNull() & F.col("vec_id").isNotNull() if dim > 0 else F.lit(False)
    key = [F.xxhash64("label", "embedding").alias("k1"), F.xxhash64(F.lit(7), "embedding", "label").alias("k2")]
    points = cut(
        own.where(fit).select("*", *key).groupBy("k1", "k2")
        .agg(F.min("vec_id").alias("node"), F.count(F.lit(1)).alias("n"), F.first("embedding").alias("embedding"), F.first("label").alias("label"))
    )
    axes = principal_axes(points, dim) if dim > 0 else np.eye(1)
    width = math.sqrt(2 - 2 * threshold) + 1e-9

    most = max(1, min(AXES, dim))

    def bands_of(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = matrix(batch.column(2), dim)
            lead = x @ axes[:, :most] / np.linalg.norm(x, axis=1, keepdims=True)
            bands = pa.FixedSizeListArray.from_arrays(pa.array(np.floor(lead / width).astype(np.int32).ravel()), most).cast(pa.list_(pa.int32()))
            yield pa.RecordBatch.from_arrays([*batch.columns, bands], ["node", "n", "embedding", "label", "bands"])

    kind = points.schema["label"].dataType.simpleString()
    item = points.schema["embedding"].dataType.simpleString()
    banded = cut(points.select("node", "n", "embedding", "label").mapInArrow(bands_of, f"node long, n long, embedding {item}, label {kind}, bands array<int>"))
    k = axes_taken or _cell_axes(banded, most, tile)
    banded = banded.withColumn("cell", F.slice("bands", 1, k)).drop("bands")
    tiles = banded.groupBy("label", "cell").agg(F.ceil(F.count(F.lit(1)) / tile).cast("int").alias("tiles"))
    steps = [d for d in itertools.product((-1, 0, 1), repeat=k) if d >= (0,) * k]  # a cell's own place, and of two neighbours the upper one
    beside = F.explode(F.array(*[F.array(*[F.col("cell")[i] + F.lit(x) for i, x in enumerate(d)]) for d in steps]))
    meets = tiles.select("label", "cell", beside.alias("at")).join(tiles.withColumnRenamed("cell", "at"), ["label", "at"])
    visits = banded.join(meets, ["label", "cell"]).withColumn("tile", F.explode(F.sequence(F.lit(0), F.col("tiles") - 1)))
    own_cell = F.col("cell") == F.col("at")
    home = own_cell & (F.pmod(F.xxhash64("node"), F.col("tiles")) == F.col("tile"))
    visits = visits.select("label", "at", "tile", "node", "n", "embedding", (~own_cell).alias("lower"), home.alias("home"))

    def compare(pdf: pd.DataFrame) -> pd.DataFrame:
        x = stacked(pdf.embedding.tolist(), dim)
        p = x / np.linalg.norm(x, axis=1, keepdims=True) @ axes
        node, n = pdf.node.to_numpy(), pdf.n.to_numpy()
        home, lower = np.flatnonzero(pdf.home.to_numpy()), pdf.lower.to_numpy()
        links, parent = np.zeros(len(pdf), np.int64), np.arange(len(pdf))
        for s in range(0, len(pdf) if len(home) else 0, 1024):
            i, j = close_pairs(x[s:s + 1024], p[s:s + 1024], x[home], p[home], threshold, LEAD)
            i, j = i + s, home[j]
            keep = i != j
            i, j = i[keep], j[keep]
            np.add.at(links, j, n[i])
            below = lower[i]
            np.add.at(links, i[below], n[j[below]])
            while len(i):
                a, b = _roots(parent, i), _roots(parent, j)
                keep = a != b
                i, j, a, b = i[keep], j[keep], a[keep], b[keep]
                np.minimum.at(parent, np.maximum(a, b), np.minimum(a, b))
        root = _roots(parent, np.arange(len(pdf)))
        some = (links > 0) | (root != np.arange(len(pdf)))
        return pd.DataFrame({"node": node[some], "links": links[some], "root": node[root[some]]})

    found = cut(visits.groupBy("label", "at", "tile").applyInPandas(compare, "node long, links long, root long"))
    counts = found.groupBy("node").agg(F.sum("links").alias("links"))
    parts = connected_components(found.select(F.col("node").alias("a"), F.col("root").alias("b")))
    known = points.select("k1", "k2", "node", "n").join(counts, "node", "left").join(parts, "node", "left").select(
        "k1", "k2", (F.col("n") - 1 + F.coalesce("links", F.lit(0))).alias("n_links"), F.coalesce("root", "node").alias("component_id")
    )
    rows = own.select("vec_id", F.when(fit, key[0]).alias("k1"), F.when(fit, key[1]).alias("k2"))
    return rows.join(known, ["k1", "k2"], "left").select(
        "vec_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"),
        F.coalesce("component_id", "vec_id").alias("component_id"),
        F.coalesce(F.col("vec_id") == F.coalesce("component_id", "vec_id"), F.lit(True)).alias("kept"),
    )
