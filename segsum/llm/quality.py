"""Quality classifier: a generalised additive model with pairwise interactions.

Shallow trees, boosted in turn over the features with a small rate, add up to
one lookup table per feature; the pairs whose tables would lower the loss most
get two-way tables in the same way. A document's score is the logistic curve of
the sum of its table entries. Features are counted over the whole text with a
fixed number of numpy passes per Arrow batch.

The tables are fitted on a bounded sample of labelled rows (`per_class`).

Defined cases: without labelled rows every text gets one and the same score; null and empty texts have all features zero; a sample with one
class only scores every row with that class's smoothed share; repeated rows
score alike; a null id is passed through and is held out; an empty table gives
an empty result; other columns are ignored.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .bytehash import owners, text_buffer, text_slices, word_hashes, word_spans
from .common import held_out, ship
from .labelled import training_rows

PER_CLASS = 8_000
THRESHOLD = 0.3
BINS = 32
PAIR_BINS = 8
PAIRS = 6
ROUNDS = 150
RATE = 0.15

FEATURES = (
    "log_bytes", "log_words", "word_bytes", "upper", "digit", "mark", "beyond_ascii", "log_lines", "line_words", "distinct",
    "top_word", "same_as_before", "short_words", "long_words", "upper_words", "marked_ends", "distinct_lines", "repeated_pairs", "word_spread", "sentence_ends",
)


def _class(*spans: tuple[int, int]) -> np.ndarray:
    out = np.zeros(256, bool)
    for a, b in spans:
        out[a:b + 1] = True
    return out


_UPPER, _DIGIT, _BEYOND = _class((65, 90)), _class((48, 57)), _class((128, 255))
_MARK = _class((33, 38), (40, 43), (47, 47), (60, 64), (91, 96), (123, 126))
_STOP = _class((33, 33), (46, 46), (63, 63))
_NEWLINE = _class((10, 10))


def _runs(owner: np.ndarray, key: np.ndarray, texts: int) -> tuple[np.ndarray, np.ndarray]:
    """Per text: number of distinct keys, and the largest count of one."""
    if not len(key):
        return np.zeros(texts), np.zeros(texts)
    order = np.lexsort((key, owner))
    o, k = owner[order], key[order]
    new = np.ones(len(o), bool)
    new[1:] = (o[1:] != o[:-1]) | (k[1:] != k[:-1])
    first = np.flatnonzero(new)
    count = np.diff(np.append(first, len(o)))
    most = np.zeros(texts)
    np.maximum.at(most, o[first], count)
    return np.bincount(o[first], minlength=texts).astype(float), most


def features(column: pa.Array) -> np.ndarray:
    """(texts, len(FEATURES)); every rate is a share, every size a logarithm."""
    parts = [_features(column.slice(i, n)) for i, n in text_slices(column)]
    return np.concatenate(parts) if parts else np.empty((0, len(FEATURES)))


def _features(column: pa.Array) -> np.ndarray:
    raw, at = text_buffer(column)
    n = len(at) - 1
    size = np.diff(at).astype(float)

    def share(kind: np.ndarray) -> np.ndarray:
        total = np.zeros(len(raw) + 1, np.int64)
        np.cumsum(kind[raw], out=total[1:])
        return np.diff(total[at])

    starts, ends = word_spans(raw, at)
    owner = owners(at, starts)
    hashes = word_hashes(raw, starts, ends)
    length = (ends - starts).astype(float)
    per = lambda w: np.bincount(owner, weights=w, minlength=n)
    words = np.bincount(owner, minlength=n).astype(float)
    w1, b1 = np.maximum(words, 1), np.maximum(size, 1)
    distinct, most = _runs(owner, hashes, n)
    same = np.zeros(len(starts))
    pair = np.zeros(max(len(starts) - 1, 0), np.uint64)
    if len(starts) > 1:
        same[1:] = (hashes[1:] == hashes[:-1]) & (owner[1:] == owner[:-1])
        pair = hashes[1:] * np.uint64(3) + hashes[:-1]
        inside = owner[1:] == owner[:-1]
        pairs, _ = _runs(owner[1:][inside], pair[inside], n)
    else:
        pairs = np.zeros(n)
    lines_at, lines_end = word_spans(raw, at, _NEWLINE)
    line_owner = owners(at, lines_at)
    lines = np.bincount(line_owner, minlength=n).astype(float)
    kinds, _ = _runs(line_owner, word_hashes(raw, lines_at, lines_end), n)
    ups = np.zeros(len(raw) + 1, np.int64)
    np.cumsum(_UPPER[raw], out=ups[1:])
    all_upper = (ups[ends] - ups[starts]) * 2 > length
    mean = per(length) / w1
    return np.column_stack([
        np.log1p(size), np.log1p(words), mean, share(_UPPER) / b1, share(_DIGIT) / b1, share(_MARK) / b1, share(_BEYOND) / b1, np.log1p(lines),
        words / np.maximum(lines, 1), distinct / w1, most / w1, per(same) / w1, per(length <= 3) / w1, per(length > 12) / w1, per(all_upper & (length > 1)) / w1,
        per(_MARK[raw[ends - 1]] if len(ends) else length) / w1, kinds / np.maximum(lines, 1), 1 - pairs / np.maximum(words - 1, 1),
        np.sqrt(np.maximum(per(length**2) / w1 - mean**2, 0)), per(_STOP[raw[ends - 1]] if len(ends) else length) / w1,
    ])


def _step(g: np.ndarray, h: np.ndarray, leaves: int = 3, least: float = 2.0) -> tuple[np.ndarray, float]:
    """A tree of up to `leaves` leaves over ordered bins with gradient and curvature sums: its value per bin, and its gain."""
    cuts, gained = [0, len(g)], 0.0
    G, H = np.concatenate(([0], np.cumsum(g))), np.concatenate(([0], np.cumsum(h)))
    worth = lambda a, b: (G[b] - G[a]) ** 2 / (H[b] - H[a] + 1.0)
    for _ in range(leaves - 1):
        best = (1e-9, 0)
        for a, b in zip(cuts[:-1], cuts[1:], strict=True):
            k = np.arange(a + 1, b)
            if len(k):
                ok = (H[k] - H[a] >= least) & (H[b] - H[k] >= least)
                gain = np.where(ok, worth(a, k) + worth(k, b) - worth(a, b), -1.0)
                best = max(best, (float(gain.max()), int(k[gain.argmax()])))
        if not best[1]:
            break
        cuts, gained = sorted([*cuts, best[1]]), gained + best[0]
    out = np.zeros(len(g))
    for a, b in zip(cuts[:-1], cuts[1:], strict=True):
        out[a:b] = -(G[b] - G[a]) / (H[b] - H[a] + 1.0)
    return out, gained


def _cross(g: np.ndarray, h: np.ndarray) -> tuple[np.ndarray, float]:
    """One cut of the first axis and one of the second on either side, over a grid of sums."""
    best, out = 0.0, np.zeros_like(g)
    for flip in (False, True):
        a, b = (g.T, h.T) if flip else (g, h)
        for k in range(1, len(a)):
            value, gain = np.zeros_like(a), 0.0
            for rows in (slice(0, k), slice(k, None)):
                v, w = _step(a[rows].sum(0), b[rows].sum(0), 2)
                value[rows], gain = v, gain + w
            if gain > best:
                best, out = gain, value.T if flip else value
    return out, best


@dataclass
class AdditiveModel:
    edges: list[np.ndarray]
    pair_edges: list[np.ndarray]
    tables: list[np.ndarray]
    pairs: list[tuple[int, int]]
    pair_tables: list[np.ndarray]
    base: float

    def score(self, x: np.ndarray) -> np.ndarray:
        z = np.full(len(x), self.base)
        for f, (edges, table) in enumerate(zip(self.edges, self.tables, strict=True)):
            z += table[np.searchsorted(edges, x[:, f], side="right")]
        coarse = {f: np.searchsorted(self.pair_edges[f], x[:, f], side="right") for p in self.pairs for f in p}
        for (a, b), table in zip(self.pairs, self.pair_tables, strict=True):
            z += table[coarse[a], coarse[b]]
        return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def fit_tables(x: np.ndarray, y: np.ndarray, rounds: int = ROUNDS, rate: float = RATE, pairs: int = PAIRS) -> AdditiveModel:
    edges = [np.unique(np.quantile(c, np.linspace(0, 1, BINS + 1)[1:-1])) for c in x.T]
    pair_edges = [np.unique(np.quantile(c, np.linspace(0, 1, PAIR_BINS + 1)[1:-1])) for c in x.T]
    base = float(np.log((y.sum() + 0.5) / ((1 - y).sum() + 0.5)))
    model = AdditiveModel(edges, pair_edges, [np.zeros(len(e) + 1) for e in edges], [], [], base)
    if len(np.unique(y)) < 2:
        return model
    bins = [np.searchsorted(e, c, side="right") for e, c in zip(edges, x.T, strict=True)]
    z = np.full(len(y), base)

    def pull() -> tuple[np.ndarray, np.ndarray]:
        p = 1 / (1 + np.exp(-z))
        return p - y, p * (1 - p)

    for _ in range(rounds):
        for f, table in enumerate(model.tables):
            g, h = pull()
            n = len(table)
            value, _ = _step(np.bincount(bins[f], weights=g, minlength=n), np.bincount(bins[f], weights=h, minlength=n))
            table += rate * value
            z += rate * value[bins[f]]
    coarse = [np.searchsorted(e, c, side="right") for e, c in zip(pair_edges, x.T, strict=True)]
    side = [len(e) + 1 for e in pair_edges]

    def grids(a: int, b: int, g: np.ndarray, h: np.ndarray) -> list[np.ndarray]:
        cell = coarse[a] * side[b] + coarse[b]
        return [np.bincount(cell, weights=w, minlength=side[a] * side[b]).reshape(side[a], side[b]) for w in (g, h)]

    g, h = pull()
    ranked = sorted(((_cross(*grids(a, b, g, h))[1], (a, b)) for a in range(x.shape[1]) for b in range(a)), reverse=True)
    model.pairs = [p for gain, p in ranked[:pairs] if gain > 0]
    model.pair_tables = [np.zeros((side[a], side[b])) for a, b in model.pairs]
    for _ in range(rounds // 5):
        for (a, b), table in zip(model.pairs, model.pair_tables, strict=True):
            g, h = pull()
            value, _ = _cross(*grids(a, b, g, h))
            table += rate * value
            z += rate * value[coarse[a], coarse[b]]
    return model


def fit(docs: DataFrame, labels: DataFrame, target: str = "quality", per_class: int = PER_CLASS, id_col: str = "doc_id", text_col: str = "text") -> AdditiveModel:
    def counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = np.ascontiguousarray(features(batch.column(1)))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), pa.array([r.tobytes() for r in x], pa.binary())], ["doc_id", "y", "x"])

    rows = training_rows(docs, labels, target, per_class, id_col, text_col).mapInArrow(counted, "doc_id long, y int, x binary").toPandas().sort_values(["doc_id", "x"], kind="stable")
    x = np.frombuffer(b"".join(rows.x), np.float64).reshape(-1, len(FEATURES))
    if not len(x):
        x, y = np.zeros((1, len(FEATURES))), np.array([1.0])
    else:
        y = rows.y.to_numpy().astype(float)
    return fit_tables(x, y)


def classify(
    docs: DataFrame, labels: DataFrame, target: str = "quality", threshold: float = THRESHOLD, per_class: int = PER_CLASS, id_col: str = "doc_id", text_col: str = "text",
) -> DataFrame:
    """(doc_id, held_out, score, predicted) for every row of `docs`."""
    shared = ship(docs.sparkSession, fit(docs, labels, target, per_class, id_col, text_col))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = pickle.loads(shared.value)
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(model.score(features(batch.column(1))))], ["doc_id", "score"])

    scored = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(run, "doc_id long, score double")
    return scored.select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))
