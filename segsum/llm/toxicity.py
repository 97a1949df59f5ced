"""Toxicity by class-conditional Kneser-Ney language models.

An expression is a word, spelled out through its beginnings of one to eight
bytes: a model of one class gives a beginning's next step by absolute discounting
over the texts of the class that hold it, and hands what it discounts, and
`SHARED` texts more, to the share that the step has in both classes together. So
a rare expression speaks for neither class, and a word never seen is judged by
its longest known beginning.

A text's evidence is the difference of its two log-likelihoods per word, relative
to the text's own ordinary level (the mean of its words without the highest and
the lowest tenth): what a language or a topic adds to every word alike says
nothing. A logistic curve, fitted on labelled texts that the counts leave out,
turns it into a score.

Counts are gathered by distributed aggregation over the labelled rows (at most
`per_class` of each class, a parameter); no task holds the texts. The model keeps
the expressions in at least `MIN_TEXTS` texts of the sample, however many; others
are judged by their beginnings.

Defined cases: null and empty texts score the curve at zero evidence; if the
sample lacks a class, every row scores 0; repeated rows score alike; a null id is
passed through and is held out; an empty table gives an empty result; other
columns are ignored.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .bytehash import _LOWER, mix, owners, text_buffer, text_slices, word_hashes, word_spans
from .common import cut, held_out, ship
from .labelled import training_rows

#: Bound of the sample: ordinary and toxic texts.
PER_CLASS = (200_000, 200_000)
DISCOUNT = 0.75
#: Texts that the share in both classes counts for in each.
SHARED = 40.0
#: Longest beginning, in bytes, before the whole word.
BEGIN = 8
MIN_TEXTS = 3
#: Words of no evidence that stand in a text's ordinary level, so that a text of a few words has one.
PAD = 5
#: One in so many labelled texts is kept from the counts to fit the curve, at most CURVE_ROWS of each class.
CURVE = 6
CURVE_ROWS = 4_000
THRESHOLD = 0.5
#: Letters, digits and all bytes beyond ASCII make words here.
_BREAKS = np.array([not (48 <= b <= 57 or 65 <= b <= 90 or 97 <= b <= 122 or b >= 128) for b in range(256)])
_ROOT = 1


def tokens(column: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Steps of the distinct words (one row a word: keys of its beginnings and of itself, 0 where there is none), each token's word, and its text."""
    raw, at = text_buffer(column)
    starts, ends = word_spans(raw, at, _BREAKS)
    words, owner = word_hashes(raw, starts, ends, lower=True), owners(at, starts)
    vocabulary, first, word = np.unique(words, return_index=True, return_inverse=True)
    starts, size = starts[first], ends[first] - starts[first]
    steps = np.zeros((len(vocabulary), BEGIN + 1), np.uint64)
    run = np.zeros(len(vocabulary), np.uint64)
    for k in range(BEGIN):
        inner = k + 1 < size
        byte = _LOWER[raw[np.minimum(starts + k, len(raw) - 1)]] if len(raw) else np.zeros(0, np.uint8)
        run = (run + byte.astype(np.uint64) + np.uint64(1)) * np.uint64(0x100000001B3)
        steps[inner, k] = mix(run[inner] ^ np.uint64(k))
    steps[:, BEGIN] = vocabulary | np.uint64(2)
    return steps, word, owner


def parents(steps: np.ndarray) -> np.ndarray:
    """The key that each step extends."""
    out = np.full(steps.shape, _ROOT, np.uint64)
    for k in range(1, BEGIN + 1):
        out[:, k] = np.where(steps[:, k - 1] != 0, steps[:, k - 1], out[:, k - 1])
    return out


def text_counts(steps: np.ndarray, word: np.ndarray, owner: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct keys, their parents, and in how many texts of each class (columns) they stand; `y` has each text's class."""
    up = parents(steps)
    pairs = np.unique(owner.astype(np.int64) * len(steps) + word)
    text, word = pairs // max(1, len(steps)), pairs % max(1, len(steps))
    keys, above, counts = [], [], []
    for k in range(BEGIN + 1):
        own = steps[word, k] != 0
        known, at, place = np.unique(steps[word[own], k], return_index=True, return_inverse=True)
        held = np.unique(text[own] * len(known) + place)
        n = np.bincount(held % max(1, len(known)) * 2 + y[held // max(1, len(known))], minlength=2 * len(known)).reshape(-1, 2)
        keys.append(known), above.append(up[word[own][at], k]), counts.append(n)
    return np.concatenate(keys), np.concatenate(above), np.concatenate(counts)


def evidence_of(values: np.ndarray, owner: np.ndarray, texts: int) -> np.ndarray:
    """(texts, 2): mean of each text's word values above its ordinary level, and that times the root of its words."""
    n = np.bincount(owner, minlength=texts)
    order = np.lexsort((values, owner))
    rank = np.arange(len(order)) - np.repeat(np.cumsum(n) - n, n)
    tail = -(-n // 10)
    inner = (rank >= tail[owner[order]]) & (rank < (n - tail)[owner[order]])
    middle = np.bincount(owner[order][inner], weights=values[order][inner], minlength=texts)
    level = middle / (np.maximum(n - 2 * tail, 0) + PAD)
    mean = np.bincount(owner, weights=values, minlength=texts) / np.maximum(n, 1)
    z = np.where(n > 0, mean - level, 0.0)
    return np.column_stack([z, z * np.sqrt(n)])


@dataclass
class KneserNeyContrast:
    """What the models' steps add to the difference of the log-likelihoods, by key, and the curve."""

    keys: np.ndarray
    steps: np.ndarray
    weights: np.ndarray

    def words(self, steps: np.ndarray) -> np.ndarray:
        """Difference of the log-likelihoods of each word; an unknown step ends its sum."""
        total, open_ = np.zeros(len(steps)), np.ones(len(steps), bool)
        for k in range(BEGIN + 1):
            own = np.flatnonzero(open_ & (steps[:, k] != 0))
            at = np.minimum(np.searchsorted(self.keys, steps[own, k]), max(len(self.keys) - 1, 0))
            ok = self.keys[at] == steps[own, k] if len(self.keys) else np.zeros(len(own), bool)
            total[own[ok]] += self.steps[at[ok]]
            open_[own[~ok]] = False
        return total

    def evidence(self, column: pa.Array) -> np.ndarray:
        out = [np.empty((0, 2))]
        for i, n in text_slices(column):
            steps, word, owner = tokens(column.slice(i, n))
            out.append(evidence_of(self.words(steps)[word], owner, n))
        return np.concatenate(out)

    def score_texts(self, column: pa.Array) -> np.ndarray:
        z = self.evidence(column) @ self.weights[1:] + self.weights[0]
        return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1.0, steps: int = 50) -> np.ndarray:
    """Intercept and weights by Newton's method."""
    scale = np.maximum(x.std(axis=0), 1e-9)
    a = np.column_stack([np.ones(len(x)), x / scale])
    w, keep = np.zeros(a.shape[1]), np.diag([1e-6, *[ridge] * x.shape[1]])
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(a @ w, -30, 30)))
        g = a.T @ (p - y) + keep @ w
        step = np.linalg.solve((a * (p * (1 - p))[:, None]).T @ a + keep, g)
        w -= step
        if np.abs(step).max() < 1e-8:
            break
    return np.concatenate([w[:1], w[1:] / scale])


def _probability(c: int) -> Column:
    """A class's probability of a step: discounted count, and the rest by the share in both classes."""
    n, above, kinds = F.col(f"n{c}"), F.col(f"p{c}"), F.col(f"t{c}")
    share = (F.col("n0") + F.col("n1")) / (F.col("p0") + F.col("p1"))
    return (F.greatest(n - DISCOUNT, F.lit(0.0)) + (DISCOUNT * kinds + SHARED) * share) / (above + SHARED)


def learn_steps(rows: DataFrame) -> DataFrame:
    """(key, n, step): texts that hold the key and log-likelihood difference of its step, from (doc_id, text, y)."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            y = batch.column(2).to_numpy(zero_copy_only=False)
            for i, n in text_slices(batch.column(1)):
                keys, above, counts = text_counts(*tokens(batch.column(1).slice(i, n)), y[i:i + n])
                yield pa.RecordBatch.from_arrays(
                    [pa.array(keys.view(np.int64)), pa.array(above.view(np.int64)), pa.array(counts[:, 0]), pa.array(counts[:, 1])], ["key", "above", "n0", "n1"],
                )

    counted = cut(
        rows.select("doc_id", "text", "y").mapInArrow(count, "key long, above long, n0 long, n1 long")
        .groupBy("key", "above").agg(F.sum("n0").alias("n0"), F.sum("n1").alias("n1"))
    )
    above = counted.groupBy(F.col("above").alias("parent")).agg(
        F.sum("n0").alias("p0"), F.sum("n1").alias("p1"), F.sum((F.col("n0") > 0).cast("long")).alias("t0"), F.sum((F.col("n1") > 0).cast("long")).alias("t1")
    )
    often = counted.where(F.col("n0") + F.col("n1") >= MIN_TEXTS)
    return often.join(above, often.above == above.parent).select("key", (F.col("n0") + F.col("n1")).alias("n"), F.log(_probability(1) / _probability(0)).alias("step"))


def fit(docs: DataFrame, labels: DataFrame, target: str = "toxic", per_class: int | tuple[int, int] = PER_CLASS, id_col: str = "doc_id", text_col: str = "text") -> KneserNeyContrast | None:
    """Models and curve from the sample; None if it holds one class only."""
    rows = training_rows(docs, labels, target, per_class, id_col, text_col)
    apart = F.pmod(F.xxhash64("doc_id", F.lit("curve")), F.lit(CURVE)) == 0
    steps = learn_steps(rows.where(~apart))
    table = steps.select("key", F.col("step").cast("float").alias("step")).toArrow()  # bounded by the sample
    keys = table.column("key").to_numpy().view(np.uint64)
    order = np.argsort(keys)
    model = KneserNeyContrast(keys[order], table.column("step").to_numpy()[order], np.zeros(3))
    shared = ship(docs.sparkSession, model)

    def weigh(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = pickle.loads(shared.value)
        for batch in batches:
            z = m.evidence(batch.column(1))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), pa.array(z[:, 0]), pa.array(z[:, 1])], ["doc_id", "y", "z", "zn"])

    most = per_class if isinstance(per_class, int) else max(per_class)
    seen = training_rows(docs, labels, target, min(most, CURVE * CURVE_ROWS), id_col, text_col).where(apart)
    curve = seen.select("doc_id", "text", "y").mapInArrow(weigh, "doc_id long, y int, z double, zn double").toPandas().sort_values(["doc_id", "z"])
    if curve.y.nunique() < 2:
        return None
    model.weights = logistic(curve[["z", "zn"]].to_numpy(), curve.y.to_numpy())
    return model


def score(docs: DataFrame, model: KneserNeyContrast | None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, score) for every row."""
    shared = ship(docs.sparkSession, model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = pickle.loads(shared.value)
        for batch in batches:
            s = np.zeros(batch.num_rows) if m is None else m.score_texts(batch.column(1))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(s)], ["doc_id", "score"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(run, "doc_id long, score double")


def classify(docs: DataFrame, labels: DataFrame, target: str = "toxic", threshold: float = THRESHOLD, per_class: int | tuple[int, int] = PER_CLASS) -> DataFrame:
    """(doc_id, held_out, score, predicted) for every row of `docs`."""
    return score(docs, fit(docs, labels, target, per_class)).select(
        "doc_id", held_out().alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted")
    )


def drop_toxic(docs: DataFrame, labels: DataFrame, threshold: float = THRESHOLD, per_class: int | tuple[int, int] = PER_CLASS) -> DataFrame:
    """`docs` without the rows that score as toxic, in one scan: all columns pass by the scorer."""
    model = ship(docs.sparkSession, fit(docs, labels, "toxic", per_class))
    at = docs.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = pickle.loads(model.value)
        for batch in batches:
            if m is None:
                yield batch
                continue
            yield batch.filter(pa.array(m.score_texts(batch.column(at)) < threshold))

    return docs.mapInArrow(run, docs.schema)
