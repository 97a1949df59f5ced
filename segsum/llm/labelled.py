"""A bounded, deterministic sample of labelled rows to fit on."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import held_out


def training_labels(labels: DataFrame, target: str, per_class: int | tuple[int, int], id_col: str = "doc_id") -> DataFrame:
    """(doc_id, y): at most `per_class` rows of each class (or of class 0 and of class 1) outside the held-out fold, those with the smallest hash of the id.

    Labels other than 0 and 1 and null ids are left out; of repeated ids one row counts.
    """
    known = labels.where(F.col(id_col).isNotNull() & F.col(target).isin(0, 1) & ~held_out(id_col)).groupBy(
        F.col(id_col).cast("long").alias("doc_id")
    ).agg(F.max(target).cast("int").alias("y"))
    most = per_class if isinstance(per_class, tuple) else (per_class, per_class)
    part = lambda y: known.where(F.col("y") == y).orderBy(F.xxhash64("doc_id"), "doc_id").limit(most[y])
    return part(0).union(part(1))


def training_rows(docs: DataFrame, labels: DataFrame, target: str, per_class: int | tuple[int, int], id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, text, y) of the sample, which is bounded and so may be broadcast."""
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    return rows.join(F.broadcast(training_labels(labels, target, per_class, id_col)), "doc_id")
