"""Repeated passages: remove every word inside a window of words that starts more than once.

Documents travel in packs (a few MB of text each, compressed), written once as a
table bucketed by the task that packed them: every pass sees the same packs where
they lie, and only sketches, hashes and answers of one bit are shuffled.

1. Each pack hashes its windows into the cells of a count-min sketch (one row,
   counters that stop at two, CELLS cells for each word of the corpus), kept
   sparse: sorted cells, as deltas, cut into stripes. A stripe merges the
   sketches of all packs and answers each with one bit per cell sent: estimated
   repeated or not. The estimate never falls short, so no repeated window is lost.
   A dense sketch of every partition would be larger: its width has to follow the
   windows of all partitions, its load only those of one.
2. Only windows estimated repeated are sent on, as 96-bit hashes of their word
   sequence, grouped exactly, and answered with one bit each.
3. Each pack marks the words that repeated windows cover and writes its rows.

A window goes out once per pack however often it stands there, so a passage
that a third of all documents share costs one entry per pack and no group grows
with its copies. Stripes grow in number with the text, not in size.

Defined cases: null and empty texts have no words (kept text empty); texts
shorter than a window keep all words; repeated rows are repeats; a null id is
passed through; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import uuid
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .bytehash import _BLANK, owners, text_buffer, window_hashes, word_hashes, word_spans
from .common import cut, ensure_checkpoint_dir

WIDTH = 35
PACK_BYTES = 4 << 20
#: Cells of the sketch for each word: one window in so many meets another one's cell by chance.
CELLS = 32
STRIPE_BYTES = 16 << 20
PACKS = "task long, pack long, n long, words long, data binary"
ENTRIES = "task long, pack long, part int, kind string, n long, data binary"
RESULT_SCHEMA = "doc_id long, n_words long, n_removed long, kept_sha256 string, kept string"


def _squeeze(columns: list[np.ndarray]) -> bytes:
    """Byte planes of unsigned columns, compressed."""
    planes = [np.ascontiguousarray(c.view(np.uint8).reshape(len(c), -1).T).tobytes() for c in columns]
    return zstandard.ZstdCompressor(level=1).compress(b"".join(planes))


def _stretch(data: bytes, n: int, kinds: list[str]) -> list[np.ndarray]:
    raw, out, at = np.frombuffer(zstandard.ZstdDecompressor().decompress(data), np.uint8), [], 0
    for kind in kinds:
        size = np.dtype(kind).itemsize
        out.append(np.ascontiguousarray(raw[at:at + n * size].reshape(size, n).T).reshape(-1).view(kind))
        at += n * size
    return out


def pack_documents(docs: DataFrame, id_col: str, text_col: str, pack_bytes: int) -> DataFrame:
    """One row per pack: an Arrow stream of (doc_id, text), compressed, its bytes and words, and the task that packed it."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        task, made, held, size = TaskContext.get().partitionId(), 0, [], 0

        def seal() -> pa.RecordBatch:
            table = pa.Table.from_batches(held)
            sink = pa.BufferOutputStream()
            with pa.ipc.new_stream(sink, table.schema) as out:
                out.write_table(table)
            data = zstandard.ZstdCompressor(level=3).compress(sink.getvalue().to_pybytes())
            words = sum(_words(c) for c in table.column(1).chunks)
            return pa.RecordBatch.from_arrays([pa.array([task]), pa.array([made]), pa.array([table.nbytes]), pa.array([words], pa.int64()), pa.array([data])], ["task", "pack", "n", "words", "data"])

        for batch in batches:
            batch = pa.RecordBatch.from_arrays([batch.column(0), batch.column(1).cast(pa.large_string())], ["doc_id", "text"])
            ends = np.cumsum(_lengths(batch.column(1)))
            at = 0
            while at < batch.num_rows:
                base = ends[at - 1] if at else 0
                upto = max(at + 1, int(np.searchsorted(ends, base + pack_bytes - size, side="right")))
                held.append(batch.slice(at, upto - at))
                size += int(ends[upto - 1] - base)
                at = upto
                if size >= pack_bytes or at < batch.num_rows:
                    yield seal()
                    made, held, size = made + 1, [], 0
        if held:
            yield seal()

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(run, PACKS)


def _lengths(column: pa.Array) -> np.ndarray:
    return np.diff(text_buffer(column)[1])


def _words(column: pa.Array) -> int:
    """Words of all texts, or a few less where one text ends and the next begins without a blank."""
    solid = ~_BLANK[text_buffer(column)[0]]
    return int((solid[1:] & ~solid[:-1]).sum()) + 1


def _stored(packs: DataFrame) -> DataFrame:
    """`packs` as a table bucketed by task in the shared checkpoint folder: read again without a shuffle."""
    spark = packs.sparkSession
    ensure_checkpoint_dir(spark)
    name = f"segsum_packs_{uuid.uuid4().hex}"
    buckets = min(100_000, int(spark.conf.get("spark.sql.shuffle.partitions")))
    packs.write.format("parquet").option("compression", "none").option("path", f"{spark.sparkContext.getCheckpointDir()}/{name}").bucketBy(buckets, "task").saveAsTable(name)
    return spark.table(name)


def _open(data: bytes) -> pa.Table:
    return pa.ipc.open_stream(zstandard.ZstdDecompressor().decompress(data)).read_all().combine_chunks()


class _Windows:
    """Words and windows of one pack."""

    def __init__(self, table: pa.Table, width: int, bits: int):
        self.bits = np.uint64(64 - bits)
        self.ids = table.column(0).combine_chunks()
        self.raw, self.at = text_buffer(table.column(1))
        self.starts, self.ends = word_spans(self.raw, self.at)
        self.owner = owners(self.at, self.starts)
        self.words = word_hashes(self.raw, self.starts, self.ends)
        self.width = width
        first = window_hashes(self.words, width)
        whole = self.owner[:len(first)] == self.owner[width - 1:] if len(first) else np.empty(0, bool)
        self.where = np.flatnonzero(whole)
        self.first = first[self.where]

    def cells(self) -> tuple[np.ndarray, np.ndarray]:
        """Sorted distinct cells, and whether each holds more than one window of this pack."""
        return np.unique(self.first >> self.bits, return_counts=True)

    def candidates(self, repeated: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Windows whose cell is among the sorted `repeated`: both hashes and counts of the distinct ones in order, and for each window its place among them (-1 if none)."""
        cell = self.first >> self.bits
        hit = np.flatnonzero(_among(cell, repeated))
        place = np.full(len(cell), -1, np.int64)
        h1 = self.first[hit]
        h2 = (window_hashes(self.words, self.width, 0xA0761D6478BD642F)[self.where[hit]] >> np.uint64(32)).astype(np.uint32)
        order = np.lexsort((h2, h1))
        h1, h2 = h1[order], h2[order]
        new = np.ones(len(hit), bool)
        new[1:] = (h1[1:] != h1[:-1]) | (h2[1:] != h2[:-1])
        group = np.cumsum(new) - 1
        place[hit[order]] = group
        return h1[new], h2[new], np.bincount(group, minlength=int(new.sum())), place


def _among(x: np.ndarray, ordered: np.ndarray) -> np.ndarray:
    if not len(ordered):
        return np.zeros(len(x), bool)
    at = np.minimum(np.searchsorted(ordered, x), len(ordered) - 1)
    return ordered[at] == x


def _stripes(values: np.ndarray, bits: int, stripes: int) -> np.ndarray:
    """Where each of the equal ranges of sorted `bits`-bit values begins (one more at the end)."""
    edges = np.array([(i << bits) // stripes for i in range(1, stripes)], dtype=np.uint64)
    return np.concatenate(([0], np.searchsorted(values, edges), [len(values)]))


NAMES = ["task", "pack", "part", "kind", "n", "data"]


def _batch(rows: list[tuple[int, int, int, str, int, bytes]]) -> pa.RecordBatch:
    cols = list(zip(*rows, strict=True)) if rows else [[]] * 6
    kinds = [pa.int64(), pa.int64(), pa.int32(), pa.string(), pa.int64(), pa.binary()]
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], NAMES)


def _bits(flags: np.ndarray) -> bytes:
    return np.packbits(flags).tobytes()


def _flags(pdf: pd.DataFrame, kind: str) -> np.ndarray:
    """One pack's answers of a kind, in order of stripe."""
    rows = pdf[pdf.kind == kind].sort_values("part")
    parts = [np.unpackbits(np.frombuffer(d, np.uint8), count=n).astype(bool) for n, d in zip(rows.n, rows.data, strict=True)]
    return np.concatenate(parts) if parts else np.empty(0, bool)


def remove_repeats(
    docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = WIDTH, pack_bytes: int = PACK_BYTES, stripe_bytes: int = STRIPE_BYTES, with_text: bool = True,
) -> DataFrame:
    """(doc_id, n_words, n_removed, kept_sha256, kept) per row; `kept` is null unless `with_text`."""
    packs = _stored(pack_documents(docs, id_col, text_col, pack_bytes))
    size = packs.agg(F.sum("n"), F.sum("words")).first()
    stripes = max(24, -(-(size[0] or 0) // stripe_bytes))
    bits = max(16, min(63, int(CELLS * (size[1] or 0)).bit_length()))

    def sketch(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for task, pack, data in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2), strict=True):
                cells, counts = _Windows(_open(data.as_py()), width, bits).cells()
                rows, at = [], _stripes(cells, bits, stripes)
                for i in range(stripes):
                    c, n = cells[at[i]:at[i + 1]], counts[at[i]:at[i + 1]]
                    if len(c):
                        gaps = np.diff(c, prepend=np.uint64(0))
                        rows.append((task, pack, i, "cells", len(c), _squeeze([gaps, (n > 1).astype(np.uint8)])))
                if rows:
                    yield _batch(rows)

    def merge(pdf: pd.DataFrame) -> pd.DataFrame:
        sent = []
        for n, data in zip(pdf.n, pdf.data, strict=True):
            gaps, more = _stretch(data, n, ["<u8", "u1"])
            sent.append((np.cumsum(gaps, dtype=np.uint64), more.astype(bool)))
        cells = np.sort(np.concatenate([c for c, _ in sent] + [c[m] for c, m in sent]))
        repeated = np.unique(cells[1:][cells[1:] == cells[:-1]])
        out = pdf[["task", "pack", "part", "n"]].copy()
        out["kind"] = "cell answers"
        out["data"] = [_bits(_among(c, repeated)) for c, _ in sent]
        return out[NAMES]

    def narrowed(data: bytes, answers: pd.DataFrame) -> tuple[_Windows, tuple]:
        own = _Windows(_open(data), width, bits)
        cells, _ = own.cells()
        flags = _flags(answers, "cell answers")
        return own, own.candidates(cells[flags] if len(flags) else cells[:0])

    def propose(packs: pd.DataFrame, answers: pd.DataFrame) -> pd.DataFrame:
        rows = []
        for task, pack, data in zip(packs.task, packs.pack, packs.data, strict=True):
            _, (h1, h2, counts, _) = narrowed(data, answers[answers.pack == pack])
            at = _stripes(h1, 64, stripes)
            for i in range(stripes):
                a, b = at[i], at[i + 1]
                if b > a:
                    gaps = np.diff(h1[a:b], prepend=np.uint64(0))
                    rows.append((task, pack, i, "windows", b - a, _squeeze([gaps, h2[a:b], (counts[a:b] > 1).astype(np.uint8)])))
        return pd.DataFrame(rows, columns=NAMES)

    def settle(pdf: pd.DataFrame) -> pd.DataFrame:
        firsts, seconds, mores = [], [], []
        for n, data in zip(pdf.n, pdf.data, strict=True):
            gaps, h2, more = _stretch(data, n, ["<u8", "<u4", "u1"])
            firsts.append(np.cumsum(gaps, dtype=np.uint64)), seconds.append(h2), mores.append(more > 0)
        h1, h2, more = np.concatenate(firsts), np.concatenate(seconds), np.concatenate(mores)
        order = np.lexsort((h2, h1))
        new = np.ones(len(order), bool)
        new[1:] = (h1[order][1:] != h1[order][:-1]) | (h2[order][1:] != h2[order][:-1])
        group = np.cumsum(new) - 1
        many = (np.bincount(group) > 1) | (np.bincount(group, weights=more[order]) > 0)
        flags = np.empty(len(order), bool)
        flags[order] = many[group]
        ends = np.cumsum(pdf.n.to_numpy())
        out = pdf[["task", "pack", "part", "n"]].copy()
        out["kind"] = "window answers"
        out["data"] = [_bits(flags[e - n:e]) for e, n in zip(ends, pdf.n, strict=True)]
        return out[NAMES]

    def finish(packs: pd.DataFrame, answers: pd.DataFrame) -> pd.DataFrame:
        rows = []
        for pack, data in zip(packs.pack, packs.data, strict=True):
            known = answers[answers.pack == pack]
            own, (_, _, _, place) = narrowed(data, known)
            flags = _flags(known, "window answers")
            hit = own.where[(place >= 0) & np.append(flags, False)[place]] if len(flags) else own.where[:0]
            edge = np.zeros(len(own.starts) + 1, np.int32)
            np.add.at(edge, hit, 1)
            np.add.at(edge, hit + width, -1)
            covered = np.cumsum(edge[:-1]) > 0
            raw, starts, ends = own.raw.tobytes(), own.starts, own.ends
            first = np.searchsorted(own.owner, np.arange(len(own.ids) + 1))
            for i, doc in enumerate(own.ids.to_pylist()):
                a, b = int(first[i]), int(first[i + 1])
                gone = int(covered[a:b].sum())
                if gone:
                    left = np.flatnonzero(~covered[a:b]) + a
                    kept = b" ".join([raw[s:e] for s, e in zip(starts[left].tolist(), ends[left].tolist(), strict=True)])
                else:
                    kept = b" ".join(raw[own.at[i]:own.at[i + 1]].split())
                rows.append((doc, b - a, gone, hashlib.sha256(kept).hexdigest(), kept.decode("utf-8", "replace") if with_text else None))
        out = pd.DataFrame(rows, columns=["doc_id", "n_words", "n_removed", "kept_sha256", "kept"])
        out["doc_id"] = out["doc_id"].astype("Int64")
        return out

    cell_answers = cut(packs.select("task", "pack", "data").mapInArrow(sketch, ENTRIES).groupBy("part").applyInPandas(merge, ENTRIES))
    here = packs.select("task", "pack", "data").groupBy("task")
    window_answers = cut(here.cogroup(cell_answers.groupBy("task")).applyInPandas(propose, ENTRIES).groupBy("part").applyInPandas(settle, ENTRIES))
    return here.cogroup(cell_answers.unionByName(window_answers).groupBy("task")).applyInPandas(finish, RESULT_SCHEMA)
