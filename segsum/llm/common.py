"""Shared plumbing of the training-data operators.

Everything here is DataFrame code: cutting lineage into the shared checkpoint
folder, connected components by star contraction, and dense positions inside
large groups without gathering a group in one task.
"""

from __future__ import annotations

import sys
import tempfile

from pyspark import Broadcast, cloudpickle
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

#: Code points 0x20 and 0x09-0x0D separate words; everything else belongs to a word.
WORD_PATTERN = r"[^\x20\x09-\x0D]+"
TRIMMED = " \t\r\x0b\x0c"

# Workers get the code with the task, so the package need not be installed on them.
cloudpickle.register_pickle_by_value(sys.modules[__name__.rpartition(".")[0]])


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def ensure_checkpoint_dir(spark: SparkSession) -> None:
    """Use the session's shared checkpoint folder; a local one only where none is named and the master is local."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is not None:
        return
    named = spark.conf.get("spark.checkpoint.dir", "")
    if not named:
        if not sc.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        named = tempfile.mkdtemp(prefix="segsum-checkpoint-")
    sc.setCheckpointDir(named)


def cut(df: DataFrame) -> DataFrame:
    """Materialise into the shared checkpoint folder, so that a lost executor costs no recomputation of what led here."""
    ensure_checkpoint_dir(df.sparkSession)
    return df.checkpoint()


def key_of(column: str | Column) -> Column:
    """A non-null string key: nulls form one group of their own, apart from every real value."""
    c = F.col(column) if isinstance(column, str) else column
    return F.coalesce(F.concat(F.lit("="), c.cast("string")), F.lit(""))


def word_count(text: str | Column) -> Column:
    c = F.col(text) if isinstance(text, str) else text
    return F.coalesce(F.regexp_count(c, F.lit(WORD_PATTERN)), F.lit(0)).cast("long")


def held_out(doc_id: str = "doc_id") -> Column:
    """Rows whose labels are never learned from. A null id counts as held out."""
    return F.coalesce(F.crc32(F.col(doc_id).cast("string")) % 5 == 0, F.lit(True))


def shards_for(rows: int, per_shard: int = 500_000, least: int = 16) -> int:
    return max(least, -(-rows // per_shard))


def dense_positions(df: DataFrame, keys: list[str], order: list[Column], shards: int, name: str, attach: DataFrame | None = None) -> DataFrame:
    """Add `name`: 0, 1, 2, ... inside each group of `keys` (non-null columns); `attach` adds columns that depend on `keys`.

    A group is dealt to `shards` parts by hash, numbered inside each part, and
    shifted by the rows of the parts before. The rows are read twice, so give a
    materialised table. Only the counts of parts meet by group.
    """
    shard = f"{name}__shard"
    dealt = df.withColumn(shard, F.pmod(F.xxhash64(*order, F.lit(name)), F.lit(shards)))
    parts = dealt.groupBy(*keys, shard).agg(F.count(F.lit(1)).alias(f"{name}__n"))
    before = Window.partitionBy(*keys).orderBy(shard).rowsBetween(Window.unboundedPreceding, -1)
    offsets = parts.select(*keys, shard, F.coalesce(F.sum(f"{name}__n").over(before), F.lit(0)).alias(f"{name}__from"))
    if attach is not None:  # joined to the parts, so that a hot group's rows never meet by its key
        offsets = offsets.join(attach, keys)
    inside = Window.partitionBy(*keys, shard).orderBy(*order)
    return (
        dealt.withColumn(name, F.row_number().over(inside) - 1)
        .join(offsets, [*keys, shard])
        .withColumn(name, F.col(name).cast("long") + F.col(f"{name}__from"))
        .drop(shard, f"{name}__from")
    )


def connected_components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """(node, root) for each node of `edges` (two long columns); root is the smallest node of its component.

    Alternating star contraction: links are rewired to the smallest neighbour
    until only stars are left, in a number of rounds that grows with the
    logarithm of the longest path. Hubs are met by partial aggregation and by
    joins that adaptive execution can split; nothing is collected but a
    fingerprint of each round.
    """

    def sealed(df: DataFrame) -> tuple[DataFrame, tuple]:
        df = cut(df)
        row = df.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        return df, (row[0], row[1])

    u, v, m = F.col("u"), F.col("v"), F.col("m")
    stars, mark = sealed(
        edges.select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).where(u != v).distinct()
    )
    while mark[0]:
        both = stars.union(stars.select(v, u).toDF("u", "v"))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least(u, m).alias("m"))
        wide = both.where(v > u).join(least, "u").select(v.alias("u"), m.alias("v")).union(
            least.where(m < u).select("u", m.alias("v"))
        ).where(u != v).distinct()
        floor = wide.groupBy("u").agg(F.min("v").alias("m"))
        narrow = wide.join(floor, "u").select(
            F.when(v == m, u).otherwise(v).alias("u"), m.alias("v")
        ).where(u != v).distinct()
        before = mark
        stars, mark = sealed(narrow)
        if mark == before:
            break
    return stars.select(u.alias("node"), v.alias("root")).union(stars.select(v, v)).distinct()


def component_least(parts: DataFrame, least: DataFrame, salts: int = 16) -> DataFrame:
    """(node, least): the smallest `least` (node, least) of each linked node's component.

    A component may hold a third of all nodes, so the answer goes back to its
    members by parts of the component, not by its root alone.
    """
    linked = parts.join(least, "node")
    best = linked.groupBy("root").agg(F.min("least").alias("least"))
    spread = best.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return linked.select("node", "root", F.pmod(F.xxhash64("node"), F.lit(salts)).cast("int").alias("salt")).join(spread, ["root", "salt"]).select("node", "least")


def ship(spark: SparkSession, model: object) -> Broadcast:
    """Broadcast a fitted model of bounded size, with its code, as bytes for pickle.loads."""
    return spark.sparkContext.broadcast(cloudpickle.dumps(model))
