"""The experiments' datasets on the given tables. Derived columns come from md5, so any engine can repeat them."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import uniform
from ..operators.segment import segment_interval, segment_sequence
from .tables import table, word_items

ZIPF_SHAPE = 1.1
ZIPF_ITEMS = 20_000


def lineitem_key() -> Column:
    """Order and line number alone are not unique."""
    price = F.col("l_extendedprice") * 100
    whole = F.rint(F.abs(price))  # halves away from zero as round() does, which goes through decimal text
    cents = (F.signum(price) * F.when(F.abs(price) - whole == 0.5, whole + 1).otherwise(whole)).cast("long")
    return F.concat_ws("|", *[F.col(c).cast("string") for c in ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")], cents.cast("string"))


def zipf_item(u: Column, shape: float = ZIPF_SHAPE, items: int = ZIPF_ITEMS) -> Column:
    """Whole part of a power law cut at `items`; chance of i about i ** -shape."""
    top = 1.0 - float(items) ** (1 - shape)
    return F.least(F.lit(items), F.floor(F.pow(F.lit(1.0) - u * F.lit(top), F.lit(1 / (1 - shape)))).cast("long")).cast("long")


@dataclass(frozen=True)
class IntervalData:
    """What an interval dataset is made of."""

    name: str
    goal: str
    s: int
    k_t: int


INTERVALS = {
    d.name: d
    for d in (
        IntervalData("ship_week_supp", "freq", 16, 512), IntervalData("ship_week_part", "freq", 16, 512), IntervalData("ship_day_price", "rank", 8, 1024),
        IntervalData("ship_week_price", "rank", 16, 512), IntervalData("ship_week_zipf", "freq", 16, 512), IntervalData("ship_week_unif", "rank", 16, 512),
        IntervalData("order_week_total", "rank", 8, 512), IntervalData("event_hour_user", "freq", 4, 1024), IntervalData("event_hour_k", "freq", 4, 1024),
        IntervalData("event_hour_build", "freq", 4, 1024), IntervalData("event_hour_value", "rank", 4, 1024), IntervalData("event_seq_user", "freq", 8, 256),
        IntervalData("doc_words", "freq", 64, 128),
    )
}


def word_blocks(spark: SparkSession, sf_dir: str, together: int) -> DataFrame:
    """(block, seg, item) of the words of documents, where so many segments lie together."""
    docs = segment_sequence(table(spark, sf_dir, "documents").select("doc_id", "text"), "doc_id", 8, together).repartition("block")
    return word_items(docs, "block", "seg").select("block", "seg", "item")


def interval_rows(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """(seg, item, key) of a named interval dataset; key is unique per record up to repeated records."""
    if name.startswith("ship_"):
        _, span, kind = name.split("_")
        li = table(spark, sf_dir, "lineitem")
        seconds = 86_400 * (7 if span == "week" else 1)
        u = uniform("item", lineitem_key())
        item = {"supp": F.col("l_suppkey"), "part": F.col("l_partkey"), "price": F.col("l_extendedprice"), "zipf": zipf_item(u), "unif": u}[kind]
        return segment_interval(li, "l_shipdate", seconds, "1995-01-01").select("seg", item.alias("item"), lineitem_key().alias("key"))
    if name == "order_week_total":
        o = table(spark, sf_dir, "orders")
        return segment_interval(o, "o_orderdate", 7 * 86_400, "1995-01-01").select("seg", F.col("o_totalprice").alias("item"), F.col("o_orderkey").cast("string").alias("key"))
    if name.startswith("event_"):
        ev = table(spark, sf_dir, "events")
        _, span, kind = name.split("_")
        item = {
            "user": F.col("user_id"), "k": F.get_json_object("props", "$.k").cast("long"), "value": F.col("value"),
            "build": F.concat("event_type", F.col("user_id").cast("string")),
        }[kind]
        cut = segment_sequence(ev, "event_id", 50) if span == "seq" else segment_interval(ev, "ts", 3600, "2024-01-01")
        return cut.select("seg", item.alias("item"), F.col("event_id").cast("string").alias("key"))
    if name == "doc_words":
        docs = segment_sequence(table(spark, sf_dir, "documents"), "doc_id", 8).repartition("seg")  # texts move once, words and their counts stay
        words = word_items(docs, "seg")
        return words.select("seg", "item", F.concat_ws("|", F.col("doc_id").cast("string"), F.col("pos").cast("string"), "item").alias("key"))
    raise KeyError(name)


def _log2(c: Column) -> Column:
    """Whole binary logarithm by the length of the binary form, alike in every engine."""
    return (F.length(F.bin(c.cast("long"))) - 1).cast("int")


CUBES = {
    "cube_smoke": (["l_returnflag", "l_linestatus", "o_orderstatus", "o_orderpriority"], 11),
    "cube_retail": (["c_mktsegment", "o_orderpriority", "r_name", "p_brand"], 30),
    "cube_skew": (["d_quantity", "d_size", "p_type", "o_orderpriority"], 5),
    "cube_text": (["lang", "source", "d_chars", "d_quality"], 22),
    "cube_event": (["event_type", "d_hour", "d_weekday", "d_k"], 11),
}


def cube_rows(spark: SparkSession, sf_dir: str, name: str, item: str | None = None) -> DataFrame:
    """Rows of a named cube with its dims, an item and a key. Dimension tables are small next to the facts; adaptive execution broadcasts them."""
    dims = CUBES[name][0]
    if name == "cube_text":
        docs = table(spark, sf_dir, "documents").join(table(spark, sf_dir, "labels").select("doc_id", "quality"), "doc_id", "left")
        own = docs.select("doc_id", "lang", "source", _log2(F.col("n_chars")).alias("d_chars"), F.coalesce("quality", F.lit(-1)).alias("d_quality"), F.posexplode(F.split("text", " ")).alias("pos", "item"))
        return own.where(F.col("item") != "").select(*dims, "item", F.concat_ws("|", F.col("doc_id").cast("string"), F.col("pos").cast("string"), "item").alias("key"))
    if name == "cube_event":
        ev = table(spark, sf_dir, "events")
        k = F.get_json_object("props", "$.k").cast("long")
        own = ev.select("event_type", F.hour("ts").alias("d_hour"), F.dayofweek("ts").alias("d_weekday"), _log2(k + 1).alias("d_k"), "user_id", "value", F.col("event_id").cast("string").alias("key"))
        return own.select(*dims, F.col(item or "user_id").alias("item"), "key")
    li, orders = table(spark, sf_dir, "lineitem"), table(spark, sf_dir, "orders")
    li = li.withColumn("key", lineitem_key())
    u = uniform("item", F.col("key"))
    li = li.withColumn("zipf", zipf_item(u)).withColumn("unif", u)
    rows = li.join(orders.select("o_orderkey", "o_custkey", "o_orderstatus", "o_orderpriority"), li.l_orderkey == orders.o_orderkey)
    if name == "cube_retail":
        cust = table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey", "c_mktsegment")
        nation, region = table(spark, sf_dir, "nation"), table(spark, sf_dir, "region")
        where = nation.join(region, F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "r_name")
        rows = rows.join(cust, F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(where), F.col("c_nationkey") == F.col("n_nationkey"))  # 25 rows
    if name in ("cube_retail", "cube_skew"):
        part = table(spark, sf_dir, "part").select("p_partkey", "p_brand", "p_type", _log2(F.col("p_size")).alias("d_size"))
        rows = rows.join(part, F.col("l_partkey") == F.col("p_partkey")).withColumn("d_quantity", _log2(F.col("l_quantity")))
    default = {"cube_smoke": "l_suppkey", "cube_retail": "l_partkey", "cube_skew": "zipf"}[name]
    return rows.select(*dims, F.col(item or default).alias("item"), "key")
