"""The relational surface that users of the summaries need around them, each entry with the SQL that says the same."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.hashing import md5_int
from ..operators.segment import segment_interval
from ..sources.tables import TABLES, table

Query = Callable[[SparkSession, str], DataFrame]


def _scan(name: str) -> Query:
    return lambda s, d: table(s, d, name).agg(F.count(F.lit(1)).alias("n_rows"))


def star(s: SparkSession, d: str) -> DataFrame:
    li = table(s, d, "lineitem").select("l_orderkey", "l_partkey", "l_quantity")
    o = table(s, d, "orders").select("o_orderkey", "o_orderpriority")
    p = table(s, d, "part").select("p_partkey", "p_brand")
    rows = li.join(o, F.col("l_orderkey") == F.col("o_orderkey")).join(p, F.col("l_partkey") == F.col("p_partkey"))
    return rows.groupBy("o_orderpriority", "p_brand").agg(F.count(F.lit(1)).alias("n"), F.sum("l_quantity").cast("long").alias("qty"))


def sort_merge(s: SparkSession, d: str) -> DataFrame:
    li = table(s, d, "lineitem").select("l_orderkey", "l_linenumber")
    o = table(s, d, "orders").select("o_orderkey", "o_orderstatus").hint("merge")
    return li.join(o, F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderstatus").agg(F.count(F.lit(1)).alias("n"))


def semi(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "supplier").join(table(s, d, "lineitem").where(F.col("l_quantity") > 49), F.col("s_suppkey") == F.col("l_suppkey"), "left_semi").select("s_suppkey")


def anti(s: SparkSession, d: str) -> DataFrame:
    late = table(s, d, "orders").where(F.col("o_orderdate") >= F.lit("1999-01-01").cast("timestamp_ntz"))
    return table(s, d, "customer").join(late, F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey")


def left_missing(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "documents").join(table(s, d, "labels"), "doc_id", "left").groupBy("lang").agg(F.count(F.lit(1)).alias("n"), F.count("quality").alias("n_labelled"), F.count_if(F.col("quality").isNull()).alias("n_missing"))


def full_outer(s: SparkSession, d: str) -> DataFrame:
    """Every event counts as early or late, by the middle of the table's own ids."""
    ev = table(s, d, "events")
    middle = ev.agg(F.floor((F.min("event_id") + F.max("event_id")) / 2).alias("middle"))
    cut = ev.select("user_id", "event_id").crossJoin(F.broadcast(middle))
    early = cut.where(F.col("event_id") <= F.col("middle")).groupBy("user_id").agg(F.count(F.lit(1)).alias("n_early"))
    late = cut.where(F.col("event_id") > F.col("middle")).groupBy("user_id").agg(F.count(F.lit(1)).alias("n_late"))
    return early.join(late, "user_id", "full").select("user_id", F.coalesce("n_early", F.lit(0)).alias("n_early"), F.coalesce("n_late", F.lit(0)).alias("n_late"))


def range_join(s: SparkSession, d: str) -> DataFrame:
    spans = s.createDataFrame([(0, 0, 24), (1, 12, 300), (2, 100, 101)], "qid long, lo long, hi long")
    ev = segment_interval(table(s, d, "events"), "ts", 3600, "2024-01-01").groupBy("seg").agg(F.count(F.lit(1)).alias("n"))
    return ev.join(F.broadcast(spans), (F.col("seg") >= F.col("lo")) & (F.col("seg") < F.col("hi"))).groupBy("qid").agg(F.sum("n").cast("long").alias("n"))


def as_of(s: SparkSession, d: str) -> DataFrame:
    """Latest sealed segment at or before each time: union and a running last value, no inequality join."""
    ev = segment_interval(table(s, d, "events"), "ts", 3600, "2024-01-01")
    sealed = ev.groupBy("event_type", "seg").agg(F.count(F.lit(1)).alias("n")).select("event_type", F.col("seg").alias("t"), F.lit(0).alias("ask"), "n")
    asks = sealed.select("event_type").distinct().withColumn("t", F.explode(F.sequence(F.lit(0), F.lit(700), F.lit(100)))).select("event_type", F.col("t").cast("long").alias("t"), F.lit(1).alias("ask"), F.lit(None).cast("long").alias("n"))
    run = Window.partitionBy("event_type").orderBy("t", "ask").rowsBetween(Window.unboundedPreceding, 0)
    return sealed.unionByName(asks).withColumn("last_n", F.last("n", True).over(run)).where(F.col("ask") == 1).select("event_type", "t", F.coalesce("last_n", F.lit(0)).alias("last_n"))


def grouping(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.grouping_id().cast("long").alias("gid"), F.count(F.lit(1)).alias("n"))


def rolled(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "lineitem").rollup("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"), F.sum("l_quantity").cast("long").alias("qty"))


def sets(s: SparkSession, d: str) -> DataFrame:
    table(s, d, "lineitem").createOrReplaceTempView("segsum_lineitem")
    return s.sql("SELECT l_returnflag, l_linestatus, count(*) AS n FROM segsum_lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())")


def filtered(s: SparkSession, d: str) -> DataFrame:
    v = F.col("value")
    return table(s, d, "events").groupBy("event_type").agg(
        F.count_if(v > 100).alias("n_large"), F.count_distinct("user_id").alias("users"), F.max_by("event_id", F.struct("value", "event_id")).alias("top_event"), F.round(F.percentile("value", F.lit(0.5)), 6).alias("median"),
    )


def pivoted(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).count().na.fill(0)


def ranks(s: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("c_mktsegment").orderBy(F.desc("c_acctbal"), "c_custkey")
    by_nation = Window.partitionBy("c_mktsegment").orderBy("c_nationkey")
    return table(s, d, "customer").select(
        "c_custkey", F.row_number().over(w).cast("long").alias("rn"), F.rank().over(by_nation).cast("long").alias("rk"), F.dense_rank().over(by_nation).cast("long").alias("dr"),
        F.ntile(4).over(w).cast("long").alias("nt"), F.round(F.percent_rank().over(by_nation), 6).alias("pr"), F.round(F.cume_dist().over(by_nation), 6).alias("cd"),
        F.lag("c_custkey").over(w).alias("prev"), F.lead("c_custkey").over(w).alias("next"), F.first("c_custkey").over(w).alias("best"),
    )


def sums(s: SparkSession, d: str) -> DataFrame:
    """Running, suffix and sliding sums over segments; the sliding one is the exact moving frequency."""
    per = segment_interval(table(s, d, "events"), "ts", 3600, "2024-01-01").groupBy("event_type", "seg").agg(F.count(F.lit(1)).alias("n"))
    w = Window.partitionBy("event_type").orderBy("seg")
    return per.select(
        "event_type", "seg", F.sum("n").over(w.rowsBetween(Window.unboundedPreceding, 0)).cast("long").alias("running"),
        F.sum("n").over(w.rowsBetween(0, Window.unboundedFollowing)).cast("long").alias("suffix"), F.sum("n").over(w.rangeBetween(-11, 0)).cast("long").alias("sliding"),
    )


def top_per_group(s: SparkSession, d: str) -> DataFrame:
    rank = F.row_number().over(Window.partitionBy("event_type").orderBy(F.desc("value"), "event_id"))
    return table(s, d, "events").withColumn("rank", rank.cast("long")).where(F.col("rank") <= 3).select("event_type", "event_id", "rank")


def ordered(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(25).select("o_orderkey", "o_totalprice")


def _items(s: SparkSession, d: str, lo: int, hi: int) -> DataFrame:
    seg = segment_interval(table(s, d, "lineitem"), "l_shipdate", 7 * 86_400, "1995-01-01")
    return seg.where((F.col("seg") >= lo) & (F.col("seg") < hi)).select(F.col("l_partkey").alias("item"))


def scalars(s: SparkSession, d: str) -> DataFrame:
    ev = table(s, d, "events")
    k = F.get_json_object("props", "$.k").cast("long")
    return ev.select(
        "event_id", F.upper(F.substring("event_type", 1, 3)).alias("tag"), md5_int("7", F.col("event_id")).alias("h"), F.date_trunc("hour", "ts").cast("timestamp_ntz").alias("hour_start"),
        F.hour("ts").cast("long").alias("hr"), (F.dayofweek("ts") - 1).cast("long").alias("dow"), k.alias("k"), F.pmod(k, F.lit(7)).alias("k7"),
        F.round(F.sqrt(F.greatest("value", F.lit(1.0))), 6).alias("root"), F.round(F.exp(-F.col("value") / 100), 6).alias("decay"), F.regexp_replace("event_type", "[aeiou]", "").alias("consonants"),
    )


def arrays(s: SparkSession, d: str) -> DataFrame:
    words = F.split("text", " ")
    sizes = F.transform(words, lambda w: F.length(w))
    return table(s, d, "documents").select(
        "doc_id", F.size(words).cast("long").alias("n"), F.aggregate(sizes, F.lit(0), lambda a, x: a + x).cast("long").alias("letters"),
        F.size(F.filter(sizes, lambda x: x > 8)).cast("long").alias("n_long"), F.element_at(F.sort_array(sizes, False), 1).cast("long").alias("longest"),
        F.size(F.array_distinct(words)).cast("long").alias("n_distinct"),
    )


def hosts(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "pages").groupBy(F.regexp_extract("url", "://([^/?#]*)", 1).alias("host")).agg(F.count(F.lit(1)).alias("n"))


def roles(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "conversations").groupBy("role").agg(F.count(F.lit(1)).alias("n"), F.max("turn").alias("last_turn"))


def predicates(s: SparkSession, d: str) -> DataFrame:
    li = table(s, d, "lineitem")
    t = lambda x: F.lit(x).cast("timestamp_ntz")
    kept = li.where((F.col("l_shipdate") >= t("1996-01-01")) & (F.col("l_shipdate") < t("1997-01-01")) & F.col("l_returnflag").isin("A", "R") & F.col("l_discount").between(0.02, 0.06))
    size = F.when(F.col("l_quantity") < 10, "small").when(F.col("l_quantity") < 40, "medium").otherwise("large")
    return kept.groupBy(size.alias("size")).agg(F.count(F.lit(1)).alias("n"))


def like(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "part").where(F.col("p_brand").like("%1%") & F.col("p_type").isNotNull()).groupBy("p_brand").agg(F.count(F.lit(1)).alias("n"))


def between_joins(s: SparkSession, d: str) -> DataFrame:
    """Theta join with a bounded side: parts by price band."""
    bands = s.createDataFrame([(0, 0.0, 1000.0), (1, 1000.0, 1500.0), (2, 1500.0, 1e9)], "band long, lo double, hi double")
    return table(s, d, "part").join(F.broadcast(bands), (F.col("p_retailprice") >= F.col("lo")) & (F.col("p_retailprice") < F.col("hi"))).groupBy("band").agg(F.count(F.lit(1)).alias("n"))


SEG_W = "floor(date_diff('day', DATE '1995-01-01', l_shipdate::DATE) / 7)::BIGINT"
SEG_H = "floor(date_diff('minute', TIMESTAMP '2024-01-01', date_trunc('hour', ts)) / 60)::BIGINT"
_JSON_K = "json_extract_string(props, '$.k')::BIGINT"

RELATIONAL: dict[str, tuple[Query, str | None]] = {f"scan_{t}": (_scan(t), f"SELECT count(*) AS n_rows FROM {t}") for t in TABLES}
RELATIONAL |= {
    "join_star": (star, "SELECT o_orderpriority, p_brand, count(*) AS n, sum(l_quantity)::BIGINT AS qty FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey GROUP BY 1, 2"),
    "join_sort_merge": (sort_merge, "SELECT o_orderstatus, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1"),
    "join_semi": (semi, "SELECT s_suppkey FROM supplier WHERE s_suppkey IN (SELECT l_suppkey FROM lineitem WHERE l_quantity > 49)"),
    "join_anti": (anti, "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders WHERE o_orderdate >= TIMESTAMP '1999-01-01')"),
    "join_left": (left_missing, "SELECT lang, count(*) AS n, count(quality) AS n_labelled, count(*) - count(quality) AS n_missing FROM documents LEFT JOIN labels USING (doc_id) GROUP BY 1"),
    "join_full": (full_outer, "WITH m AS (SELECT (min(event_id) + max(event_id)) // 2 AS middle FROM events) SELECT user_id, coalesce(n_early, 0)::BIGINT AS n_early, coalesce(n_late, 0)::BIGINT AS n_late FROM (SELECT user_id, count(*) AS n_early FROM events, m WHERE event_id <= middle GROUP BY 1) FULL JOIN (SELECT user_id, count(*) AS n_late FROM events, m WHERE event_id > middle GROUP BY 1) USING (user_id)"),
    "join_range": (range_join, f"SELECT qid::BIGINT AS qid, sum(n)::BIGINT AS n FROM (SELECT {SEG_H} AS seg, count(*) AS n FROM events GROUP BY 1) JOIN (VALUES (0, 0, 24), (1, 12, 300), (2, 100, 101)) q(qid, lo, hi) ON seg >= lo AND seg < hi GROUP BY 1"),
    "join_as_of": (as_of, f"WITH s AS (SELECT event_type, {SEG_H} AS seg, count(*) AS n FROM events GROUP BY 1, 2), a AS (SELECT * FROM (SELECT DISTINCT event_type FROM s), (SELECT unnest(generate_series(0, 700, 100))::BIGINT AS t)) SELECT a.event_type, a.t, coalesce(s.n, 0)::BIGINT AS last_n FROM a ASOF LEFT JOIN s ON a.event_type = s.event_type AND a.t >= s.seg"),
    "join_theta": (between_joins, "SELECT CASE WHEN p_retailprice < 1000 THEN 0 WHEN p_retailprice < 1500 THEN 1 ELSE 2 END::BIGINT AS band, count(*) AS n FROM part GROUP BY 1"),
    "agg_cube": (grouping, "SELECT l_returnflag, l_linestatus, grouping_id(l_returnflag, l_linestatus)::BIGINT AS gid, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)"),
    "agg_rollup": (rolled, "SELECT l_returnflag, l_linestatus, count(*) AS n, sum(l_quantity)::BIGINT AS qty FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)"),
    "agg_grouping_sets": (sets, "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())"),
    "agg_filtered": (filtered, "SELECT event_type, count(*) FILTER (value > 100) AS n_large, count(DISTINCT user_id) AS users, arg_max(event_id, (value, event_id)) AS top_event, round(quantile_cont(value, 0.5), 6) AS median FROM events GROUP BY 1"),
    "agg_pivot": (pivoted, "SELECT o_orderpriority, count(*) FILTER (o_orderstatus = 'F') AS \"F\", count(*) FILTER (o_orderstatus = 'O') AS \"O\", count(*) FILTER (o_orderstatus = 'P') AS \"P\" FROM orders GROUP BY 1"),
    "win_ranks": (ranks, "SELECT c_custkey, row_number() OVER w AS rn, rank() OVER n AS rk, dense_rank() OVER n AS dr, ntile(4) OVER w AS nt, round(percent_rank() OVER n, 6) AS pr, round(cume_dist() OVER n, 6) AS cd, lag(c_custkey) OVER w AS prev, lead(c_custkey) OVER w AS next, first_value(c_custkey) OVER w AS best FROM customer WINDOW w AS (PARTITION BY c_mktsegment ORDER BY c_acctbal DESC, c_custkey), n AS (PARTITION BY c_mktsegment ORDER BY c_nationkey)"),
    "win_sums": (sums, f"WITH p AS (SELECT event_type, {SEG_H} AS seg, count(*) AS n FROM events GROUP BY 1, 2) SELECT event_type, seg, (sum(n) OVER (PARTITION BY event_type ORDER BY seg))::BIGINT AS running, (sum(n) OVER (PARTITION BY event_type ORDER BY seg ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING))::BIGINT AS suffix, (sum(n) OVER (PARTITION BY event_type ORDER BY seg RANGE BETWEEN 11 PRECEDING AND CURRENT ROW))::BIGINT AS sliding FROM p"),
    "win_top_per_group": (top_per_group, "SELECT event_type, event_id, rank FROM (SELECT *, row_number() OVER (PARTITION BY event_type ORDER BY value DESC, event_id) AS rank FROM events) WHERE rank <= 3"),
    "sort_limit": (ordered, "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25"),
    "set_union": (lambda s, d: _items(s, d, 10, 20).unionByName(_items(s, d, 15, 25)).groupBy("item").agg(F.count(F.lit(1)).alias("n")), f"WITH l AS (SELECT l_partkey AS item, {SEG_W} AS seg FROM lineitem) SELECT item, count(*) AS n FROM (SELECT item FROM l WHERE seg >= 10 AND seg < 20 UNION ALL SELECT item FROM l WHERE seg >= 15 AND seg < 25) GROUP BY 1"),
    "set_intersect": (lambda s, d: _items(s, d, 10, 20).intersect(_items(s, d, 100, 110)), f"WITH l AS (SELECT l_partkey AS item, {SEG_W} AS seg FROM lineitem) SELECT item FROM l WHERE seg >= 10 AND seg < 20 INTERSECT SELECT item FROM l WHERE seg >= 100 AND seg < 110"),
    "set_except": (lambda s, d: _items(s, d, 10, 20).distinct().exceptAll(_items(s, d, 100, 110).distinct()), f"WITH l AS (SELECT l_partkey AS item, {SEG_W} AS seg FROM lineitem) SELECT item FROM l WHERE seg >= 10 AND seg < 20 EXCEPT SELECT item FROM l WHERE seg >= 100 AND seg < 110"),
    "fn_scalars": (scalars, f"SELECT event_id, upper(substr(event_type, 1, 3)) AS tag, ('0x' || substr(md5('7|' || event_id), 1, 8))::BIGINT AS h, date_trunc('hour', ts)::TIMESTAMP AS hour_start, hour(ts)::BIGINT AS hr, dayofweek(ts)::BIGINT AS dow, {_JSON_K} AS k, {_JSON_K} % 7 AS k7, round(sqrt(greatest(value, 1)), 6) AS root, round(exp(-value / 100), 6) AS decay, regexp_replace(event_type, '[aeiou]', '', 'g') AS consonants FROM events"),
    "fn_arrays": (arrays, "WITH w AS (SELECT doc_id, string_split(text, ' ') AS w FROM documents), s AS (SELECT doc_id, w, list_transform(w, lambda x: length(x)) AS z FROM w) SELECT doc_id, len(w)::BIGINT AS n, list_sum(z)::BIGINT AS letters, len(list_filter(z, lambda x: x > 8))::BIGINT AS n_long, list_max(z)::BIGINT AS longest, len(list_distinct(w))::BIGINT AS n_distinct FROM s"),
    "fn_hosts": (hosts, "SELECT regexp_extract(url, '://([^/?#]*)', 1) AS host, count(*) AS n FROM pages GROUP BY 1"),
    "fn_roles": (roles, "SELECT role, count(*) AS n, max(turn) AS last_turn FROM conversations GROUP BY 1"),
    "filter_predicates": (predicates, "SELECT CASE WHEN l_quantity < 10 THEN 'small' WHEN l_quantity < 40 THEN 'medium' ELSE 'large' END AS size, count(*) AS n FROM lineitem WHERE l_shipdate >= TIMESTAMP '1996-01-01' AND l_shipdate < TIMESTAMP '1997-01-01' AND l_returnflag IN ('A', 'R') AND l_discount BETWEEN 0.02::DOUBLE AND 0.06::DOUBLE GROUP BY 1"),
    "filter_like": (like, "SELECT p_brand, count(*) AS n FROM part WHERE p_brand LIKE '%1%' AND p_type IS NOT NULL GROUP BY 1"),
}
