"""Boilerplate lines: drop lines that stand on more than a given share of a site's pages.

Plan, all in DataFrame functions: each page gives its distinct trimmed lines,
counted by (site, 64-bit hash) with partial aggregation, so only hashes and
counts are shuffled. Lines whose hash count passes the ratio are counted again
by their text, which makes the result exact. What is left per site holds at
most (mean lines per page / ratio) lines; pages meet it by a join on the site,
broadcast only when its counted size is small, else a join that adaptive
execution splits at hot sites. No page text is shuffled in the broadcast case.

Defined cases: a null or empty text stays as it is; blank lines are never
counted or dropped; null sites form one site; a line counts once per page
however often it repeats there; repeated rows are pages of their own; an empty
table gives an empty result; every other column is kept.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import TRIMMED, cut, key_of

RATIO = 0.1
MIN_PAGES = 3
#: Bytes of lines and sites up to which they are broadcast; beyond, they are joined.
SMALL = 32 << 20


def _small(df: DataFrame, *texts: str) -> bool:
    size = sum((F.octet_length(t) for t in texts), F.lit(48))
    return (df.agg(F.sum(size)).first()[0] or 0) <= SMALL


def _trimmed(line: Column) -> Column:
    return F.btrim(line, F.lit(TRIMMED))


def _page_lines(docs: DataFrame, site: str, text: str) -> DataFrame:
    lines = F.array_distinct(F.transform(F.split(F.col(text), "\n"), _trimmed))
    return docs.select(key_of(site).alias("site"), F.explode(lines).alias("line")).where(F.col("line") != "")


def boilerplate_lines(
    docs: DataFrame, site: str = "source", text: str = "text", ratio: float = RATIO, min_pages: int = MIN_PAGES,
) -> DataFrame:
    """(site key, line, pages, site_pages) of every line on more than `ratio` of its site's pages, and on `min_pages` at least."""
    totals = docs.groupBy(key_of(site).alias("site")).agg(F.count(F.lit(1)).alias("site_pages"))
    lines = _page_lines(docs, site, text)
    passes = (F.col("pages") >= min_pages) & (F.col("pages") > F.col("site_pages") * F.lit(ratio))
    suspects = cut(
        lines.groupBy("site", F.xxhash64("line").alias("h"))
        .agg(F.count(F.lit(1)).alias("pages"))
        .where(F.col("pages") >= min_pages)
        .join(totals, "site")
        .where(passes)
        .select("site", "h", "site_pages")
    )
    small = _small(suspects, "site")
    again = lines.withColumn("h", F.xxhash64("line")).join(F.broadcast(suspects) if small else suspects, ["site", "h"])
    return again.groupBy("site", "line", "site_pages").agg(F.count(F.lit(1)).alias("pages")).where(passes)


def drop_boilerplate(
    docs: DataFrame, site: str = "source", text: str = "text", ratio: float = RATIO, min_pages: int = MIN_PAGES, counts: bool = False,
) -> DataFrame:
    """`docs` with those lines taken out of `text`; with `counts`, also __n_lines and __n_removed."""
    found = cut(boilerplate_lines(docs, site, text, ratio, min_pages))
    small = _small(found, "site", "line")
    by_site = found.groupBy(F.col("site").alias("__site")).agg(F.collect_set("line").alias("__drop"))
    own = docs.join(F.broadcast(by_site) if small else by_site, key_of(docs[site]) == F.col("__site"), "left")
    lines = F.split(F.col(text), "\n")
    hits = F.array_intersect(F.transform(lines, _trimmed), F.col("__drop"))
    own = own.withColumn("__hits", F.coalesce(hits, F.array().cast("array<string>")))
    kept = F.filter(lines, lambda x: ~F.array_contains(F.col("__hits"), _trimmed(x)))
    untouched = F.size("__hits") == 0
    if counts:
        own = own.withColumn("__n_lines", F.coalesce(F.size(F.nullif(lines, F.array().cast("array<string>"))), F.lit(0)).cast("long")).withColumn(
            "__n_removed", F.when(untouched, F.lit(0)).otherwise(F.size(lines) - F.size(kept)).cast("long")
        )
    out = own.withColumn(text, F.when(untouched, F.col(text)).otherwise(F.array_join(kept, "\n")))
    return out.select(*docs.columns, *(["__n_lines", "__n_removed"] if counts else []))
