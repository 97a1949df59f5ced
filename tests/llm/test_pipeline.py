from collections import Counter

from pyspark.sql import functions as F

import corpus_pipeline as cp
from test_near_copies import plain_components, plain_fingerprints

from segsum.llm import line_dedup, mixing, simhash_wide, toxicity


def test_stages_take_effect(spark, medium, tmp_path):
    docs = spark.read.parquet(f"{medium}/documents.parquet")
    names, at = docs.columns, docs
    kept = {}
    for name, stage in cp.STAGES:
        out = stage(spark, at, medium)
        out.write.parquet(str(tmp_path / name))
        before, at = at, spark.read.parquet(str(tmp_path / name))
        kept[name] = (before, at)
        if name != cp.STAGES[-1][0]:
            assert at.columns == names
    labels = spark.read.parquet(f"{medium}/labels.parquet")

    before, after = kept["toxicity"]
    scores = toxicity.classify(before, labels).where("predicted = 0").select("doc_id")
    assert Counter(r[0] for r in after.select("doc_id").collect()) == Counter(r[0] for r in scores.collect())

    before, after = kept["line_dedup"]
    assert after.count() == before.count()
    gone = line_dedup.boilerplate_lines(before).collect()
    assert gone
    text = {r["doc_id"]: (r["source"], r["text"]) for r in after.collect()}
    for r in before.collect():
        drop = {g["line"] for g in gone if g["site"] == f"={r['source']}"}
        assert text[r["doc_id"]][1] == "\n".join(x for x in r["text"].split("\n") if x.strip(" \t\r\x0b\x0c") not in drop)

    before, after = kept["simhash_dedup"]
    text = {r["doc_id"]: r["text"] for r in before.collect()}
    parts = plain_components(sorted(text), plain_fingerprints([text[i] for i in sorted(text)]), simhash_wide.reach_of(0.8))
    assert sorted(r["doc_id"] for r in after.collect()) == sorted(set(parts.values()))

    before, after = kept["mixing"]
    copies = {r["doc_id"]: r["copies"] for r in mixing.mix(before).where("copies > 0").collect()}
    assert Counter(r["doc_id"] for r in after.collect()) == Counter(copies)

    before, after = kept["packing"]
    assert Counter(r["doc_id"] for r in before.collect()) == Counter(r["doc_id"] for r in after.collect())


def test_run_is_the_stages_in_order(spark, small):
    out = cp.run(spark, small)
    assert out.count() > 0 and out.columns == ["doc_id", "n_tokens", "bucket", "bucket_len", "batch", "n_pad"]
    assert [n for n, _ in cp.STAGES] == ["toxicity", "line_dedup", "simhash_dedup", "mixing", "packing"]


def test_stages_take_empty_tables(spark, small, tmp_path):
    at = spark.read.parquet(f"{small}/documents.parquet").where(F.col("doc_id") < -1)
    for name, stage in cp.STAGES:
        stage(spark, at, small).write.parquet(str(tmp_path / name))
        at = spark.read.parquet(str(tmp_path / name))
    assert at.count() == 0


def test_stages_take_odd_input(spark, small, tmp_path):
    """Nulls in every column, empty and repeated rows, repeated ids with other texts, and columns with clashing names."""
    good = "plain words of an ordinary text that nobody minds at all and that goes on for a while"
    rows = [(1, good, "en", "s", 10), (1, good, "en", "s", 10), (1, "other text under the same id " * 3, "en", "s", 10), (2, None, None, None, None), (3, "", "en", None, 0), (None, good + " again", "en", "t", 9)]
    at = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    for extra in ("site", "h", "key", "node", "t", "size", "copies", "score", "leaf"):
        at = at.withColumn(extra, F.lit("x"))
    names = at.columns
    for name, stage in cp.STAGES:
        stage(spark, at, small).write.parquet(str(tmp_path / name))
        at = spark.read.parquet(str(tmp_path / name))
        assert name == "packing" or at.columns == names
        if name == "simhash_dedup":
            assert sorted((r["doc_id"] or 0, len(r["text"] or "")) for r in at.collect()) == sorted([(0, len(good) + 6), (1, 87), (1, len(good)), (2, 0)])
