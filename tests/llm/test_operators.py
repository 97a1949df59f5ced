import hashlib
import re
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
import xxhash
from pyspark.sql import functions as F

from segsum.llm import ann, embed_dedup, html_extract, line_dedup, mixing, packing, quality, simhash, substring, toxicity
from segsum.llm.bytehash import text_buffer, word_hashes, word_spans
from segsum.llm.common import connected_components, dense_positions
from segsum.llm.queries import ORACLE_SQL, QUERIES

DOCS = "doc_id long, text string, lang string, source string, n_chars long"
WORD = re.compile(r"[^\x20\x09-\x0D]+")


def documents(spark, texts, sources=None):
    sources = sources or ["a"] * len(texts)
    return spark.createDataFrame([(i, t, "en", s, len(t or "")) for i, (t, s) in enumerate(zip(texts, sources, strict=True))], DOCS)


def odd_documents(spark):
    """Nulls in every column, empty, blank, very long and repeated rows, and columns with clashing names."""
    long = " ".join(f"w{i % 977}" for i in range(60_000))
    rows = [(1, "a b c d e f", "en", "s", 11), (1, "a b c d e f", "en", "s", 11), (2, None, None, None, None), (3, "", "en", "s", 0), (4, " \n\t ", "en", "s", 4), (5, long, "en", "t", len(long)), (None, "lost id here now", "en", "t", 16)]
    df = spark.createDataFrame(rows, DOCS)
    for extra in ("key", "site", "h", "size", "pos", "copies", "word", "node", "fp"):
        df = df.withColumn(extra, F.lit("x"))
    return df


def labels_for(spark, rows):
    return spark.createDataFrame(rows, "doc_id long, quality int, toxic int")


def test_word_spans_and_hashes():
    col = pa.array(["ab cd", None, "", "cd\x0bé ab", " x"])
    raw, at = text_buffer(col)
    s, e = word_spans(raw, at)
    words = [raw[a:b].tobytes().decode() for a, b in zip(s, e, strict=True)]
    assert words == ["ab", "cd", "cd", "é", "ab", "x"]
    h = word_hashes(raw, s, e)
    assert h[0] == h[4] and h[1] == h[2] and len(set(h.tolist())) == 4
    raw, at = text_buffer(pa.array(["xx", "yy"]))  # no blank between two texts
    assert len(word_spans(raw, at)[0]) == 2


def test_components_of_a_long_path_and_a_hub(spark):
    rows = [(i, i + 1) for i in range(300)] + [(1000, i) for i in range(1001, 1400)]
    got = {r["node"]: r["root"] for r in connected_components(spark.createDataFrame(rows, "a long, b long")).collect()}
    assert all(got[i] == 0 for i in range(301)) and all(got[i] == 1000 for i in range(1000, 1400))
    assert connected_components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_dense_positions(spark):
    df = spark.range(500).select((F.col("id") % 3).cast("string").alias("k"), "id")
    got = dense_positions(df, ["k"], [F.col("id")], 7, "p").groupBy("k").agg(F.sort_array(F.collect_list("p")).alias("p"), F.count("*").alias("n"))
    assert all(r["p"] == list(range(r["n"])) for r in got.collect())


@pytest.mark.parametrize("name", sorted(ORACLE_SQL))
def test_query_equals_sql(spark, medium, name):
    from oracle import connect, rows_of, sql_rows

    assert rows_of(QUERIES[name](spark, medium)) == sql_rows(connect(medium), ORACLE_SQL[name])


# 1 quality and 4 toxicity

def held_out(i):
    return zlib.crc32(str(i).encode()) % 5 == 0


@pytest.mark.parametrize("name,target", [("op1_quality", "quality"), ("op4_toxicity", "toxic")])
def test_held_out_accuracy(spark, target, name):
    sf = "/root/testdata/sf0.1"
    got = QUERIES[name](spark, sf).join(spark.read.parquet(f"{sf}/labels.parquet"), "doc_id").where("held_out").toPandas()
    y, s = got[target].to_numpy(), got.score.to_numpy()
    order = s.argsort(kind="stable").argsort()
    auc = (order[y == 1].sum() - (y == 1).sum() * ((y == 1).sum() - 1) / 2) / ((y == 1).sum() * (y == 0).sum())
    assert auc > (0.98 if target == "quality" else 0.94)
    assert (got.held_out == got.doc_id.map(held_out)).all() and got.score.between(0, 1).all()


def test_classifiers_take_odd_input(spark):
    docs = odd_documents(spark)
    labels = labels_for(spark, [(1, 1, 0), (3, 0, 0), (5, 1, 1), (4, None, None), (None, 1, 1)])
    for mod in (quality, toxicity):
        rows = mod.classify(docs, labels).collect()
        assert len(rows) == 7 and all(0 <= r["score"] <= 1 for r in rows)
        assert mod.classify(docs.limit(0), labels).count() == 0
        assert mod.classify(docs, labels.limit(0)).count() == 7
    assert toxicity.drop_toxic(docs, labels).columns == docs.columns


def test_labels_of_the_held_out_fold_change_nothing(spark):
    texts = [f"good words here number {i}" if i % 2 else f"vile scum talk {i}" for i in range(80)]
    docs = documents(spark, texts)
    rows = [(i, i % 2, 1 - i % 2) for i in range(80)]
    turned = [(i, 1 - q, 1 - t) if held_out(i) else (i, q, t) for i, q, t in rows]
    for mod in (quality, toxicity):
        a, b = (mod.classify(docs, labels_for(spark, r)).toPandas().set_index("doc_id").score for r in (rows, turned))
        assert (a == b).all()
    a = toxicity.classify(docs, labels_for(spark, rows)).toPandas()
    assert ((a.score >= 0.5) == (a.doc_id % 2 == 0)).mean() > 0.95


def test_additive_tables_find_an_interaction():
    rng = np.random.default_rng(0)
    x = rng.random((3000, 3))
    y = ((x[:, 0] > 0.5) ^ (x[:, 1] > 0.5)).astype(float)
    plain = quality.fit_tables(x, y, rounds=30, pairs=0)
    paired = quality.fit_tables(x, y, rounds=60, pairs=2)
    assert paired.pairs[0] == (1, 0)
    assert ((paired.score(x) > 0.5) == y).mean() > 0.95 > ((plain.score(x) > 0.5) == y).mean()
    z = paired.base + sum(t[np.searchsorted(e, c, side="right")] for e, t, c in zip(paired.edges, paired.tables, x.T, strict=True))
    assert z.shape == (3000,)


def lowered(t):
    return "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or "")


def plain_model(rows):
    """Step differences and class probabilities by dictionaries: {(beginning, whole word?): ...}."""
    held = [Counter(), Counter()]
    for text, y in rows:
        found = set()
        for w in set(re.findall(r"[0-9A-Za-z\x80-\U0010ffff]+", lowered(text))):
            b = w.encode()
            path = [(b"", 0)] + [(b[:k], 0) for k in range(1, 9) if k < len(b)] + [(b, 1)]
            found |= set(zip(path, path[1:], strict=False))
        held[y].update(found)
    total, kinds = [Counter(), Counter()], [Counter(), Counter()]
    for c in (0, 1):
        for (h, _), n in held[c].items():
            total[c][h] += n
            kinds[c][h] += 1
    out = {}
    for h, x in set(held[0]) | set(held[1]):
        share = (held[0][h, x] + held[1][h, x]) / (total[0][h] + total[1][h])
        out[h, x] = [(max(held[c][h, x] - 0.75, 0) + (0.75 * kinds[c][h] + 40) * share) / (total[c][h] + 40) for c in (0, 1)]
    return out, {k: held[0][k] + held[1][k] for k in out}


def test_toxicity_equals_a_plain_recomputation(spark, small, monkeypatch):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    y = {r["doc_id"]: int(r["doc_id"] % 3 == 0) for r in docs.select("doc_id").collect()}
    rows = [(r["doc_id"], r["text"], y[r["doc_id"]]) for r in docs.collect()]
    probability, texts = plain_model([(t, c) for _, t, c in rows])
    for h in {h for h, _ in probability}:  # each class's steps from one beginning are a distribution
        assert np.allclose(np.sum([p for (up, _), p in probability.items() if up == h], axis=0), 1) if len(h[0]) < 2 else True
    step = {x: np.log(p[1] / p[0]) for (h, x), p in probability.items() if texts[h, x] >= toxicity.MIN_TEXTS}
    got = toxicity.learn_steps(spark.createDataFrame(rows, "doc_id long, text string, y int").repartition(3)).toArrow()
    assert np.allclose(sorted(got.column("step").to_pylist()), sorted(step.values()))

    keys, order = got.column("key").to_numpy().view(np.uint64), got.column("key").to_numpy().view(np.uint64).argsort()
    model = toxicity.KneserNeyContrast(keys[order], got.column("step").to_numpy()[order], np.array([-1.0, 2.0, 0.5]))
    some = [t for _, t, _ in rows[:40]] + ["unknownword zzz", "", "the", None]
    want = []
    for t in some:
        values = []
        for w in re.findall(r"[0-9A-Za-z\x80-\U0010ffff]+", t or ""):
            b = lowered(w).encode()
            total = 0.0
            for x in [(b[:k], 0) for k in range(1, 9) if k < len(b)] + [(b, 1)]:
                if x not in step:
                    break
                total += step[x]
            values.append(total)
        n, tail = len(values), -(-len(values) // 10)
        level = sum(sorted(values)[tail:n - tail]) / (max(n - 2 * tail, 0) + toxicity.PAD)
        z = sum(values) / n - level if n else 0.0
        want.append(1 / (1 + np.exp(1 - 2 * z - 0.5 * z * n**0.5)))
    assert np.allclose(model.score_texts(pa.array(some)), want)


def test_toxicity_by_language(spark):
    """Found by the contrast alone, in every language with more than a handful of toxic texts."""
    sf = "/root/testdata/sf0.1"
    got = QUERIES["op4_toxicity"](spark, sf).join(spark.read.parquet(f"{sf}/labels.parquet"), "doc_id").join(spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "lang"), "doc_id").where("held_out").toPandas()
    assert got[got.toxic == 0].predicted.mean() < 0.02
    for lang in ("en", "de", "fr"):
        assert got[(got.toxic == 1) & (got.lang == lang)].predicted.mean() > 0.5


# 2 mixing

def test_mix_meets_targets(spark, medium):
    docs = spark.read.parquet(f"{medium}/documents.parquet")
    got = mixing.mix(docs).join(docs.select("doc_id", "source"), "doc_id").toPandas()
    sizes = docs.toPandas().set_index("doc_id").text.map(lambda t: len(WORD.findall(t)))
    assert (got.set_index("doc_id")["size"].sort_index() == sizes.sort_index()).all()
    assert (got.taken <= 2 * got["size"]).all() and set(got.copies) <= {0, 1, 2}
    by = got.groupby("source").agg(size=("source_size", "first"), target=("target", "first"), taken=("taken", "sum")).sort_index()
    weight = dict(zip(sorted(by.index), [3.0, 1.0, 2.0] * 20, strict=False))
    total, open_, want = 1.5 * by["size"].sum(), set(by.index), {}
    while open_:  # hand out shares, fix what is over, share the rest again
        rate = (total - sum(want.values())) / sum(weight[s] for s in open_)
        over = {s for s in open_ if rate * weight[s] > 2 * by["size"][s]}
        if not over:
            want |= {s: rate * weight[s] for s in open_}
            break
        want |= {s: 2.0 * by["size"][s] for s in over}
        open_ -= over
    assert all(abs(by.target[s] - want[s]) < 1e-6 * want[s] for s in want)
    assert ((by.taken - by.target).abs() <= 0.01 * by.target + 2).all()
    again = mixing.mix(docs.repartition(5)).select("doc_id", "taken")
    assert again.exceptAll(spark.createDataFrame(got[["doc_id", "taken"]])).count() == 0


def test_mix_rates_solve_the_dual(spark):
    rng = np.random.default_rng(2)
    n = rng.integers(1, 400, 300)
    docs = documents(spark, [" ".join(["x"] * int(k)) for k in n], ["a"] * 200 + ["b"] * 100)
    got = mixing.mix(docs).toPandas()
    for s, own in (("a", n[:200]), ("b", n[200:])):
        t = got[got.doc_id < 200 if s == "a" else got.doc_id >= 200].target.iloc[0]
        x, lo, hi = own / own.mean(), -500.0, 500.0
        for _ in range(200):
            mid = (lo + hi) / 2
            lo, hi = (mid, hi) if (own * np.minimum(2, np.exp(np.minimum(mid * x, 50)))).sum() < t else (lo, mid)
        rate = np.minimum(2, np.exp(np.minimum(lo * x, 50)))
        copies = got.set_index("doc_id").copies.loc[range(200) if s == "a" else range(200, 300)].to_numpy()
        assert abs(copies.sum() - rate.sum()) <= 12 and abs((copies * own).sum() - t) <= 0.01 * t + 2


def test_a_met_target_stays_met(spark):
    """A count that meets the target, or is over it by rounding, must not send the multiplier back to the middle of its bracket."""
    cells = spark.createDataFrame([("a", s, 3, s / 50) for s in range(1, 100)], "key string, size long, n long, x double")
    targets = spark.createDataFrame([("a", 9000.0)], "key string, target double")
    lam = mixing.tilted_rates(cells, targets).first()["lam"]
    words = lambda t: sum(3 * s * min(2.0, np.exp(t * s / 50)) for s in range(1, 100))
    assert abs(words(lam) / 9000 - 1) < 1e-6
    for over in (0.0, 1e-13, -1e-13):
        state = spark.createDataFrame([("a", float(words(lam) * (1 + over)), lam, -100.0, 50.0)], "key string, target double, lam double, lo double, hi double")
        assert abs(mixing._newton(cells, state, 2).first()["lam"] - lam) < 1e-9


def test_mix_takes_odd_input(spark):
    docs = odd_documents(spark)
    rows = mixing.mix(docs).collect()
    assert len(rows) == 7 and all(0 <= r["taken"] <= 2 * r["size"] for r in rows)
    assert mixing.mix(docs.limit(0)).count() == 0
    assert mixing.mix(documents(spark, [None, ""])).agg(F.sum("taken")).first()[0] == 0
    taken = mixing.take_copies(docs)
    assert taken.columns == docs.columns
    assert taken.count() == mixing.mix(docs).agg(F.sum("copies")).first()[0]


# 3 simhash

def plain_fingerprint(text):
    lowered = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
    w = WORD.findall(lowered)
    if not w:
        return 0
    hs = [xxhash.xxh64_intdigest(" ".join(w[i:i + 4]).encode(), 42) for i in range(max(1, len(w) - 3))]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > len(hs))


def components(ids, links):
    parent = {i: i for i in ids}

    def find(a):
        while parent[a] != a:
            a = parent[a]
        return a

    for a, b in links:
        a, b = find(a), find(b)
        parent[max(a, b)] = min(a, b)
    return {i: find(i) for i in ids}


def test_simhash_equals_brute_force(spark, medium):
    docs = spark.read.parquet(f"{medium}/documents.parquet")
    text = {r["doc_id"]: r["text"] for r in docs.collect()}
    got = {r["doc_id"]: r for r in simhash.near_duplicates(docs).collect()}
    some = sorted(text)[::25]
    assert all(int(got[i]["fingerprint"], 16) == plain_fingerprint(text[i]) for i in some)
    ids = sorted(text)
    fp = np.array([int(got[i]["fingerprint"], 16) for i in ids], dtype=np.uint64)
    near = np.argwhere(np.bitwise_count(fp[:, None] ^ fp[None]) <= 4)
    want = components(ids, [(ids[a], ids[b]) for a, b in near if a < b])
    assert {i: got[i]["component_id"] for i in ids} == want


@pytest.mark.parametrize("leaf,tile", [(8, 1 << 20), (64, 16)])
def test_forest_loses_no_link(spark, leaf, tile):
    rng = np.random.default_rng(3)
    base = rng.integers(0, 1 << 63, 400, dtype=np.uint64)
    near = base[:150].copy()
    for i in range(150):
        for b in rng.choice(64, i % 7, replace=False):
            near[i] ^= np.uint64(1) << np.uint64(b)
    fps = np.unique(np.concatenate((base, near)))
    df = spark.createDataFrame([(int(x),) for x in fps.view(np.int64)], "fp long")
    links = simhash.hamming_links(df, len(fps), leaf=leaf, tile=tile).collect()
    got = components(range(len(fps)), [(int(np.searchsorted(fps, np.uint64(r["a"] % (1 << 64)))), int(np.searchsorted(fps, np.uint64(r["b"] % (1 << 64))))) for r in links])
    pairs = np.argwhere(np.bitwise_count(fps[:, None] ^ fps[None]) <= 4)
    assert got == components(range(len(fps)), [(a, b) for a, b in pairs.tolist() if a < b])


def test_simhash_takes_odd_input(spark):
    docs = odd_documents(spark)
    rows = simhash.near_duplicates(docs).collect()
    assert len(rows) == 7
    empty = {r["doc_id"]: r for r in rows if r["fingerprint"] == "0" * 16}
    assert set(empty) == {2, 3, 4} and all(r["component_id"] == 2 for r in empty.values())
    assert simhash.near_duplicates(docs.limit(0)).count() == 0


# 5 embeddings and 6 search

def vectors(spark, rows):
    return spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int")


def odd_vectors(spark, n=60, dim=8):
    rng = np.random.default_rng(4)
    x = rng.normal(size=(n, dim)).astype(np.float32)
    x[10:20] = x[0] + rng.normal(size=(10, dim)).astype(np.float32) * 0.02
    x[20:24] = x[1]
    rows = [(i, x[i].tolist(), int(i % 2) if i < 40 else None) for i in range(n)]
    rows += [(100, None, 1), (101, [0.0] * dim, 1), (102, [float("nan")] * dim, 0), (103, [float("inf")] * dim, 0), (104, [1.0, None] + [0.0] * (dim - 2), 0), (105, [1.0], 0), (0, x[0].tolist(), 0), (None, x[0].tolist(), 0)]
    return rows


def test_embedding_links_equal_brute_force(spark):
    rows = odd_vectors(spark)
    got = embed_dedup.near_duplicates(vectors(spark, rows), tile=7).collect()
    assert len(got) == len(rows)
    fit = [(i, np.array(v, dtype=np.float32).astype(float), c) for i, v, c in rows if i is not None and c is not None and v is not None and len(v) == 8 and all(x is not None and np.isfinite(x) for x in v) and any(v)]
    links, n = [], Counter()
    for a, (i, v, c) in enumerate(fit):
        for b, (j, w, d) in enumerate(fit):
            if a != b and c == d and v @ w / (np.linalg.norm(v) * np.linalg.norm(w)) >= 0.98:
                n[i, a] += 1
                links.append((i, j))
    want = components({r[0] for r in rows if r[0] is not None}, links)
    expect = Counter((i, n[i, a], want[i]) for a, (i, _, _) in enumerate(fit))
    expect += Counter((i, 0, i) for i, _, _ in rows if i not in {x[0] for x in fit})
    assert Counter((r["vec_id"], r["n_links"], r["component_id"]) for r in got) == expect
    assert sum(n.values()) > 50
    assert all(r["kept"] == (r["vec_id"] is None or r["vec_id"] == r["component_id"]) for r in got)
    assert embed_dedup.near_duplicates(vectors(spark, [])).count() == 0


def test_search_recall_and_order(spark, medium):
    df = spark.read.parquet("/root/testdata/sf0.1/embeddings.parquet")
    got = ann.nearest(df, F.col("vec_id") % 20 == 0, shard_rows=700, block_rows=40).toPandas()
    e = df.toPandas()
    x, ids, hit = np.stack(e.embedding).astype(float), e.vec_id.to_numpy(), 0
    for q, g in got.groupby("query_id"):
        g = g.sort_values("rank")
        i = int(np.flatnonzero(ids == q)[0])
        score = x @ x[i]
        score[i] = -np.inf
        best = ids[np.lexsort((ids, -score))[:20]]
        hit += len(set(best) & set(g.vec_id))
        assert g["rank"].tolist() == list(range(1, 21)) and q not in set(g.vec_id)
        assert np.allclose(g.score, score[np.searchsorted(ids, g.vec_id)]) and (np.diff(g.score) <= 1e-12).all()
    assert hit / len(got) > 0.95


def test_search_takes_odd_input(spark):
    got = ann.nearest(vectors(spark, odd_vectors(spark)), F.col("vec_id") % 20 == 0).toPandas()
    assert set(got.query_id) == {0, 20, 40} and not set(got.vec_id) & {100, 101, 102, 103, 104, 105}
    few = ann.nearest(vectors(spark, [(0, [1.0, 2.0], 0), (1, [1.0, 2.0], 0), (2, [1.0, 2.0], 0)]), F.col("vec_id") == 0).collect()
    assert [(r["rank"], r["vec_id"]) for r in few] == [(1, 1), (2, 2)]
    assert ann.nearest(vectors(spark, []), F.col("vec_id") == 0).count() == 0
    assert ann.nearest(vectors(spark, [(0, None, 0)]), F.col("vec_id") == 0).count() == 0


def test_vector_operators_take_clashing_columns(spark):
    df = vectors(spark, odd_vectors(spark))
    wide = df
    for extra in ("node", "root", "rank", "score", "query_id", "band", "tile", "code", "component_id", "n_links", "kept", "e", "v", "x"):
        wide = wide.withColumn(extra, F.lit("x"))
    for run in (lambda d: embed_dedup.near_duplicates(d), lambda d: ann.nearest(d, F.col("vec_id") % 20 == 0)):
        assert Counter(map(str, run(wide).collect())) == Counter(map(str, run(df).collect()))


def test_quality_without_labels(spark):
    got = quality.classify(documents(spark, ["a b c", "", None]), labels_for(spark, [])).collect()
    assert len({r["score"] for r in got}) == 1 and 0 <= got[0]["score"] <= 1


def test_anisotropic_codes_have_less_parallel_error():
    rng = np.random.default_rng(5)
    x = rng.normal(size=(2000, 16))
    unit = x / np.linalg.norm(x, axis=1, keepdims=True)
    err = {}
    for eta in (1.0, 6.0):
        books = ann.fit_codebooks(x, 2, eta)
        codes = ann.encode(x, books, eta)
        err[eta] = float((ann._cost_parts(x, unit, books, codes).sum(1) ** 2).mean())
        tables = ann.scan_tables(x[:3], books)
        near = sum(tables[:, b][:, ann.packed(codes)[:, b]] for b in range(tables.shape[1]))
        exact = (books[np.arange(8), codes].reshape(2000, 16) @ x[:3].T).T
        assert np.allclose(near, exact, atol=1e-3)
    assert err[6.0] < 0.6 * err[1.0]


# 7 packing

def test_bounds_are_optimal():
    rng = np.random.default_rng(6)
    top = np.sort(rng.choice(200, 9, replace=False))
    n = rng.integers(1, 30, 9)
    ends = packing.optimal_bounds(top, n, n * top, 3)

    def cost(ends):
        out, a = 0, 0
        for e in ends:
            out += sum(n[i] * (top[e] - top[i]) for i in range(a, e + 1))
            a = e + 1
        return out

    best = min(cost([a, b, 8]) for a in range(8) for b in range(a + 1, 8))
    assert ends[-1] == 8 and cost(ends) == best


def test_packing_fills_batches(spark, medium):
    got = packing.pack(spark.read.parquet(f"{medium}/documents.parquet"), budget=4096).toPandas()
    assert len(got) == 1000 and (got.n_tokens <= got.bucket_len).all() and (got.n_pad == got.bucket_len - got.n_tokens).all()
    for (bucket, _), g in got.groupby(["bucket", "batch"]):
        assert len(g) * g.bucket_len.iloc[0] <= 4096 or len(g) == 1
    for _, g in got.groupby("bucket"):  # only the last batch of a bucket is not full
        room = max(1, 4096 // g.bucket_len.iloc[0])
        sizes = g.groupby("batch").size().sort_index()
        assert sizes.index.tolist() == list(range(len(sizes))) and (sizes.iloc[:-1] == room).all()


def test_packing_takes_odd_input(spark):
    docs = odd_documents(spark)
    rows = packing.pack(docs).collect()
    assert len(rows) == 7 and max(r["bucket_len"] for r in rows) == 60_000
    assert packing.pack(docs.limit(0)).count() == 0


# 8 lines

def test_lines_of_a_site_go(spark):
    texts = [f"Menu\nown line {i}\n  Menu\t\nonce {i % 3}" for i in range(30)] + ["Menu\nother"] * 2
    docs = documents(spark, texts, ["a"] * 30 + ["b"] * 2).withColumn("site", F.lit("clash"))
    out = line_dedup.drop_boilerplate(docs, counts=True).orderBy("doc_id").collect()
    assert out[0]["text"] == "own line 0" and out[0]["__n_lines"] == 4 and out[0]["__n_removed"] == 3
    assert out[30]["text"] == "Menu\nother"  # two pages are too few to tell


def test_lines_take_odd_input(spark):
    docs = odd_documents(spark)
    out = line_dedup.drop_boilerplate(docs)
    assert out.columns == docs.columns and out.exceptAll(docs).count() == 0 and out.count() == 7
    assert line_dedup.drop_boilerplate(docs.limit(0)).count() == 0
    nulls = documents(spark, ["x\ny"] * 4, [None] * 4)
    assert {r["text"] for r in line_dedup.drop_boilerplate(nulls).collect()} == {""}
    large = line_dedup.SMALL
    try:
        line_dedup.SMALL = -1  # the way without broadcast gives the same
        texts = [f"Menu\nown {i}" for i in range(20)]
        assert {r["text"] for r in line_dedup.drop_boilerplate(documents(spark, texts)).collect()} == {f"own {i}" for i in range(20)}
    finally:
        line_dedup.SMALL = large


# 9 substrings

def plain_removal(texts, width):
    words = [(t or "").encode().split() for t in map(lambda t: t, texts)]
    seen = Counter(tuple(w[i:i + width]) for w in words for i in range(len(w) - width + 1))
    out = []
    for w in words:
        gone = [False] * len(w)
        for i in range(len(w) - width + 1):
            if seen[tuple(w[i:i + width])] > 1:
                gone[i:i + width] = [True] * width
        kept = b" ".join(x for x, g in zip(w, gone, strict=True) if not g)
        out.append((len(w), sum(gone), hashlib.sha256(kept).hexdigest()))
    return out


@pytest.mark.parametrize("seed", range(3))
def test_repeats_equal_brute_force(spark, seed):
    rng = np.random.default_rng(seed)
    texts = [" ".join(rng.choice(["a", "b", "c", "é"], rng.integers(0, 60))) for _ in range(40)] + [None, "", "x " * 50, "same words here now"] + ["same words here now"]
    got = substring.remove_repeats(documents(spark, texts).repartition(3), width=4, pack_bytes=200, stripe_bytes=500).orderBy("doc_id").collect()
    assert [(r["n_words"], r["n_removed"], r["kept_sha256"]) for r in got] == plain_removal(texts, 4)
    assert all(hashlib.sha256(r["kept"].encode()).hexdigest() == r["kept_sha256"] for r in got)


def test_repeats_take_odd_input(spark):
    docs = odd_documents(spark)
    rows = substring.remove_repeats(docs).collect()
    assert len(rows) == 7 and {r["doc_id"] for r in rows} == {1, 2, 3, 4, 5, None}
    assert substring.remove_repeats(docs.limit(0)).count() == 0


# 10 pages

PAGE = """<!DOCTYPE html><html><head><title>t</title><style>p{{}}</style></head><body><header class="site-header"><h1>Site</h1><nav><a>Home</a></nav></header>
<div class="cookie-notice">We use cookies</div><div class="layout with-sidebar"><div class="sidebar">Side</div>
<article class="post"><header><h1>Title {i} &amp; more</h1></header><p>One <b>two</b>
 three {i}<p>Follow us today</p><script>if (a < b) {{ x("</p>") }}</script><table><tr><td>x<td>y{i}</table><p>1 < 2</p>
<div class="comments"><article>reader {i}</article></div><form><input><label>Mail</label></form></article></div><!-- ad --><footer>&copy; site</footer></body>"""


def pages(spark, rows):
    return spark.createDataFrame(rows, "page_id long, url string, html string")


def test_wrapper_drops_template_and_chrome(spark):
    rows = [(i, f"https://Host.example/{i}", PAGE.format(i=i)) for i in range(12)]
    got = html_extract.extract(pages(spark, rows).withColumn("host", F.lit("clash"))).orderBy("page_id").collect()
    assert got[3]["text"] == "Title 3 & more\nOne two three 3\nx y3"  # what all pages of the host share is template
    few = html_extract.extract(pages(spark, rows[:3])).orderBy("page_id").collect()
    assert few[2]["text"] == "Title 2 & more\nOne two three 2\nFollow us today\nx y2\n1 < 2"
    assert few[2]["n_chars"] == len(few[2]["text"])


def test_copies_of_one_page_are_no_template(spark):
    rows = [(i, "http://h/", PAGE.format(i=0)) for i in range(15)]
    got = html_extract.extract(pages(spark, rows)).collect()
    assert {r["text"] for r in got} == {"Title 0 & more\nOne two three 0\nFollow us today\nx y0\n1 < 2"}


def test_pages_without_article_and_odd_input(spark):
    deep = "<div>" * 3000 + "deep" + "</div>" * 3000
    rows = [(1, None, None), (2, "", ""), (3, "http://a/", "plain text"), (4, "http://a/", "<div><p>x<nav>menu</nav><ul><li>a<li>b</ul>"), (5, "http://b/", deep), (6, "http://b/", "<p class='a\" >t</p><p>u"), (6, "http://b/", "<p>r"), (None, "http://c/", "<!-- never closed <p>x")]
    got = html_extract.extract(pages(spark, rows)).collect()
    text = {r["page_id"]: r["text"] for r in got}
    assert len(got) == 8 and text[1] == text[2] == text[None] == "" and text[3] == "plain text" and text[4] == "x\na\nb" and text[5] == "deep"
    assert html_extract.extract(pages(spark, [])).count() == 0


def plain_reading(page):
    import html

    body = page.split("<article>")[1].split("</article>")[0].split("<footer>")[0]
    parts = [" ".join(html.unescape(re.sub(r"<[^>]+>", " ", re.sub("</?b>", "", x))).split()) for x in re.split(r"</?(?:p|h1)>", body)]
    return "\n".join(x for x in parts if x)


def test_given_pages_equal_a_plain_reading(spark, medium):
    df = spark.read.parquet(f"{medium}/pages.parquet")
    got = {r["page_id"]: r["text"] for r in html_extract.extract(df).collect()}
    for r in df.collect():
        assert got[r["page_id"]] == plain_reading(r["html"])


MUTE = {"nav": "div", "article": "div", "footer": "div", "ul": "div", "li": "div", "h1": "p"}


def mute(page, n):
    """The page without telling names: every element a div or p, one class each that means nothing."""
    def plain(m):
        tag = m.group(2)
        cls = {"nav": "qa", "ul": "qb", "li": "qc", "article": "qd", "footer": "qe"}.get(tag)
        return f"<{m.group(1)}{MUTE[tag]}" + (f' class="{cls}{n}"' if cls and not m.group(1) else "") + ">"

    return re.sub(r"<(/?)(nav|article|footer|ul|li|h1)>", plain, page).replace('class="ad"', 'class="qf"')


def test_induction_needs_no_telling_names(spark, medium):
    """Pages of hosts with enough of them, their names made meaningless, give the same texts; without what was learned they don't."""
    df = spark.read.parquet(f"{medium}/pages.parquet")
    rows = [(r["page_id"], r["url"], r["html"].replace("</body></html>", "")) for r in df.collect()]
    hosts = Counter(re.sub(r"^https?://([^/]*).*", r"\1", u) for _, u, _ in rows)
    rows = [r for r in rows if hosts[re.sub(r"^https?://([^/]*).*", r"\1", r[1])] >= 12 and "</article>" in r[2]]
    muted = pages(spark, [(i, u, mute(h, i)) for i, u, h in rows])
    got = {r["page_id"]: r["text"] for r in html_extract.extract(muted).collect()}
    assert len(rows) > 20 and all(got[i] == plain_reading(h) for i, _, h in rows)
    root, blocks = html_extract.parse(mute(rows[0][2], 1))
    untaught = html_extract.Wrapper(html_extract.frame(root), [], set())
    assert untaught.region == 0 and untaught.read(root, blocks) != got[rows[0][0]]


def test_long_and_deep_pages(spark):
    """Thousands of siblings that no fold joins, and nesting beyond any recursion limit, are aligned all the same."""
    sections = "".join(f"<div class='{'abcdefgh'[i * i % 8]}{'xyz'[i % 3]}'><p>part {i} of {{i}}</p></div><ul><li>item</li></ul>" for i in range(1500))
    many = f"<div class='menu'><p>Home</p></div><main>{sections}</main><div class='end'><p>bye</p></div>"
    deep = "<div>" * 4000 + "<p>deep {i}</p><p>same</p>" + "</div>" * 4000
    rows = [(i, "http://many/", many.replace("{i}", str(i))) for i in range(9)] + [(100 + i, "http://deep/", deep.replace("{i}", str(i))) for i in range(9)]
    got = {r["page_id"]: r["text"] for r in html_extract.extract(pages(spark, rows)).collect()}
    assert got[3] == "\n".join(f"part {i} of 3" for i in range(1500)) and got[104] == "deep 4"


def test_unclosed_elements_hold_what_follows():
    text = lambda page: [t for _, t, _ in html_extract.parse(page)[1]]
    assert text("<p>a<svg><p>b<object><p>c<audio>d") == ["a", "b", "c d"] and text("<p>a<script>b<p>c") == ["a"]


def tree(rng, depth=0):
    kids = [tree(rng, depth + 1) for _ in range(rng.integers(0, 4))] if depth < 3 else []
    return "abc"[rng.integers(3)], kids


def written(t):
    return t[0] + (f"({' '.join(written(k) for k in t[1])})" if t[1] else "")


def plain_matching(x, y):
    """Largest simple tree matching, by recursion over all cells."""
    if x[0] != y[0]:
        return 0
    best = [[0] * (len(y[1]) + 1) for _ in range(len(x[1]) + 1)]
    for i, p in enumerate(x[1]):
        for j, q in enumerate(y[1]):
            w = plain_matching(p, q)
            best[i + 1][j + 1] = max(best[i][j + 1], best[i + 1][j], best[i][j] + w if w else 0)
    return 1 + best[-1][-1]


def test_tree_matching_is_the_largest():
    rng = np.random.default_rng(11)
    for _ in range(300):
        x, y = ("a", tree(rng)[1]), ("a", tree(rng)[1])
        found = html_extract.matched(written(x), written(y))
        hit = [j for j in found if j >= 0]
        assert len(hit) == plain_matching(x, y) and hit == sorted(set(hit))
        labels = [re.findall("[abc]", written(z)) for z in (x, y)]
        assert all(labels[0][i] == labels[1][j] for i, j in enumerate(found) if j >= 0)


def test_tree_matching_keeps_order():
    m = html_extract.matched("body(nav div(h1 p) footer)", "body(div(p) aside footer)")
    assert m == [0, -1, 1, -1, 2, 4]


def test_repeats_fold():
    def folds(page):
        return html_extract.frame(html_extract.parse(page)[0])

    assert folds("<p>a<p>b<p>c") == "html(p)" and folds("<div>m</div><div>t</div><div>f</div>") == "html(div div div)"
    assert folds("<h2>a</h2><p>b<h2>c</h2><p>d<h2>e</h2><p>f") == "html(h2 p)" and folds("<div>x</div>" * 9) == "html(div div div)"
