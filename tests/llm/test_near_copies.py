from collections import Counter

import numpy as np
import pyarrow as pa
import pytest

import corpus_pipeline as cp
from segsum.llm import simhash_wide as sw
from segsum.llm.bytehash import mix


def plain_set(text):
    w = (text or "").encode("utf-8", "surrogatepass").lower().split()
    return frozenset(tuple(w[i:i + 5]) for i in range(max(1, len(w) - 4))) if w else frozenset()


def plain_fingerprints(texts):
    """Majority bits counted one by one over the shingle hashes."""
    hashes, n = sw.shingle_hashes(pa.array(texts, pa.string()))
    out, at = np.zeros((len(texts), sw.BITS // 64), np.uint64), 0
    for i, k in enumerate(n.tolist()):
        own, at = hashes[at:at + k], at + k
        for w in range(out.shape[1] if k else 0):
            x = mix(own + np.uint64((w + 1) * 0x9E3779B97F4A7C15 % (1 << 64)))
            bits = [2 * int(((x >> np.uint64(b)) & np.uint64(1)).sum()) > k for b in range(64)]
            out[i, w] = sum(1 << b for b, on in enumerate(bits) if on)
    return out


def plain_components(ids, fps, reach):
    """Components of all pairs within reach, named by the least id."""
    parent = list(range(len(ids)))

    def find(a):
        while parent[a] != a:
            a = parent[a]
        return a

    for i in range(len(ids)):
        for j in np.flatnonzero(np.bitwise_count(fps[i + 1:] ^ fps[i]).sum(axis=1) <= reach) + i + 1:
            a, b = find(i), find(int(j))
            parent[max(a, b)] = min(a, b)
    return {ids[i]: ids[find(i)] for i in range(len(ids))}


def as_groups(of):
    out = {}
    for k, c in of.items():
        out.setdefault(c, set()).add(k)
    return {frozenset(g) for g in out.values()}


def test_shingles_are_those_of_the_words():
    texts = ["A b c d e F", "a  b\tc d E f", "a b", None, "", "x", "a b c d e", "b a", " "]
    hashes, n = sw.shingle_hashes(pa.array(texts))
    assert n.tolist() == [2, 2, 1, 0, 0, 1, 1, 1, 0] and hashes[:2].tolist() == hashes[2:4].tolist() and len(set(hashes.tolist())) == 5


@pytest.mark.parametrize("leaf", [sw.LEAF, 64])
def test_forest_equals_all_pairs(spark, medium, leaf, monkeypatch):
    monkeypatch.setattr(sw.wide_links, "__defaults__", (leaf, *sw.wide_links.__defaults__[1:]))
    docs = spark.read.parquet(f"{medium}/documents.parquet")
    text = {r["doc_id"]: r["text"] for r in docs.collect()}
    ids = sorted(text)
    fps = plain_fingerprints([text[i] for i in ids])
    got = {r["doc_id"]: r["root"] for r in sw.near_copies(docs).collect()}
    assert as_groups(got) == as_groups(plain_components(ids, fps, sw.reach_of(0.8)))


def test_similar_texts_are_found_and_others_left_alone(spark):
    """Of texts that share four fifths of their shingles nearly all are linked, of those that share two thirds none."""
    rng = np.random.default_rng(7)
    rows, want = [], {}
    for i in range(200):
        words = [f"w{x}" for x in rng.integers(0, 10**6, 300)]
        tail = {0: 33, 1: 60, 2: 0}[i % 3]  # J = .8, .67, 1 for the second of each pair
        rows += [(2 * i, " ".join(words)), (2 * i + 1, " ".join(words[:300 - tail] + [f"v{x}" for x in rng.integers(0, 10**6, tail)]))]
        want[i] = i % 3
    got = {r["doc_id"]: r["root"] for r in sw.near_copies(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    same = {k: [got[2 * i] == got[2 * i + 1] for i, v in want.items() if v == k] for k in (0, 1, 2)}
    assert all(same[2]) and not any(same[1]) and np.mean(same[0]) > 0.8
    assert len(set(got.values())) >= 400 - sum(map(sum, same.values()))


def test_an_overfull_leaf_is_split_and_a_chain_stays_whole(spark):
    """Each text shares .9 with the next only; a hundred variants of one text fill a leaf."""
    words = [f"w{i}" for i in range(400)]
    chain = [(i, " ".join(words[i * 12:i * 12 + 204])) for i in range(10)]
    copies = [(1000 + i, " ".join([*words[::-1][:300], f"x{i}"])) for i in range(100)]
    df = spark.createDataFrame(chain + copies, "doc_id long, text string")
    points = sw.wide_fingerprints(df).cache()
    for leaf, tile in ((512, 8192), (8, 30)):
        links = sw.wide_links(points, 110, sw.reach_of(0.8), leaf, tile).collect()
        node = {r["node"]: r["doc_id"] for r in points.collect()}
        parent = {i: i for i in node.values()}
        for r in links:
            a, b = node[r["a"]], node[r["b"]]
            while parent[a] != a:
                a = parent[a]
            while parent[b] != b:
                b = parent[b]
            parent[max(a, b)] = min(a, b)
        assert sum(1 for k, v in parent.items() if k == v) == 2
        assert len(links) < 40 * 110  # no copy meets all others


def test_stage_takes_odd_input(spark):
    rows = [(1, "a b c"), (2, None), (3, ""), (4, " \n"), (5, "A  b\tc"), (5, "x y z"), (6, "a b d"), (None, "a b c"), (6, "a b d")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    for extra in ("node", "t", "fp", "root", "leaf", "row"):
        docs = docs.withColumn(extra, docs.doc_id)
    kept = Counter((r["doc_id"], r["text"]) for r in sw.drop_near_copies(docs).collect())
    assert kept == Counter({(1, "a b c"): 1, (2, None): 1, (5, "x y z"): 1, (6, "a b d"): 1, (None, "a b c"): 1})
    assert sw.drop_near_copies(docs).columns == docs.columns
    assert sw.drop_near_copies(docs.limit(0)).count() == 0


def test_stage_keeps_the_columns(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    kept = dict(cp.STAGES)["simhash_dedup"](spark, docs, small)
    assert kept.columns == docs.columns and 0 < kept.count() <= docs.count()


def test_an_overfull_leaf_loses_no_link(spark):
    """Chains of points that only their neighbours reach: parts of any size give the components of the whole leaf."""
    rng = np.random.default_rng(4)
    fps = [rng.integers(0, 2, 1024)]
    for i in range(119):
        nxt = fps[-1].copy() if i % 4 else rng.integers(0, 2, 1024)
        if i % 4:
            nxt[rng.choice(1024, 150, replace=False)] ^= 1
        fps.append(nxt)
    packed_ = [np.packbits(f.astype(np.uint8), bitorder="little").tobytes() for f in fps]
    points = spark.createDataFrame([(int(rng.integers(1 << 60)), b) for b in packed_], "node long, fp binary").cache()

    def roots(tile):
        links = sw.wide_links(points, 100, sw.reach_of(0.8), 512, tile)
        return {r.node: r.root for r in sw.connected_components(links).collect()}

    assert len(set(roots(1 << 20).values())) == 30 and roots(30) == roots(1 << 20)


def test_a_batch_is_handed_on_in_small_parts_and_whole():
    """All trees of 10,000 points at once filled a worker; no part may hold more than the bound and one leaf's points."""
    rng = np.random.default_rng(5)
    fps = rng.integers(0, 1 << 63, (4_000, sw.BITS // 64), dtype=np.uint64)
    nodes = np.arange(4_000, dtype=np.int64)
    forest = sw.StretchForest(200_000, sw.reach_of(0.8))
    code = forest.leaves(fps, 0)
    full = int(code[0])  # an overfull leaf, dealt to three parts
    got, widest = [], 0
    for batch in sw.dealt(forest, nodes, fps, {full: 3}, 100_000):
        bytes_ = [len(a) + len(b) for a, b in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist(), strict=True)]
        assert sum(bytes_[:-1]) < 100_000
        widest = max(widest, batch.num_rows)
        for leaf, own, point in zip(batch.column(0).to_pylist(), batch.column(2).to_pylist(), batch.column(3).to_pylist(), strict=True):
            at = np.frombuffer(own, np.int64)
            assert np.array_equal(np.frombuffer(point, np.uint64).reshape(-1, sw.BITS // 64), fps[at])
            got.extend((leaf, int(i)) for i in at)
    want = [(int(c), i) for t in range(forest.trees) for i, c in enumerate(forest.leaves(fps, t).tolist()) for _ in range(2 if c == full else 1)]
    assert widest and sorted(got) == sorted(want)
