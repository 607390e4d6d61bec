"""Near-duplicate groups of the pipeline against brute-force Jaccard of five-word shingles."""

import re

import numpy as np
import pytest

import corpus_pipeline
from partnet.llm import shingle_links

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def brute_set(text):
    w = re.findall(rb"[^\x20\x09-\x0D]+", re.sub(rb"[A-Z]", lambda m: m[0].lower(), (text or "").encode()))
    return {b" ".join(w[i : i + 5]) for i in range(max(1, len(w) - 4))}


def brute_groups(texts):
    sets, parent = [brute_set(t) for t in texts], list(range(len(texts)))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i in range(len(texts)):
        for j in range(i):
            both = len(sets[i] & sets[j])
            if 5 * both >= 4 * (len(sets[i]) + len(sets[j]) - both):
                a, b = find(i), find(j)
                parent[max(a, b)] = min(a, b)
    return [find(k) for k in range(len(texts))]


def varied():
    """Groups of every spread, chains that are alike only link by link, and unlike texts that share a passage."""
    rng = np.random.default_rng(5)
    texts = [None, "", " \n", "One two", "one  TWO", "a b c d e", "a b c d f"]
    passage = [f"p{k}" for k in range(30)]
    for g in range(12):
        base = [f"g{g}w{k}" for k in range(60)]
        for _ in range(8):
            new = list(base)
            for k in rng.choice(60, rng.integers(0, 4), replace=False):
                new[int(k)] = f"n{rng.integers(1 << 30)}"
            texts.append(" ".join(new))
        texts.append(" ".join(passage + base[:8]))
    chain = [f"c{k}" for k in range(200)]
    texts += [" ".join(chain[k : k + 100]) for k in range(0, 100, 10)]
    return texts


def groups(labels):
    first: dict = {}
    return [first.setdefault(x, k) for k, x in enumerate(labels)]


@pytest.mark.parametrize("small", [2, shingle_links.SMALL])
def test_links_are_those_of_brute_force(spark, small):
    texts = varied()
    df = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id long, text string").repartition(3)
    got = {r.doc_id: r.root for r in shingle_links.similar_groups(df, small=small).collect()}
    assert groups([got[i] for i in range(len(texts))]) == groups(brute_groups(texts))
    assert shingle_links.similar_groups(df.limit(0)).count() == 0


def test_near_stage_keeps_one_of_each_similar_group(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").where("doc_id < 500")
    rows = sorted(((r.doc_id, r.text) for r in docs.collect()), key=lambda r: r[0])
    want = {rows[k][0] for k in brute_groups([t for _, t in rows])}
    out = corpus_pipeline.near_stage(spark, docs, "")
    assert out.columns == docs.columns and sorted(r.doc_id for r in out.collect()) == sorted(want)


def test_a_border_pair_goes_and_a_looser_one_stays(spark):
    """Similarity 4/5 exactly is in; a fingerprint of 4 bits would part the first and could join the second."""
    words = [f"w{k}" for k in range(49)]
    in_it, below = words[:-5] + [f"x{k}" for k in range(5)], words[:-6] + [f"y{k}" for k in range(6)]
    texts = [" ".join(words), " ".join(in_it), " ".join(below)]
    sims = [len(brute_set(texts[0]) & brute_set(t)) / len(brute_set(texts[0]) | brute_set(t)) for t in texts[1:]]
    assert sims[0] == 0.8 > sims[1]
    docs = spark.createDataFrame([(k, t, "en", "s", 0) for k, t in enumerate(texts)], SCHEMA)
    assert sorted(r.doc_id for r in corpus_pipeline.near_stage(spark, docs, "").collect()) == [0, 2]


def test_rows_without_an_id_and_with_a_shared_one(spark):
    """A null-id text that is nobody's copy stays, a group of null ids keeps one, as do near copies with the same id."""
    words = [f"w{k}" for k in range(60)]
    near = lambda k, tag: " ".join(words[:-1] + [f"{tag}{k}"])
    other = lambda tag: " ".join(f"{tag}{k}" for k in range(60))
    rows = [(None, other("a")), (None, other("b")), (None, other("b") + " x"), (None, near(0, "m")), (4, near(1, "m")), (7, other("c")), (7, other("c") + " x"), (8, other("d")), (8, other("e")), (None, "same"), (None, "same")]
    docs = spark.createDataFrame([(i, t, "en", "s", 0) for i, t in rows], SCHEMA)
    got = sorted(((r.doc_id, brute_groups([t for _, t in rows])[[t for _, t in rows].index(r.text)]) for r in corpus_pipeline.near_stage(spark, docs, "").collect()), key=str)
    assert got == sorted([(None, 0), (None, 1), (4, 3), (7, 5), (8, 7), (8, 8), (None, 9)], key=str)
    assert len({tuple(r) for r in corpus_pipeline.near_stage(spark, docs.repartition(4), "").collect()} ^ {tuple(r) for r in corpus_pipeline.near_stage(spark, docs, "").collect()}) == 0


def test_sketches_rule_out_no_pair_and_blocks_lose_none():
    """Sets of every overlap: what the sketch or a unit of blocks rejects is below the similarity."""
    rng, made = np.random.default_rng(3), shingle_links.Shingler()
    sets = []
    for n in (1, 5, 40, 64, 65, 300, 1100):
        base = rng.integers(0, 1 << 63, n, dtype=np.uint64) * np.uint64(2)
        sets.append(np.unique(base))
        for share in (0.02, 0.05, 0.1, 0.11, 0.12, 0.2, 0.5):
            other = base.copy()
            swap = rng.random(n) < share
            other[swap] = rng.integers(0, 1 << 63, int(swap.sum()), dtype=np.uint64)
            sets.append(np.unique(np.append(other, rng.integers(0, 1 << 63, n // 20, dtype=np.uint64))))
    alike = lambda x, y: 5 * (both := np.intersect1d(x, y).size) >= 4 * (x.size + y.size - both)
    sketches = [shingle_links.sketch_of(x) for x in sets]
    n = len(sets)
    likely = {(i, j) for i in range(n) for j in range(n) if i < j and shingle_links.may_be_alike(sets[i].size, sets[j].size, sketches[i], sketches[j])}
    true = {(i, j) for i in range(n) for j in range(i + 1, n) if alike(sets[i], sets[j])}
    assert true <= likely and len(likely) < n * n / 8
    u, v = shingle_links.pairs_of_unit(np.arange(n), np.arange(n), np.array([x.size for x in sets]), [np.frombuffer(x, np.uint64) for x in sketches])
    assert {(min(a, b), max(a, b)) for a, b in zip(u.tolist(), v.tolist(), strict=True)} == likely and u.size == len(likely)
    assert made.set_of(b"").tolist() == [0] and made.set_of(b"A b").tolist() == made.set_of(b"a  B").tolist() != made.set_of(b"b a").tolist()


def test_large_buckets_in_blocks_are_complete(spark):
    """Unlike texts that share most of a prefix stay apart, alike ones meet, with every bucket treated as large."""
    words = [f"q{k}" for k in range(40)]
    texts = [" ".join(words[:25] + [f"t{t}x{k}" for k in range(15 if t % 3 else 4)]) for t in range(12)] + [" ".join(words[:25] + [f"t{t}x{k}" for k in range(14)] + ["z"]) for t in range(1, 12, 3)]
    df = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id long, text string")
    printed = shingle_links.materialize(shingle_links.prints(df), "p")
    nodes = {r.doc_id: r.node for r in printed.where("node IS NOT NULL").collect()}
    members = df.select("doc_id").join(printed.select("doc_id", "node"), "doc_id").selectExpr("7L AS key", "node", "node AS root")
    got = {(r.a, r.b) for r in shingle_links.block_pairs(members, printed, block=5).collect()}
    for i in range(len(texts)):
        for j in range(i):
            x, y = brute_set(texts[i]), brute_set(texts[j])
            if 5 * len(x & y) >= 4 * len(x | y):
                assert (min(nodes[i], nodes[j]), max(nodes[i], nodes[j])) in got
