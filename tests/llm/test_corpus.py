"""The corpus operators against brute force on small tables, with every awkward case in them."""

import hashlib
import html
import os
import re
import zlib

import numpy as np
import public_tokenizers
import pytest
import xxhash
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from partnet.llm import components, exact_dedup, html_text, mixing, packing, quality, rules, shards, simhash, token_files, urls
from partnet.llm.queries import QUERIES
from partnet.llm.tokens import MemoEncoder, pack
from test_shingle_links import brute_groups

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, keep_id string, size string, score string, u string, bucket string"
LONG = " ".join(f"word{i % 977} tail{i % 31}" for i in range(40_000))
TEXTS = [
    (1, "alpha beta gamma delta epsilon zeta", "b"), (2, "alpha  beta\tgamma\ndelta epsilon zeta", "a"), (3, None, None), (4, "", "a"), (5, " \n ", "a"),
    (6, LONG, "b"), (7, LONG + " more", "b"), (8, "Alpha beta gamma delta epsilon zeta", "a"), (9, "word", None), (None, "word", "c"), (11, "word", "c"), (11, "word", "c"),
    (12, "<|endoftext|> don't 12345 ½ é x", "a"), (13, "naïve 日本語 😀", "c"), (None, None, "b"),
]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame([(i, t, "en", s, 0, "x", "y", "z", "u", "b") for i, t, s in TEXTS], SCHEMA).repartition(3)


@pytest.fixture(scope="module")
def empty(docs):
    return docs.limit(0)


@pytest.fixture(scope="module")
def real(spark, sf):
    return spark.read.parquet(f"{sf}/documents.parquet")


def words(text):
    return re.findall(r"[^\x20\x09-\x0D]+", text or "")


def normal(text):
    return re.sub(r"[\x20\x09-\x0D]+", " ", text or "")


# --- quality classifier ---


def test_quality_learns_and_scores_everything(spark, sf, docs, empty):
    labels = spark.read.parquet(f"{sf}/labels.parquet")
    rows = QUERIES["op1_quality"](spark, sf).join(labels, "doc_id").collect()
    fitted = [r for r in rows if not r.held_out]
    assert all((zlib.crc32(str(r.doc_id).encode()) % 3 == 1) == r.held_out for r in rows)
    assert np.mean([r.predicted == r.quality for r in fitted]) > 0.95
    weights = quality.fit_quality(docs, labels.limit(0))
    assert {r.score for r in quality.score_documents(docs, weights).collect()} == {0.5}
    scored = quality.score_documents(docs, weights)
    assert scored.count() == len(TEXTS) and dict(scored.dtypes)["score"] == "double" and quality.score_documents(empty, weights).count() == 0
    beside = quality.score_documents(docs, weights, names=("own", "says"))
    assert {r.score for r in beside.collect()} == {"z"} and {r.own for r in beside.collect()} == {0.5}
    assert quality.fit_quality(real_rows(spark, sf).unionAll(real_rows(spark, sf)), labels).tolist() == quality.fit_quality(real_rows(spark, sf), labels).tolist()


def real_rows(spark, sf):
    return spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text")


def brute_slots(text, bits=18):
    """Feature slots in plain whole-number arithmetic."""
    tokens, wide = re.findall(r"\w+|[^\w\s]+", text or ""), 1 << 64
    if not tokens:
        return []
    h = [zlib.crc32(x.encode("utf-8", "surrogatepass")) for x in tokens]
    mix = 0x9E3779B97F4A7C15
    pairs = {(a * 0xC2B2AE3D27D4EB4F + b + 7) * mix % wide for a, b in zip(h, h[1:])}
    shares = [sum(a == b for a, b in zip(h, h[gap:])) / (len(h) - gap) if len(h) > gap else 0.0 for gap in (1, 2)] + [1 - len(pairs) / max(1, len(h) - 1)]
    repeats = [(100 * k + int(10 * x) + (1 << 40)) * mix % wide for k, x in enumerate(shares)]
    return sorted({x >> (64 - bits) for x in [(a + 1) * mix % wide for a in h] + list(pairs) + repeats})


def brute_ftrl(examples, config):
    """Plain per-coordinate FTRL-proximal over dictionaries."""
    import math

    z, n, bias = {}, {}, 1 << config.bits
    ones = sum(y for y, _ in examples)
    weight = {1: len(examples) / max(1, 2 * ones), 0: len(examples) / max(1, 2 * (len(examples) - ones))}

    def w(i):
        zi = z.get(i, 0.0)
        return 0.0 if abs(zi) <= config.l1 else -(zi - math.copysign(config.l1, zi)) / ((config.beta + math.sqrt(n.get(i, 0.0))) / config.alpha + config.l2)

    for _ in range(-(-config.updates // max(1, len(examples)))):
        for y, slots in examples:
            x = {i: 1 / math.sqrt(len(slots)) for i in slots} | {bias: 1.0}
            at = {i: w(i) for i in x}
            p = 1 / (1 + math.exp(-max(-35.0, min(35.0, sum(at[i] * v for i, v in x.items())))))
            for i, v in x.items():
                g = (p - y) * v * weight[y]
                sigma = (math.sqrt(n.get(i, 0.0) + g * g) - math.sqrt(n.get(i, 0.0))) / config.alpha
                z[i] = z.get(i, 0.0) + g - sigma * at[i]
                n[i] = n.get(i, 0.0) + g * g
    return lambda slots: 1 / (1 + math.exp(-max(-35.0, min(35.0, sum(w(i) for i in slots) / math.sqrt(max(1, len(slots))) + w(bias)))))


def test_every_score_against_a_plain_refit(spark, sf):
    """op1's fit and all its scores over the whole table, from the given labels outside the held-out third, in plain Python."""
    labels = {r.doc_id: r.quality for r in spark.read.parquet(f"{sf}/labels.parquet").collect()}
    texts = {r.doc_id: r.text for r in real_rows(spark, sf).collect()}
    ids = [i for i in labels if zlib.crc32(str(i).encode()) % 3 != 1 and i in texts]
    turn = {r.doc_id: r.turn for r in real_rows(spark, sf).select("doc_id", F.xxhash64("doc_id").alias("turn")).collect()}
    score = brute_ftrl([(labels[i], brute_slots(texts[i])) for i in sorted(ids, key=turn.get)], quality.QualityConfig())
    rows = QUERIES["op1_quality"](spark, sf).collect()
    assert len(rows) == len(texts)
    for r in rows:
        assert r.score == pytest.approx(score(brute_slots(texts[r.doc_id])), abs=1e-4) and r.predicted == (r.score >= 0.5)
        assert r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 3 == 1)


def test_ftrl_separates():
    config = quality.QualityConfig(bits=12, updates=400)
    hasher = quality.NgramHasher(12)
    data = [(i % 2, hasher.slots(("good fine text " if i % 2 else "spam !! buy ") + f"w{i}")) for i in range(40)]
    weights = quality.ftrl_fit(data, config)
    assert quality.score_text(weights, hasher, "good fine text") > 0.5 > quality.score_text(weights, hasher, "spam !! buy")


def test_repetition_has_slots_of_its_own():
    hasher = quality.NgramHasher(18)
    assert hasher.slots(" \n").size == hasher.slots("").size == hasher.slots(None).size == 0
    data = [(0, " ".join([f"v{i}"] * 40)) for i in range(40)] + [(1, " ".join(f"v{(i * j) % 997}" for j in range(1, 41))) for i in range(1, 41)]
    weights = quality.ftrl_fit([(y, hasher.slots(x)) for y, x in sorted(data, key=lambda x: x[1])], quality.QualityConfig(updates=2_000))
    assert quality.score_text(weights, hasher, "unseen " * 60) < 0.5 < quality.score_text(weights, hasher, " ".join(f"fresh{k}" for k in range(60)))


# --- exact dedup ---


@pytest.mark.parametrize("trie_bytes,owner_bytes", [(exact_dedup.TRIE_BYTES, exact_dedup.OWNER_BYTES), (2_000, 1_000)])
def test_exact_groups(docs, empty, trie_bytes, owner_bytes):
    rows = exact_dedup.exact_groups(docs, ["doc_id"], trie_bytes, owner_bytes).collect()
    groups: dict = {}
    for i, t, _ in TEXTS:
        groups.setdefault(normal(t), []).append(i)
    want = []
    for text, ids in groups.items():
        known = [i for i in ids if i is not None]
        keep = min(known, default=None)
        kept_once = False
        for i in sorted(ids, key=lambda x: (x is None, x)):
            kept = i == keep and not kept_once
            kept_once |= kept
            want.append((str(i), str(keep), len(ids), kept, hashlib.sha256(text.encode()).hexdigest()))
    assert sorted((str(r.doc_id), str(r.keep_id), r.group_size, r.kept, r.text_sha256) for r in rows) == sorted(want)
    assert exact_dedup.exact_groups(empty, ["doc_id"]).count() == 0
    assert exact_dedup.exact_groups(docs).count() == len(TEXTS)


def test_trie_against_a_dictionary():
    rng = np.random.default_rng(0)
    keys = [bytes(rng.integers(97, 99, rng.integers(0, 12)).astype(np.uint8)) for _ in range(500)]
    trie, want = exact_dedup.PatriciaTrie(), {}
    got: dict = {}
    for owner, key in enumerate(keys):
        trie.insert(key, 500 - owner)
        low, n = want.get(key, (10**9, 0))
        want[key] = (min(low, 500 - owner), n + 1)
        if owner % 97 == 0:
            prefix, terminals = trie.cut()
            for k, o, _, n in terminals:
                assert k.startswith(prefix)
                low, m = got.get(k, (10**9, 0))
                got[k] = (min(low, o), m + n)
    for k, o, _, n in trie.drain():
        low, m = got.get(k, (10**9, 0))
        got[k] = (min(low, o), m + n)
    assert got == want


def test_one_trie_holds_a_partition_and_spills_by_subtree():
    """Strings with common beginnings share nodes; what is below a cut prefix leaves unfinished, the rest is owned, nothing is lost."""
    import pyarrow as pa

    rng = np.random.default_rng(2)
    keys = [b"shared beginning " + bytes(rng.integers(97, 100, rng.integers(1, 9)).astype(np.uint8)) for _ in range(600)]
    trie = exact_dedup.PatriciaTrie()
    for k, key in enumerate(keys):
        trie.insert(key, k)
    assert trie.size < len(set(keys)) * 2 * exact_dedup.NODE_BYTES and len(trie.root.children) == 1
    rows = [(key, None if k % 7 == 0 else 600 - k, 1, 1) for k, key in enumerate(keys)]
    for limit in (1 << 20, 30_000, 500):
        batches = list(exact_dedup.in_chunks(iter(rows), exact_dedup.LOCAL_SCHEMA))
        out = pa.Table.from_batches(exact_dedup.owner_side(limit)(iter(batches))).to_pylist()
        open_keys = {r["body"] for r in out if r["body"] is not None}
        done = {r["digest"]: r for r in out if r["body"] is None}
        assert (limit == 1 << 20) == (not open_keys) and sum(r["group_size"] for r in out) == 600
        for key in set(keys) - open_keys:
            mine = [600 - k for k, x in enumerate(keys) if x == key and k % 7]
            r = done[hashlib.sha256(key).digest()]
            assert r["keep_id"] == min(mine, default=None) and r["group_size"] == keys.count(key)
        assert not {hashlib.sha256(k).digest() for k in open_keys} & done.keys()


def test_kept_rows_are_those_of_the_groups(docs, real, empty):
    """kept_rows returns the input's columns, clashing ones too, and the rows that exact_groups marks."""
    for df in (docs, real, docs.unionAll(docs)):
        marked = exact_dedup.exact_groups(df.select("doc_id", "text"))
        want = sorted(str((r.doc_id, r.text)) for r in marked.where("kept").collect())
        out = exact_dedup.kept_rows(df)
        # of rows that repeat id and normalised text, any one may stay
        assert out.columns == df.columns and sorted(str((r.doc_id, normal(r.text))) for r in out.collect()) == sorted(str((i, normal(t))) for i, t in map(lambda r: (r.doc_id, r.text), marked.where("kept").collect())) and len(want) == out.count()
    assert {r.keep_id for r in exact_dedup.kept_rows(docs).collect()} == {"x"}
    assert exact_dedup.kept_rows(empty).count() == 0


# --- rules ---


def brute_measures(text):
    text, w = text or "", words(text)
    at: dict = {}
    for k in range(len(w) - 2):
        at.setdefault(tuple(w[k : k + 3]), []).append(k)
    covered = {k + j for v in at.values() if len(v) > 1 for k in v for j in range(3)}
    seen, dup = set(), 0
    for line in text.split("\n"):
        dup += bool(words(line)) and line in seen
        seen.add(line)
    return len(w), sum(map(len, w)), sum(x in "#*$%&|<>" for x in text), dup, len(covered)


def test_rule_measures(docs, real, empty):
    for df in (docs, real):
        rows = rules.quality_rules(df).collect()
        texts = [(r.doc_id, r.text) for r in df.collect()]
        assert sorted(map(str, [(i, *brute_measures(t)) for i, t in texts])) == sorted(str((r.doc_id, r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words)) for r in rows)
        assert all(r.base_failed == (r.n_words < 50 or 100 * r.n_repeat_words > 50 * r.n_words) for r in rows)
        assert not any(r.kept and r.base_failed for r in rows)
    assert rules.quality_rules(empty).count() == 0


def test_verdict_does_not_depend_on_order(real):
    texts = [r.text.encode() for r in real.limit(60).collect()]
    for text in texts:
        m = rules.measure(text)
        assert (rules.first_rejection(m, list(rules.RULES)) is None) == (rules.first_rejection(m, list(reversed(rules.RULES))) is None)
    order = rules.plan_order(rules.trials(texts))
    assert [x["rank"] for x in order] == sorted((x["rank"] for x in order), reverse=True)
    named = lambda df: sorted(str((r.doc_id, r.rejected_by)) for r in rules.quality_rules(df).collect())
    assert named(real) == named(real.repartition(5))


def test_letters_are_those_of_the_categories(spark, real):
    """Powers, fractions and circled letters are no letters; capitals are Lu alone. The order of the rules comes from counts over the sample."""
    import unicodedata

    texts = [" ".join(["²½ ¾¼"] * 40), " ".join(["Ⓐ① ab"] * 40), " ".join(f"ÄÖ{k} ªº" for k in range(40)), " ".join(f"ǅ{k} Ab" for k in range(40)), " ".join(f"日本{k} ǅZz" for k in range(60))]
    for text in texts + [r.text for r in real.limit(60).collect()]:
        m = rules.measure(text.encode())
        kinds = [unicodedata.category(x) for x in text]
        lettered = sum(any(unicodedata.category(x)[0] == "L" for x in w) for w in words(text))
        assert rules.few_words_with_letters(m) == (10 * lettered < 7 * len(m.words)) and rules.shouting(m) == (kinds.count("Lu") > kinds.count("Ll"))


# --- tokens, packing, files ---


@pytest.mark.parametrize("name", ["byte_bpe_50k.json", "word_bpe_49k.json"])
def test_memo_encoder_equals_the_library(name, real):
    import random

    rnd = random.Random(3)
    plain = Tokenizer.from_file(public_tokenizers.path(name))
    alphabet = "ab C1'!*\n\t é 日İΣ_<|> \x1c\x01"
    texts = ["", " ", "a ", " a", "a  b", "a\n b", LONG[:5000], "x" * 700 + " y"] + ["".join(rnd.choice(alphabet) for _ in range(rnd.randint(1, 40))) for _ in range(1500)] + [r.text for r in real.limit(50).collect()]
    ascii_marks = "aZÉßſŉǰ 's'll'D 09!\"#'_`~{}\t\n\r  "
    texts += ["".join(rnd.choice(ascii_marks) for _ in range(rnd.randint(1, 60))) for _ in range(3000)]
    anywhere = lambda: chr(rnd.choice([32, 32, 10, 39, 65, 97, 0x301, 0x18F, 0x130, rnd.randint(1, 0x24F), rnd.randint(1, 0x2FFF), rnd.randint(0xE000, 0x10FFFF)]))
    odd = ["<|endoftext|>", "<|startoftext|>", "<|ENDOFTEXT|>", "<|", "Ə", "Ʒ", "Ⱥ"]
    texts += ["".join(rnd.choice(odd) if rnd.random() < 0.03 else anywhere() for _ in range(rnd.randint(1, 40))) for _ in range(20_000)] + ["Əli", "Ʒ", "Ə 日"]
    texts += ["\n" * 500 + "a", " " * 300, "a" + "\n " * 200, "9" * 400, "!" * 400 + "'s", "l'eau d'Or I'LL we've", "\r\n\r\nx"]
    want = [pack(x.ids) for x in plain.encode_batch(texts, add_special_tokens=False)]
    assert MemoEncoder(public_tokenizers.path(name)).encode_all(texts) == want
    small = MemoEncoder(public_tokenizers.path(name), limit=50)
    assert small.encode_all(texts[:800]) + small.encode_all(texts[800:]) == want
    plain.encode_special_tokens = True
    assert MemoEncoder(public_tokenizers.path(name), strings_as_text=True).encode_all(texts) == [pack(x.ids) for x in plain.encode_batch(texts, add_special_tokens=False)]


LIBRARY = {name: Tokenizer.from_file(public_tokenizers.path(name)) for name in ("byte_bpe_50k.json", "word_bpe_49k.json")}


def ids_of(name, text, end):
    return [*LIBRARY[name].encode(text or "", add_special_tokens=False).ids, end]


def test_whole_table_of_token_files_and_pieces(spark, sf, real):
    """op4 and op6 over all documents against plain calls of the library, and sequences against best-fit over single pieces."""
    texts = {r.doc_id: r.text for r in real.collect()}
    at = 0
    for r in sorted(QUERIES["op6_token_files"](spark, sf).collect(), key=lambda r: r.doc_id):
        ids = ids_of("word_bpe_49k.json", texts[r.doc_id], 2)
        assert (r.start, r.n_tokens, r.ids_crc32) == (at, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes()))
        at += len(ids)
    rows = QUERIES["op4_best_fit_packing"](spark, sf).collect()
    pieces: dict = {}
    for r in rows:
        pieces.setdefault(r.doc_id, []).append(r)
    lengths = []
    for i, text in texts.items():
        ids, done = ids_of("byte_bpe_50k.json", text, 0), 0
        for k, r in enumerate(sorted(pieces[i], key=lambda r: r.piece)):
            assert (r.piece, r.start, r.ids_crc32) == (k, done, zlib.crc32(np.array(ids[done : done + r.length], "<u4").tobytes()))
            lengths.append(r.length)
            done += r.length
        assert done == len(ids)
    assert len({r.sequence_id for r in rows}) == plain_best_fit(lengths, 2048)


def plain_best_fit(lengths, capacity):
    free: list[int] = []
    for n in sorted(lengths, reverse=True):
        fits = [x for x in free if x >= n]
        if fits:
            free[free.index(min(fits))] -= n
        else:
            free.append(capacity - n)
    return len(free)


def test_packing(docs, empty):
    path = public_tokenizers.path("byte_bpe_50k.json")
    rows = packing.best_fit_pack(docs, path).collect()
    got: dict = {}
    for r in rows:
        got.setdefault(r.doc_id, []).append(r)
    for i, t, _ in TEXTS:
        if i in (None, 11):
            continue
        ids, at = ids_of("byte_bpe_50k.json", t, 0), 0
        for k, r in enumerate(sorted(got[i], key=lambda r: r.piece)):
            assert (r.piece, r.start) == (k, at) and r.ids_crc32 == zlib.crc32(np.array(ids[at : at + r.length], "<u4").tobytes())
            assert r.length == 2048 or k == 0
            at += r.length
        assert at == len(ids)
    assert len(got[11]) == 2 and len(got[None]) == 2
    by_seq: dict = {}
    for r in rows:
        by_seq.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for items in by_seq.values():
        at = 0
        for offset, length in sorted(items):
            assert offset == at
            at += length
        assert at <= 2048
    assert packing.best_fit_pack(empty, path).count() == 0


def test_best_fit_plan_against_documents():
    """Planning over counts opens as many sequences as best-fit over single pieces, longest first."""
    rng = np.random.default_rng(1)
    lengths = rng.integers(1, 60, 400)
    rows, opened = packing.best_fit_plan({int(n): int(c) for n, c in zip(*np.unique(lengths, return_counts=True), strict=True)}, 64)
    assert opened == plain_best_fit(lengths.tolist(), 64)
    assert sum(r.count for r in rows) == 400


def test_ranges_ascend_and_split_repeated_ids(spark):
    """Every row's range, for few and many bounds: ranges ascend with the id, an id of several ranges fills them, nulls come first."""
    rng = np.random.default_rng(4)
    ids = sorted([*rng.integers(-50, 5000, 400).tolist(), *[77] * 500, *[4000] * 120])
    df = spark.createDataFrame([(i, f"t{k}") for k, i in enumerate([*ids, *[None] * 90])], "doc_id long, text string")
    for n in (1, 3, 40, 300):
        bounds = [ids[len(ids) * k // n] for k in range(1, n)]
        rows = df.select("doc_id", token_files.range_number(F.col("doc_id"), F.col("text"), bounds, 3).alias("at")).collect()
        assert {r.at for r in rows if r.doc_id is None} == {0, 1, 2}
        named = sorted((r.at, r.doc_id) for r in rows if r.doc_id is not None)
        assert [i for _, i in named] == ids and named[0][0] >= 3 and named[-1][0] <= 3 + len(bounds)
        if n == 40:
            assert len({at for at, i in named if i == 77}) == bounds.count(77) > 10


def test_token_files(spark, docs, empty, tmp_path):
    path = public_tokenizers.path("word_bpe_49k.json")
    token_files.write_token_files(docs, str(tmp_path / "t"), path)
    rows = sorted(token_files.token_digest(spark, str(tmp_path / "t")).collect(), key=lambda r: r.start)
    assert [r.doc_id for r in rows] == sorted((i for i, _, _ in TEXTS), key=lambda i: (i is not None, i))
    at, texts = 0, {i: t for i, t, _ in TEXTS}
    for r in rows:
        assert r.start == at
        at += r.n_tokens
        if r.doc_id is not None:
            ids = ids_of("word_bpe_49k.json", texts[r.doc_id], 2)
            assert (r.n_tokens, r.ids_crc32) == (len(ids), zlib.crc32(np.array(ids, "<u4").tobytes()))
    assert [r.n_tokens for r in token_files.lookup(spark, str(tmp_path / "t"), 9).collect()] == [len(ids_of("word_bpe_49k.json", "word", 2))]
    raw = next(p for p in (tmp_path / "t").iterdir() if p.suffix == ".orc" and p.stat().st_size > 500)
    assert raw.read_bytes()[:3] == b"ORC"
    assert token_files.token_round_trip(empty, path).count() == 0


# --- near duplicates ---


def brute_fingerprint(text):
    w = re.findall(rb"[^\x20\x09-\x0D]+", re.sub(rb"[A-Z]", lambda m: m[0].lower(), (text or "").encode()))
    if not w:
        return 0
    grams = [b" ".join(w[i : i + 4]) for i in range(max(1, len(w) - 3))]
    counts = [0] * 64
    for g in grams:
        h = xxhash.xxh64_intdigest(g, 42)
        for b in range(64):
            counts[b] += h >> b & 1
    return sum(1 << b for b in range(64) if 2 * counts[b] > len(grams))


def brute_components(ids, prints):
    parent = list(range(len(ids)))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i in range(len(ids)):
        for j in range(i):
            if (prints[i] ^ prints[j]).bit_count() <= 4:
                a, b = find(i), find(j)
                parent[max(a, b)] = min(a, b)
    least: dict = {}
    for k, i in enumerate(ids):
        if i is not None:
            least[find(k)] = min(i, least.get(find(k), i))
    return [least.get(find(k)) for k in range(len(ids))]


def test_simhash(docs, real, empty):
    for df in (docs, real):
        pairs = [(r.doc_id, r.text) for r in df.collect()]
        prints = [brute_fingerprint(t) for _, t in pairs]
        want = brute_components([i for i, _ in pairs], prints)
        got = simhash.near_duplicates(df, block=64).collect()
        assert sorted(map(str, zip([i for i, _ in pairs], [f"{p:016x}" for p in prints], want, strict=True))) == sorted(str((r.doc_id, r.fingerprint, r.component_id)) for r in got)
    assert simhash.near_duplicates(empty).count() == 0


def test_fingerprint_hash_is_the_engines(spark):
    row = spark.sql("SELECT xxhash64('a b c d') AS h").first()
    assert simhash.shingle_hashes(b"A b\tc d").view(np.int64)[0] == row["h"]


def test_search_loses_no_link(spark):
    """Clusters of every spread around random centres: components equal brute force whatever the thresholds."""
    rng = np.random.default_rng(7)
    prints = []
    for _ in range(40):
        centre = int(rng.integers(0, 2**63))
        for _ in range(12):
            x = centre
            for b in rng.choice(64, rng.integers(0, 4), replace=False):
                x ^= 1 << int(b)
            prints.append(x)
    prints = list(dict.fromkeys(prints))
    signed = np.array(prints, dtype=np.uint64).view(np.int64).tolist()
    df = spark.createDataFrame([(x,) for x in signed], "fp long")
    want = brute_components(list(range(len(prints))), prints)
    n, both = simhash.bit_counts(df)
    assert n == len(prints)
    plans = [simhash.plan_thresholds(n, both), simhash.plan_thresholds(10**10, both / n * 1e10), [(list(range(32)), 2), (list(range(32, 64)), 1)], [(list(range(16 * k, 16 * k + 16)), int(k == 0)) for k in range(4)]]
    for plan in plans:
        assert sum(t for _, t in plan) == 4 - len(plan) + 1 and sorted(b for bits, _ in plan for b in bits) == list(range(64))
        for block in (16, 4096):
            roots = {r.node: r.root for r in components.components(simhash.link_edges(df, plan, block=block)).collect()}
            labels = [roots.get(x, x) for x in signed]
            first: dict = {}
            assert [first.setdefault(x, k) for k, x in enumerate(labels)] == want


def test_long_chain_components(spark):
    edges = spark.range(0, 300).select(F.col("id").alias("u"), (F.col("id") + 1).alias("v")).repartition(7)
    assert {r.root for r in components.components(edges).collect()} == {0}
    assert components.components(edges.limit(0)).count() == 0


# --- mixing ---


def brute_targets(sizes: dict, share=1.5, limit=2.0):
    order = sorted(sizes, key=lambda s: (s is None, s or ""))
    weight = {s: (5, 2, 1)[k % 3] for k, s in enumerate(order)}
    target, left, rest = {}, set(order), share * sum(sizes.values())
    while left:
        unit = rest / sum(weight[s] for s in left)
        over = [s for s in left if unit * weight[s] > limit * sizes[s]]
        if not over:
            return target | {s: unit * weight[s] for s in left}
        for s in over:
            target[s] = limit * sizes[s]
            rest -= target[s]
            left.discard(s)
    return target


def test_mixing(docs, real, empty):
    for df in (docs, real):
        pairs = [(r.doc_id, r.text, r.source) for r in df.collect()]
        sizes: dict = {}
        for _, t, s in pairs:
            sizes[s] = sizes.get(s, 0) + len(words(t))
        want = brute_targets(sizes)
        rows = mixing.systematic_mix(df, ["doc_id", "source"]).collect()
        assert len(rows) == len(pairs)
        taken: dict = {}
        for r in rows:
            assert r.source_size == sizes[r.source] and r.target == pytest.approx(want[r.source]) and r.taken <= 2 * r["size"]
            taken[r.source] = taken.get(r.source, 0) + r.taken
        largest: dict = {}
        for _, t, s in pairs:
            largest[s] = max(largest.get(s, 0), len(words(t)))
        assert all(abs(taken[s] - want[s]) <= largest[s] + 1e-6 for s in sizes)
        again = mixing.systematic_mix(df.repartition(5), ["doc_id", "source"]).collect()
        assert sorted(map(str, rows)) == sorted(map(str, again))
    assert mixing.systematic_mix(empty, ["doc_id"]).count() == 0


# --- pages and urls ---

PAGES = [
    (1, "http://a.Example.COM/en/x?q", "<nav>menu</nav><article><h1>T &amp; t</h1><p>One <b>two</b>.<br>Three<p>Four</article><footer>f</footer>"),
    (2, None, None), (3, "no scheme", ""), (4, "https://WWW.example.com/en/", "<div class='comments'><p>hi</p></div><script>if (a<b) {}</script>"),
    (5, "https://spam-farm.example.org", "<header>H</header><p>Plain body text that is long enough to count here.</p><aside>x</aside>"),
    (6, "ftp://b.net/es/", "<article><p>A&nbsp; b</p><aside>ad</aside><form>f</form><p>x</p></article>"), (None, "http://x.net/fr", "<p>unclosed <![weird"), (6, "http://[::1]/a#b", "&lt;p&gt; only text"),
    (7, "https://www.spam-farm.example.org/a?b", "<main><article><header><h1>Head</h1></header><p>body</p></article></main>"),
]


@pytest.fixture(scope="module")
def pages(spark):
    return spark.createDataFrame([(*p, "x", "y") for p in PAGES], "page_id long, url string, html string, text string, host string")


def test_main_text(pages, spark, sf):
    got = {(r.page_id, r.url): r.text for r in html_text.extract_pages(pages).collect()}
    assert got[1, PAGES[0][1]] == "T & t\nOne two. Three\nFour"
    assert got[2, None] == "" and got[3, "no scheme"] == "" and got[4, PAGES[3][1]] == ""
    assert got[5, PAGES[4][1]] == "Plain body text that is long enough to count here."
    assert got[6, "ftp://b.net/es/"] == "A b\nx" and got[7, PAGES[8][1]] == "Head\nbody"
    assert html_text.extract_pages(pages.limit(0)).count() == 0
    real = spark.read.parquet(f"{sf}/pages.parquet")
    found = {r.page_id: r for r in html_text.extract_pages(real).collect()}
    for r in real.collect():
        inside = re.search(r"<article>(.*?)</article>", r.html, re.S)[1].replace("<br>", " ")
        blocks = [" ".join(html.unescape(re.sub(r"<[^>]+>", "", b)).split()) for b in re.split(r"</?(?:p|h1)>", inside)]
        text = "\n".join(b for b in blocks if b)
        assert found[r.page_id].text == text and found[r.page_id].n_chars == len(text)


def brute_url(url):
    m = re.match(r"(?s).*?://([^/?#]*)([^?#]*)", url or "")
    host, path = (re.sub("[A-Z]", lambda x: x[0].lower(), m[1]), m[2]) if m else ("", "")

    def best(entries):
        fits = [(len(k), k, v) for k, v in entries if (host == k.split("/")[0] or host.endswith("." + k.split("/")[0])) and path.startswith(k[k.index("/") :])]
        return max(fits, default=None)

    rule, listed = best(urls.RULES), best([(k, "block") for k in urls.LISTED])
    return host, path, rule and rule[1], rule[2] if rule else "block" if listed else "allow"


def test_urls(spark, pages, sf):
    listed = urls.entries(spark, urls.RULES, urls.LISTED)
    for df in (pages, spark.read.parquet(f"{sf}/pages.parquet")):
        want = sorted(str((r.page_id, *brute_url(r.url))) for r in df.collect())
        assert sorted(str((r.page_id, r.host, r.path, r.rule, r.verdict)) for r in urls.judge_urls(df, listed).collect()) == want
    assert {r.verdict for r in urls.judge_urls(pages, urls.entries(spark, (), ())).collect()} == {"allow"}
    assert urls.judge_urls(pages.limit(0), listed).count() == 0


def test_bloom_has_no_false_negatives_and_few_false_positives(spark):
    keys = spark.range(2000).select(F.concat(F.lit("k"), "id").alias("key"))
    bloom = urls.blocked_bloom(keys, 125)
    asked = spark.range(6000).select(F.concat(F.lit("k"), "id").alias("key"), "id")
    block, bits = urls.bloom_bits(F.col("key"), 125)
    hit = asked.select("id", block.alias("block"), *(b.alias(f"b{k}") for k, b in enumerate(bits))).join(bloom, "block").where(" AND ".join(f"(w{k} & b{k}) != 0" for k in range(4)))
    ids = [r.id for r in hit.collect()]
    assert {i for i in ids if i < 2000} == set(range(2000)) and sum(i >= 2000 for i in ids) < 400


# --- shards ---


def test_shards(docs, real, empty):
    for df in (docs, real):
        rows = shards.shard_rows(df).collect()
        texts = sorted(str((r.doc_id, len((r.text or "").encode()) + 1, zlib.crc32((r.text or "").encode()))) for r in df.collect())
        assert sorted(str((r.doc_id, r["size"], r.text_crc32)) for r in rows) == texts
        slots: dict = {}
        for r in rows:
            slots.setdefault(r.shard, []).append(r.slot)
        counts = [len(slots.get(s, [])) for s in range(8)]
        assert max(counts) - min(counts) <= 1 and all(sorted(v) == list(range(len(v))) for v in slots.values())
    assert shards.shard_rows(empty).count() == 0


def test_every_place_against_a_walk_of_the_ring(spark, docs, real):
    """Shards and slots of whole tables against a walk in plain Python: rows clockwise from cell 0, each to the next shard with room."""
    hot = real.limit(40).unionAll(real.limit(40)).unionAll(real.limit(1).withColumn("doc_id", F.lit(7))).unionAll(real.withColumn("doc_id", F.lit(7).cast("long")))
    for df in (docs.select("doc_id", "text"), real.select("doc_id", "text"), hot.select("doc_id", "text")):
        spots = df.select("doc_id", F.xxhash64("doc_id").alias("spot"), "text").collect()
        rows, crowd = [], {}
        for _, spot, _ in spots:
            crowd[spot % shards.CELLS] = crowd.get(spot % shards.CELLS, 0) + 1
        for i, spot, text in spots:
            body, cell = (text or "").encode(), spot % shards.CELLS
            spread = zlib.crc32(body) % 8 if crowd[cell] > max(64, 4 * len(spots) / shards.CELLS) else 0
            rows.append((cell, spread, spot, zlib.crc32(body), len(body) + 1, i))
        nodes = sorted((xxhash.xxh64_intdigest(f"{s}/{v}", 0) % shards.CELLS, s) for s in range(8) for v in range(shards.VIRTUAL_NODES))
        room = [len(rows) // 8 + (s < len(rows) % 8) for s in range(8)]
        used, want = [0] * 8, []
        for cell, _, _, code, size, i in sorted(rows, key=lambda r: r[:5]):
            ahead = [s for c, s in nodes if c >= cell] + [s for c, s in nodes if c < cell]
            shard = next(s for s in ahead if used[s] < room[s])
            want.append((i, size, code, "rows", shard, used[shard], None))
            used[shard] += 1
        got = shards.shard_rows(df).drop("is_home").collect()
        assert sorted(map(str, want)) == sorted(str(tuple(r)) for r in got)


def test_only_overflow_leaves_home():
    counts = {(c * 64, 0): 3 for c in range(1000)}
    plan = shards.plan_cells(counts, 8)
    assert sum(hi - lo for _, _, lo, hi, *_ in plan) == 3000
    home = sum(hi - lo for _, _, lo, hi, _, _, is_home in plan if is_home)
    assert home > 0.8 * 3000


# --- pipeline ---


def test_pipeline_against_brute_force(spark, sf, tmp_path):
    """Each stage on what the stage before kept, held against the plain computation of the same decision."""
    import corpus_pipeline as p

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    columns, kept = docs.columns, {}
    for k, (name, stage) in enumerate(p.STAGES):
        out = stage(spark, docs, sf)
        out.write.parquet(str(tmp_path / str(k)))
        kept[name] = (docs, spark.read.parquet(str(tmp_path / str(k))))
        if k < len(p.STAGES) - 1:
            assert out.columns == columns
        docs = kept[name][1]
    before, after = kept["quality classifier"]
    labels = {r.doc_id: r.quality for r in spark.read.parquet(f"{sf}/labels.parquet").collect()}
    gone = {r.doc_id for r in before.collect()} - {r.doc_id for r in after.collect()}
    assert sum(labels.get(i) == 1 for i in gone) <= 2
    before, after = kept["exact dedup"]
    first: dict = {}
    for r in sorted(before.collect(), key=lambda r: r.doc_id):
        first.setdefault(normal(r.text), r.doc_id)
    assert sorted(first.values()) == sorted(r.doc_id for r in after.collect())
    before, after = kept["SimHash near-dedup"]
    pairs = sorted((r.doc_id, r.text) for r in before.collect())
    assert sorted({pairs[k][0] for k in brute_groups([t for _, t in pairs])}) == sorted(r.doc_id for r in after.collect())
    before, after = kept["mixing to target weights"]
    taken = sorted(r.doc_id for r in mixing.systematic_mix(before, ["doc_id"]).collect() for _ in range(r.copies))
    assert sorted(r.doc_id for r in after.collect()) == taken
    before, after = kept["best-fit packing"]
    whole = sum(len(ids_of("byte_bpe_50k.json", r.text, 0)) for r in before.limit(10).collect())
    assert whole > 0 and after.where("piece = 0").count() == before.count()
    assert p.run(spark, sf).count() == after.count()


def test_scratch_lies_in_the_shared_folder(spark):
    from partnet.llm.common import scratch_path, shared_dir

    assert os.path.dirname(scratch_path(spark, "x")) == shared_dir(spark)
