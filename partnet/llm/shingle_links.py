"""All pairs of texts whose shingle sets reach a Jaccard similarity, as components.

Candidates come from two searches. SimHash fingerprints of the sets are linked
by generalised pigeonhole (`simhash`), which finds large groups at little cost
but, at an affordable radius, not every pair. Prefixes find the rest: two sets
with similarity 4/5 or more share at least 4/5 of the larger one, so under any
order of the shingles their first `n - ceil(4n/5) + 1` meet. Texts are filed
under those alone. Shingles in crowded cells of a count over all texts come
last; the order changes cost, not links.

Every candidate pair is checked, twice. A parity sketch of about two bits a
shingle bounds the difference of two sets from below, so a pair that it rejects
is none; what passes is compared on the whole sets, made anew from the texts.

Small buckets give their pairs. In a large one all members are first checked
against one of them, a few times over; members that are then still in different
components meet in blocks, each pair of blocks a unit of work, and only what
passes the sketch leaves it. No group is gathered.

Texts are read several times and moved once at most: a blocked Bloom filter of
fixed size tells which rows a small table can concern.

Defined results: null and empty texts have one common set; fewer words than a
shingle count as one shingle; shingles and sets are known by 64-bit hashes; an
empty table gives no rows; columns beside doc_id and text pass through.
"""

from __future__ import annotations

import itertools
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from partnet.llm.bloom import concerned, one_row_each
from partnet.llm.common import STEP_ROWS, map_rows, materialize, texts_as_bytes, tidy
from partnet.llm.components import components
from partnet.llm.simhash import bit_counts, link_edges, majority_bits, plan_thresholds

#: similarity as a fraction of whole numbers, so that the border is exact
TOP, BOTTOM = 4, 5
CELL_BITS = 16
SMALL = 32
STAR_ROUNDS = 2
UNIT_BLOCK = 512
WORD_CACHE = 40_000
FACTOR = np.uint64(0x9E3779B97F4A7C15)


class Shingler:
    """Hashed word shingles of a text, A-Z lower-cased. Hashes of words are cached up to a fixed number."""

    def __init__(self, shingle: int = 5):
        self.shingle, self.seen = shingle, {}

    def set_of(self, text: bytes) -> np.ndarray:
        """Sorted distinct hashes."""
        words = text.lower().split()  # for bytes: A-Z only, and exactly the contract's white space
        if not words:
            return np.zeros(1, dtype=np.uint64)
        if len(self.seen) > WORD_CACHE:
            self.seen = {}
        seen = self.seen
        for x in set(words).difference(seen):
            seen[x] = xxhash.xxh3_64_intdigest(x)
        w = np.fromiter(map(seen.__getitem__, words), dtype=np.uint64, count=len(words))
        k = min(self.shingle, w.size)
        n = w.size - k + 1
        h = w[:n] + np.uint64(k)
        for i in range(1, k):
            h = h * FACTOR + w[i : i + n]
        h ^= h >> np.uint64(30)
        h *= np.uint64(0xBF58476D1CE4E5B9)
        h ^= h >> np.uint64(27)
        h *= np.uint64(0x94D049BB133111EB)
        return np.unique(h ^ (h >> np.uint64(31)))


def cell_of(hashes: np.ndarray) -> np.ndarray:
    return (hashes >> np.uint64(64 - CELL_BITS)).astype(np.int64)


def prefix_of(found: np.ndarray, loads: np.ndarray) -> np.ndarray:
    n = found.size
    return found[np.argsort(loads[cell_of(found)], kind="stable")[: n - -(-TOP * n // BOTTOM) + 1]]


def sketch_of(found: np.ndarray) -> bytes:
    """For each of 2n bits or more, a power of two: whether an odd number of the set's hashes falls on it."""
    bits = max(64, 1 << int(2 * found.size - 1).bit_length())
    odd = np.bincount((found & np.uint64(bits - 1)).astype(np.int64), minlength=bits) & 1
    return np.packbits(odd.astype(np.uint8), bitorder="little").tobytes()


def folded(sketch: np.ndarray, words: int) -> np.ndarray:
    """The sketch of the same set with fewer bits: halves laid over each other. Last axis: 64-bit words."""
    while sketch.shape[-1] > words:
        half = sketch.shape[-1] // 2
        sketch = sketch[..., :half] ^ sketch[..., half:]
    return sketch


def may_be_alike(n: int, m: int, x: bytes, y: bytes) -> bool:
    """False only for sets below the similarity. Bits that differ in parity never outnumber the hashes that differ."""
    if BOTTOM * min(n, m) < TOP * max(n, m):
        return False
    a, b = np.frombuffer(x, np.uint64), np.frombuffer(y, np.uint64)
    words = min(a.size, b.size)
    return bool((TOP + BOTTOM) * int(np.bitwise_count(folded(a, words) ^ folded(b, words)).sum()) <= (BOTTOM - TOP) * (n + m))


def prints(documents: DataFrame, shingle: int = 5) -> DataFrame:
    """A row for each document: doc_id, h (hash of the text), node (hash of the set), n, fp, sketch; and rows (cell, load) with nulls in these."""
    kind = dict(documents.dtypes)["doc_id"]
    read = documents.select("doc_id", F.xxhash64("text").alias("h"), F.col("text").cast("binary").alias("text"))
    names = ["doc_id", "h", "node", "n", "fp", "sketch", "cell", "load"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        made, total, id_type = Shingler(shingle), np.zeros(1 << CELL_BITS, dtype=np.int64), None
        for whole in batches:
            id_type = whole["doc_id"].type
            for at in range(0, whole.num_rows, STEP_ROWS):
                batch = whole.slice(at, STEP_ROWS)
                sets = [made.set_of(x) for x in texts_as_bytes(batch["text"])]
                total += np.bincount(cell_of(np.concatenate(sets)), minlength=total.size)
                nodes = np.array([xxhash.xxh3_64_intdigest(x.tobytes()) for x in sets], dtype=np.uint64).view(np.int64)
                fps = np.array([majority_bits(x) for x in sets], dtype=np.uint64).view(np.int64)
                cols = [batch["doc_id"], batch["h"], pa.array(nodes), pa.array([x.size for x in sets], pa.int64()), pa.array(fps), pa.array(list(map(sketch_of, sets)), pa.binary())]
                yield pa.RecordBatch.from_arrays([*cols, pa.nulls(len(sets), pa.int64()), pa.nulls(len(sets), pa.int64())], names)
        cells = np.flatnonzero(total)
        if cells.size:
            none = [pa.nulls(cells.size, t) for t in (id_type, pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.binary())]
            yield pa.RecordBatch.from_arrays([*none, pa.array(cells), pa.array(total[cells])], names)

    return read.mapInArrow(tidy(run), f"doc_id {kind}, h long, node long, n long, fp long, sketch binary, cell long, load long")


def cell_loads(printed: DataFrame) -> np.ndarray:
    """Shingles of all texts by cell of their hash; as many numbers as there are cells, whatever the texts."""
    rows = printed.where("cell IS NOT NULL").groupBy("cell").agg(F.sum("load").alias("load")).toPandas()
    loads = np.zeros(1 << CELL_BITS, dtype=np.int64)
    loads[rows["cell"].to_numpy(dtype=np.int64)] = rows["load"].to_numpy(dtype=np.int64)
    return loads


def filed(documents: DataFrame, loads: np.ndarray, shingle: int = 5) -> DataFrame:
    """(key, node) for each shingle of a text's prefix."""
    shared = documents.sparkSession.sparkContext.broadcast(loads)

    def start():
        made = Shingler(shingle)

        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            sets = [made.set_of(x) for x in texts_as_bytes(batch["text"])]
            nodes = np.array([xxhash.xxh3_64_intdigest(x.tobytes()) for x in sets], dtype=np.uint64).view(np.int64)
            parts = [prefix_of(x, shared.value) for x in sets]
            return pa.RecordBatch.from_arrays([pa.array(np.concatenate(parts).view(np.int64)), pa.array(np.repeat(nodes, [x.size for x in parts]))], ["key", "node"])

        return step

    return map_rows(documents.select(F.col("text").cast("binary").alias("text")), start, "key long, node long")


def whole_sets(documents: DataFrame, printed: DataFrame, nodes: DataFrame, shingle: int = 5) -> DataFrame:
    """(node, found) of the nodes asked for, from one text of each."""
    asked = materialize(printed.join(nodes, "node", "left_semi").groupBy("node").agg(F.min("h").alias("h")), "near-asked")
    made_of = concerned(documents.select("text", F.xxhash64("text").alias("h")), F.col("h"), asked.select(F.col("h").alias("key")), "near__hit").where("near__hit").select("h", F.col("text").cast("binary").alias("text"))

    def start():
        made = Shingler(shingle)

        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([batch["node"], pa.array([made.set_of(x).tobytes() for x in texts_as_bytes(batch["text"])], pa.binary())], ["node", "found"])

        return step

    # equal texts are one row for each task before they move
    texts = made_of.groupBy("h").agg(F.first("text").alias("text")).join(asked, "h")
    return map_rows(texts.select("node", "text"), start, "node long, found binary")


def checked(pairs: DataFrame, documents: DataFrame, printed: DataFrame, shingle: int = 5) -> DataFrame:
    """The pairs (a, b) of nodes whose whole sets reach the similarity, as (u, v)."""
    nodes = pairs.select(F.explode(F.array("a", "b")).alias("node")).distinct()
    held = materialize(printed.select("node", "n", "sketch").join(nodes, "node", "left_semi").dropDuplicates(["node"]), "near-sketches")
    side = lambda k, m, s: held.select(F.col("node").alias(k), F.col("n").alias(m), F.col("sketch").alias(s))

    def bound():
        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            keep = [may_be_alike(*x) for x in zip(*(batch[c].to_pylist() for c in ("n", "m", "x", "y")), strict=True)]
            return batch.select(["a", "b"]).filter(pa.array(keep, pa.bool_()))

        return step

    def check():
        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            keep = []
            for x, y in zip(batch["x"].to_pylist(), batch["y"].to_pylist(), strict=True):
                x, y = np.frombuffer(x, np.uint64), np.frombuffer(y, np.uint64)
                both = np.intersect1d(x, y, assume_unique=True).size
                keep.append(BOTTOM * both >= TOP * (x.size + y.size - both))
            return batch.select(["u", "v"]).filter(pa.array(keep, pa.bool_()))

        return step

    left = materialize(map_rows(pairs.join(side("a", "n", "x"), "a").join(side("b", "m", "y"), "b").select("a", "b", "n", "m", "x", "y"), bound, "a long, b long"), "near-likely")
    sets = materialize(whole_sets(documents, printed, left.select(F.explode(F.array("a", "b")).alias("node")).distinct(), shingle), "near-sets")
    x, y = sets.select(F.col("node").alias("a"), F.col("found").alias("x")), sets.select(F.col("node").alias("b"), F.col("found").alias("y"))
    return map_rows(left.join(x, "a").join(y, "b").select(F.col("a").alias("u"), F.col("b").alias("v"), "x", "y"), check, "u long, v long")


def print_pairs(printed: DataFrame, distance: int = 4) -> DataFrame:
    """(a, b): one node of each linked pair of fingerprints, and of each fingerprint with its other nodes."""
    nodes = printed.where("node IS NOT NULL").select("fp", "node").distinct()
    one = materialize(nodes.groupBy("fp").agg(F.min("node").alias("one")), "near-prints-of")
    n, both = bit_counts(one)
    edges = link_edges(one, plan_thresholds(n, both, distance), distance)
    ends = edges.join(one.select(F.col("fp").alias("u"), F.col("one").alias("a")), "u").join(one.select(F.col("fp").alias("v"), F.col("one").alias("b")), "v")
    same = nodes.join(one, "fp").where("node != one").select(F.col("one").alias("a"), F.col("node").alias("b"))
    return ends.select("a", "b").unionAll(same).select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))


def small_pairs(members: DataFrame) -> DataFrame:
    """(a, b) of all members (key, node) of buckets with few of them."""
    x, y = (members.select("key", F.col("node").alias(k)) for k in "ab")
    return x.join(y, "key").where(F.col("a") < F.col("b")).select("a", "b")


def star_pairs(members: DataFrame, salt: int) -> DataFrame:
    """(a, b) of one member of each bucket, another for each salt, with all that are not yet with it.

    The first is the member with most of its prefix in large buckets: copies that were changed much have rare shingles there instead,
    so it is nearest to the others.
    """
    order = F.struct((-F.col("score") if not salt else F.lit(0)).alias("s"), F.xxhash64("node", F.lit(salt)).alias("h"), "node", "root")
    centre = materialize(members.groupBy("key").agg(F.min(order).alias("c")).select("key", F.col("c.node").alias("centre"), F.col("c.root").alias("its")), "near-centres")
    met = members.join(centre, "key").where("root != its")
    return met.select(F.least("node", "centre").alias("a"), F.greatest("node", "centre").alias("b"))


def pairs_of_unit(nodes: np.ndarray, roots: np.ndarray, sizes: np.ndarray, sketches: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Pairs of members of different components that the sketch doesn't rule out."""
    widths, us, vs = np.array([x.size for x in sketches]), [], []
    for words in np.unique(widths):
        at = np.flatnonzero((widths == words) | (widths == 2 * words))  # sizes that may be alike are at most one doubling apart
        table = np.stack([folded(sketches[i], int(words)) for i in at])
        for k in np.flatnonzero(widths[at] == words):
            i = at[k]
            alike = (roots[at] != roots[i]) & (BOTTOM * np.minimum(sizes[at], sizes[i]) >= TOP * np.maximum(sizes[at], sizes[i]))
            alike &= (widths[at] > words) | (nodes[at] > nodes[i])  # each pair once
            j = np.flatnonzero(alike)
            if j.size:
                apart = np.bitwise_count(table[j] ^ table[k]).sum(axis=1, dtype=np.int64)
                j = j[(TOP + BOTTOM) * apart <= (BOTTOM - TOP) * (sizes[at[j]] + sizes[i])]
                us.append(np.full(j.size, nodes[i]))
                vs.append(nodes[at[j]])
    empty = np.empty(0, dtype=np.int64)
    return (np.concatenate(us), np.concatenate(vs)) if us else (empty, empty)


def block_pairs(members: DataFrame, printed: DataFrame, block: int = UNIT_BLOCK) -> DataFrame:
    """(a, b) of members (key, node, root) of a bucket in different components, as far as sketches allow."""
    counts = materialize(members.groupBy("key").agg(F.ceil(F.count(F.lit(1)) / block).cast("int").alias("blocks")), "near-blocks")
    held = printed.select("node", "n", "sketch").join(members.select("node").distinct(), "node", "left_semi").dropDuplicates(["node"])
    dealt = members.join(counts, "key").join(materialize(held, "near-held"), "node").withColumn("mine", F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int"))
    units = dealt.select("key", "node", "root", "n", "sketch", "mine", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("other"))
    units = units.select("key", (F.least("mine", "other").cast("long") * 1_000_003 + F.greatest("mine", "other")).alias("unit"), "node", "root", "n", "sketch")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = (x for b in batches for x in zip(*(b[c].to_pylist() for c in ("key", "unit", "node", "root", "n", "sketch")), strict=True))
        for _, unit in itertools.groupby(rows, key=lambda x: x[:2]):
            _, _, nodes, roots, sizes, sketches = zip(*unit, strict=True)
            u, v = pairs_of_unit(np.array(nodes), np.array(roots), np.array(sizes), [np.frombuffer(x, np.uint64) for x in sketches])
            if u.size:
                yield pa.RecordBatch.from_arrays([pa.array(np.minimum(u, v)), pa.array(np.maximum(u, v))], ["a", "b"])

    return units.repartition("key", "unit").sortWithinPartitions("key", "unit").mapInArrow(tidy(run), "a long, b long")


def node_roots(documents: DataFrame, printed: DataFrame, shingle: int = 5, small: int = SMALL, distance: int = 4) -> DataFrame:
    """(node, root) of nodes in a component with others, like components()."""
    under = filed(documents, cell_loads(printed), shingle)
    met = materialize(under.groupBy("key").agg(F.count(F.lit(1)).alias("size")).where("size > 1"), "near-buckets")
    members = materialize(materialize(under.join(met, "key"), "near-filed").distinct(), "near-members")
    filed_large = members.where(F.col("size") > small).select("key", "node")
    scores = materialize(filed_large.groupBy("node").agg(F.count(F.lit(1)).alias("score")), "near-scores")
    large = materialize(filed_large.join(scores, "node").withColumn("root", F.col("node")), "near-large")
    pairs = print_pairs(printed, distance).unionAll(small_pairs(members.where(F.col("size") <= small))).unionAll(star_pairs(large, 0))
    links = materialize(checked(materialize(pairs.distinct(), "near-pairs"), documents, printed, shingle), "near-links")
    for salt in range(1, STAR_ROUNDS + 1):
        roots = components(links, "near-roots")
        now = large.drop("root").join(roots, "node", "left").withColumn("root", F.coalesce("root", "node"))
        mixed = now.groupBy("key").agg(F.min("root").alias("lo"), F.max("root").alias("hi")).where("lo < hi").select("key")
        large = materialize(now.join(materialize(mixed, "near-mixed"), "key", "left_semi").select("key", "node", "score", "root"), "near-large")
        if not large.take(1):
            return roots
        pairs = star_pairs(large, salt) if salt < STAR_ROUNDS else block_pairs(large, printed)
        links = materialize(links.unionAll(checked(materialize(pairs.distinct(), "near-pairs"), documents, printed, shingle)), "near-links")
    return components(links, "near-roots")


def similar_groups(documents: DataFrame, shingle: int = 5, small: int = SMALL) -> DataFrame:
    """The documents with root: one for each component of similar texts."""
    printed = materialize(prints(documents, shingle), "near-prints")
    roots = node_roots(documents, printed, shingle, small)
    by_text = materialize(printed.where("node IS NOT NULL").groupBy(F.col("h").alias("near__h")).agg(F.min("node").alias("node")).join(roots, "node", "left").select("near__h", F.coalesce("root", "node").alias("root")), "near-texts")
    return documents.drop("root").withColumn("near__h", F.xxhash64("text")).join(by_text, "near__h").drop("near__h")


def one_of_each(documents: DataFrame, shingle: int = 5) -> DataFrame:
    """One row of each component: least by id (null last), then by text hash, then by its other columns. Only ids and hashes are ranked, by pre-aggregated minima."""
    printed = materialize(prints(documents, shingle), "near-prints")
    roots = node_roots(documents, printed, shingle)
    named = lambda c: [F.coalesce(c.cast("string"), F.lit("")).alias("near__id"), c.isNull().alias("near__unnamed")]
    keys = ["near__h", "near__id", "near__unnamed"]
    rank = F.struct(F.col("doc_id").isNull().alias("unnamed"), "doc_id", "h")
    least = printed.where("node IS NOT NULL").groupBy("node").agg(F.min(rank).alias("least")).join(roots, "node", "left")
    stay = least.groupBy(F.coalesce("root", "node").alias("root")).agg(F.min("least").alias("least")).select(F.col("least.h").alias("near__h"), *named(F.col("least.doc_id")), F.lit(True).alias("stays"))
    counted = printed.where("node IS NOT NULL").groupBy(F.col("h").alias("near__h"), *named(F.col("doc_id"))).agg(F.count(F.lit(1)).alias("n"))
    #: rows that go, and rows of which one stays
    touched = materialize(counted.join(stay, keys, "left").where("stays IS NULL OR n > 1").select(*keys, F.coalesce("stays", F.lit(False)).alias("stays")), "near-touched")
    read = concerned(documents.withColumn("near__h", F.xxhash64("text")), F.col("near__h"), touched.select(F.col("near__h").alias("key")), "near__hit")
    hit = read.where("near__hit").select("*", *named(F.col("doc_id")))
    out = read.where("NOT near__hit").select(*documents.columns).unionAll(hit.join(touched, keys, "left_anti").select(*documents.columns))
    if not touched.where("stays").take(1):
        return out
    return out.unionAll(one_row_each(hit.join(touched.where("stays").select(*keys), keys, "left_semi"), keys, documents.columns))
