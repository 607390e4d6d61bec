"""SimHash near-dedup with generalised pigeonhole search.

A fingerprint has a bit for each bit of the shingle hashes, set if more than
half of the hashes (repeats included) set it. Bits that agree with each other
are put into the same partition; dynamic programming then gives each partition
its own threshold, from -1 (skipped) up, so that the thresholds add up to
`distance - partitions + 1` and the estimated number of candidates is least. By
the pigeonhole principle two fingerprints within `distance` are within the
threshold of at least one partition, whatever the estimates were.

Candidates meet in buckets of a partition's key. Buckets hold distinct
fingerprints only; a bucket over the block size is cut into blocks and each
pair of blocks is a unit of work of its own. Within a unit every pair is
verified on all 64 bits, but a spanning forest is all that leaves it, so a group
of k near copies costs k edges.

Defined results: null and empty texts have no words, fingerprint zero, and link
like any other; fewer words than a shingle are hashed as a whole; null ids are
never the smallest unless a group has no other; repeated rows get a row each;
an empty table gives no rows.
"""

from __future__ import annotations

import itertools
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from partnet.llm.common import map_rows, materialize, texts_as_bytes, tidy
from partnet.llm.components import components

BITS = 64
BLOCK = 4096
SMALL_RUN = 48
SLICE = 1 << 15


def shingle_hashes(text: bytes, shingle: int = 4, seed: int = 42) -> np.ndarray:
    words = text.lower().split()  # for bytes: A-Z only, and exactly the contract's white space
    if not words:
        return np.empty(0, dtype=np.uint64)
    joined, h = b" ".join(words), xxhash.xxh64_intdigest
    if len(words) <= shingle:
        return np.array([h(joined, seed)], dtype=np.uint64)
    ends = list(itertools.accumulate(len(x) + 1 for x in words))
    starts = [0, *ends[: -shingle]]
    return np.array([h(joined[a : b - 1], seed) for a, b in zip(starts, ends[shingle - 1 :], strict=True)], dtype=np.uint64)


def majority_bits(hashes: np.ndarray) -> int:
    """Bits that more than half of the hashes set; zero without any hash."""
    counts = np.zeros(BITS, dtype=np.int64)
    for at in range(0, hashes.size, SLICE):
        part = hashes[at : at + SLICE]
        counts += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    bits = np.packbits(2 * counts > hashes.size, bitorder="little")
    return int(bits.view("<u8")[0]) if hashes.size else 0


def fingerprint(text: bytes, shingle: int = 4, seed: int = 42) -> int:
    return majority_bits(shingle_hashes(text, shingle, seed))


def fingerprints(documents: DataFrame, shingle: int = 4, seed: int = 42) -> DataFrame:
    """(doc_id, fp): the fingerprint as a signed long."""

    def start():
        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            made = np.array([fingerprint(x, shingle, seed) for x in texts_as_bytes(batch["text"])], dtype=np.uint64).view(np.int64)
            return pa.RecordBatch.from_arrays([batch["doc_id"], pa.array(made)], ["doc_id", "fp"])

        return step

    return map_rows(documents.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), start, "doc_id long, fp long")


def as_bits(fps: np.ndarray) -> np.ndarray:
    return np.unpackbits(fps.astype("<i8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")


def bit_counts(distinct: DataFrame) -> tuple[int, np.ndarray]:
    """How many fingerprints there are, and a 64 x 64 table of how many set both bits, over all of them."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table, n = np.zeros((BITS, BITS)), 0
        for batch in batches:
            bits = as_bits(batch["fp"].to_numpy()).astype(np.float32)
            table += bits.T @ bits
            n += batch.num_rows
        if n:
            cells = pa.array(np.append(table.ravel(), n).astype(np.int64))
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(BITS * BITS + 1)), cells], ["cell", "n"])

    found = distinct.select("fp").mapInArrow(tidy(count), "cell long, n long").groupBy("cell").agg(F.sum("n").alias("n")).collect()
    cells = np.zeros(BITS * BITS + 1)
    for r in found:
        cells[r["cell"]] = r["n"]
    return int(cells[-1]), cells[:-1].reshape(BITS, BITS)


def agreement(n: int, both: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Chance that two random fingerprints agree on a bit, and on both of two bits."""
    n = max(1, n)
    p11 = both / n
    one = np.diag(p11)
    p10, p01 = one[:, None] - p11, one[None, :] - p11
    p00 = 1 - p11 - p10 - p01
    return one**2 + (1 - one) ** 2, p11**2 + p10**2 + p01**2 + p00**2


def correlated_parts(one: np.ndarray, two: np.ndarray, parts: int) -> list[list[int]]:
    """Bits dealt to equal parts, each filled with the bits that most agree with those it has."""
    excess = np.abs(two - one[:, None] * one[None, :])
    np.fill_diagonal(excess, 0)
    left, out = set(range(BITS)), []
    for k in range(parts):
        want = len(left) // (parts - k)
        seed = max(left, key=lambda b: (excess[b, list(left)].sum(), -b))
        mine = [seed]
        left.discard(seed)
        while len(mine) < want:
            best = max(left, key=lambda b: (excess[b, mine].max(), -b))
            mine.append(best)
            left.discard(best)
        out.append(mine)
    return out


def distance_chances(bits: list[int], one: np.ndarray, two: np.ndarray, most: int) -> np.ndarray:
    """Chance that two random fingerprints differ in d of the bits, d = 0..most: a chain along the bits keeps pairwise agreement."""
    agree, differ = np.zeros(most + 1), np.zeros(most + 1)
    a = one[bits[0]]
    agree[0] = a
    if most:
        differ[1] = 1 - a
    for last, bit in itertools.pairwise(bits):
        a, b, ab = one[last], one[bit], two[last, bit]
        up = min(1.0, max(0.0, ab / a)) if a > 0 else b
        down = min(1.0, max(0.0, (b - ab) / (1 - a))) if a < 1 else b
        wrong = agree * (1 - up) + differ * (1 - down)
        agree, differ = agree * up + differ * down, np.concatenate([[0.0], wrong[:-1]])
    return agree + differ


def radius_keys(width: int, threshold: int) -> int:
    """Keys a fingerprint is filed under in a partition, about."""
    if threshold <= 0:
        return threshold + 1
    if threshold == 1:
        return 1 + width // 2
    return sum(len(list(itertools.combinations(range(width), r))) for r in range(-(-threshold // 2) + 1))


def plan_thresholds(n: int, both: np.ndarray, distance: int = 4, key_cost: float = 8.0) -> list[tuple[list[int], int]]:
    """(bits, threshold) for each partition, cheapest over the numbers of partitions by dynamic programming."""
    one, two = agreement(n, both)
    best, best_cost = None, np.inf
    for parts in range(2, distance + 2):
        groups, total = correlated_parts(one, two, parts), distance - parts + 1
        top = min(2, distance)
        costs = []
        for bits in groups:
            chance = np.cumsum(distance_chances(bits, one, two, top))
            costs.append([0.0] + [n * key_cost * radius_keys(len(bits), t) + chance[t] * n * (n - 1.0) / 2 for t in range(top + 1)])
        states: dict[int, tuple[float, list[int]]] = {0: (0.0, [])}
        for row in costs:
            fresh: dict[int, tuple[float, list[int]]] = {}
            for spent, (cost, chosen) in states.items():
                for k, c in enumerate(row):
                    key = spent + k - 1
                    if key not in fresh or cost + c < fresh[key][0]:
                        fresh[key] = (cost + c, [*chosen, k - 1])
            states = fresh
        if total in states and states[total][0] < best_cost:
            best_cost, best = states[total][0], list(zip(groups, states[total][1], strict=True))
    return best


def bucket_keys(distinct: DataFrame, plan: list[tuple[list[int], int]]) -> DataFrame:
    """(bucket, fp): every key under which a fingerprint is filed; a bucket's number holds its partition and key."""

    def expand(fps: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        bits, keys, owners = as_bits(fps).astype(np.int64), [], []
        for part, (own, threshold) in enumerate(plan):
            if threshold < 0:
                continue
            powers = np.left_shift(np.int64(1), np.arange(len(own), dtype=np.int64))
            key, base = bits[:, own] @ powers, np.int64(part) << np.int64(48)
            keys.append(key + base)
            owners.append(fps)
            if threshold == 1:  # of two keys that differ in a bit, the one without it is filed under the other as well
                rows, cols = np.nonzero(bits[:, own] == 0)
                keys.append(key[rows] + powers[cols] + base)
                owners.append(fps[rows])
            elif threshold > 1:  # both go half way
                for r in range(1, -(-threshold // 2) + 1):
                    for flips in itertools.combinations(range(len(own)), r):
                        keys.append((key ^ np.int64(sum(1 << x for x in flips))) + base)
                        owners.append(fps)
        return np.concatenate(keys), np.concatenate(owners)

    def start():
        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            keys, owners = expand(batch["fp"].to_numpy())
            return pa.RecordBatch.from_arrays([pa.array(keys), pa.array(owners)], ["bucket", "fp"])

        return step

    return map_rows(distinct.select("fp"), start, "bucket long, fp long")


def forest_of_run(fps: np.ndarray, distance: int) -> tuple[np.ndarray, np.ndarray]:
    """A spanning forest of the links within a run: each reached fingerprint is compared with those not yet reached."""
    left, us, vs = np.unique(fps), [], []
    while left.size:
        todo, left = [left[0]], left[1:]
        while todo and left.size:
            at = todo.pop()
            near = np.bitwise_count(left ^ at) <= distance
            if near.any():
                new = left[near]
                us.append(np.full(new.size, at))
                vs.append(new)
                todo += list(new)
                left = left[~near]
    empty = np.empty(0, dtype=np.uint64)
    return (np.concatenate(us), np.concatenate(vs)) if us else (empty, empty)


def links_of_runs(bucket: np.ndarray, unit: np.ndarray, fps: np.ndarray, distance: int) -> tuple[np.ndarray, np.ndarray]:
    """Verified links within sorted runs of (bucket, unit): all pairs of short runs, forests of long ones."""
    n = fps.size
    cuts = np.flatnonzero((bucket[1:] != bucket[:-1]) | (unit[1:] != unit[:-1])) + 1
    starts = np.concatenate([[0], cuts])
    lengths = np.diff(np.append(starts, n))
    us, vs = [], []
    for k in np.flatnonzero(lengths > SMALL_RUN):
        u, v = forest_of_run(fps[starts[k] : starts[k] + lengths[k]], distance)
        us.append(u)
        vs.append(v)
    short = np.repeat(lengths <= SMALL_RUN, lengths)
    end = np.repeat(starts + lengths, lengths)
    at = np.flatnonzero(short)
    for gap in range(1, SMALL_RUN):
        at = at[at + gap < end[at]]
        if not at.size:
            break
        a, b = fps[at], fps[at + gap]
        near = (np.bitwise_count(a ^ b) <= distance) & (a != b)
        us.append(a[near])
        vs.append(b[near])
    empty = np.empty(0, dtype=np.uint64)
    return (np.concatenate(us), np.concatenate(vs)) if us else (empty, empty)


def link_edges(distinct: DataFrame, plan: list[tuple[list[int], int]], distance: int = 4, block: int = BLOCK) -> DataFrame:
    """(u, v) links between distinct fingerprints, enough of them to keep every component whole."""
    filed = bucket_keys(distinct, plan)
    counts = filed.groupBy("bucket").agg(F.count(F.lit(1)).alias("n"))
    large = counts.where(F.col("n") > block).select("bucket", F.ceil(F.col("n") / block).cast("int").alias("blocks"))
    joined = filed.join(large, "bucket", "left").withColumn("mine", F.coalesce(F.pmod(F.xxhash64("fp"), F.col("blocks")).cast("int"), F.lit(0)))
    units = joined.select("bucket", "fp", "mine", F.explode(F.sequence(F.lit(0), F.coalesce(F.col("blocks"), F.lit(1)) - 1)).alias("other"))
    units = units.select("bucket", (F.least("mine", "other").cast("long") * 1_000_003 + F.greatest("mine", "other")).alias("unit"), "fp")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept = [np.empty(0, dtype=np.int64), np.empty(0, dtype=np.int64), np.empty(0, dtype=np.uint64)]

        def linked(cols: list[np.ndarray]) -> pa.RecordBatch:
            u, v = links_of_runs(*cols, distance)
            return pa.RecordBatch.from_arrays([pa.array(u.view(np.int64)), pa.array(v.view(np.int64))], ["u", "v"])

        for batch in batches:
            kept = [np.concatenate([a, b]) for a, b in zip(kept, (batch["bucket"].to_numpy(), batch["unit"].to_numpy(), batch["fp"].to_numpy().view(np.uint64)), strict=True)]
            if not kept[0].size:
                continue
            last = np.flatnonzero((kept[0] != kept[0][-1]) | (kept[1] != kept[1][-1]))
            cut = int(last[-1]) + 1 if last.size else 0  # the last run may go on in the next batch
            if cut:
                yield linked([x[:cut] for x in kept])
                kept = [x[cut:] for x in kept]
        if kept[0].size:
            yield linked(kept)

    return units.repartition("bucket", "unit").sortWithinPartitions("bucket", "unit").mapInArrow(tidy(run), "u long, v long")


def near_duplicates(documents: DataFrame, shingle: int = 4, seed: int = 42, distance: int = 4, block: int = BLOCK) -> DataFrame:
    """Per document: doc_id, fingerprint (hex), component_id (smallest doc_id reachable)."""
    rows = materialize(fingerprints(documents, shingle, seed), "fingerprints")
    distinct = materialize(rows.groupBy("fp").agg(F.min("doc_id").alias("least")), "distinct-fingerprints")
    n, both = bit_counts(distinct)
    roots = components(link_edges(distinct, plan_thresholds(n, both, distance), distance, block), "near-links")
    labelled = materialize(distinct.join(roots, distinct["fp"] == roots["node"], "left").select("fp", "least", F.coalesce("root", "fp").alias("root")), "labelled-fingerprints")
    # written, so that both sides of the joins are plain exchanges and a root or fingerprint with many rows is split
    smallest = materialize(labelled.groupBy("root").agg(F.min("least").alias("component_id")), "components")
    by_print = materialize(labelled.join(smallest, "root").select("fp", "component_id"), "component-of-fingerprint")
    return rows.join(by_print, "fp").select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
