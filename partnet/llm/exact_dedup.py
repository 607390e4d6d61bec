"""Exact dedup by Patricia-trie owners.

Every text is normalised (each run of ASCII white space becomes one space) and
goes, as a full byte string, into a compressed radix trie. Map tasks build a trie
of what they read and pass on one row for each distinct text with its smallest
id and its count. Those rows are dealt out by length and content hash; each
receiving task inserts all byte strings of its partition into one trie, whose
terminals own the groups.

Memory is bounded by spilling subtrees. A map-side trie that outgrows its budget
sends its largest subtree downstream, which is exact because receivers merge. A
receiver does the same, but whatever lies below a spilled prefix, now or later,
leaves it as unfinished rows, which are dealt out again by another hash to tries
with twice the budget, until no row is unfinished.

Texts are read twice, for the tries and for the digests of the rows, and moved
once.

Defined results: null text counts as empty; null ids sort after all others (a
group of null ids only has keep_id null); of rows that repeat both the smallest
id and the text exactly one is kept; an empty table gives no rows. Input columns
with the names of results give way to them in `exact_groups`; `kept_rows`
returns the input's columns as they are.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from partnet.llm.bloom import concerned, one_row_each
from partnet.llm.common import SPACE_PATTERN, materialize, tidy

NO_ID = 1 << 63  # above every id
TRIE_BYTES = 24 << 20
OWNER_BYTES = 96 << 20
NODE_BYTES = 200
FLUSH_BYTES = 4 << 20
LOCAL_SCHEMA = "body binary, keep_id long, n_least long, group_size long"
OWNER_SCHEMA = "body binary, digest binary, content_hash long, keep_id long, n_least long, group_size long"


class Node:
    __slots__ = ("label", "children", "owner", "least", "count")

    def __init__(self, label: bytes):
        self.label, self.children, self.owner, self.least, self.count = label, None, NO_ID, 0, 0


def common_prefix(a: bytes, b: bytes) -> int:
    """Length of the longest common prefix, by halving over C comparisons."""
    low, high = 0, min(len(a), len(b))
    if a[:high] == b[:high]:
        return high
    while low < high:
        mid = (low + high + 1) // 2
        if a[low:mid] == b[low:mid]:
            low = mid
        else:
            high = mid - 1
    return low


class PatriciaTrie:
    """Byte strings to (smallest id, how many rows have it, count); size holds an estimate of the bytes used."""

    def __init__(self):
        self.root, self.size = Node(b""), 0

    def insert(self, key: bytes, owner: int, least: int = 1, count: int = 1) -> None:
        node, at = self.root, 0
        while at < len(key):
            if node.children is None:
                node.children = {}
            child = node.children.get(key[at])
            if child is None:
                child = node.children[key[at]] = Node(key[at:])
                self.size += NODE_BYTES + len(child.label)
                node, at = child, len(key)
                break
            label = child.label
            if key.startswith(label, at):
                node, at = child, at + len(label)
                continue
            cut = common_prefix(label, key[at : at + len(label)])
            upper = Node(label[:cut])
            upper.children = {label[cut]: child}
            child.label = label[cut:]
            node.children[key[at]] = upper
            self.size += NODE_BYTES
            node, at = upper, at + cut
        if node.count == 0 or owner < node.owner:
            node.owner, node.least = owner, least
        elif owner == node.owner:
            node.least += least
        node.count += count

    def drain(self, node: Node | None = None, prefix: bytes = b"") -> Iterator[tuple[bytes, int, int, int]]:
        """(string, smallest id, rows with it, count) of each terminal at or below a node."""
        todo = [(node or self.root, prefix)]
        while todo:
            at, above = todo.pop()
            key = above + at.label
            if at.count:
                yield key, at.owner, at.least, at.count
            if at.children:
                todo += [(x, key) for x in at.children.values()]

    def cut(self) -> tuple[bytes, Iterator[tuple[bytes, int, int, int]]]:
        """Cuts off the largest subtree below the first branching: (its prefix, its terminals)."""
        node, prefix = self.root, b""
        while node.children and len(node.children) == 1 and not node.count:
            node = next(iter(node.children.values()))
            prefix += node.label
        if not node.children:
            whole, self.root, self.size = self.root, Node(b""), 0
            return prefix, self.drain(whole)
        weights = {k: self.weight(x) for k, x in node.children.items()}
        largest = max(weights, key=weights.get)
        gone = node.children.pop(largest)
        self.size -= weights[largest]
        return prefix + gone.label, self.drain(gone, prefix)

    def has_one(self) -> bool:
        """Whether it holds a single string."""
        node = self.root
        while not node.count and node.children and len(node.children) == 1:
            node = next(iter(node.children.values()))
        return not node.children

    @staticmethod
    def weight(node: Node) -> int:
        total, todo = 0, [node]
        while todo:
            x = todo.pop()
            total += NODE_BYTES + len(x.label)
            if x.children:
                todo += x.children.values()
        return total


def in_chunks(rows: Iterator[tuple], schema: str) -> Iterator[pa.RecordBatch]:
    """Batches of bounded size; the first column is the text."""
    names = [x.split()[0] for x in schema.split(", ")]
    types = [{"binary": pa.binary(), "long": pa.int64()}[x.split()[1]] for x in schema.split(", ")]
    out = lambda kept: pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*kept, strict=True), types, strict=True)], names)
    kept, held = [], 0
    for row in rows:
        kept.append(row)
        held += len(row[0] or b"") + 64
        if held >= FLUSH_BYTES:
            yield out(kept)
            kept, held = [], 0
    if kept:
        yield out(kept)


def id_or_none(owner: int) -> int | None:
    return None if owner == NO_ID else owner


def map_side(trie_bytes: int):
    """One row for each distinct text that the task's trie held."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def rows() -> Iterator[tuple]:
            trie = PatriciaTrie()
            for batch in batches:
                for body, owner in zip(batch["body"].cast(pa.binary()).to_pylist(), batch["doc_id"].to_pylist(), strict=True):
                    trie.insert(body, NO_ID if owner is None else owner)
                    while trie.size > trie_bytes:
                        for key, least_id, least, count in trie.cut()[1]:
                            yield key, id_or_none(least_id), least, count
            for key, least_id, least, count in trie.drain():
                yield key, id_or_none(least_id), least, count

        yield from in_chunks(rows(), LOCAL_SCHEMA)

    return run


def owner_side(owner_bytes: int):
    """The trie of a partition: its terminals with their digests, or, below a prefix that was cut off, unfinished with their texts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def unfinished(terminal: tuple[bytes, int, int, int]) -> tuple:
            key, owner, least, count = terminal
            return key, None, None, id_or_none(owner), least, count

        def rows() -> Iterator[tuple]:
            trie, cut = PatriciaTrie(), ()
            for batch in batches:
                for body, owner, least, count in zip(*(batch[x].to_pylist() for x in ("body", "keep_id", "n_least", "group_size")), strict=True):
                    trie.insert(body, NO_ID if owner is None else owner, least, count)
                    while trie.size > owner_bytes and not trie.has_one():
                        prefix, terminals = trie.cut()
                        cut += (prefix,)
                        yield from map(unfinished, terminals)
            for terminal in trie.drain():
                if terminal[0].startswith(cut):
                    yield unfinished(terminal)
                else:
                    key, owner, least, count = terminal
                    code = xxhash.xxh64_intdigest(key, 42)  # the engine's xxhash64
                    yield None, hashlib.sha256(key).digest(), code - (code >> 63 << 64), id_or_none(owner), least, count

        yield from in_chunks(rows(), OWNER_SCHEMA)

    return run


def normalised(text) -> F.Column:
    return F.regexp_replace(F.coalesce(text, F.lit("")), SPACE_PATTERN, " ")


def trie_owners(documents: DataFrame, trie_bytes: int = TRIE_BYTES, owner_bytes: int = OWNER_BYTES) -> DataFrame:
    """One row per distinct text: digest (sha256 of the normalised text), content_hash, keep_id, n_least (rows with that id), group_size."""
    bodies = documents.select(F.col("doc_id").cast("long").alias("doc_id"), normalised(F.col("text")).alias("body"))
    dealt = bodies.mapInArrow(tidy(map_side(trie_bytes)), LOCAL_SCHEMA).repartition(F.octet_length("body"), F.xxhash64("body"))
    done, names = None, [x.split()[0] for x in OWNER_SCHEMA.split(", ")[1:]]
    while True:
        out = materialize(dealt.mapInArrow(tidy(owner_side(owner_bytes)), OWNER_SCHEMA), "trie-owners")
        finished = out.where("body IS NULL").select(*names)
        done = finished if done is None else done.unionAll(finished)
        left = out.where("body IS NOT NULL").select("body", "keep_id", "n_least", "group_size")
        held = left.agg(F.sum(F.octet_length("body") + NODE_BYTES)).first()[0]
        if not held:
            return done
        owner_bytes *= 2
        dealt = left.repartition(4 * held // owner_bytes + 1, F.xxhash64("body", F.lit(owner_bytes)))


def digest_of(text) -> F.Column:
    return F.unhex(F.sha2(normalised(text), 256))


def exact_groups(documents: DataFrame, columns: list[str] | None = None, trie_bytes: int = TRIE_BYTES, owner_bytes: int = OWNER_BYTES) -> DataFrame:
    """documents (the named columns, all if None) with keep_id, group_size, kept and text_sha256.

    The final join carries no text unless it is asked for; large groups are split by the adaptive skew join.
    """
    columns = documents.columns if columns is None else columns
    kept_columns = [x for x in columns if x.lower() not in ("keep_id", "group_size", "kept", "text_sha256")]
    digests = documents.select(F.struct(*kept_columns).alias("row"), "doc_id", digest_of(F.col("text")).alias("digest"))
    same = Window.partitionBy("digest", "doc_id").orderBy(F.lit(0))
    rows = digests.withColumn("copy_no", F.row_number().over(same))
    joined = rows.join(trie_owners(documents, trie_bytes, owner_bytes), "digest")
    return joined.select(
        "row.*", "keep_id", "group_size",
        (F.col("doc_id").eqNullSafe(F.col("keep_id")) & (F.col("copy_no") == 1)).alias("kept"),
        F.lower(F.hex("digest")).alias("text_sha256"),
    )


def kept_rows(documents: DataFrame) -> DataFrame:
    """The row that stays of each group of equal texts. Only rows that a filter of the repeated texts lets pass are joined."""
    columns = documents.columns
    repeated = materialize(trie_owners(documents).where("group_size > 1").select(F.col("digest").alias("exact__digest"), F.col("content_hash").alias("key"), F.col("keep_id").alias("exact__keep"), F.col("n_least").alias("exact__least")), "repeated-texts")
    read = concerned(documents.withColumn("exact__hash", F.xxhash64(normalised(F.col("text")))), F.col("exact__hash"), repeated.select("key"), "exact__hit")
    hit = read.where("exact__hit").withColumn("exact__digest", digest_of(F.col("text")))
    stays = F.col("exact__least").isNull() | ((F.col("exact__least") == 1) & F.col("doc_id").cast("long").eqNullSafe(F.col("exact__keep")))
    out = read.where("NOT exact__hit").select(*columns).unionAll(hit.join(repeated.drop("key"), "exact__digest", "left").where(stays).select(*columns))
    if not repeated.where("exact__least > 1").take(1):
        return out
    several = hit.join(repeated.where("exact__least > 1").drop("key"), "exact__digest").where(F.col("doc_id").cast("long").eqNullSafe(F.col("exact__keep")))
    return out.unionAll(one_row_each(several, ["exact__digest"], columns))
