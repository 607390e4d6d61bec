"""Best-fit packing planned on a length histogram.

Documents longer than a sequence are cut into full pieces behind a shorter
first one. The number of pieces of each length (at most `capacity` counters) is
all that the plan needs: best-fit, longest first, over counts. A plan row says
that the pieces of one length with ranks lo and up go, `each` to a sequence, to
consecutive sequences at a fixed offset; pieces then take their slots by their
rank within the length. Ranks are a piece's place in its task plus the number
of such pieces in the tasks before, so no length gathers in one task.

Defined results: a null or empty text is its end id alone; repeated rows and
null ids are packed each on their own; an empty table gives no rows; extra
columns are ignored.
"""

from __future__ import annotations

import zlib
from bisect import bisect_left, insort
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from partnet.llm.common import map_rows, materialize
from partnet.llm.tokens import encoder

CAPACITY = 2048
PIECE_SCHEMA = "doc_id long, piece int, start long, length long, ids_crc32 long, task int, place long"


@dataclass(frozen=True)
class PlanRow:
    """Pieces of `length` with ranks lo..lo+count-1: sequence first + (rank - lo) // each, offset + ((rank - lo) % each) * length."""

    length: int
    lo: int
    count: int
    first: int
    offset: int
    each: int


def best_fit_plan(histogram: dict[int, int], capacity: int = CAPACITY) -> tuple[list[PlanRow], int]:
    """Plan rows and the number of sequences. Work grows with the number of lengths, not of pieces."""
    room: dict[int, list[tuple[int, int]]] = {}  # free tokens -> runs of sequences (first, how many)
    frees: list[int] = []
    rows, opened = [], 0

    def put(free: int, first: int, n: int) -> None:
        if n and free:
            if free not in room:
                room[free] = []
                insort(frees, free)
            room[free].append((first, n))

    for length in sorted(histogram, reverse=True):
        lo, left = 0, histogram[length]
        while left:
            at = bisect_left(frees, length)
            if at < len(frees):
                free = frees[at]
                first, n = room[free].pop()
                if not room[free]:
                    del room[free], frees[at]
            else:
                free, first, n = capacity, opened, -(-left // (capacity // length))
                opened += n
            each = min(free // length, left)
            bins = min(n, left // each)
            rows.append(PlanRow(length, lo, bins * each, first, capacity - free, each))
            put(free - each * length, first, bins)
            put(free, first + bins, n - bins)
            lo, left = lo + bins * each, left - bins * each
    return rows, opened


def cut_lengths(n: int, capacity: int = CAPACITY) -> list[int]:
    """Lengths of a document's pieces: full ones, behind a shorter first one if it doesn't divide."""
    return [n % capacity] * bool(n % capacity) + [capacity] * (n // capacity)


def tokenised_pieces(documents: DataFrame, tokenizer_path: str, end_id: int = 0, capacity: int = CAPACITY) -> DataFrame:
    """One row per piece with its place among the pieces of its length in its task."""
    end = int(end_id).to_bytes(4, "little")

    def start():
        made, task, places = encoder(tokenizer_path), TaskContext.get().partitionId(), [0] * (capacity + 1)

        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            out = []
            for doc_id, ids in zip(batch["doc_id"].to_pylist(), made.encode_all(batch["text"].to_pylist()), strict=True):
                view, at = memoryview(ids + end), 0
                for k, n in enumerate(cut_lengths(len(view) // 4, capacity)):
                    out.append((doc_id, k, at, n, zlib.crc32(view[4 * at : 4 * (at + n)]), task, places[n]))
                    places[n] += 1
                    at += n
            types = [pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int64()]
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True), types, strict=True)], [x.split()[0] for x in PIECE_SCHEMA.split(", ")])

        step.finish = made.forget
        return step

    return map_rows(documents.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), start, PIECE_SCHEMA, keeps=True)


def best_fit_pack(documents: DataFrame, tokenizer_path: str, end_id: int = 0, capacity: int = CAPACITY) -> DataFrame:
    """Per piece: doc_id, piece, start, length, ids_crc32, sequence_id, offset.

    The pieces are written once (numbers only), so a place stays what it was when it was counted.
    """
    pieces = materialize(tokenised_pieces(documents, tokenizer_path, end_id, capacity), "pieces")
    per_task = pieces.groupBy("task", "length").agg(F.count(F.lit(1)).alias("n"))
    histogram = {r["length"]: r["n"] for r in per_task.groupBy("length").agg(F.sum("n").alias("n")).collect()}
    plan, _ = best_fit_plan(histogram, capacity)
    order = Window.partitionBy("length").orderBy("task").rowsBetween(Window.unboundedPreceding, -1)
    before = per_task.select("task", "length", F.coalesce(F.sum("n").over(order), F.lit(0)).alias("before"))
    ranked = pieces.join(before, ["task", "length"]).withColumn("rank", F.col("before") + F.col("place")).drop("task", "place", "before")
    grouped: dict[int, list[PlanRow]] = {}
    for x in plan:
        grouped.setdefault(x.length, []).append(x)
    slots = {n: tuple(np.array([getattr(x, a) for x in rows], dtype=np.int64) for a in ("lo", "first", "offset", "each")) for n, rows in grouped.items()}
    shared = documents.sparkSession.sparkContext.broadcast(slots)  # at most a few rows for each of `capacity` lengths

    def start():
        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            lengths, ranks = batch["length"].to_numpy(), batch["rank"].to_numpy()
            sequence, offset = np.zeros(lengths.size, dtype=np.int64), np.zeros(lengths.size, dtype=np.int64)
            order = np.argsort(lengths, kind="stable")
            for at in np.split(order, np.flatnonzero(np.diff(lengths[order])) + 1):
                lo, first, off, each = shared.value[int(lengths[at[0]])]
                row = np.searchsorted(lo, ranks[at], side="right") - 1
                k = ranks[at] - lo[row]
                sequence[at] = first[row] + k // each[row]
                offset[at] = off[row] + (k % each[row]) * lengths[at]
            return pa.RecordBatch.from_arrays([*(batch[x] for x in ("doc_id", "piece", "start", "length", "ids_crc32")), pa.array(sequence), pa.array(offset)], ["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"])

        return step

    return map_rows(ranked.select("doc_id", "piece", "start", "length", "ids_crc32", "rank"), start, "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long")
