"""Token ids in ORC: integer run-length encoding, row indexes and Bloom filters on the document id.

Documents are dealt out by ranges of doc_id, whose bounds are quantiles of the
ids, and sorted before they are encoded, so file after file holds ascending ids.
An id with as many rows as several ranges gets as many files, and rows without
an id get their share. Each row keeps its place in its file, its number of ids
and the ids themselves. Readers take stripes in parallel, and
the stripe statistics, row indexes and Bloom filters prune lookups by id.

Defined results: a null or empty text is its end id alone; null ids come first;
rows that repeat an id keep neighbouring places in any order; an empty table
writes and reads no rows; extra columns are ignored.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from partnet.llm.common import map_rows, scratch_path
from partnet.llm.tokens import encoder

FILE_BYTES = 512 << 20
MOST_FILES = 8192
#: 32-bit ids are stored as signed ORC integers; vocabularies stay far below 2**31.
FILE_SCHEMA = "doc_id long, place long, n_tokens int, ids array<int>"
ORC_OPTIONS = {
    "compression": "zstd",
    "orc.bloom.filter.columns": "doc_id",
    "orc.bloom.filter.fpp": "0.01",
    "orc.create.index": "true",
    "orc.row.index.stride": "2000",
    "orc.stripe.size": str(32 << 20),
    "orc.column.encoding.direct": "ids",
}


def encode_rows(documents: DataFrame, tokenizer_path: str, end_id: int) -> DataFrame:
    """FILE_SCHEMA in the order given; place counts from 0 in each task, which becomes one file."""
    end = int(end_id).to_bytes(4, "little")

    def start():
        made, done = encoder(tokenizer_path), 0

        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            nonlocal done
            packed = [x + end for x in made.encode_all(batch["text"].to_pylist())]
            counts = np.array([len(x) // 4 for x in packed], dtype=np.int32)
            flat = pa.array(np.frombuffer(b"".join(packed), dtype="<u4").astype(np.int32))
            ids = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(counts)]).astype(np.int32)), flat)
            place = pa.array(np.arange(done, done + len(packed), dtype=np.int64))
            done += len(packed)
            return pa.RecordBatch.from_arrays([batch["doc_id"], place, pa.array(counts), ids], ["doc_id", "place", "n_tokens", "ids"])

        return step

    return map_rows(documents.select("doc_id", "text"), start, FILE_SCHEMA, keeps=True)


def files_for(rows: DataFrame, n_bytes: int) -> int:
    """A file for FILE_BYTES of text, one for each shuffle partition at least, MOST_FILES at most."""
    return max(1, int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")), min(MOST_FILES, -(-n_bytes // FILE_BYTES)))


def range_number(doc_id, text, bounds: list[int], n_null: int):
    """Which of n_null + len(bounds) + 1 ranges a row belongs to. Bounds ascend; one that recurs has its rows dealt over its ranges by their texts."""
    steps = sorted(set(bounds))
    first = {x: bounds.index(x) for x in steps}
    many = {x: bounds.count(x) for x in steps}
    groups = [steps[k : k + 64] for k in range(0, len(steps), 64)]
    longs = lambda xs: F.array(*[F.lit(x).cast("long") for x in xs])
    reached = lambda xs: F.size(F.filter(xs, lambda x: x <= doc_id))
    if steps:
        at = reached(longs([g[0] for g in groups]))  # two short scans instead of one over all bounds
        within = F.when(at > 0, (at - 1) * 64 + reached(F.element_at(F.array(*map(longs, groups)), F.greatest(at, F.lit(1))))).otherwise(0)
        starts, counts = longs([0, *(first[x] + 1 for x in steps)]), longs([1, *(many[x] if many[x] > 1 else 1 for x in steps)])
        own = longs([0, *steps])
        begin, several = F.element_at(starts, within + 1), F.element_at(counts, within + 1)
        hot = (F.element_at(own, within + 1) == doc_id) & (several > 1) & (within > 0)
        number = F.when(hot, begin + F.pmod(F.xxhash64(text), several)).otherwise(F.when(within > 0, begin + several - 1).otherwise(F.lit(0).cast("long")))
    else:
        number = F.lit(0).cast("long")
    null_range = F.pmod(F.xxhash64(text), F.lit(max(1, n_null)))
    return F.when(doc_id.isNull(), null_range).otherwise(number + n_null).cast("int")


def dealt_by_range(rows: DataFrame) -> DataFrame:
    """rows in ascending ranges of doc_id, nulls first."""
    facts = rows.agg(F.count(F.lit(1)).alias("n"), F.count("doc_id").alias("named"), F.sum(F.octet_length("text")).alias("bytes")).first()
    most = files_for(rows, facts["bytes"] or 0)
    n_null = -(-most * (facts["n"] - facts["named"]) // facts["n"]) if facts["n"] else 0
    shares = [k / most for k in range(1, most)] or [0.5]
    bounds = rows.agg(F.percentile_approx("doc_id", shares, 100 * most).alias("bounds")).first()["bounds"] or []
    number = range_number(F.col("doc_id"), F.col("text"), sorted(bounds), n_null)
    return rows.repartitionById(n_null + len(bounds) + 1, number)


def write_token_files(documents: DataFrame, path: str, tokenizer_path: str, end_id: int = 2) -> None:
    rows = documents.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    encode_rows(dealt_by_range(rows).sortWithinPartitions("doc_id"), tokenizer_path, end_id).write.options(**ORC_OPTIONS).orc(path)


def read_token_files(spark: SparkSession, path: str) -> DataFrame:
    """FILE_SCHEMA and the file's name; the numbers in the names ascend with doc_id."""
    return spark.read.schema(FILE_SCHEMA).orc(path).withColumn("file", F.col("_metadata.file_name"))


def lookup(spark: SparkSession, path: str, doc_id: int) -> DataFrame:
    """The rows of one document; statistics, row indexes and Bloom filters skip the rest."""
    return spark.read.schema(FILE_SCHEMA).orc(path).where(F.col("doc_id") == doc_id)


def token_digest(spark: SparkSession, path: str) -> DataFrame:
    """Per document from the files: doc_id, start, n_tokens, ids_crc32.

    A file's first start is the total of the files before it, summed over one small row per file.
    """

    def start():
        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            ids = batch["ids"]
            at = ids.offsets.to_numpy()
            raw = memoryview(ids.values[at[0] : at[-1]].to_numpy().astype("<u4").tobytes())
            at = at - at[0]
            codes = [zlib.crc32(raw[4 * a : 4 * b]) for a, b in zip(at[:-1].tolist(), at[1:].tolist(), strict=True)]
            return pa.RecordBatch.from_arrays([batch["doc_id"], batch["place"], batch["n_tokens"], batch["file"], pa.array(codes, pa.int64())], ["doc_id", "place", "n_tokens", "file", "ids_crc32"])

        return step

    rows = map_rows(read_token_files(spark, path).select("doc_id", "place", "n_tokens", "file", "ids"), start, "doc_id long, place long, n_tokens int, file string, ids_crc32 long")
    totals = spark.read.schema(FILE_SCHEMA).orc(path).groupBy(F.col("_metadata.file_name").alias("file")).agg(F.sum("n_tokens").alias("total"))
    number = F.regexp_extract("file", r"part-(\d+)", 1).cast("long")
    earlier = Window.orderBy(number).rowsBetween(Window.unboundedPreceding, -1)
    bases = totals.select("file", F.coalesce(F.sum("total").over(earlier), F.lit(0)).alias("base"))
    inside = Window.partitionBy("file").orderBy("place").rowsBetween(Window.unboundedPreceding, -1)
    placed = rows.withColumn("inner", F.coalesce(F.sum(F.col("n_tokens").cast("long")).over(inside), F.lit(0)))
    return placed.join(bases, "file").select("doc_id", (F.col("base") + F.col("inner")).alias("start"), F.col("n_tokens").cast("long").alias("n_tokens"), "ids_crc32")


def token_round_trip(documents: DataFrame, tokenizer_path: str, end_id: int = 2) -> DataFrame:
    path = scratch_path(documents.sparkSession, "token-files")
    write_token_files(documents, path, tokenizer_path, end_id)
    return token_digest(documents.sparkSession, path)
