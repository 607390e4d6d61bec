"""Blocked Bloom filters as DataFrame expressions: 256-bit blocks, one bit in each of a block's four words."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

BLOCK_BITS = 256
BITS_PER_KEY = 16
#: most blocks of a filter that is broadcast unchecked, 40 bytes each
MOST_BLOCKS = 1 << 17


def bloom_bits(key: Column, blocks: int) -> tuple[Column, list[Column]]:
    """Block of a key and its bit in each of the block's four words."""
    h = F.xxhash64(key)
    block = F.pmod(F.xxhash64(key, F.lit(1)), F.lit(blocks)).cast("int")
    return block, [one_bit(h, 6 * k) for k in range(4)]


def one_bit(h: Column, shift: int) -> Column:
    place = F.shiftrightunsigned(h, shift).bitwiseAND(F.lit(63)).cast("int")
    return F.call_function("shiftleft", F.lit(1).cast("long"), place)


def blocked_bloom(keys: DataFrame, blocks: int) -> DataFrame:
    """(block, w0..w3) of a table with the column key."""
    block, bits = bloom_bits(F.col("key"), blocks)
    return keys.select(block.alias("block"), *(b.alias(f"b{k}") for k, b in enumerate(bits))).groupBy("block").agg(*(F.bit_or(f"b{k}").alias(f"w{k}") for k in range(4)))


def concerned(rows: DataFrame, column: Column, keys: DataFrame, mark: str) -> DataFrame:
    """rows with a boolean column named mark: whether a filter of the keys (one column, key) may hold the value.

    The filter's size is bounded whatever the number of keys; a full filter lets more rows pass, never fewer.
    """
    n = keys.agg(F.count(F.lit(1))).first()[0]
    blocks = min(MOST_BLOCKS, max(1, -(-n * BITS_PER_KEY // BLOCK_BITS)))
    words = [f"{mark}_w{k}" for k in range(4)]
    bloom = blocked_bloom(keys, blocks).withColumnsRenamed({"block": f"{mark}_block"} | {f"w{k}": x for k, x in enumerate(words)})
    block, bits = bloom_bits(column, blocks)
    held = rows.withColumn(f"{mark}_block", block).join(F.broadcast(bloom), f"{mark}_block", "left")
    hit = F.lit(True)
    for word, bit in zip(words, bits, strict=True):
        hit = hit & (F.col(word).bitwiseAND(bit) != 0)
    return held.withColumn(mark, F.coalesce(hit, F.lit(False))).drop(f"{mark}_block", *words)


def one_row_each(rows: DataFrame, keys: list[str], columns: list[str]) -> DataFrame:
    """The named columns of one row for each key, the least by all columns that have an order. Rows are aggregated before they move."""
    ordered = [c for c, kind in rows.dtypes if c in columns and "map<" not in kind and "variant" not in kind]
    return rows.groupBy(*keys).agg(F.min_by(F.struct(*columns), F.struct(*ordered)).alias("row")).select("row.*")
