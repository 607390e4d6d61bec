"""Sharding on a consistent-hash ring with virtual nodes and bounded loads.

The ring has a fixed number of cells. Each shard owns virtual nodes at hashed
cells; a key's cell belongs to the next virtual node clockwise. Shards have
capacities that add up to the number of rows and differ by one at most; keys
that find their shard full continue clockwise to the next virtual node of a
shard with room. Shards therefore end exactly full, and only what overflows
moves away from its home on the ring.

The plan needs the number of keys in each cell, not the keys. Rows then take
places by their rank within the cell, which is small and never hot for a unique
key. The law kept is `rows`.

Defined results: null text has no bytes and crc32 0; null keys share one ring
cell, repeated keys theirs, where their texts spread them if the cell is
crowded; repeated rows are placed each on their own; an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

from bisect import bisect_left

import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

CELLS = 1 << 16
VIRTUAL_NODES = 96
SPREAD = 8
#: a cell is crowded from so many times the mean on, and from so many rows
CROWDED, CROWDED_ROWS = 4, 64


def ring(shards: int, virtual_nodes: int = VIRTUAL_NODES, cells: int = CELLS) -> list[tuple[int, int]]:
    """(cell, shard) of the virtual nodes in ring order; of nodes on one cell the smaller shard is first."""
    return sorted((xxhash.xxh64_intdigest(f"{s}/{v}", 0) % cells, s) for s in range(shards) for v in range(virtual_nodes))


def capacities(rows: int, shards: int) -> list[int]:
    return [rows // shards + (s < rows % shards) for s in range(shards)]


def plan_cells(counts: dict[tuple[int, int], int], shards: int, virtual_nodes: int = VIRTUAL_NODES, cells: int = CELLS) -> list[tuple[int, int, int, int, int, int, bool]]:
    """(cell, spread, lo, hi, shard, slot of lo, is home) for keys counted by cell, clockwise from cell 0."""
    nodes, room, filled, out = ring(shards, virtual_nodes, cells), capacities(sum(counts.values()), shards), [0] * shards, []
    places = [x[0] for x in nodes]
    for (cell, spread), n in sorted(counts.items()):
        at, lo, step = bisect_left(places, cell), 0, 0
        while lo < n:
            shard = nodes[(at + step) % len(nodes)][1]
            take = min(n - lo, room[shard] - filled[shard])
            if take:
                out.append((cell, spread, lo, lo + take, shard, filled[shard], step == 0))
                filled[shard] += take
                lo += take
            step += 1
    return out


PLAN_SCHEMA = T.StructType(
    [T.StructField(x, T.IntegerType()) for x in ("cell", "spread")] + [T.StructField(x, T.LongType()) for x in ("lo", "hi")] + [T.StructField("shard", T.IntegerType()), T.StructField("first", T.LongType()), T.StructField("is_home", T.BooleanType())]
)


def shard_rows(documents: DataFrame, shards: int = 8, virtual_nodes: int = VIRTUAL_NODES, cells: int = CELLS) -> DataFrame:
    """Per document: doc_id, size, text_crc32, law, shard, slot, grown_shard, is_home.

    The counts that reach the driver and the plan that is broadcast are bounded by the ring's cells; fewer than one in CROWDED is spread.
    """
    spark = documents.sparkSession
    body = F.coalesce(F.col("text"), F.lit(""))
    keyed = documents.select(
        "doc_id", (F.octet_length(body).cast("long") + 1).alias("size"), F.crc32(body.cast("binary")).alias("text_crc32"), F.xxhash64("doc_id").alias("spot")
    ).select("*", F.pmod("spot", F.lit(cells)).cast("int").alias("cell"), F.pmod("text_crc32", F.lit(SPREAD)).cast("int").alias("spread"))
    each = keyed.groupBy("cell", "spread").agg(F.count(F.lit(1)).alias("n"))
    by_cell = {r["cell"]: r["n"] for r in each.groupBy("cell").agg(F.sum("n").alias("n")).collect()}
    limit = max(CROWDED_ROWS, CROWDED * sum(by_cell.values()) / cells)
    crowded = F.broadcast(spark.createDataFrame([(c, True) for c, n in by_cell.items() if n > limit], "cell int, crowded boolean"))
    counts = {(c, 0): n for c, n in by_cell.items() if n <= limit} | {(r["cell"], r["spread"]): r["n"] for r in each.join(crowded, "cell", "left_semi").collect()}
    keyed = keyed.join(crowded, "cell", "left").withColumn("spread", F.when(F.col("crowded"), F.col("spread")).otherwise(0)).drop("crowded")
    plan = F.broadcast(spark.createDataFrame(plan_cells(counts, shards, virtual_nodes, cells), PLAN_SCHEMA))
    rank = F.row_number().over(Window.partitionBy("cell", "spread").orderBy("spot", "text_crc32", "size")) - 1
    placed = keyed.withColumn("rank", rank).join(plan, ["cell", "spread"]).where((F.col("rank") >= F.col("lo")) & (F.col("rank") < F.col("hi")))
    return placed.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", (F.col("first") + F.col("rank") - F.col("lo")).alias("slot"), F.lit(None).cast("int").alias("grown_shard"), "is_home")
