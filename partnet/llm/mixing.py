"""Mixing sources to target weights by systematic sampling.

Sources get target shares by weight; a target stops at a multiple of its
source's size and the excess goes to the others by weight, until none is above.
Every document expects target / source size copies. Expected copies are summed
in the order of falling size within the source, one random offset is added for each
source, and a document is emitted once for each integer boundary that its
interval crosses. Order by size keeps the words taken near the target.

The prefix sum is a rank within the source, in three levels: sizes of a source,
salts of a size, rows of a salt. No level gathers a source, or a group of
equal sizes, in one task.

Defined results: null text has size 0; the null source is a source of its own
and comes last; a source without words has target 0 and nothing taken; rows of
one size stand in the order of id, null ids last, then of a hash of the text;
repeated rows are mixed each on their own; an empty table gives no rows. Input
columns with the names of results give way to them in `systematic_mix`;
`mixed_copies` returns the input's columns as they are.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from partnet.llm.common import WORD_PATTERN

WEIGHTS = (5, 2, 1)
SALTS = 1021


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD_PATTERN)), F.lit(0)).cast("long")


def source_targets(sizes: DataFrame, weights: tuple[int, ...] = WEIGHTS, share: float = 1.5, limit: float = 2.0) -> DataFrame:
    """(source, source_size) to (source, source_size, target). One row per source.

    The level at which a source fills up is limit * size / weight; in that order, the filled ones are a prefix.
    """
    order = Window.orderBy(F.col("source").asc_nulls_last())
    cycle = F.array(*[F.lit(float(x)) for x in weights])
    ranked = sizes.withColumn("turn", F.row_number().over(order) - 1)
    weighted = ranked.withColumn("weight", F.element_at(cycle, (F.pmod(F.col("turn"), F.lit(len(weights))) + 1).cast("int"))).withColumn("cap", F.col("source_size") * F.lit(limit))
    by_level = Window.orderBy(F.col("cap") / F.col("weight"), "turn")
    before, onward = by_level.rowsBetween(Window.unboundedPreceding, -1), by_level.rowsBetween(Window.currentRow, Window.unboundedFollowing)
    everything = Window.partitionBy()
    levels = weighted.select(
        "*",
        (F.sum("source_size").over(everything) * F.lit(share) - F.coalesce(F.sum("cap").over(before), F.lit(0.0))).alias("rest"),
        F.sum("weight").over(onward).alias("weight_left"),
    )
    # a source is filled if the level that the rest gives here would exceed its cap; the water level is that of the first one not filled
    water = F.min(F.when(F.col("rest") / F.col("weight_left") * F.col("weight") <= F.col("cap"), F.struct("turn_order", (F.col("rest") / F.col("weight_left")).alias("level")))).over(everything)
    numbered = levels.withColumn("turn_order", F.row_number().over(by_level))
    return numbered.withColumn("level", water["level"]).select("source", "source_size", F.coalesce(F.least(F.col("cap"), F.col("level") * F.col("weight")), F.col("cap")).alias("target"))


def source_offset(source: Column, seed: int) -> Column:
    """One offset in [0, 1) for each source, the same in every run."""
    drawn = F.substring(F.md5(F.concat(F.lit(f"{seed}:"), F.coalesce(source, F.lit("\u0000")))), 1, 8)
    return F.conv(drawn, 16, 10).cast("double") / F.lit(float(1 << 32))


def placed_copies(documents: DataFrame, columns: list[str], weights: tuple[int, ...] = WEIGHTS, share: float = 1.5, limit: float = 2.0, seed: int = 7) -> DataFrame:
    """(row, size, source_size, target, copies): row holds the named columns."""
    # rows without an id are dealt over as many salts, behind those with one
    salt = F.coalesce(F.pmod(F.col("doc_id"), F.lit(SALTS)), F.pmod(F.xxhash64("text"), F.lit(SALTS)) + SALTS).cast("int").alias("salt")
    # the source as two columns without nulls, so that the ranks' partitioning serves the join as well and texts move once
    cell = [F.coalesce("source", F.lit("")).alias("s"), F.col("source").isNull().alias("unnamed"), word_count(F.col("text")).alias("size")]
    rows = documents.select(F.struct(*columns).alias("row"), *cell, salt, F.struct(F.col("doc_id"), F.xxhash64("text")).alias("turn"))
    cells = documents.select(*cell, salt).groupBy("s", "unnamed", "size", "salt").agg(F.count(F.lit(1)).alias("n"))
    by_size = cells.groupBy("s", "unnamed", "size").agg(F.sum("n").alias("n"))
    source = F.when(~F.col("unnamed"), F.col("s"))
    totals = by_size.groupBy("s", "unnamed").agg(F.sum(F.col("size") * F.col("n")).alias("source_size")).select(source.alias("source"), "source_size")
    targets = source_targets(totals, weights, share, limit).select(F.coalesce("source", F.lit("")).alias("s"), F.col("source").isNull().alias("unnamed"), "source_size", "target")
    earlier = Window.unboundedPreceding, -1
    above = F.coalesce(F.sum("n").over(Window.partitionBy("s", "unnamed").orderBy(F.col("size").desc()).rowsBetween(*earlier)), F.lit(0))
    beside = F.coalesce(F.sum("n").over(Window.partitionBy("s", "unnamed", "size").orderBy("salt").rowsBetween(*earlier)), F.lit(0))
    bases = cells.select("s", "unnamed", "size", "salt", beside.alias("beside")).join(by_size.select("s", "unnamed", "size", above.alias("above")), ["s", "unnamed", "size"])
    bases = bases.join(targets, ["s", "unnamed"]).select("s", "unnamed", "size", "salt", (F.col("above") + F.col("beside")).alias("base"), "source_size", "target")
    ranked = rows.withColumn("place", F.row_number().over(Window.partitionBy("s", "unnamed", "size", "salt").orderBy("turn")) - 1)
    placed = ranked.join(bases, ["s", "unnamed", "size", "salt"])
    rate = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(F.lit(0.0))
    rank, shift = (F.col("base") + F.col("place")).cast("double"), source_offset(source, seed)
    copies = (F.floor((rank + 1) * rate + shift) - F.floor(rank * rate + shift)).cast("long")
    return placed.select("row", "size", "source_size", "target", copies.alias("copies"))


def systematic_mix(documents: DataFrame, columns: list[str] | None = None, weights: tuple[int, ...] = WEIGHTS, share: float = 1.5, limit: float = 2.0, seed: int = 7) -> DataFrame:
    """The named columns (all if None) with size, source_size, target, copies and taken."""
    columns = documents.columns if columns is None else columns
    named = [x for x in columns if x.lower() not in ("size", "source_size", "target", "copies", "taken")]
    placed = placed_copies(documents, named, weights, share, limit, seed)
    return placed.select("row.*", "size", "source_size", "target", "copies", (F.col("copies") * F.col("size")).alias("taken"))


def mixed_copies(documents: DataFrame, weights: tuple[int, ...] = WEIGHTS, share: float = 1.5, limit: float = 2.0, seed: int = 7) -> DataFrame:
    """The documents, a row for each copy that the mix takes."""
    placed = placed_copies(documents, documents.columns, weights, share, limit, seed).where("copies > 0")
    return placed.select("row", F.explode(F.sequence(F.lit(1), F.col("copies").cast("int")))).select("row.*")
