"""Joint distributions as sparse cell tables: columns of values, n (weight) and p (share)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def build_joint(df: DataFrame, variables: list[str], weight: Column | str | None = None, nulls: str = "drop", min_count: float = 0) -> DataFrame:
    """Weighted co-occurrence counts over their total.

    nulls: "drop" leaves out rows with a null value, "level" makes null the value "(null)". One shuffle, on the values.
    """
    if nulls == "drop":
        df = df.dropna(subset=variables)
    elif nulls == "level":
        df = df.withColumns({v: F.coalesce(F.col(v).cast("string"), F.lit("(null)")) for v in variables})
    else:
        raise ValueError(f"nulls is drop or level, not {nulls!r}")
    amount = F.lit(1.0) if weight is None else (F.col(weight) if isinstance(weight, str) else weight).cast("double")
    cells = df.groupBy(*variables).agg(F.sum(amount).alias("n")).where((F.col("n") > 0) & (F.col("n") >= min_count))
    return normalise(cells)


def normalise(cells: DataFrame) -> DataFrame:
    """p from n: the total is one row."""
    total = cells.agg(F.sum("n").alias("total"))
    return cells.crossJoin(F.broadcast(total)).withColumn("p", F.col("n") / F.col("total")).drop("total")


def marginal(joint: DataFrame, keep: list[str]) -> DataFrame:
    return joint.groupBy(*keep).agg(F.sum("p").alias("p"))


def conditional(joint: DataFrame, of: list[str], given: list[str]) -> DataFrame:
    """(given, of, p_cond)."""
    both, base = marginal(joint, [*given, *of]), marginal(joint, given).withColumnRenamed("p", "base")
    return both.join(base, given).select(*given, *of, (F.col("p") / F.col("base")).alias("p_cond"))


def ranked(rows: DataFrame, order: list, name: str = "i", summed: str | None = None) -> DataFrame:
    """rows with their place from 0 in the given order, without one task for all: sorted ranges, each with the counts of those before it.

    summed: a column whose running total, this row included, is added as `reached`. The sorted rows are written once, so that ranges and
    counts agree; there is one row of counts for each range, as many as the engine's partitions.
    """
    from pyspark.sql.window import Window

    from partnet.sources.tables import cut_lineage

    part, at = f"{name}_part", f"{name}_at"
    dealt = cut_lineage(rows.repartitionByRange(*order).sortWithinPartitions(*order).withColumn(at, F.monotonically_increasing_id()))
    dealt = dealt.withColumn(part, F.shiftright(at, 33)).withColumn(at, F.col(at).bitwiseAND(F.lit((1 << 33) - 1)))
    counts = dealt.groupBy(part).agg(F.count(F.lit(1)).alias("n"), (F.sum(summed) if summed else F.lit(0.0)).alias("s"))
    x, y = (counts.select(F.col(part).alias(f"{k}b"), F.col("n").alias(f"{k}n"), F.col("s").alias(f"{k}s")) for k in "xy")
    before = x.join(y, F.col("yb") < F.col("xb"), "left").groupBy(F.col("xb").alias(part)).agg(F.coalesce(F.sum("yn"), F.lit(0)).alias("n_before"), F.coalesce(F.sum("ys"), F.lit(0.0)).alias("s_before"))
    placed = dealt.join(F.broadcast(before), part).withColumn(name, F.col("n_before") + F.col(at))
    if summed:
        inside = Window.partitionBy(part).orderBy(at).rowsBetween(Window.unboundedPreceding, 0)
        placed = placed.withColumn("reached", F.col("s_before") + F.sum(summed).over(inside))
    return placed.drop(part, at, "n_before", "s_before")


def encode(joint: DataFrame, variables: list[str]) -> tuple[DataFrame, DataFrame]:
    """Integer codes for values: (joint of codes, dictionary(var, code, value)). Codes follow the values' order."""
    dictionary = None
    for v in variables:
        codes = ranked(joint.select(F.col(v).alias("value")).distinct(), ["value"], "code")
        joint = joint.join(codes.withColumnRenamed("code", f"{v}__code"), F.col(v) == F.col("value")).drop(v, "value").withColumnRenamed(f"{v}__code", v)
        rows = codes.select(F.lit(v).alias("var"), "code", F.col("value").cast("string").alias("value"))
        dictionary = rows if dictionary is None else dictionary.unionByName(rows)
    return joint, dictionary


def width_bins(column: Column, low: float, high: float, bins: int) -> Column:
    return F.width_bucket(column, F.lit(low), F.lit(high), F.lit(bins))
