"""Contingency tables from streams: windows, watermarks, dedup, warm restarts, drift."""

from __future__ import annotations

import math
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from partnet.operators.apply import assign
from partnet.sources.tables import cut_lineage, scratch_path


def event_stream(spark: SparkSession, directory: str, name: str = "events", time: str | None = "ts") -> DataFrame:
    """A table as a stream, whether it is one file or a folder of them; the time becomes a timestamp, since watermarks don't take one without a zone."""
    schema = spark.read.parquet(f"{directory}/{name}.parquet").schema
    rows = spark.readStream.schema(schema).parquet(f"{directory}/{name}.parque[t]")  # a stream takes a single file from a pattern only
    return rows.withColumn(time, F.col(time).cast("timestamp")) if time else rows


def windowed_joint(rows: DataFrame, variables: list[str], window: str, slide: str | None = None, watermark: str | None = "1 hour", time: str = "ts") -> DataFrame:
    """(start, end, variables, n) per tumbling or sliding window. State is the cells of live windows."""
    timed = rows.withWatermark(time, watermark) if watermark else rows
    at = F.window(time, window, slide) if slide else F.window(time, window)
    cells = timed.groupBy(at, *variables).agg(F.count(F.lit(1)).alias("n"))
    return cells.select(F.col("window.start").alias("start"), F.col("window.end").alias("end"), *variables, "n")


def session_counts(rows: DataFrame, variables: list[str], gap: str, watermark: str = "1 hour", time: str = "ts") -> DataFrame:
    timed = rows.withWatermark(time, watermark)
    sessions = timed.groupBy(F.session_window(time, gap), *variables).agg(F.count(F.lit(1)).alias("n"))
    return sessions.select(F.col("session_window.start").alias("start"), F.col("session_window.end").alias("end"), *variables, "n")


def deduplicated(rows: DataFrame, key: str, watermark: str = "1 hour", time: str = "ts") -> DataFrame:
    return rows.withWatermark(time, watermark).dropDuplicatesWithinWatermark([key])


def drain(stream: DataFrame, mode: str = "complete", folder: str | None = None) -> DataFrame:
    """Runs a stream over all that is there and returns what it wrote.

    Every batch becomes Parquet files, and the state lies beside them, in the folder given or a fresh one in shared storage; a run that was
    stopped goes on from there, and a batch that is sent again replaces itself. In complete mode the last batch holds everything.
    """
    spark = stream.sparkSession
    folder = folder or scratch_path(spark, "stream")

    def keep(batch: DataFrame, batch_id: int) -> None:
        batch.write.mode("overwrite").parquet(f"{folder}/rows/batch={batch_id}")

    stream.writeStream.foreachBatch(keep).outputMode(mode).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start().awaitTermination()
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{folder}/rows")
    if not path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(path):
        return spark.createDataFrame([], stream.schema)
    rows = spark.read.schema(stream.schema.add("batch", "long")).parquet(f"{folder}/rows")
    if mode == "complete":
        rows = rows.where(F.col("batch") == rows.agg(F.max("batch")).first()[0])
    return rows.drop("batch")


def late_rows(rows: DataFrame, kept: DataFrame) -> DataFrame:
    """One row: sent, kept and late, from what was sent and the counts (n) that came out. Spark's own counter tells groups, not rows."""
    sent = rows.agg(F.count(F.lit(1)).alias("sent"))
    return sent.crossJoin(kept.agg(F.coalesce(F.sum("n"), F.lit(0)).cast("long").alias("kept"))).select("sent", "kept", (F.col("sent") - F.col("kept")).alias("late"))


def resolve_each_batch(refit, state: dict):
    """foreachBatch function: adds a batch's counts to those held and refits from the last tables.

    refit(cells, previous) gets the summed cells (variables, n) and returns the new model; state keeps both.
    """

    def step(batch: DataFrame, batch_id: int) -> None:
        if batch_id <= state.get("batch", -1):  # a replayed batch was counted already
            return
        variables = [c for c in batch.columns if c != "n"]
        cells = batch if state.get("cells") is None else state["cells"].unionByName(batch).groupBy(*variables).agg(F.sum("n").alias("n"))
        state["cells"] = cut_lineage(cells)
        state["model"] = refit(state["cells"], state.get("model"))
        state["batch"] = batch_id

    return step


def label_stream(rows: DataFrame, part: DataFrame, sources: list[str]) -> DataFrame:
    """Arriving rows with the label of a stored table."""
    return rows.join(assign(part, sources), sources, "left")


def drift(rows: DataFrame, key: str, value: str, reference: dict[str, float]) -> DataFrame:
    """(key, n, kl): for each key, how far the values seen so far are from a reference distribution, in bits. Stateful."""
    levels = sorted(reference)

    def update(group: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        counts = list(state.get[0]) if state.exists else [0] * len(levels)
        for rows in batches:
            seen = rows[value].value_counts()
            counts = [c + int(seen.get(x, 0)) for c, x in zip(counts, levels, strict=True)]
        state.update((counts,))
        n = sum(counts)
        kl = sum(c / n * math.log2(c / n / reference[x]) for c, x in zip(counts, levels, strict=True) if c) if n else 0.0
        yield pd.DataFrame({key: [group[0]], "n": [n], "kl": [kl]})

    kind = dict(rows.dtypes)[key]
    return rows.select(key, value).groupBy(key).applyInPandasWithState(update, f"{key} {kind}, n long, kl double", "counts array<long>", "update", GroupStateTimeout.NoTimeout)
