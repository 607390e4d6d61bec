"""What the corpus operators share: shared storage, word rules and the Arrow map."""

from __future__ import annotations

import ctypes
import tempfile
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

#: Words of every contract: runs of anything but the ASCII white space below.
WORD_PATTERN = r"[^\x20\x09-\x0D]+"
#: rows that a Python step holds at once
STEP_ROWS = 1_000
SPACE_PATTERN = r"[\x20\x09-\x0D]+"


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share; one is made only where the session names none."""
    sc = spark.sparkContext
    named = spark.conf.get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if not named:
        named = tempfile.mkdtemp(prefix="partnet-")
        sc.setCheckpointDir(named)
        named = sc.getCheckpointDir()
    return named.rstrip("/")


def scratch_path(spark: SparkSession, label: str) -> str:
    """A fresh path in the shared folder, removed when the driver's JVM ends."""
    path = f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"
    hadoop = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    hadoop.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).deleteOnExit(hadoop)
    return path


def materialize(df: DataFrame, label: str) -> DataFrame:
    """Writes df to the shared folder and reads it back: lineage ends there and lost executors cost nothing."""
    spark = df.sparkSession
    path = scratch_path(spark, label)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


#: what a worker process keeps from task to task, such as a tokenizer
KEPT: dict[str, object] = {}


def kept(name: str, make: Callable[[str], object]) -> object:
    """make(name), once in a worker process for as long as its tasks are those that keep things."""
    if name not in KEPT:
        KEPT[name] = make(name)
    return KEPT[name]


def drop_kept() -> None:
    KEPT.clear()


def give_back() -> None:
    """Freed memory goes back to the system. Workers live on after a stage, and their free memory counts for the stages that follow."""
    pa.default_memory_pool().release_unused()
    getattr(ctypes.CDLL(None), "malloc_trim", lambda _: 0)(0)


def tidy(run: Callable[[Iterator], Iterator], keeps: bool = False) -> Callable[[Iterator], Iterator]:
    """The Python step of a task. Unless it keeps things itself, what the worker kept from other steps goes before it starts."""

    def whole(batches: Iterator) -> Iterator:
        if not keeps:
            drop_kept()
        try:
            yield from run(batches)
        finally:
            give_back()

    return whole


def map_rows(df: DataFrame, start: Callable[[], Callable[[pa.RecordBatch], pa.RecordBatch | None]], schema: str, keeps: bool = False) -> DataFrame:
    """mapInArrow with per-task state: start() makes the batch function once per task; its attribute finish, if any, is called last. keeps: start() uses kept()."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        step = start()
        for batch in batches:
            for at in range(0, batch.num_rows, STEP_ROWS):
                if (out := step(batch.slice(at, STEP_ROWS))) is not None:
                    yield out
        getattr(step, "finish", lambda: None)()

    return df.mapInArrow(tidy(run, keeps), schema)


def fresh_name(name: str, columns: list[str]) -> str:
    """The name, with as many underscores behind it as keep it apart from the columns (names that differ in case only are the same)."""
    taken = {x.lower() for x in columns}
    while name.lower() in taken:
        name += "_"
    return name


def texts_as_bytes(column: pa.Array) -> list[bytes]:
    """Whole texts in UTF-8; null counts as empty."""
    return [x or b"" for x in column.cast(pa.binary()).to_pylist()]
