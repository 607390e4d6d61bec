"""Readers and writers: given tables, joints given as cell files, fitted models."""

from __future__ import annotations

import json
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def read_table(spark: SparkSession, directory: str, name: str, schema: T.StructType | str | None = None) -> DataFrame:
    reader = spark.read.schema(schema) if schema is not None else spark.read
    return reader.parquet(f"{directory}/{name}.parquet")


def read_cells(spark: SparkSession, path: str, variables: list[str], fmt: str = "csv") -> DataFrame:
    """A joint given as rows of values and weight, in CSV, JSON, ORC or Parquet."""
    schema = T.StructType([*(T.StructField(v, T.StringType()) for v in variables), T.StructField("n", T.DoubleType())])
    reader = spark.read.schema(schema).format(fmt)
    return (reader.option("header", "true") if fmt == "csv" else reader).load(path)


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share; one is made only where the session names none."""
    sc = spark.sparkContext
    if not sc.getCheckpointDir():
        sc.setCheckpointDir(spark.conf.get("spark.checkpoint.dir", None) or tempfile.mkdtemp(prefix="partnet-"))
    return sc.getCheckpointDir()


def scratch_path(spark: SparkSession, label: str) -> str:
    """A fresh path in the shared folder, removed when the driver ends."""
    path = f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"
    hadoop = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    hadoop.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).deleteOnExit(hadoop)
    return path


def cut_lineage(df: DataFrame) -> DataFrame:
    """A reliable checkpoint in the session's folder, for tables that stay."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)


class Written:
    """Tables of a loop, written to the shared folder and read back; each lives until it is dropped."""

    def __init__(self, spark: SparkSession, label: str):
        self.spark, self.folder, self.paths = spark, scratch_path(spark, label), {}

    def keep(self, df: DataFrame) -> DataFrame:
        path = f"{self.folder}/{len(self.paths)}"
        df.write.parquet(path)
        out = self.spark.read.schema(df.schema).parquet(path)
        self.paths[len(self.paths)] = (path, out)
        return out

    def drop(self, df: DataFrame) -> None:
        """Removes the files behind a table that keep() returned; others are left alone."""
        for k, (path, held) in list(self.paths.items()):
            if held is df and path:
                hadoop = self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
                hadoop.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).delete(hadoop, True)
                self.paths[k] = ("", None)


def save_partitions(parts: dict[str, DataFrame], spec_json: str, path: str, mode: str = "errorifexists") -> None:
    """Each cluster variable's table under its name, the specification as one JSON row."""
    for name, df in parts.items():
        df.write.mode(mode).parquet(f"{path}/part={name}")
        spark = df.sparkSession
    spark.createDataFrame([(spec_json,)], "spec string").coalesce(1).write.mode(mode).json(f"{path}/spec")


def load_partitions(spark: SparkSession, path: str) -> tuple[dict[str, DataFrame], dict]:
    spec = json.loads(spark.read.schema("spec string").json(f"{path}/spec").first()["spec"])
    return {name: spark.read.parquet(f"{path}/part={name}") for name in spec["clusters"]}, spec


def bucketed_copies(joint: DataFrame, variables: list[str], prefix: str, buckets: int) -> dict[str, DataFrame]:
    """A saved copy of the joint for each variable, bucketed and sorted by it: loops then join without moving the joint."""
    spark, out = joint.sparkSession, {}
    for v in variables:
        joint.write.mode("overwrite").bucketBy(buckets, v).sortBy(v).saveAsTable(f"{prefix}_{v}")
        out[v] = spark.table(f"{prefix}_{v}")
    return out


def ship_value(price: str = "l_extendedprice", discount: str = "l_discount"):
    return F.col(price) * (1 - F.col(discount))
