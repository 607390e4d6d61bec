"""Streams of tables that are folders of files, and of rows without values, against the queries' SQL."""

import duckdb

from partnet import catalog
from partnet.streaming import joint_stream as streams


def by_sql(name, directory, table):
    with duckdb.connect() as db:
        db.execute(f"CREATE VIEW {table} AS SELECT * FROM '{directory}/{table}.parquet/*.parquet'")
        return sorted(db.execute(catalog.oracles()[name]).fetchall(), key=str)


def test_labels_of_a_table_in_several_files(spark, sf, tmp_path):
    rows = spark.read.parquet(f"{sf}/conversations.parquet").select("conv_id", "turn", "role", "text")
    odd = spark.createDataFrame([(-1, None, "user", "x"), (-2, 50, None, "x"), (-3, -7, None, "x"), (-4, None, None, None)], rows.schema)
    rows.unionByName(odd).repartition(3).write.parquet(f"{tmp_path}/conversations.parquet")
    got = [tuple(r) for r in catalog.queries()["stream_labels"](spark, str(tmp_path)).select("turn", "role", "t", "n").collect()]
    assert got and sorted(got, key=str) == by_sql("stream_labels", tmp_path, "conversations")


def test_events_in_several_files(spark, sf, tmp_path):
    events = spark.read.parquet(f"{sf}/events.parquet")
    events.repartition(3).write.parquet(f"{tmp_path}/events.parquet")
    for directory in (sf, str(tmp_path)):
        counted = streams.drain(streams.event_stream(spark, directory).groupBy("event_type").count())
        assert {tuple(r) for r in counted.collect()} == {tuple(r) for r in events.groupBy("event_type").count().collect()}
