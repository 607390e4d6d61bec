"""What workers keep between stages."""

import public_tokenizers
import pyarrow as pa

from partnet.llm import packing
from partnet.llm.common import map_rows


def kept_by_workers(df):
    """Names kept in the worker processes, as steps see them that keep nothing themselves."""

    def start():
        from partnet.llm import common

        held = len(common.KEPT)
        return lambda batch: pa.RecordBatch.from_arrays([pa.array([held] * batch.num_rows)], ["held"])

    return {r["held"] for r in map_rows(df.select("doc_id"), start, "held long").collect()}


def test_the_tokenizer_goes_when_another_stage_starts(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").repartition(8)
    path = public_tokenizers.path("byte_bpe_50k.json")
    pieces = packing.tokenised_pieces(docs, path)
    first = sorted(map(tuple, pieces.select("doc_id", "piece", "ids_crc32").collect()))
    assert kept_by_workers(docs) == {0}
    assert sorted(map(tuple, pieces.select("doc_id", "piece", "ids_crc32").collect())) == first
