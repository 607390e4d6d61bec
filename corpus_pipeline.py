"""From raw documents to packed training sequences, stage by stage.

Each stage gets what the stage before it kept, as a Parquet table with the
columns of documents; the last one returns the packed pieces.
"""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from partnet.llm import exact_dedup, mixing, packing, quality, shingle_links
from partnet.llm.common import fresh_name, materialize, read_table

Stage = Callable[[SparkSession, DataFrame, str], DataFrame]


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier rejects go."""
    weights = quality.fit_quality(docs, read_table(spark, sf_dir, "labels"))
    names = (fresh_name("score", docs.columns), fresh_name("predicted", docs.columns))
    return quality.score_documents(docs, weights, names=names).where(f"{names[1]} = 1").select(*docs.columns)


def exact_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts the smallest id stays."""
    return exact_dedup.kept_rows(docs)


def near_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each near-duplicate group stays: that with the smallest id, of several the one with the smallest text hash. Null ids come last.

    Texts are linked from a Jaccard similarity of 0.8 of their five-word shingles on. The fingerprint search of operator 5 finds most
    candidates; no affordable radius of 64 bits covers all, so shared prefixes add the rest, and every candidate is checked on its whole sets.
    """
    return shingle_links.one_of_each(docs).select(*docs.columns)


def mix_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """A row for each copy that the mix takes."""
    return mixing.mixed_copies(docs)


def pack_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.best_fit_pack(docs, public_tokenizers.path("byte_bpe_50k.json"))


STAGES: list[tuple[str, Stage]] = [
    ("quality classifier", quality_stage),
    ("exact dedup", exact_stage),
    ("SimHash near-dedup", near_stage),
    ("mixing to target weights", mix_stage),
    ("best-fit packing", pack_stage),
]

#: the learnt classifier and the tokenizer have no SQL form; tests hold run() against a brute-force version
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = materialize(stage(spark, docs, sf_dir), name.split()[0].lower())
    return STAGES[-1][1](spark, docs, sf_dir)
