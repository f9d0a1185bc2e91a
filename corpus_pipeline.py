"""A corpus pipeline of five operators; each stage's output is written and read again."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from pathsieve.llm.decontaminate import without_contaminated
from pathsieve.llm.line_dedup import without_repeated_lines
from pathsieve.llm.near_dedup import without_near_duplicates
from pathsieve.llm.quality_rules import passing
from pathsieve.llm.sentence_pieces import encode
from pathsieve.loop import cut, scratch


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that pass the quality rules."""
    return passing(docs)


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without later repeats of passages of lines; a document of which nothing is left goes."""
    return without_repeated_lines(docs, emptied=False).select(*docs.columns)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates."""
    return without_near_duplicates(docs)


def decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without benchmark passages."""
    return without_contaminated(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def sentence_pieces(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Piece ids of each text, and whether decoding them gives the text back."""
    import public_tokenizers

    return encode(docs, public_tokenizers.path("piece_bpe_32k.model"))


STAGES = [
    ("quality_rules", quality),
    ("line_dedup", line_dedup),
    ("near_dedup", near_duplicates),
    ("decontamination", decontaminate),
    ("sentence_pieces", sentence_pieces),
]
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; what a stage wrote on its way goes once its output is written."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (name, stage) in enumerate(STAGES):
        if k == len(STAGES) - 1:
            return stage(spark, docs, sf_dir)
        with scratch(spark) as held:
            docs = held.keep(cut(stage(spark, docs, sf_dir), name))
    return docs
