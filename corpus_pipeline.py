"""A corpus pipeline of five text operators. Each stage takes documents and returns documents; the last adds piece ids."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from skyjoin.llm import crf_language, line_dedup, pfair_mix, piece_transducer, prefix_join
from skyjoin.llm.common import checkpointed, prepare, table
from skyjoin.llm.queries import vocabulary

#: A document stays if its likeliest language has this share of its words.
LEAST_SHARE = 0.5


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a letter, or in no language by more than half, go: numbers, keys and mixtures. Learned from docs' own lang."""
    prepare(spark)
    return crf_language.keep_confident(docs, least=LEAST_SHARE)


def shared_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines that at least three documents share stay in the one with the largest id; n_chars follows the text."""
    prepare(spark)
    out = line_dedup.dedup_lines(docs).select(*docs.columns)
    return out.withColumn("n_chars", F.char_length("text").cast("long")).select(*docs.columns) if "n_chars" in docs.columns else out


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of near-duplicates stays: the one with the smallest id."""
    prepare(spark)
    return prefix_join.first_of_each_class(docs)


def source_mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in the order of the mix of their sources, over files in order."""
    prepare(spark)
    return pfair_mix.mixed(docs)


def piece_encoding(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with the ids of their pieces."""
    prepare(spark)
    return piece_transducer.encode_texts(docs, vocabulary())


STAGES = [
    ("language_id", language_id),
    ("line_dedup", shared_lines),
    ("near_duplicates", near_duplicates),
    ("source_mix", source_mix),
    ("piece_encoding", piece_encoding),
]

#: The learned language model can't be said in SQL; tests hold the pipeline against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents. What a stage kept is checkpointed, as the next one reads it more than once.

    The rows carry mix_order, their place in the mix: sorting by it gives the mix again after any write and read.
    """
    docs = table(spark, sf_dir, "documents")
    for k, (name, stage) in enumerate(STAGES):
        docs = pfair_mix.mixed(docs, place=True) if name == "source_mix" else stage(spark, docs, sf_dir)
        if k + 1 < len(STAGES):
            docs = checkpointed(docs)
    return docs
