"""The queries of this subpackage: each applies one operator with production parameters to its whole table."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import crf_language, lexicon_automata, line_dedup, minhash, pfair_mix, piece_transducer, prefix_join, surrogates, token_counts, transport_stream
from .common import table

PIECES = "piece_bpe_32k.model"


def vocabulary(name: str = PIECES) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_lexicon_automata(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lexicon_automata.toxicity_report(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op2_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts.token_counts(table(spark, sf_dir, "documents"), vocabulary())


def op3_transport_streams(spark: SparkSession, sf_dir: str) -> DataFrame:
    return transport_stream.media_columns(table(spark, sf_dir, "documents"))


def op4_crf_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    return crf_language.language_report(table(spark, sf_dir, "documents"))


def op5_piece_transducer(spark: SparkSession, sf_dir: str) -> DataFrame:
    return piece_transducer.round_trip(table(spark, sf_dir, "documents"), vocabulary())


def op6_one_permutation_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return minhash.edited_fingerprints(table(spark, sf_dir, "documents"))


def op7_keyed_surrogates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return surrogates.surrogate_report(table(spark, sf_dir, "documents"))


def op8_prefix_tree_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return prefix_join.link_classes(table(spark, sf_dir, "documents"))


def op9_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_dedup.digest_columns(table(spark, sf_dir, "documents"))


def op10_pfair_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pfair_mix.mix(table(spark, sf_dir, "documents").select("doc_id", "source"))


ALL = (
    op1_lexicon_automata, op2_token_counts, op3_transport_streams, op4_crf_language, op5_piece_transducer,
    op6_one_permutation_minhash, op7_keyed_surrogates, op8_prefix_tree_join, op9_line_dedup, op10_pfair_mix,
)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in ALL}


def oracle_sql() -> dict[str, str]:
    """SQL of the queries that it can express; the others are tested against brute force, round trips or held-out rows."""
    return {"op8_prefix_tree_join": prefix_join.ORACLE, "op9_line_dedup": line_dedup.ORACLE, "op10_pfair_mix": pfair_mix.ORACLE}
