"""Queries of the training-data operators, and the SQL of those that SQL can express on whole tables."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from voxtable.llm import chat_examples, decontaminate, exact_dedup, fuzzy_lines, hilbert_shards, mix_sources, secret_grammar, simhash_dedup, token_fst, toxicity
from voxtable.llm.common import table


def op1_pigeonhole_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op2_fuzzy_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fuzzy_lines.line_report(table(spark, sf_dir, "documents"))


def op3_string_kernel_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return toxicity.score(docs, toxicity.fit_on(docs, table(spark, sf_dir, "labels")))


def op4_salted_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.exact_groups(table(spark, sf_dir, "documents"))


def op5_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix_sources.mix_table(table(spark, sf_dir, "documents"))


def op6_simhash_bytes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash_dedup.simhash_components(table(spark, sf_dir, "documents"))


def op7_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return token_fst.token_counts(table(spark, sf_dir, "documents"), public_tokenizers.path("piece_bpe_32k.model"))


def op8_secret_grammar(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secret_grammar.secret_spans(table(spark, sf_dir, "documents"))


def op9_prefix_targets(spark: SparkSession, sf_dir: str) -> DataFrame:
    conversations = chat_examples.with_control_conversation(spark, table(spark, sf_dir, "conversations"))
    return chat_examples.read_back(chat_examples.examples(chat_examples.segments(conversations)))


def op10_hilbert_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return hilbert_shards.place(table(spark, sf_dir, "documents"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f
    for f in (
        op1_pigeonhole_decontamination, op2_fuzzy_lines, op3_string_kernel_toxicity, op4_salted_exact_dedup, op5_mix_sources,
        op6_simhash_bytes, op7_token_counts, op8_secret_grammar, op9_prefix_targets, op10_hilbert_shards,
    )
}

ORACLES = {
    "op4_salted_exact_dedup": exact_dedup.ORACLE,
    "op5_mix_sources": mix_sources.ORACLE,
    "op9_prefix_targets": chat_examples.ORACLE,
}
