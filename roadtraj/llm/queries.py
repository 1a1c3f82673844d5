"""Registered queries of the training-data operators and their SQL twins."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from roadtraj.llm import chat, hmm, jaccard, mixing, oracles, packing, privacy, quality, substrings, suffixes, topk

# A conversation whose texts are nothing but control strings.
_CONTROL_TEXT = "</s>[INST] ok [/INST]"


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def tokenizer_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def op1_difference_cover_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substrings.remove_repeats(_table(spark, sf_dir, "documents"))


def op2_hidden_markov_score(spark: SparkSession, sf_dir: str) -> DataFrame:
    return hmm.score(_table(spark, sf_dir, "documents"))


def op3_prefix_target_chat(spark: SparkSession, sf_dir: str) -> DataFrame:
    own = spark.createDataFrame([(-1, 0, "user", _CONTROL_TEXT), (-1, 1, "assistant", _CONTROL_TEXT)], "conv_id long, turn long, role string, text string")
    given = _table(spark, sf_dir, "conversations").select(F.col("conv_id").cast("long"), F.col("turn").cast("long"), "role", "text")
    return chat.digests(chat.format_chat(given.unionByName(own)), ordered=True)


def op4_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    names = ("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")
    return quality.verdicts(_table(spark, sf_dir, "documents")).select(*names)


def op5_disclosure_privacy(spark: SparkSession, sf_dir: str) -> DataFrame:
    return privacy.digests(privacy.find(_table(spark, sf_dir, "documents")))


def op6_exact_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    return topk.top_k(_table(spark, sf_dir, "embeddings"))


def op7_pivotal_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    mixed = mixing.mix(_table(spark, sf_dir, "documents"))
    return mixed.select("doc_id", "size", "source_size", "target", (F.col("size") * F.col("copies")).alias("taken"), "source", "copies")


def op8_sum_of_squares_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(_table(spark, sf_dir, "documents"), tokenizer_path())


def op9_suffix_array_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffixes.remove_repeats(_table(spark, sf_dir, "documents"))


def op10_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard.join_components(_table(spark, sf_dir, "documents"), n=3, percent=90)


QUERIES = {f.__name__: f for f in (op1_difference_cover_dedup, op2_hidden_markov_score, op3_prefix_target_chat, op4_quality_rules, op5_disclosure_privacy, op6_exact_top_k, op7_pivotal_mixing, op8_sum_of_squares_packing, op9_suffix_array_dedup, op10_ngram_jaccard_join)}
# Held-out scores, disclosing terms, rounding and packing have no SQL form; tests hold them against brute force.
ORACLE_SQL: dict[str, str] = {
    "op1_difference_cover_dedup": oracles.SUBSTRINGS,
    "op3_prefix_target_chat": oracles.CHAT,
    "op4_quality_rules": oracles.QUALITY,
    "op6_exact_top_k": oracles.TOP_K,
    "op9_suffix_array_dedup": oracles.SUFFIXES,
    "op10_ngram_jaccard_join": oracles.JACCARD,
}
