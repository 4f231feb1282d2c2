"""Queries of the training-data operators over the whole given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from assocmine.llm import bpe, chat, mixing, mtree, quality, repeats, sharding, simhash, token_files, toxicity
from assocmine.llm.vocabulary import public_path


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def op1_bpe_automaton(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = public_path("word_bpe_49k.json")
    encoded = bpe.encode(documents(spark, sf_dir), path, ["doc_id"])
    return bpe.digest(bpe.decode(encoded, path, ["doc_id"]))


def op2_decision_list(spark: SparkSession, sf_dir: str) -> DataFrame:
    judged = quality.judge(documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return judged.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "rule")


def op3_bit_plane_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_files.write_and_read(documents(spark, sf_dir), public_path("byte_bpe_50k.json"))


def op4_prefix_free_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return repeats.digest(repeats.removed(documents(spark, sf_dir), words=repeats.WORDS))


def op5_prefix_target_chat(spark: SparkSession, sf_dir: str) -> DataFrame:
    said = "\\### Assistant: </turn> ok"
    added = spark.createDataFrame([(-7, 0, "user", said), (-7, 1, "assistant", said)], "conv_id long, turn long, role string, text string")
    return chat.digest(chat.stream(spark.read.parquet(f"{sf_dir}/conversations.parquet").select("conv_id", "turn", "role", "text").unionByName(added)))


def op6_mtree_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mtree.top_of_every_hundredth(spark.read.parquet(f"{sf_dir}/embeddings.parquet"))


def op7_source_schedule(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(documents(spark, sf_dir)).drop("h")


def op8_simhash_ball(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(documents(spark, sf_dir))


def op9_toxicity_lexicon(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    return toxicity.score(docs, toxicity.fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")))


def op10_histogram_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.shards(documents(spark, sf_dir))


QUERIES = {
    "op1_bpe_automaton": op1_bpe_automaton,
    "op2_decision_list": op2_decision_list,
    "op3_bit_plane_files": op3_bit_plane_files,
    "op4_prefix_free_dedup": op4_prefix_free_dedup,
    "op5_prefix_target_chat": op5_prefix_target_chat,
    "op6_mtree_search": op6_mtree_search,
    "op7_source_schedule": op7_source_schedule,
    "op8_simhash_ball": op8_simhash_ball,
    "op9_toxicity_lexicon": op9_toxicity_lexicon,
    "op10_histogram_shards": op10_histogram_shards,
}
ORACLES = {"op5_prefix_target_chat": chat.ORACLE, "op6_mtree_search": mtree.ORACLE}
