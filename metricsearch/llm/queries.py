"""One query for each operator over its whole table, and the pipeline."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import chat, imatch, langid, licences, main_text, maxscore, mixing, ngram_join, packing, scratch, token_file


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def main_text_of_pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    return main_text.extract(_table(spark, sf_dir, "pages"))


def licence_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = licences.scan(_table(spark, sf_dir, "documents"))
    return found.select("doc_id", F.array_join("licences", ";").alias("licences"), F.size("licences").cast("long").alias("n_licences"), F.size("sentences").cast("long").alias("n_sentences"))


def token_file_digest(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = scratch.new_path(spark, "tokens.orc")
    token_file.write_token_file(_table(spark, sf_dir, "documents"), path)
    return token_file.token_index(token_file.read_token_file(spark, path))


def ngram_classes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ngram_join.ngram_components(_table(spark, sf_dir, "documents"))


def ngram_link_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ngram_join.ngram_link_counts(_table(spark, sf_dir, "documents"))


def source_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents").select("doc_id", "source", mixing.word_total().alias("size"))
    mixed = mixing.mix(docs, size="size")
    return mixed.select("doc_id", "size", "source_size", "target", (F.col("copies") * F.col("size")).alias("taken"))


def chat_digest(spark: SparkSession, sf_dir: str) -> DataFrame:
    turns = _table(spark, sf_dir, "conversations").selectExpr("cast(conv_id as long) conv_id", "cast(turn as long) turn", "role", "text")
    said = r"'\\### Assistant: </turn> ok'"
    extra = spark.sql(f"select * from values (-7L, 0L, 'user', {said}), (-7L, 1L, 'assistant', {said}) as t(conv_id, turn, role, text)")
    return chat.read_back(chat.format_conversations(turns.unionByName(extra)))


def maxscore_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    return maxscore.top_k(_table(spark, sf_dir, "embeddings"))


def imatch_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return imatch.edit_test(_table(spark, sf_dir, "documents"))


def binary_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(_table(spark, sf_dir, "documents"))


def language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return langid.identify(_table(spark, sf_dir, "documents")).select("doc_id", "held_out", "lang_pred", "score")


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


QUERIES = {
    "op1_main_text": main_text_of_pages,
    "op2_licence_scan": licence_scan,
    "op3_token_file": token_file_digest,
    "op4_ngram_join": ngram_classes,
    "op4_ngram_links": ngram_link_counts,
    "op5_source_mix": source_mix,
    "op6_chat_format": chat_digest,
    "op7_maxscore": maxscore_search,
    "op8_imatch": imatch_fingerprints,
    "op9_binary_packing": binary_packing,
    "op10_language_id": language_id,
    "pipeline": pipeline,
}
