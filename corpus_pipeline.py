"""From raw documents to packed sequences: language, near duplicates, mix, packing.

Each stage takes (spark, docs, sf_dir) with the rows its predecessor kept, written and read again in between.
"""

from __future__ import annotations

import uuid
from contextvars import ContextVar

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from metricsearch.llm import langid, mixing, ngram_join, packing, scratch

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]
LEAST_SCORE = 0.5  # of the best language; below it no language holds a majority
PACKED_WORDS = 50_000  # that a packing worker remembers, in each of two generations; executors are full by then
_owner: ContextVar[str | None] = ContextVar("owner", default=None)


def _own(spark: SparkSession) -> str:
    """Whose tables a stage writes: those of its run; called on its own, a stage deletes what the stage called so
    before it has left, as that one's result has been written by then."""
    if _owner.get() is None:
        scratch.release(spark, "stage")
    return _owner.get() or "stage"


def known_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose language can be told, as they are; null texts, texts without letters and undecided ones go.

    Repeated rows all stay or all go; a null lang, source or doc_id is no reason to go. Texts of any length are read
    whole. Where no row that may be learnt from has a language, all go. An empty table gives no rows. Of other
    columns than ``COLUMNS`` none is returned, whatever their names.
    """
    owner = _own(spark)
    with scratch.small_batches(spark, 1000, 1 << 20):
        found = langid.identify(docs.select(*COLUMNS))
        kept = found.where((F.col("lang_pred") != langid.UNKNOWN) & (F.col("score") >= LEAST_SCORE)).select(*COLUMNS)
        return scratch.write_table(kept, "known-language", owner)  # here, as the small batches end with this block


def one_of_each(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document, the least doc_id, of each component of near duplicates.

    Null, empty and blank texts are like nothing and stay, and so do rows without doc_id. Repeated rows of a doc_id
    that stays all stay. An empty table gives no rows. Of other columns than ``COLUMNS`` none is returned.
    """
    return ngram_join.first_of_each(docs.select(*COLUMNS), owner=_own(spark))


def target_mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the mix takes them, copies as rows of their own.

    Null sources are one source; rows without words are taken at their source's rate; ties of size stand by doc_id and
    a hash of the row, so reruns agree. An empty table gives no rows. Of other columns than ``COLUMNS`` none is returned.
    """
    return mixing.take(mixing.mix(docs.select(*COLUMNS), owner=_own(spark))).select(*COLUMNS)


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of binary length, each a sequence; see :func:`packing.pack` for its columns.

    A null or empty text is one piece with the end id. Repeated rows, as the mix makes them, are packed each. An empty
    table gives no rows. Columns other than doc_id and text take no part.
    """
    return packing.pack(docs.select("doc_id", "text"), owner=_own(spark), most_words=PACKED_WORDS)


STAGES = [("language_id", known_language), ("ngram_join", one_of_each), ("source_mix", target_mix), ("packing", packed)]

#: Tokenizer ids and a fitted model are beyond SQL; tests hold the result against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the documents of ``sf_dir``, each written and reread as the next one's input.

    What a stage has written beside its result is deleted once that is written; the last stage's tables, which the
    lazy result reads, stay to the end of the driver's process, and so runs do not touch each other.
    """
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    name = f"pipeline-{uuid.uuid4().hex}"
    for k, (stage_name, stage) in enumerate(STAGES):
        token = _owner.set(f"{name}/{k}")
        try:
            out = stage(spark, docs, sf_dir)
            if k + 1 == len(STAGES):
                return out
            docs = scratch.write_table(out, f"stage-{k}-{stage_name}", f"{name}-out/{k}")
        finally:
            _owner.reset(token)
        scratch.release(spark, f"{name}/{k}")
    return docs
