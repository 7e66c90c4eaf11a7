"""Packing by powers of two: each document is cut into pieces of binary length, and equal lengths share a bucket.

A document of n ids becomes n // longest pieces of ``longest`` ids and one piece for each set bit of the rest, the
longest first. A piece is a sequence of its own, so no sequence holds two documents and none is padded.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import scratch, tokens, workers

PIECES = "doc_id long, part int, place long, start long, length long, ids_crc32 long, doc_tokens long, bucket int"


def piece_lengths(n: int, longest: int = 4096) -> list[int]:
    """Lengths of a document's pieces in order; they sum to n."""
    rest = n % longest
    return [longest] * (n // longest) + [1 << k for k in range(rest.bit_length() - 1, -1, -1) if rest >> k & 1]


def cut_documents(docs: DataFrame, tokenizer_path: str, end_id: int | None, longest: int, with_ids: bool, most_words: int = tokens.MAX_WORDS) -> DataFrame:
    """Pieces of every whole text of ``docs`` (doc_id, text), numbered by task and place; optionally with their ids."""
    end = b"" if end_id is None else end_id.to_bytes(4, "little")
    if longest < 1 or longest & (longest - 1):
        raise ValueError("the longest sequence must be a power of two")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        place = 0
        for batch in workers.slices(batches):
            out: list[list] = [[] for _ in range(8 + with_ids)]
            for doc_id, part, ids in zip(batch["doc_id"].to_pylist(), batch["part"].to_pylist(), tokens.encoded(batch["text"], tokenizer_path, most_words), strict=True):
                data, start = memoryview(ids + end), 0
                for n in piece_lengths(len(data) // 4, longest):
                    piece = data[4 * start : 4 * (start + n)]
                    row = (doc_id, part, place, start, n, zlib.crc32(piece), len(data) // 4, n.bit_length() - 1)
                    for column, value in zip(out, (*row, piece.tobytes()) if with_ids else row, strict=True):
                        column.append(value)
                    start, place = start + n, place + 1
            kinds = [pa.int64(), pa.int32(), *[pa.int64()] * 5, pa.int32(), pa.binary()]
            names = [*(x.split()[0] for x in PIECES.split(", ")), "ids"]
            yield pa.RecordBatch.from_arrays([pa.array(v, k) for v, k in zip(out, kinds, strict=False)], names[: len(out)])

    return docs.select("doc_id", F.spark_partition_id().alias("part"), "text").mapInArrow(run, PIECES + ", ids binary" * with_ids)


def pack(docs: DataFrame, tokenizer_path: str | None = None, end_id: int | None = 2, longest: int = 4096, with_ids: bool = False, owner: str = "query", most_words: int = tokens.MAX_WORDS) -> DataFrame:
    """One row for each piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset, bucket (and ids).

    A null text counts as empty; with an end id it still makes a piece of one id, without one it makes none. Repeated
    rows are packed as often as they occur; columns other than doc_id and text are left out. Sequences are numbered
    without gaps, bucket by bucket from the longest, in input order. Documents are neither sorted nor shuffled:
    only counts by task and bucket move, and one number per sequence comes from the count of those before.
    ``most_words`` bounds what a worker remembers, not what is packed.
    """
    with scratch.small_batches(docs.sparkSession, 1000, 1 << 20):
        pieces = scratch.write_table(cut_documents(docs, tokenizer_path or tokens.default_tokenizer_path(), end_id, longest, with_ids, most_words), "pieces", owner)
    counts = pieces.groupBy("bucket", "part").agg(F.count("*").alias("_n"))
    by_bucket = Window.partitionBy("bucket").orderBy("part")
    counts = counts.withColumn("_in_bucket", F.sum("_n").over(by_bucket) - F.col("_n"))
    buckets = pieces.groupBy("bucket").agg(F.count("*").alias("_all"))
    buckets = buckets.select("bucket", (F.sum("_all").over(Window.orderBy(F.desc("bucket"))) - F.col("_all")).alias("_first"))
    order = Window.partitionBy("part", "bucket").orderBy("place")
    numbered = pieces.withColumn("_k", F.row_number().over(order).cast("long") - 1)
    counts = scratch.small_side(scratch.write_table(counts, "piece-counts", owner))
    placed = numbered.join(counts, ["bucket", "part"]).join(F.broadcast(buckets), "bucket")  # at most one row per bit of ``longest``
    kept = ["doc_id", "start", "length", "ids_crc32", "doc_tokens"]
    return placed.select(*kept, (F.col("_first") + F.col("_in_bucket") + F.col("_k")).alias("sequence_id"), F.lit(0).cast("long").alias("offset"), "bucket", *["ids"] * with_ids)
