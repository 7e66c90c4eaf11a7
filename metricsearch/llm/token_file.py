"""Token files: whole texts as token ids in ORC, in document order, with row indexes and Bloom filters on the ids.

ORC writes integer lists with run-length encoding, cuts a file into stripes that tasks read in parallel, and keeps
minima, maxima and a Bloom filter of ``doc_id`` for every stripe and row group, so that a read by document id opens
few of them. Each range of document ids is one file, and ``part`` numbers the files in document order.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import scratch, tokens, workers

ORC_OPTIONS = {
    "orc.bloom.filter.columns": "doc_id",
    "orc.bloom.filter.fpp": "0.01",
    "orc.row.index.stride": "2000",
    "orc.stripe.size": str(16 << 20),
    "compression": "zstd",
}
FILE_SCHEMA = "doc_id long, part int, ids array<int>"


def token_lists(docs: DataFrame, tokenizer_path: str, end_id: int | None) -> DataFrame:
    """(doc_id, part, ids) of rows (doc_id, text, part), in the rows' order; a null text counts as empty."""
    end = b"" if end_id is None else end_id.to_bytes(4, "little")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in workers.slices(batches):
            lists = [x + end for x in tokens.encoded(batch["text"], tokenizer_path)]
            offsets, total = [0], 0
            for x in lists:
                total += len(x) // 4
                offsets.append(total)
            values = pa.Array.from_buffers(pa.int32(), total, [None, pa.py_buffer(b"".join(lists))])
            ids = pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), values)
            yield pa.RecordBatch.from_arrays([batch["doc_id"], batch["part"], ids], ["doc_id", "part", "ids"])

    return docs.mapInArrow(run, FILE_SCHEMA)


def write_token_file(docs: DataFrame, path: str, tokenizer_path: str | None = None, end_id: int | None = 1, mode: str = "errorifexists") -> None:
    """Encode every whole text of ``docs`` (doc_id, text; other columns are left out) and write the token file.

    Rows are dealt by ranges of (doc_id, hash of the text), so repeated ids stay neighbours in a fixed order; null
    ids come first. A null or empty text is the end id alone, or an empty list without one. An empty table gives a
    folder without rows, which reads back as an empty table. The text is shuffled once and encoded after that, so a lost task encodes only its own range.
    """
    rows = docs.select("doc_id", "text", F.xxhash64("text").alias("_tie"))
    dealt = scratch.deal_by_range(rows, "doc_id", "_tie").sortWithinPartitions("doc_id", "_tie")
    lists = token_lists(dealt.select("doc_id", F.spark_partition_id().alias("part"), "text"), tokenizer_path or tokens.default_tokenizer_path(), end_id)
    lists.write.mode(mode).format("orc").options(**ORC_OPTIONS).save(path)


def read_token_file(spark: SparkSession, path: str, doc_ids: list[int] | None = None) -> DataFrame:
    """(doc_id, part, ids); with ``doc_ids`` stripes without them are skipped by their minima, maxima and filters."""
    table = spark.read.schema(FILE_SCHEMA).orc(path)
    return table if doc_ids is None else table.where(F.col("doc_id").isin(doc_ids))


def _digests(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        ids = batch["ids"]
        data = memoryview(ids.values.buffers()[1] or b"").cast("B")
        at, shift = ids.offsets.to_pylist(), ids.values.offset
        crc = [zlib.crc32(data[4 * (a + shift) : 4 * (b + shift)]) for a, b in zip(at[:-1], at[1:], strict=True)]
        n = [b - a for a, b in zip(at[:-1], at[1:], strict=True)]
        yield pa.RecordBatch.from_arrays([batch["doc_id"], batch["part"], pa.array(n, pa.int64()), pa.array(crc, pa.int64())], ["doc_id", "part", "n_tokens", "ids_crc32"])


def token_index(table: DataFrame) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32) of a token file read back; ``start`` counts the ids of all rows before.

    The running sum is taken within files; files before add their totals, one row each. Repeated ids order by length
    and checksum, which is the same for any layout.
    """
    rows = table.mapInArrow(_digests, "doc_id long, part int, n_tokens long, ids_crc32 long")
    rows = scratch.write_table(rows, "token-index")
    totals = rows.groupBy("part").agg(F.sum("n_tokens").alias("_n"))
    before = totals.select("part", (F.sum("_n").over(Window.orderBy("part")) - F.col("_n")).alias("_before"))
    order = Window.partitionBy("part").orderBy("doc_id", "n_tokens", "ids_crc32").rowsBetween(Window.unboundedPreceding, 0)
    within = rows.withColumn("_upto", F.sum("n_tokens").over(order))
    return within.join(before, "part").select("doc_id", (F.col("_before") + F.col("_upto") - F.col("n_tokens")).alias("start"), "n_tokens", "ids_crc32")
