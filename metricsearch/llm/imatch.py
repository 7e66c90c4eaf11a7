"""I-Match fingerprints: terms within a band of inverse document frequency, hashed over randomised lexicon subsets.

The lexicon holds the terms found in a share of documents between ``LEAST_SHARE`` and ``MOST_SHARE``, that is, those
within a band of inverse document frequency. A document with d distinct terms adds 1/N to the share of each of them,
so the lexicon has at most mean(d) / LEAST_SHARE terms for any corpus, and is sent to the executors as hashes. The
subsets keep each term of the lexicon with a probability of their level, from one half down to 1/512; a fingerprint
has a hash of the sorted distinct terms in each subset, and one over the whole lexicon.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import scratch, words

LEAST_SHARE, MOST_SHARE = 0.0004, 0.25
LEVELS = (1, 3, 5, 7, 9)  # a subset of level j keeps a term with probability 2**-j
SUBSETS = 16  # for each level
ACTIVE = 8  # subsets with terms that a level needs to be believed
EMPTY = "-"
_SEEDS = words.mix(np.arange(1, SUBSETS + 1, dtype=np.uint64) * np.uint64(words.BASE))


def _term_counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in words.slices(batches, 5000):
        rows = list(words.distinct_words(batch["text"]))
        found, count = np.unique(np.concatenate(rows) if rows else np.zeros(0, np.uint64), return_counts=True)
        yield pa.RecordBatch.from_arrays([pa.array(found.view(np.int64)), pa.array(count.astype(np.int64))], ["term", "df"])


def lexicon(docs: DataFrame, least_share: float = LEAST_SHARE, most_share: float = MOST_SHARE) -> np.ndarray:
    """Sorted hashes of the terms of ``docs`` (text) whose share of documents lies in the band; counts cover all rows.

    Terms are counted by batch first. In a corpus of fewer than 2 / least_share documents a term needs two of them.
    """
    n = docs.count()
    terms = docs.select("text").mapInArrow(_term_counts, "term long, df long").groupBy("term").agg(F.sum("df").alias("df"))
    band = terms.where((F.col("df") >= max(2.0, least_share * n)) & (F.col("df") <= max(2.0, most_share * n)))
    return np.sort(band.select("term").toPandas()["term"].to_numpy(np.int64).view(np.uint64))


def fingerprint(terms: np.ndarray, in_band: np.ndarray) -> str:
    """Space-separated hexadecimal hashes of a document's sorted distinct ``terms`` (all) and ``in_band`` ones.

    The first one covers the whole lexicon, or all terms where none is in the band; the others follow by level, with
    ``-`` for a subset that holds none of the document's terms. Without terms all is ``-``.
    """
    base = in_band if len(in_band) else terms
    if not len(base):
        return " ".join([EMPTY] * (1 + len(LEVELS) * SUBSETS))
    spread = words.mix(base ^ np.uint64(0xA5A5A5A5A5A5A5A5))
    out = [f"{int(np.add.reduce(spread, dtype=np.uint64)):016x}"]
    drawn = words.mix(base[None, :] + _SEEDS[:, None])
    for level in LEVELS:
        chosen = drawn < np.uint64(1 << (64 - level))
        sums = np.where(chosen, spread[None, :], np.uint64(0)).sum(axis=1, dtype=np.uint64) >> np.uint64(32)
        out += [f"{x:08x}" if some else EMPTY for x, some in zip(sums.tolist(), chosen.any(axis=1).tolist(), strict=True)]
    return " ".join(out)


def likeness(a: str, b: str) -> float:
    """Share of equal hashes, 0 to 1, among the subsets in which a or b has terms, at the finest level with enough.

    Subsets with few terms survive edits in proportion to what two documents have in common; 1 for equal prints.
    """
    if a == b:
        return 1.0
    x, y = a.split(" "), b.split(" ")
    best = (0, 0.0)
    for i in reversed(range(len(LEVELS))):
        pairs = [p for p in zip(x[1 + i * SUBSETS : 1 + (i + 1) * SUBSETS], y[1 + i * SUBSETS : 1 + (i + 1) * SUBSETS], strict=True) if p != (EMPTY, EMPTY)]
        if len(pairs) > best[0]:
            best = (len(pairs), sum(p == q for p, q in pairs) / len(pairs))
        if best[0] >= ACTIVE:
            break
    return best[1]


def prints_of(texts: pa.Array, lex: np.ndarray) -> Iterator[str]:
    for terms in words.distinct_words(texts):
        if len(lex) and len(terms):
            at = np.minimum(np.searchsorted(lex, terms), len(lex) - 1)
            yield fingerprint(terms, terms[lex[at] == terms])
        else:
            yield fingerprint(terms, terms[:0])


def fingerprints(docs: DataFrame, lex: np.ndarray) -> DataFrame:
    """(doc_id, fingerprint) of every whole text of ``docs``; a null text counts as empty, equal texts are equal."""
    shared = docs.sparkSession.sparkContext.broadcast(lex)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch["doc_id"], pa.array(list(prints_of(batch["text"], shared.value)), pa.string())], ["doc_id", "fingerprint"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, fingerprint string")


def _edited(text: str, follower: str) -> str:
    cut = len(text) // 3
    return text[: len(text) - cut] + follower[:cut]


def _compare(shared):
    """Rows come sorted by (part, doc_id down); a copied row ends its part and only serves the row before it."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept = None  # the last row, whose follower is not known yet: (doc_id, text, fingerprint, copied)
        for batch in batches:
            ids, texts, copied = batch["doc_id"].to_pylist(), [x or "" for x in batch["text"].to_pylist()], batch["copied"].to_pylist()
            prints = list(prints_of(pa.array(texts, pa.large_string()), shared.value))
            rows = ([kept] if kept else []) + list(zip(ids, texts, prints, copied, strict=True))
            pairs = [(a, b) for a, b in zip(rows, rows[1:], strict=False) if not a[3]]
            kept = rows[-1] if rows else None
            for first in range(0, len(pairs), 500):
                some = pairs[first : first + 500]
                new = [_edited(a[1], b[1]) for a, b in some]
                own = list(prints_of(pa.array(new, pa.large_string()), shared.value))
                columns = [
                    [a[0] for a, _ in some], [len(a[1]) for a, _ in some], [hashlib.sha256(x.encode("utf-8", "surrogatepass")).hexdigest() for x in new], [a[2] for a, _ in some], own,
                    [likeness(a[2], p) for (a, _), p in zip(some, own, strict=True)], [likeness(a[2], b[2]) for a, b in some],
                ]
                kinds = [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.float64(), pa.float64()]
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, kinds, strict=True)], ["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next"])
        if kept and not kept[3]:
            raise RuntimeError("a range of documents has no row after its last one")

    return run


RESULT = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"


def edit_test(docs: DataFrame, rows_per_part: int = 3000) -> DataFrame:
    """Fingerprints of every document and of its edited text, with both likenesses.

    Edited: the last third of the code points gives way to as many from the start of the next document, in falling
    order of doc_id, the last followed by the first. Null texts count as empty. Null ids come last; rows of equal id
    stand by their text. One row alone is its own follower. Documents are dealt by ranges of ids once; each range
    also gets a copy of the first row of the next, so no order runs through one task; one id with many texts, or null
    ids, are split by a hash of the text.
    """
    spark: SparkSession = docs.sparkSession
    docs = docs.select("doc_id", "text")
    low = F.lit(1 - (1 << 63)).cast("long")
    rows = docs.select(F.coalesce("doc_id", low).alias("key"), "doc_id", "text", F.xxhash64("text").alias("tie"))
    n = rows.count()
    if not n:
        return spark.createDataFrame([], RESULT)
    shared = spark.sparkContext.broadcast(lexicon(docs))
    parts = max(1, min(-(-n // rows_per_part), 100_000))
    found = np.array(rows.approxQuantile("key", [k / parts for k in range(1, parts)], 0.1 / parts) if parts > 1 else [], np.float64)
    held = spark.sparkContext.broadcast(-found.astype(np.int64)[::-1])  # ascending; parts count from the largest ids

    @F.arrow_udf("int")
    def part_of(key: pa.Array, tie: pa.Array) -> pa.Array:
        """Parts before the key's own by the cuts above it; an id that fills several parts is split by its texts' hash."""
        down = -key.to_numpy()
        above, upto = np.searchsorted(held.value, down, "left"), np.searchsorted(held.value, down, "right")
        place = (tie.to_numpy().astype(np.float64) / 2.0**64 + 0.5).clip(0, 1 - 2.0**-53)
        return pa.array(np.where(upto > above, above + 1 + np.floor(place * (upto - above)), above).astype(np.int32))

    rows = rows.withColumn("part", part_of("key", "tie"))
    heads = rows.groupBy("part").agg(F.min(F.struct((-F.col("key")).alias("down"), "tie")).alias("x")).select("part", "x.*").orderBy("part").collect()  # one row for each part
    before = spark.createDataFrame([(-r["down"], r["tie"], heads[(i - 1) % len(heads)]["part"]) for i, r in enumerate(heads)], "key long, tie long, before int")
    first = rows.drop("part").join(F.broadcast(before), ["key", "tie"]).groupBy("before").agg(F.min(F.struct("text", "doc_id", "tie")).alias("x"))
    copies = first.select(low.alias("key"), F.col("x.doc_id").alias("doc_id"), F.col("x.text").alias("text"), F.col("x.tie").alias("tie"), F.col("before").alias("part"), F.lit(True).alias("copied"))
    dealt = rows.withColumn("copied", F.lit(False)).unionByName(copies).repartitionById(heads[-1]["part"] + 1, "part")
    dealt = dealt.sortWithinPartitions("part", "copied", F.desc("key"), "tie", "text")
    return dealt.select("doc_id", "text", "copied").mapInArrow(_compare(shared), RESULT)
