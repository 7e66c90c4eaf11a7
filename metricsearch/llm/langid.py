"""Language identification by multinomial naive Bayes over hashed character n-grams.

Grams of one to three characters of the lower-cased text are hashed to ``BUCKETS`` columns. The log-probability
matrix (languages by columns, 128 kB a language) is broadcast, and a batch is scored by gathering its rows in numpy.
Priors are even, not the shares of languages among the labelled rows, as these say little about unlabelled ones.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import workers

UNKNOWN = "und"
BUCKETS = 1 << 15
GRAMS = (1, 2, 3)
SMOOTHING = 0.5
TRAINING_ROWS = 40_000  # labelled rows that a model is fitted on, at most about; chosen by a hash of their ids
_CHUNK = 1 << 17  # characters whose grams are held at once
_TEXTS = 500  # texts that are Python strings at once
_MULTIPLIERS = np.array([0x9E3779B1, 0x85EBCA77, 0xC2B2AE3D], np.uint32)


def _codes(text: str) -> np.ndarray:
    """Code points of the lower-cased text; everything but letters and marks is one space."""
    return np.frombuffer(text.lower().encode("utf-32-le", "surrogatepass"), np.uint32)


def _letters_only(codes: np.ndarray, table: np.ndarray) -> np.ndarray:
    return np.where(table[np.minimum(codes, len(table) - 1)], codes, np.uint32(32))


def _letter_table() -> np.ndarray:
    """Which code points are letters; the last entry stands for those beyond and counts as letter."""
    table = np.fromiter((chr(i).isalpha() for i in range(0x3400)), bool, 0x3400)
    table[-1] = True
    return table


_LETTERS = _letter_table()


def gram_columns(texts: list[str | None]) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """Yield (first, end, columns, row of each column) for runs of whole texts of about ``_CHUNK`` characters.

    Grams of white space and signs alone are left out; runs of them count as one.
    """
    first, n = 0, len(texts)
    while first < n:
        end, size, parts = first, 0, []
        while end < n and (end == first or size + len(texts[end] or "") <= _CHUNK):
            parts.append(_codes(f" {texts[end] or ''} "))
            size += len(parts[-1])
            end += 1
        codes = _letters_only(np.concatenate(parts), _LETTERS)
        rows = np.repeat(np.arange(first, end), [len(x) for x in parts])
        space = codes == 32
        keep = ~(space & np.concatenate([[False], space[:-1]]) & np.concatenate([[False], rows[1:] == rows[:-1]]))
        codes, rows, space = codes[keep], rows[keep], space[keep]
        columns, owners = [], []
        for g in GRAMS:
            m = len(codes) - g + 1
            if m <= 0:
                continue
            h = np.full(m, g * 0x27D4EB2F & 0xFFFFFFFF, np.uint32)
            for k in range(g):
                h = (h ^ codes[k : k + m]) * _MULTIPLIERS[k]
                h ^= h >> np.uint32(15)
            ok = rows[:m] == rows[g - 1 :]
            ok &= ~space[:m] if g == 1 else ~(space[:m] & space[g - 1 :]) if g == 2 else True
            columns.append((h[ok] * np.uint32(0x2545F491)) >> np.uint32(32 - BUCKETS.bit_length() + 1))
            owners.append(rows[:m][ok])
        yield first, end, np.concatenate(columns) if columns else np.zeros(0, np.uint32), np.concatenate(owners) if owners else np.zeros(0, np.int64)
        first = end


def _gram_counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    counts: dict[str, np.ndarray] = {}
    workers.begin("langid")
    for batch in (x.slice(i, _TEXTS) for x in batches for i in range(0, x.num_rows, _TEXTS)):
        langs, texts = batch["lang"].to_pylist(), batch["text"].to_pylist()
        for first, end, columns, rows in gram_columns(texts):
            own = np.array(langs[first:end], object)
            for lang in set(own):
                mine = np.bincount(columns[(own == lang)[rows - first]], minlength=BUCKETS)
                counts[lang] = counts.get(lang, 0) + mine
    for lang, vector in counts.items():
        at = np.flatnonzero(vector)
        yield pa.RecordBatch.from_arrays([pa.array([lang] * len(at)), pa.array(at.astype(np.int32)), pa.array(vector[at].astype(np.int64))], ["lang", "bucket", "n"])


class Model:
    """Languages in code-point order, log probabilities (columns by languages) and log priors (even)."""

    def __init__(self, langs: list[str], counts: np.ndarray):
        self.langs = langs
        smooth = counts + SMOOTHING
        self.logs = np.ascontiguousarray(np.log(smooth / smooth.sum(axis=1, keepdims=True)).T.astype(np.float32)) if langs else np.zeros((BUCKETS, 0), np.float32)

    def predict(self, texts: list[str | None]) -> tuple[list[str], np.ndarray]:
        """Language and score of each text; ``und`` with score 0 for null, letterless or any text without a model."""
        lang, score = [UNKNOWN] * len(texts), np.zeros(len(texts))
        if not self.langs:
            return lang, score
        for first, end, columns, rows in gram_columns(texts):
            if not len(rows):
                continue
            order = np.argsort(rows, kind="stable")
            columns, rows = columns[order], rows[order]
            total = np.zeros((end - first, len(self.langs)))
            starts = np.flatnonzero(np.concatenate([[True], rows[1:] != rows[:-1]]))
            for k in range(len(self.langs)):
                total[rows[starts] - first, k] = np.add.reduceat(self.logs[columns, k].astype(np.float64), starts)
            total /= len(GRAMS)  # grams of several lengths tell the same characters
            total -= total.max(axis=1, keepdims=True)
            odds = np.exp(total)
            odds /= odds.sum(axis=1, keepdims=True)
            best = odds.argmax(axis=1)
            for i in np.unique(rows).tolist():
                if any(c.isalpha() for c in texts[i]):
                    lang[i], score[i] = self.langs[best[i - first]], odds[i - first, best[i - first]]
        return lang, score


def held_out(doc_id: str = "doc_id") -> Column:
    """Rows kept from training: crc32 of the id as text leaves 1 when divided by 3. A null id is not held out."""
    return F.coalesce(F.crc32(F.col(doc_id).cast("string").cast("binary")) % 3 == 1, F.lit(False))


def train(labelled: DataFrame, training_rows: int = TRAINING_ROWS) -> Model:
    """Fit on (doc_id, text, lang) rows with a language and a text; about ``training_rows`` of them at most.

    Every language gets an equal share of that bound, and its rows are chosen by a hash of their ids, so the choice
    does not depend on order or layout. The driver receives one count for each language and column.
    """
    rows = labelled.where("lang is not null and text is not null and doc_id is not null")
    sizes = {r["lang"]: r["n"] for r in rows.groupBy("lang").agg(F.count("*").alias("n")).collect()}
    langs = sorted(sizes)
    if not langs:
        return Model([], np.zeros((0, BUCKETS)))
    share = [(x, min(1.0, training_rows / len(langs) / sizes[x])) for x in langs]
    draw = F.pmod(F.xxhash64("doc_id"), F.lit(1 << 30)) / float(1 << 30)
    chosen = F.lit(False)
    for lang, part in share:
        chosen = chosen | ((F.col("lang") == lang) & (draw < part)) if part < 1 else chosen | (F.col("lang") == lang)
    grams = rows.where(chosen).select("lang", "text").mapInArrow(_gram_counts, "lang string, bucket int, n long")
    table = grams.groupBy("lang", "bucket").agg(F.sum("n").alias("n")).toPandas()
    counts = np.zeros((len(langs), BUCKETS))
    counts[table["lang"].map({x: i for i, x in enumerate(langs)}).to_numpy(np.int64), table["bucket"].to_numpy(np.int64)] = table["n"]
    return Model(langs, counts)


def predict(docs: DataFrame, model: Model) -> DataFrame:
    """``docs`` with ``lang_pred`` and ``score`` (made anew if there) from the whole text; other columns pass through
    under any name. Only the text goes to Python, and a few hundred texts at a time become strings there."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    @F.arrow_udf("lang_pred string, score double")
    def of(text: pa.Array) -> pa.Array:
        workers.begin("langid")
        found = [shared.value.predict(text.slice(i, _TEXTS).to_pylist()) for i in range(0, len(text), _TEXTS)]
        lang, score = [x for names, _ in found for x in names], np.concatenate([np.zeros(0), *[x for _, x in found]])
        return pa.StructArray.from_arrays([pa.array(lang, pa.string()), pa.array(score, pa.float64())], ["lang_pred", "score"])

    kept = F.struct(*[F.col(f"`{c}`") for c in docs.columns if c not in ("lang_pred", "score")])
    return docs.select(kept.alias("row"), of("text").alias("found")).select("row.*", "found.lang_pred", "found.score")


def identify(docs: DataFrame, training_rows: int = TRAINING_ROWS) -> DataFrame:
    """``docs`` with held_out, lang_pred and score; learnt from the text and non-null lang of rows not held out.

    Null texts, texts without a letter, and all texts where no row has a language are ``und`` with score 0. Equal
    texts get equal predictions. An empty table gives no rows.
    """
    docs = docs.withColumn("held_out", held_out())
    model = train(docs.where(~F.col("held_out")).select("doc_id", "text", "lang"), training_rows)
    return predict(docs, model)
