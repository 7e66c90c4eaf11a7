"""Token ids of whole texts by a public tokenizer file, as bytes of little-endian unsigned 32-bit integers.

The word tokenizer lower-cases, cuts a text into words by one pattern, drops white space and merges within words
only. So a text's ids are those of its space-free pieces in order, and a piece's ids those of its words. Arrow cuts a
column of texts into pieces and finds the different ones; only these pass Python, and a bounded table of words has the
library's merges run once for each new word. Where the tokenizer file has another make-up, or a piece has characters
outside plain Latin, the library encodes the whole text or piece itself.
"""

from __future__ import annotations

import json
import os
from array import array
from collections.abc import Callable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from . import workers

MAX_WORDS = 200_000  # in each of two generations
LONGEST_KEPT = 48
SIGNS = "!\"#$%&'()*+,-./:;<=>?@[\\]^_`{|}~"  # a run of them at the end of a piece of letters is one word


def default_tokenizer_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


class _Kept:
    """A table of two generations: when the young one is full it becomes the old one, which is dropped in turn."""

    def __init__(self, most: int):
        self.most, self.young, self.old = most, {}, {}

    def get(self, key: str, make: Callable[[str], bytes]) -> bytes:
        """The value of a key, made if the table lacks it."""
        if (value := self.young.get(key)) is None:
            if (value := self.old.get(key)) is None:
                value = make(key)
            if len(key) <= LONGEST_KEPT:
                if len(self.young) >= self.most:
                    self.old, self.young = self.young, {}
                self.young[key] = value
        return value


class TextEncoder:
    """Encodes texts with one tokenizer file, ids as in ``encode(text, add_special_tokens=False)``."""

    def __init__(self, path: str, most_words: int = MAX_WORDS):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        import regex
        from tokenizers import Tokenizer, pre_tokenizers

        self.tokenizer = Tokenizer.from_file(path)
        with open(path, encoding="utf-8") as f:
            made = json.load(f)
        kinds = [[x["type"] for x in ((made.get(part) or {}).get(inner) or [])] for part, inner in (("normalizer", "normalizers"), ("pre_tokenizer", "pretokenizers"))]
        self.by_word = kinds == [["NFC", "Replace", "Lowercase"], ["Split", "ByteLevel"]] and not made.get("post_processor") and all(x["special"] and " " not in x["content"] for x in made["added_tokens"])
        if self.by_word:
            self.cut = regex.compile(made["pre_tokenizer"]["pretokenizers"][0]["pattern"]["Regex"]).findall
            # characters that normal forms leave alone and whose lower case is one character anywhere
            self.plain = regex.compile("[\x20-\x7e\xa1-\xac\xae-\xbfÀ-įĲ-ňŊ-ɏ‐-‧€]*+").fullmatch
            self.special = tuple(x["content"] for x in made["added_tokens"])
            # the character that stands for each byte beyond ASCII; a word is shown by those of its bytes
            bytes_of = pre_tokenizers.ByteLevel(add_prefix_space=False, use_regex=False).pre_tokenize_str
            chars = map(chr, [*range(0x80, 0x800), *range(0x800, 0xD800, 64)])
            self.shown = {byte: shown for char in chars for byte, shown in zip(char.encode(), bytes_of(char)[0][0], strict=True)}
            self.merge = self.tokenizer.model.tokenize
        self.words = _Kept(most_words)

    def whole(self, text: str) -> bytes:
        """The library's own ids of a text."""
        return np.array(self.tokenizer.encode(text, add_special_tokens=False).ids, "<u4").tobytes()

    def _merged(self, word: str) -> bytes:
        """The library's own ids of a word."""
        shown = word if word.isascii() else word.encode().decode("latin-1").translate(self.shown)
        return array("I", [x.id for x in self.merge(shown)]).tobytes()

    def _clear(self, text: str) -> bool:
        return bool(self.plain(text)) and not ("<" in text and any(x in text for x in self.special))

    def _pieces(self, pieces: list[str]) -> list[bytes]:
        """Ids of space-free pieces. Most are letters, or letters and signs: a word or two without the pattern."""
        words, get, merged, out = self.words, self.words.get, self._merged, []
        for piece in pieces:
            low = piece.lower()
            core = low.rstrip(SIGNS)
            if core.isalpha() and (piece.isascii() or self.plain(piece)):
                ids = words.young.get(core) or get(core, merged)
                if len(core) < len(low):
                    tail = low[len(core) :]
                    ids += words.young.get(tail) or get(tail, merged)
                out.append(ids)
            elif self._clear(piece):
                out.append(b"".join([get(word, merged) for word in self.cut(low)]))
            else:
                out.append(get(piece, self.whole))
        return out

    def encode_column(self, texts: pa.Array) -> Iterator[bytes]:
        """Ids of every text of a string column; a null text counts as empty."""
        if not self.by_word:
            yield from (self.whole(x) if x else b"" for x in texts.to_pylist())
            return
        if not len(texts):
            return
        cut = pc.split_pattern(pc.replace_substring(pc.fill_null(texts, ""), "\n", " "), " ")
        pieces = cut.flatten().dictionary_encode()
        known = pa.array(self._pieces(pieces.dictionary.to_numpy(zero_copy_only=False).tolist()), pa.large_binary())
        ids = known.take(pieces.indices)
        ends = np.frombuffer(ids.buffers()[1], np.int64, len(ids) + 1, 8 * ids.offset)
        at = cut.offsets.to_numpy().astype(np.int64)
        data, at = memoryview(ids.buffers()[2] or b""), ends[at - at[0]].tolist()
        for first, end in zip(at[:-1], at[1:], strict=True):
            yield bytes(data[first:end])

    def encode(self, text: str | None) -> bytes:
        return next(self.encode_column(pa.array([text], pa.string())))


@lru_cache(maxsize=2)
def encoder(path: str, most_words: int = MAX_WORDS) -> TextEncoder:
    """One encoder for each Python worker; workers are kept between tasks, and so is its table, until another operator begins."""
    return TextEncoder(path, most_words)


def encoded(texts: pa.Array | list[str | None], path: str, most_words: int = MAX_WORDS) -> Iterator[bytes]:
    workers.begin("tokens")
    workers.keeps("tokens", encoder.cache_clear)
    yield from encoder(path, most_words).encode_column(texts if isinstance(texts, pa.Array) else pa.array(texts, pa.string()))
