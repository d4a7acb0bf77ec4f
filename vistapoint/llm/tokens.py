"""Encoding by a public tokenizer with a memory of words, and the exact histogram of encoded lengths."""

from __future__ import annotations

import os
import re
from array import array
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .storage import frugal

#: Words that an encoder remembers; twice as many at most are held at once.
REMEMBERED_WORDS = 250_000
_ODD_SPACE = re.compile("[\x1c-\x1f\x85\xa0 ᠎ -​    　﻿]")
#: Words with other characters than Latin letters, digits and signs below U+0180, or with what may begin a special token.
_NOT_PLAIN = re.compile("[^!-~¡-įı-ſ]|<\\|")
_encoders: dict[str, WordEncoder] = {}


def default_tokenizer() -> str:
    """The path of the word-level BPE vocabulary among the installed public tokenizers."""
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


class WordEncoder:
    """Ids of texts under a lower-casing byte-level BPE whose pre-tokens never span white space.

    Each word is encoded once and remembered, and so is each pre-token inside words; letters that are both are remembered
    once. Words of plain Latin letters are split here and go straight to the BPE model; all others go through the whole
    tokenizer, and so do whole texts with white space that Python and the tokenizer may see differently. Memory is bounded:
    words live in two generations, the older of which is dropped when the younger is full.
    """

    def __init__(self, path: str, remembered: int = REMEMBERED_WORDS) -> None:
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        import regex
        from tokenizers import Tokenizer, pre_tokenizers

        self.tokenizer = Tokenizer.from_file(path)
        self.model = self.tokenizer.model
        self.remembered = remembered
        self.young = _Words(self._known)
        self.old: dict[str, bytes] = {}
        self.parts: dict[str, bytes] = {}
        # The pre-token pattern of the vocabulary.
        self.split = regex.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+").findall
        self.split_ascii = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[a-z]+|[0-9]|[^\sa-z0-9]+").findall
        level = pre_tokenizers.ByteLevel(add_prefix_space=False, use_regex=False)
        shown = {}
        for c in map(chr, range(0x180)):
            for byte, char in zip(c.encode(), level.pre_tokenize_str(c)[0][0], strict=True):
                shown[byte] = char
        self.shown = shown

    def _whole(self, text: str) -> bytes:
        return array("I", self.tokenizer.encode(text, add_special_tokens=False).ids).tobytes()

    def _made(self, part: str) -> bytes:
        """The ids of a lower-case pre-token, by the model."""
        bytes_shown = part if part.isascii() and part.isprintable() else part.encode().decode("latin-1").translate(self.shown)
        return array("I", [t.id for t in self.model.tokenize(bytes_shown)]).tobytes()

    def _part(self, part: str) -> bytes:
        ids = self._made(part)
        if len(self.parts) >= self.remembered:
            self.parts.clear()
        self.parts[part] = ids
        return ids

    def _word(self, word: str) -> bytes:
        ascii_only = word.isascii()
        if not ascii_only and _NOT_PLAIN.search(word):
            return self._whole(word)
        # Most words are letters, or letters and one sign. Lower-case letters are a pre-token and a word, remembered as a word only.
        low = word.lower()
        if low.isalpha():
            return self._made(low) if low == word else self.young[low]
        get, make = self.parts.get, self._part
        core, sign = low[:-1], low[-1]
        if core.isalpha() and "!" <= sign <= "~":
            return self.young[core] + (get(sign) or make(sign))
        if ascii_only and _NOT_PLAIN.search(word):
            return self._whole(word)
        return b"".join([get(p) or make(p) for p in (self.split_ascii if low.isascii() else self.split)(low)])

    def encode(self, text: str) -> bytes:
        """The ids of a text as little-endian unsigned 32-bit integers."""
        if _ODD_SPACE.search(text):
            return self._whole(text)
        ids = b"".join(map(self.young.__getitem__, text.split()))
        if len(self.young) > self.remembered:
            self.old, self.young = self.young, _Words(self._known)
        return ids

    def _known(self, word: str) -> bytes:
        return self.old.get(word) or self._word(word)


class _Words(dict):
    """Ids by word; what is missing is made and kept."""

    def __init__(self, make: Callable[[str], bytes]) -> None:
        super().__init__()
        self.make = make

    def __missing__(self, word: str) -> bytes:
        ids = self[word] = self.make(word)
        return ids


def encoder(path: str) -> WordEncoder:
    """This worker's encoder for a tokenizer file; it lives as long as the worker."""
    if path not in _encoders:
        _encoders[path] = WordEncoder(path)
    return _encoders[path]


def forget() -> None:
    """Drop this worker's encoders with all that they remember."""
    _encoders.clear()


def encoded_lengths(docs: DataFrame, text: str | Column = "text", tokenizer: str | None = None, end_ids: int = 0) -> DataFrame:
    """One row per document: n_tokens long, the ids of its whole text plus ``end_ids``. Null counts as empty."""
    path = tokenizer or default_tokenizer()

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = encoder(path).encode
        for batch in batches:
            lengths = [len(encode(t)) // 4 + end_ids if t else end_ids for t in batch.column(0).to_pylist()]
            yield pa.RecordBatch.from_arrays([pa.array(lengths, pa.int64())], ["n_tokens"])

    column = F.col(text) if isinstance(text, str) else text
    return docs.select(column.cast("string").alias("text")).mapInArrow(frugal(count, keep_words=True), "n_tokens long")


def length_histogram(docs: DataFrame, text: str | Column = "text", tokenizer: str | None = None, end_ids: int = 0) -> DataFrame:
    """The exact histogram of encoded lengths: n_tokens, n_docs. Its rows are the distinct lengths, however many documents there are."""
    return encoded_lengths(docs, text, tokenizer, end_ids).groupBy("n_tokens").agg(F.count("*").alias("n_docs"))


def context_totals(histogram: DataFrame) -> DataFrame:
    """Suffix sums of a length histogram: what every context limit keeps and loses.

    For each distinct length L as limit: n_docs of that length, docs_within (length <= L), docs_over (length > L),
    tokens_within, tokens_over, truncated_total (sum of min(length, L)), lost_tokens (what the limit cuts off),
    total_tokens, and quantile (share of documents with length <= L). For a limit between two lengths, the row of the
    largest length below it answers all but truncated_total, to which docs_over * (limit - L) is added.
    An empty histogram gives no row. The window runs over distinct lengths, not documents.
    """
    upwards = Window.orderBy("n_tokens")
    downwards = Window.orderBy(F.col("n_tokens").desc())
    own = F.col("n_docs") * F.col("n_tokens")
    whole = Window.orderBy("n_tokens").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    sums = histogram.select(
        "n_tokens",
        "n_docs",
        F.sum("n_docs").over(upwards).alias("docs_within"),
        F.sum(own).over(upwards).alias("tokens_within"),
        (F.sum("n_docs").over(downwards) - F.col("n_docs")).alias("docs_over"),
        (F.sum(own).over(downwards) - own).alias("tokens_over"),
        F.sum("n_docs").over(whole).alias("all_docs"),
        F.sum(own).over(whole).alias("total_tokens"),
    )
    return sums.select(
        "n_tokens",
        "n_docs",
        "docs_within",
        "docs_over",
        "tokens_within",
        "tokens_over",
        (F.col("tokens_within") + F.col("docs_over") * F.col("n_tokens")).alias("truncated_total"),
        (F.col("tokens_over") - F.col("docs_over") * F.col("n_tokens")).alias("lost_tokens"),
        "total_tokens",
        (F.col("docs_within") / F.col("all_docs")).alias("quantile"),
    )


def length_quantiles(histogram: DataFrame, shares: tuple[float, ...] = (0.25, 0.5, 0.75, 0.9, 0.99)) -> DataFrame:
    """share, n_tokens: the smallest length that at least that share of the documents does not exceed."""
    totals = context_totals(histogram)
    wanted = histogram.sparkSession.createDataFrame([(s,) for s in shares], "share double")
    return totals.join(F.broadcast(wanted), totals["quantile"] >= wanted["share"]).groupBy("share").agg(F.min("n_tokens").alias("n_tokens"))
