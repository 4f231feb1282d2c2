"""BPE encoding and decoding with the tokenization automaton.

Nulls count as empty texts, which have no ids and decode to the empty string. Texts of any length are encoded
whole. Repeated rows are encoded each by itself. Only the named columns of the input are read, so extra columns,
whatever their names, never clash with the results.
"""

from __future__ import annotations

import ctypes
import functools
import re
import struct
import unicodedata
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from assocmine.llm import automaton
from assocmine.plans.materialize import ship_package

#: Pieces that a worker remembers with their ids, and the longest piece that it remembers.
REMEMBERED = 250_000
#: Rows of a batch handed back at once; decoded texts are longer than texts.
ROWS_AT_ONCE = 500
LONGEST_REMEMBERED = 64
#: Characters below this point have had the same classes and case pairs in every Unicode version.
STABLE = "\u0250"
#: Words of text without white space, and the parts that a public tokenizer may treat in a way of its own.
WORDS = regex.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+")
UNUSUAL = re.compile("<\\||[\x00-\x20\x7f-\xa0\xad\u0130]")


def packed(ids: list[int]) -> bytes:
    """Little-endian unsigned 32-bit integers."""
    return struct.pack(f"<{len(ids)}I", *ids)


class Remembered(dict):
    """ids of pieces as little-endian 32-bit integers; emptied when full."""

    def __init__(self, encode, limit: int = REMEMBERED):
        super().__init__()
        self.encode, self.limit = encode, limit

    def __missing__(self, piece: bytes) -> bytes:
        ids = self.encode(piece)
        if len(piece) <= LONGEST_REMEMBERED:
            if len(self) >= self.limit:
                self.clear()
            self[piece] = ids
        return ids


class WordTokenizer:
    """Encoder for vocabularies whose splitter drops white space, so that words are independent of each other.

    Pieces between ASCII white space are split into words and encoded by the automaton. Pieces with control
    characters, special tokens or characters outside the Latin blocks are normalised and split by the public library.
    """

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.machine = automaton.load(path)
        public = Tokenizer.from_file(path)
        self.normalizer, self.splitter = public.normalizer, public.pre_tokenizer
        self.special = {t.content: i for i, t in public.get_added_tokens_decoder().items()}
        self.marks = re.compile("(" + "|".join(map(re.escape, sorted(self.special, key=len, reverse=True))) + ")")
        self.bytes_of = {ord(s): chr(b) for s, b in automaton.byte_symbols().items()}
        self.pieces = Remembered(self._piece)
        self.words = Remembered(lambda word: packed(self.machine.encode(word.decode("latin-1"))))

    def _piece(self, piece: bytes) -> bytes:
        words = self.words
        if piece.isalpha():  # ASCII letters only
            return words[piece.lower()]
        if piece[:-1].isalpha() and piece[-1] in b",.;:":
            return words[piece[:-1].lower()] + words[piece[-1:]]
        text = piece.decode("utf-8")
        if max(text) < STABLE and not UNUSUAL.search(text):
            return b"".join([words[w.encode("utf-8")] for w in WORDS.findall(unicodedata.normalize("NFC", text).lower())])
        ids: list[int] = []
        for part in self.marks.split(text):
            if part in self.special:
                ids.append(self.special[part])
            elif part:
                for word, _ in self.splitter.pre_tokenize_str(self.normalizer.normalize_str(part)):
                    ids += self.machine.encode(word.translate(self.bytes_of))
        return packed(ids)

    def forget(self) -> None:
        """Empty the tables of seen pieces, words and transitions; idle workers of a cluster then hold little."""
        self.pieces.clear()
        self.words.clear()
        self.machine.rows.clear()
        self.machine.known = 0

    def encode(self, text: bytes) -> bytes:
        """Ids of a UTF-8 text as little-endian 32-bit integers."""
        pieces = self.pieces
        return b"".join([pieces[piece] for piece in text.split()])


def spell(ids: bytes, labels: list[str]) -> str:
    """Arc labels along the path of ``ids``, joined with single spaces, as the public library does for a vocabulary without decoder."""
    return " ".join([labels[i] for i in np.frombuffer(ids, dtype="<u4").tolist()])


@functools.lru_cache(maxsize=2)
def tokenizer(path: str) -> WordTokenizer:
    return WordTokenizer(path)


def small(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Batches cut into few rows each, so that texts become Python objects a few at a time; freed memory goes back."""
    for batch in batches:
        for start in range(0, batch.num_rows, ROWS_AT_ONCE):
            yield batch.slice(start, ROWS_AT_ONCE)
    pa.default_memory_pool().release_unused()
    _trim()


def _trim() -> None:
    """Give the C heap's free pages back: a worker process that idles through the next stages keeps none of the texts' room."""
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # a C library without it
        pass


def utf8_values(column: pa.Array) -> list[bytes]:
    """The UTF-8 bytes of a string column; null becomes empty."""
    return [b"" if v is None else v for v in column.cast(pa.binary()).to_pylist()]


def encode(docs: DataFrame, path: str, keys: list[str], text: str | Column = "text") -> DataFrame:
    """``keys`` and ``ids``: binary, little-endian unsigned 32-bit token ids of each whole text."""
    ship_package(docs.sparkSession)
    narrow = docs.select(*keys, F.col(text).alias("__text") if isinstance(text, str) else text.alias("__text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tool = tokenizer(path)
        for part in small(batches):
            ids = [tool.encode(t) for t in utf8_values(part.column(len(keys)))]
            yield pa.RecordBatch.from_arrays([*part.columns[: len(keys)], pa.array(ids, pa.binary())], names=[*keys, "ids"])
        tool.forget()

    schema = ", ".join([*(f"`{k}` {narrow.schema[k].dataType.simpleString()}" for k in keys), "ids binary"])
    return narrow.mapInArrow(run, schema)


def decode(encoded: DataFrame, path: str, keys: list[str]) -> DataFrame:
    """``keys``, ``ids`` and ``decoded``: the text that the ids spell."""
    ship_package(encoded.sparkSession)
    narrow = encoded.select(*keys, "ids")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        labels = automaton.arc_labels(path)
        for part in small(batches):
            texts = [spell(v or b"", labels) for v in part.column(len(keys)).to_pylist()]
            yield pa.RecordBatch.from_arrays([*part.columns, pa.array(texts, pa.string())], names=[*keys, "ids", "decoded"])

    schema = ", ".join([*(f"`{k}` {narrow.schema[k].dataType.simpleString()}" for k in keys), "ids binary", "decoded string"])
    return narrow.mapInArrow(run, schema)


def encode_and_decode(docs: DataFrame, path: str, keys: list[str], text: str | Column = "text") -> DataFrame:
    """``keys``, ``ids`` and ``decoded`` as by :func:`encode` and :func:`decode`, in one worker a task instead of two that each hold the vocabulary."""
    ship_package(docs.sparkSession)
    narrow = docs.select(*keys, F.col(text).alias("__text") if isinstance(text, str) else text.alias("__text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tool, labels = tokenizer(path), automaton.arc_labels(path)
        _trim()  # what loading the vocabulary has left free
        for part in small(batches):
            ids = [tool.encode(t) for t in utf8_values(part.column(len(keys)))]
            texts = [spell(v, labels) for v in ids]
            yield pa.RecordBatch.from_arrays([*part.columns[: len(keys)], pa.array(ids, pa.binary()), pa.array(texts, pa.string())], names=[*keys, "ids", "decoded"])
        tool.forget()
        _trim()

    schema = ", ".join([*(f"`{k}` {narrow.schema[k].dataType.simpleString()}" for k in keys), "ids binary", "decoded string"])
    return narrow.mapInArrow(run, schema)


def digest(decoded: DataFrame) -> DataFrame:
    """One row per document with the counts and hashes of its ids and its decoded text."""
    return decoded.select(
        "doc_id",
        F.expr("cast(octet_length(ids) div 4 as bigint)").alias("n_tokens"),
        F.sha2("ids", 256).alias("ids_sha256"),
        F.sha2(F.col("decoded").cast("binary"), 256).alias("decoded_sha256"),
    )
