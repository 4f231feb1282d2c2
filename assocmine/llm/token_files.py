"""Token-id files: bit-plane shuffled blocks, each plane compressed with zstandard, with a chunk index.

File layout (all integers little-endian):

* ``MAGIC``;
* blocks of up to ``BLOCK_IDS`` ids: every id is an unsigned 32-bit integer; the block's bits are transposed so that
  plane p holds bit p of all ids (eight ids a byte, first id in the highest bit). Planes above the highest bit used in
  the block are left out. Each plane is one zstandard frame;
* the footer, one zstandard frame: the chunk index (for each block: offset, number of ids, number of planes, and the
  length of each plane) and the documents of the file in order (key, whether the key is null, number of ids);
* length of the footer (8 bytes), ``MAGIC``.

Writing is safe against lost executors and repeated tasks: each attempt writes a file of its own name, and only the
manifest rows of successful tasks, kept by Spark as Parquet, name files that count. Files are opened through
``pyarrow.fs`` by URI, in the shared folder of the cluster.

Nulls count as empty texts: such a document has the end id alone. Documents are ordered by key (nulls first) and, for
repeated keys, by a hash of the text. An empty table gives an empty manifest and no rows. Only the named columns are
read, so extra columns of any name do no harm.
"""

from __future__ import annotations

import functools
import json
import re
import struct
import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from assocmine.llm import automaton
from assocmine.llm.bpe import Remembered, packed, small, utf8_values
from assocmine.plans.materialize import fresh_path, materialize, ship_package

MAGIC = b"BPLANES1"
BLOCK_IDS = 1 << 16
LEVEL = 3
#: Runs that a worker remembers with their ids.
REMEMBERED_RUNS = 600_000
MANIFEST = "part int, file string, n_docs long, n_ids long"


class Planes:
    """Coding of one block."""

    @staticmethod
    def split(ids: np.ndarray) -> list[bytes]:
        """Bit planes of unsigned 32-bit ids, lowest bit first, as many as the largest id needs."""
        used = int(ids.max()).bit_length() if ids.size else 0
        rows = np.unpackbits(ids.astype("<u4").view(np.uint8).reshape(-1, 4), axis=1, bitorder="little")
        return [row.tobytes() for row in np.packbits(np.ascontiguousarray(rows[:, :used].T), axis=1)]

    @staticmethod
    def join(planes: list[bytes], n: int) -> np.ndarray:
        """Inverse of :meth:`split`."""
        bits = np.zeros((n, 32), dtype=np.uint8)
        for p, plane in enumerate(planes):
            bits[:, p] = np.unpackbits(np.frombuffer(plane, dtype=np.uint8), count=n)
        return np.packbits(bits, axis=1, bitorder="little").view("<u4").ravel()


class Writer:
    """Streams documents into one file; memory holds one block and the index."""

    def __init__(self, sink):
        self.sink, self.at, self.held, self.n_held = sink, 0, [], 0
        self.blocks: list[tuple[int, int, list[int]]] = []
        self.docs: list[tuple[int, bool, int]] = []
        self.n_ids = 0
        self.packer = zstandard.ZstdCompressor(level=LEVEL)
        self._put(MAGIC)

    def _put(self, data: bytes) -> None:
        self.sink.write(data)
        self.at += len(data)

    def add(self, key: int | None, ids: np.ndarray) -> None:
        self.docs.append((key or 0, key is None, len(ids)))
        self.n_ids += len(ids)
        self.held.append(ids)
        self.n_held += len(ids)
        if self.n_held >= BLOCK_IDS:
            self._flush(False)

    def _flush(self, all_of_it: bool) -> None:
        ids = np.concatenate(self.held) if self.held else np.empty(0, "<u4")
        end = len(ids) if all_of_it else len(ids) - len(ids) % BLOCK_IDS
        for start in range(0, end, BLOCK_IDS):
            block = ids[start : min(start + BLOCK_IDS, end)]
            frames = [self.packer.compress(plane) for plane in Planes.split(block)]
            self.blocks.append((self.at, len(block), [len(f) for f in frames]))
            for frame in frames:
                self._put(frame)
        rest = ids[end:]
        self.held, self.n_held = [rest] if len(rest) else [], len(rest)

    def close(self) -> None:
        self._flush(True)
        parts = [struct.pack("<QQ", len(self.blocks), len(self.docs))]
        parts += [struct.pack(f"<QII{len(sizes)}I", at, n, len(sizes), *sizes) for at, n, sizes in self.blocks]
        keys, nulls, counts = (np.array(x) for x in zip(*self.docs)) if self.docs else ([], [], [])
        parts += [np.asarray(keys, "<i8").tobytes(), np.asarray(nulls, "u1").tobytes(), np.asarray(counts, "<u8").tobytes()]
        footer = self.packer.compress(b"".join(parts))
        self._put(footer)
        self._put(struct.pack("<Q", len(footer)) + MAGIC)


class Reader:
    """Random access by block through the chunk index."""

    def __init__(self, source):
        self.source = source
        size = source.size()
        tail = self._at(size - 16, 16)
        if tail[8:] != MAGIC or self._at(0, 8) != MAGIC:
            raise ValueError("not a bit-plane token file")
        (length,) = struct.unpack("<Q", tail[:8])
        unpacker = zstandard.ZstdDecompressor()
        footer = unpacker.decompress(self._at(size - 16 - length, length))
        n_blocks, n_docs = struct.unpack_from("<QQ", footer)
        place, self.blocks = 16, []
        for _ in range(n_blocks):
            at, n, planes = struct.unpack_from("<QII", footer, place)
            self.blocks.append((at, n, struct.unpack_from(f"<{planes}I", footer, place + 16)))
            place += 16 + 4 * planes
        self.keys = np.frombuffer(footer, "<i8", n_docs, place)
        self.nulls = np.frombuffer(footer, "u1", n_docs, place + 8 * n_docs)
        self.counts = np.frombuffer(footer, "<u8", n_docs, place + 9 * n_docs)
        self.unpacker = unpacker

    def _at(self, place: int, length: int) -> bytes:
        self.source.seek(place)
        return self.source.read(length)

    def block(self, k: int) -> np.ndarray:
        at, n, sizes = self.blocks[k]
        data, planes, place = self._at(at, sum(sizes)), [], 0
        for size in sizes:
            planes.append(self.unpacker.decompress(data[place : place + size]))
            place += size
        return Planes.join(planes, n)

    def documents(self) -> Iterator[tuple[int | None, Iterator[np.ndarray], int]]:
        """(key, runs of its ids, number of ids) in file order; one block is held at a time."""
        k, block, place = -1, np.empty(0, "<u4"), 0

        def runs(left: int) -> Iterator[np.ndarray]:
            nonlocal k, block, place
            while left:
                if place == len(block):
                    k, place = k + 1, 0
                    block = self.block(k)
                run = block[place : place + left]
                place += len(run)
                left -= len(run)
                yield run

        for key, null, count in zip(self.keys.tolist(), self.nulls.tolist(), self.counts.tolist()):
            yield None if null else key, runs(count), count


#: White space beyond ASCII's, and control characters that Python alone counts as white space.
WIDE_SPACE = re.compile("[" + "".join(map(chr, [*range(0x1C, 0x20), 0x85, 0xA0, 0x1680, *range(0x2000, 0x200B), 0x2028, 0x2029, 0x202F, 0x205F, 0x3000])) + "]")
#: Runs that the splitter never joins: a word with the space before it, or white space. For texts of ASCII white space.
RUNS = re.compile(rb" ?[^\s]+|\s+(?!\S)|\s+")
SPLIT = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"


class ByteTokenizer:
    """Encoder for byte-level vocabularies whose words carry the space before them.

    Runs that the splitter never joins are encoded one by one and remembered. Byte-pair ranks are the token ids, which
    holds for vocabularies numbered in the order of their merges; others are refused.
    """

    def __init__(self, path: str):
        import tiktoken

        with open(path, encoding="utf-8") as source:
            definition = json.load(source)
        symbols, vocab = automaton.byte_symbols(), definition["model"]["vocab"]
        merged = [vocab["".join(m.split(" ") if isinstance(m, str) else m)] for m in definition["model"]["merges"]]
        if merged != sorted(merged):
            raise ValueError("token ids do not follow the order of merges")
        special = {a["content"]: a["id"] for a in definition.get("added_tokens", [])}
        ranks = {bytes(symbols[c] for c in label): token for label, token in vocab.items() if label not in special}
        self.public = tiktoken.Encoding("byte-level", pat_str=SPLIT, mergeable_ranks=ranks, special_tokens=special)
        self.marks = [mark.encode() for mark in special]
        self.runs = Remembered(lambda run: packed(self.public.encode_ordinary(run.decode("utf-8"))), REMEMBERED_RUNS)

    def encode(self, data: bytes) -> bytes:
        """Ids of a UTF-8 text as little-endian 32-bit integers."""
        if any(mark in data for mark in self.marks):
            return packed(self.public.encode(data.decode("utf-8"), allowed_special="all"))
        if WIDE_SPACE.search(text := data.decode("utf-8")):
            return packed(self.public.encode_ordinary(text))
        runs = self.runs
        return b"".join([runs[r] for r in RUNS.findall(data)])


@functools.lru_cache(maxsize=2)
def tokenizer(path: str) -> ByteTokenizer:
    return ByteTokenizer(path)


def open_uri(uri: str, write: bool):
    """A file of the shared folder, by URI, with whatever file system its scheme names."""
    from pyarrow import fs

    system, path = fs.FileSystem.from_uri(uri if "://" in uri or uri.startswith("file:") else f"file://{uri}")
    if write:
        system.create_dir(path.rpartition("/")[0], recursive=True)
        return system.open_output_stream(path)
    return system.open_input_file(path)


def write(docs: DataFrame, path: str, folder: str, key: str = "doc_id", text: str = "text", end_id: int = 2) -> DataFrame:
    """Encode whole texts, append ``end_id`` to each and write files in ascending key order; the manifest.

    The one shuffle is the range exchange of the raw rows. A key that many rows share is spread by a hash of the text.
    """
    ship_package(docs.sparkSession)
    ordered = docs.select(F.col(key).cast("long").alias("k"), F.col(text).alias("t")).withColumn("h", F.xxhash64("t"))
    parts = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    ordered = ordered.repartitionByRange(parts, "k", "h").sortWithinPartitions("k", "h").withColumn("p", F.spark_partition_id())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tool, out, sink = tokenizer(path), None, None
        end = packed([end_id])
        for batch in small(batches):
            if out is None:
                part, name = batch.column(3)[0].as_py(), f"{folder}/part-{batch.column(3)[0].as_py():06d}-{uuid.uuid4().hex}.bpl"
                sink = open_uri(name, True)
                out = Writer(sink)
            for k, t in zip(batch.column(0).to_pylist(), utf8_values(batch.column(1))):
                out.add(k, np.frombuffer(tool.encode(t) + end, dtype="<u4"))
        if out is not None:
            out.close()
            sink.close()
            tool.runs.clear()
            yield pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), pa.array([name]), pa.array([len(out.docs)], pa.int64()), pa.array([out.n_ids], pa.int64())], names=["part", "file", "n_docs", "n_ids"])

    return materialize(ordered.mapInArrow(run, MANIFEST), "token-manifest")


def read(manifest: DataFrame) -> DataFrame:
    """``doc_id``, ``start``, ``n_tokens`` and ``ids_crc32`` of every document, read back from the files.

    ``start`` counts the ids of all documents before it: those of earlier files from the manifest (one row a file),
    those of the same file from its index.
    """
    ship_package(manifest.sparkSession)
    before = F.coalesce(F.sum("n_ids").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    files = manifest.withColumn("base", before).select("part", "file", "base")
    files = files.repartition(int(manifest.sparkSession.conf.get("spark.sql.shuffle.partitions")), "part")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for file, start in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist()):
                with open_uri(file, False) as source:
                    keys, starts, counts, sums = [], [], [], []
                    for key, runs, count in Reader(source).documents():
                        crc = 0
                        for part in runs:
                            crc = zlib.crc32(part.tobytes(), crc)
                        keys.append(key)
                        starts.append(start)
                        counts.append(count)
                        sums.append(crc)
                        start += count
                        if len(keys) == 10_000:
                            yield _rows(keys, starts, counts, sums)
                            keys, starts, counts, sums = [], [], [], []
                    if keys:
                        yield _rows(keys, starts, counts, sums)

    return files.mapInArrow(run, "doc_id long, start long, n_tokens long, ids_crc32 long")


def _rows(*columns: list) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], names=["doc_id", "start", "n_tokens", "ids_crc32"])


def write_and_read(docs: DataFrame, path: str, end_id: int = 2) -> DataFrame:
    """Files in the shared folder, then the documents as the files hold them."""
    return read(write(docs, path, fresh_path(docs.sparkSession, "token-files"), end_id=end_id))
