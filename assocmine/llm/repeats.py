"""Suffix-array dedup by prefix-free parsing: what lies in strings of a fixed length that start twice in the corpus goes.

Views. A text is read as a sequence of units: its UTF-8 bytes, and, where asked for, a 32-bit hash of each of its words.
Strings of ``length`` units are looked for in each view by itself, in the same passes.

Parsing. A rolling hash of every window of a few units puts triggers into every text: the trigger of a string is the
window with the smallest hash (the first of equal ones) among the windows that begin in its first ``reach`` units. It
depends on the string alone. Strings with the same trigger are neighbours and make up a phrase, which reaches from the
first of them to the end of the last; phrases overlap by nearly ``length`` units, so every string is the beginning of
exactly one phrase suffix, and no such suffix is a prefix of another at that depth.

Dictionary and parse. The parse is one narrow row a phrase, and is written once. Two equal strings lie in phrases with
the same *core* (the units behind the trigger that every string of the phrase holds), so rows whose core has one place
in the parse are done with. The dictionary holds the distinct phrases of the others with the number of their places:

* a phrase with two places repeats with all its suffixes;
* a phrase with one place, alone in its core, repeats nowhere;
* what is left are places where two repeats begin or end differently. One copy of each of these phrases is cut into
  sections of few strings, with long cores, and judged in the same way once more.

Suffix order. The sections that are still left are the dictionary whose suffixes are sorted. Their distinct cores get
ranks by content. A suffix that begins i units before its core is ordered by these i units, the rank of the core that
follows, and the units behind it: the end of a phrase and the rank of what comes after it in the parse, which is the
order of the suffixes at depth ``length``. Equal strings have the same i, so the order is kept for each i by itself. It
is spread over range partitions, ties broken by place, so a class with a third of all suffixes spans many tasks; equal
neighbours repeat, and neighbours across tasks are compared by the tasks' first and last suffixes.

Phrases are compared by two 64-bit hashes (of the core and of the whole), suffixes and cores by their bytes, words by 32
bits each. No suffix, phrase or count reaches the driver, and no group is gathered. Tables are dropped as soon as their
last reader is done.

Texts travel compressed, and only texts with phrases that need it travel a second time. Nulls count as empty texts.
Equal rows count each. Texts shorter than ``length`` lose nothing. Words are what ASCII white space separates, as their
exact bytes. Empty tables give no rows. Extra columns are not read.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from assocmine.llm.bpe import utf8_values
from assocmine.plans.materialize import collecting, materialize, note, release, ship_package

LENGTH = 400
#: Words of the shortest passage that the word view looks for.
WORDS = 51
#: The base of the rolling hash, an odd multiplier that mixes it, and bits of a packed value that hold the place.
BASE, MIXER, PLACE_BITS = 0x100000001B3, np.uint64(0x9E3779B97F4A7C15), 24
#: Units of a text parsed at once, and rows handed back at once: texts, and small rows.
PIECE, ROWS_AT_ONCE, SMALL_ROWS = 1 << 22, 500, 50_000
#: Strings of a section of a phrase.
SECTION = 16
#: Bits of a place for the view, and for each of the two distances that it holds; see :func:`placed`.
VIEW_BITS, LEAD_BITS = 1, 11
PARSE = ("id", "place", "core", "p")
#: Of a suffix: units before its core, these units, rank of the core, and units behind it.
SUFFIX = ("i", "before", "rank", "behind")
WORD = re.compile(rb"[^ \t\n\r\x0b\x0c]+")


@dataclass(frozen=True)
class View:
    """How a text is read: its number, the length of its strings and of trigger windows in units, and bytes of a unit."""

    number: int
    length: int
    trigger: int
    unit: int

    def __post_init__(self):
        if self.length < max(2 * self.trigger, SECTION + 1):
            raise ValueError(f"strings need {max(2 * self.trigger, SECTION + 1)} units at least")
        if reach_of(self.length) >= 1 << LEAD_BITS:
            raise ValueError(f"strings may have {(1 << LEAD_BITS) * 10 // 7} units at most")

    def units(self, text: bytes) -> np.ndarray:
        if self.unit == 1:
            return np.frombuffer(text, dtype=np.uint8)
        code = xxhash.xxh32_intdigest
        return np.array([code(w) for w in text.split()], dtype="<u4")


def byte_view(length: int = LENGTH) -> View:
    return View(0, length, 8, 1)


def word_view(words: int = WORDS) -> View:
    return View(1, words, 2, 4)


def reach_of(length: int) -> int:
    """Windows that compete for a string's trigger."""
    return max(1, length * 7 // 10)


def core_of(length: int) -> int:
    """Units behind a trigger's start that every string with this trigger holds."""
    return length - reach_of(length)


def phrases(units: np.ndarray, view: View) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of every phrase: its trigger's start, and the starts of its first and last string."""
    step = max(PIECE, view.length)
    found = [_phrases(units[start : start + step + view.length - 1], view, start) for start in range(0, max(0, len(units) - view.length + 1), step)]
    if not found:
        return (np.empty(0, dtype=np.int64),) * 3
    return tuple(np.concatenate(x) for x in zip(*found))


def rolling(units: np.ndarray, window: int) -> np.ndarray:
    """Rolling hash of every window (a power of two): the value at BASE of the polynomial of its units, modulo 2 ** 64, by doubling windows."""
    h, size = units.astype(np.uint64), 1
    while size < window:
        h = h[:-size] * np.uint64(pow(BASE, size, 1 << 64)) + h[size:]
        size *= 2
    return h


def _phrases(units: np.ndarray, view: View, offset: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The phrases of a piece of text; memory is bounded by the piece."""
    width, strings = reach_of(view.length), len(units) - view.length + 1
    n = strings + width - 1
    h = rolling(units, view.trigger)[:n] * MIXER
    h ^= h >> np.uint64(31)
    h *= MIXER
    h &= ~np.uint64((1 << PLACE_BITS) - 1)
    h |= np.arange(n, dtype=np.uint64)
    # smallest of every run of `width` windows, by running minima of blocks from both sides
    blocks = -(-n // width)
    padded = np.full(blocks * width, np.iinfo(np.uint64).max, dtype=np.uint64)
    padded[:n] = h
    table = padded.reshape(blocks, width)
    ahead = np.minimum.accumulate(table, axis=1).ravel()
    behind = np.minimum.accumulate(table[:, ::-1], axis=1)[:, ::-1].ravel()
    at = (np.minimum(behind[:strings], ahead[width - 1 : width - 1 + strings]) & np.uint64((1 << PLACE_BITS) - 1)).astype(np.int64)
    last = np.flatnonzero(np.append(at[1:] != at[:-1], True))
    first = np.concatenate([[0], last[:-1] + 1])
    return at[last] + offset, first + offset, last + offset


def placed(view: View, at: int, first: int, last: int) -> int:
    """View, start of the trigger or core, and the starts of the first and last string around it, in one long."""
    return ((at << LEAD_BITS | at - first) << LEAD_BITS | last - first) << VIEW_BITS | view.number


def unplaced(place: int) -> tuple[int, int, int]:
    """The three places of :func:`placed`."""
    place >>= VIEW_BITS
    span, lead, at = place & (1 << LEAD_BITS) - 1, place >> LEAD_BITS & (1 << LEAD_BITS) - 1, place >> 2 * LEAD_BITS
    return at, at - lead, at - lead + span


def of_view(places: list[int] | None, view: View) -> list[tuple[int, int, int]]:
    return [unplaced(p) for p in places or () if p & (1 << VIEW_BITS) - 1 == view.number]


def _types(df: DataFrame, columns: tuple[str, ...]) -> str:
    return ", ".join(f"`{c}` {df.schema[c].dataType.simpleString()}" for c in columns)


def pack(docs: DataFrame, carry: tuple[str, ...]) -> DataFrame:
    """``id`` (a number of the row), the carried columns and the compressed UTF-8 text of every row."""
    n = len(carry) + 1

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        packer = zstandard.ZstdCompressor(level=3)
        for batch in batches:
            for start in range(0, batch.num_rows, ROWS_AT_ONCE):
                part = batch.slice(start, ROWS_AT_ONCE)
                yield pa.RecordBatch.from_arrays([*part.columns[:n], pa.array([packer.compress(t) for t in utf8_values(part.column(n))], pa.binary())], names=["id", *carry, "packed"])

    numbered = docs.select(F.monotonically_increasing_id().alias("id"), *carry, F.col("text").alias("__text"))
    return numbered.mapInArrow(run, f"id long, {_types(numbered, carry)}, packed binary")


def parse(packed: DataFrame, views: tuple[View, ...]) -> DataFrame:
    """One row per phrase of the parse: row ``id``, ``place``, and hashes of its ``core`` and of all of it (``p``)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        unpacker = zstandard.ZstdDecompressor()
        for batch in batches:
            for start in range(0, batch.num_rows, ROWS_AT_ONCE):
                part = batch.slice(start, ROWS_AT_ONCE)
                rows: list[tuple] = []
                for number, data in zip(part.column(0).to_pylist(), part.column(1).to_pylist()):
                    text = unpacker.decompress(data)
                    for view in views:
                        units = view.units(text)
                        found = zip(*(x.tolist() for x in phrases(units, view)))
                        rows += _hashed(number, units, view, ((at, first, last, at - first) for at, first, last in found), core_of(view.length))
                yield _records(rows)

    return packed.select("id", "packed").mapInArrow(run, ", ".join(f"{c} long" for c in PARSE))


def _hashed(number: int, units: np.ndarray, view: View, found: Iterator[tuple[int, int, int, int]], width: int) -> list[tuple]:
    """Rows of the parse from (start of the core, first and last string's start, seed of the whole); ``width`` units make a core."""
    data, u, length, low, digest = units.tobytes(), view.unit, view.length, 1 << 63, xxhash.xxh3_64_intdigest
    return [(number, placed(view, at, first, last), digest(data[at * u : (at + width) * u], view.number) - low, digest(data[first * u : (last + length) * u], seed) - low) for at, first, last, seed in found]


def _records(rows: list[tuple]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in (list(zip(*rows)) or [()] * len(PARSE))], names=list(PARSE))


def sections(at: int, first: int, last: int) -> Iterator[tuple[int, int, int, int]]:
    """A phrase in sections: (start of the section's core, first and last string's start, units from first string to trigger).

    A section holds the strings that begin up to SECTION - 1 units before its core; cores lie a multiple of SECTION before the trigger.
    """
    for j in range((at - last) // SECTION, (at - first) // SECTION + 1):
        base = at - SECTION * j
        begin = max(first, base - SECTION + 1)
        yield base, begin, min(last, base), at - begin


def parse_sections(marked: DataFrame, views: tuple[View, ...]) -> DataFrame:
    """As :func:`parse`, for sections of the phrases at ``places``: their cores are nearly as long as their strings."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        unpacker = zstandard.ZstdDecompressor()
        for batch in batches:
            rows: list[tuple] = []
            for number, data, places in zip(*(c.to_pylist() for c in batch.columns)):
                text = unpacker.decompress(data)
                for view in views:
                    if found := of_view(places, view):
                        rows += _hashed(number, view.units(text), view, (x for f in found for x in sections(*f)), view.length - SECTION + 1)
                if len(rows) >= SMALL_ROWS:
                    yield _records(rows)
                    rows = []
            yield _records(rows)

    return marked.select("id", "packed", "places").mapInArrow(run, ", ".join(f"{c} long" for c in PARSE))


_PART = pa.schema([("id", pa.int64()), ("view", pa.int64()), ("base", pa.int64()), ("least", pa.int32()), ("most", pa.int32()), ("core", pa.binary()), ("before", pa.binary()), ("behind", pa.binary())])


def section_parts(marked: DataFrame, views: tuple[View, ...]) -> DataFrame:
    """Of each section in ``parts``: its ``core`` and where that starts (``base``), how many units before it the last and first string begin, and the units around it."""

    def records(rows: list[tuple]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(list(zip(*rows)) or [()] * len(_PART), _PART)], schema=_PART)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        unpacker = zstandard.ZstdDecompressor()
        for batch in batches:
            rows: list[tuple] = []
            for number, data, parts in zip(*(c.to_pylist() for c in batch.columns)):
                text = unpacker.decompress(data)
                for view in views:
                    found, width = of_view(parts, view), view.length - SECTION + 1
                    units = view.units(text) if found else None
                    for base, first, last in found:
                        rows.append((number, view.number, base, base - last, base - first, units[base : base + width].tobytes(), units[first:base].tobytes(), units[base + width : last + view.length].tobytes()))
                if len(rows) >= SMALL_ROWS // SECTION:
                    yield records(rows)
                    rows = []
            yield records(rows)

    return marked.select("id", "packed", "parts").mapInArrow(run, "id long, view long, base long, least int, most int, core binary, before binary, behind binary")


def suffix_order(parts: DataFrame, unit: dict[int, int]) -> DataFrame:
    """All suffixes of rows of :func:`section_parts` (a written table) in their order: ``id``, ``view``, ``start``, the columns of SUFFIX, and the range partition ``task``. ``unit`` has the bytes of each view's units."""
    tasks = int(parts.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    cores = parts.groupBy("core").agg(F.count("*").alias("m")).filter("m > 1").select("core")
    ranks = materialize(cores.repartitionByRange(tasks, "core").sortWithinPartitions("core").withColumn("rank", F.monotonically_increasing_id()), "core-ranks")
    each = parts.join(ranks, "core").select("id", "view", "base", "rank", "before", "behind", "most", F.explode(F.sequence("least", "most")).alias("i"))
    wide = F.element_at(F.create_map(*[F.lit(x) for pair in unit.items() for x in pair]), F.col("view").cast("int"))
    before = F.substring(F.col("before"), (F.col("most") - F.col("i")) * wide + 1, F.col("i") * wide)
    behind = F.substring(F.col("behind"), F.lit(1), (F.lit(SECTION - 1) - F.col("i")) * wide)
    suffixes = each.select("id", "view", (F.col("base") - F.col("i")).alias("start"), "i", before.alias("before"), "rank", behind.alias("behind"))
    place = [*SUFFIX, "id", "view", "start"]
    return materialize(suffixes, "suffixes").repartitionByRange(tasks, *place).sortWithinPartitions(*place).withColumn("task", F.spark_partition_id())


PLACE = ("id", "view", "start")
_NEAR = pa.schema([("id", pa.int64()), ("view", pa.int64()), ("start", pa.int64()), ("i", pa.int32()), ("before", pa.binary()), ("rank", pa.int64()), ("behind", pa.binary()), ("task", pa.int32()), ("twice", pa.bool_()), ("edge", pa.bool_())])


def equal_neighbours(ordered: DataFrame) -> DataFrame:
    """``id``, ``view`` and ``start`` of the suffixes that equal a neighbour in their order."""

    def near(rows: list[tuple]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(list(zip(*rows)) or [()] * len(_NEAR), _NEAR)], schema=_NEAR)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out: list[tuple] = []
        before, was = None, False  # the suffix before this one, and whether it equals the one before it
        for batch in batches:
            for row in zip(*(c.to_pylist() for c in batch.columns)):
                if before is None:
                    out.append((*row, False, True))
                    same = False
                else:
                    same = before[3:7] == row[3:7]
                    if same or was:
                        out.append((*before, True, False))
                before, was = row, same
                if len(out) >= SMALL_ROWS:
                    yield near(out)
                    out = []
        if before is not None:
            out.append((*before, was, True))
        yield near(out)

    fields = "id long, view long, start long, i int, before binary, rank long, behind binary, task int, twice boolean, edge boolean"
    found = materialize(ordered.select(*PLACE, *SUFFIX, "task").mapInArrow(run, fields), "neighbours")
    # the first and last suffix of every task, in order of tasks: two rows a task
    beside = Window.orderBy("task", *SUFFIX, *PLACE)
    key = F.struct(*SUFFIX)
    edges = found.filter("edge").withColumn("up", F.lag(key).over(beside)).withColumn("up_task", F.lag("task").over(beside)).withColumn("down", F.lead(key).over(beside)).withColumn("down_task", F.lead("task").over(beside))
    met = ((F.col("up_task") != F.col("task")) & (F.col("up") == key)) | ((F.col("down_task") != F.col("task")) & (F.col("down") == key))
    return found.filter("twice").select(*PLACE).unionByName(edges.filter(met).select(*PLACE)).distinct()


def judge(parsed: DataFrame, name: str) -> tuple[DataFrame, DataFrame]:
    """Places (``id``, ``place``) whose phrase has two places, and of one copy of every phrase that shares its core with another phrase.

    Only rows whose core has two places or more are compared; the others go before any phrase is looked at.
    """
    cores = materialize(parsed.groupBy("core").agg(F.count("*").alias("m")).filter("m > 1").select("core"), f"{name}-cores")
    open_rows = materialize(parsed.join(cores, "core", "left_semi"), f"{name}-rows")
    dictionary = materialize(open_rows.groupBy("core", "p").agg(F.count("*").alias("n"), F.min(F.struct("id", "place")).alias("copy")), name)
    twice = open_rows.join(dictionary.filter("n > 1").select("core", "p"), ["core", "p"], "left_semi").select("id", "place")
    shared = dictionary.groupBy("core").agg(F.count("*").alias("m")).filter("m > 1").select("core")
    return twice, dictionary.join(shared, "core", "left_semi").select("copy.id", "copy.place")


def removed(docs: DataFrame, length: int = LENGTH, carry: tuple[str, ...] = ("doc_id",), words: int | None = None, keep: str = "bytes") -> DataFrame:
    """The carried columns, ``n_bytes``, ``n_removed``, ``spans`` (offset, length) and ``kept`` (binary) of every row.

    With ``words`` passages of that many words are looked for too: ``passages`` has their spans in bytes, from the first
    byte of their first word to the last of their last, and ``n_passage_words`` their words. With ``keep`` "text" they
    are cut out like the byte strings, and ``kept`` is a string, without characters that a cut has parted; with "bytes"
    it lacks the byte strings only.
    """
    ship_package(docs.sparkSession)
    spark, views = docs.sparkSession, (byte_view(length), *([word_view(words)] if words else []))
    packed = materialize(pack(docs, carry), "packed-texts")
    scratch: list[str] = []
    with collecting(scratch):
        whole, copies = judge(materialize(parse(packed, views), "parse"), "dictionary")
        marks = whole.withColumn("repeats", F.lit(True)).unionByName(copies.withColumn("repeats", F.lit(False))).groupBy("id").agg(
            F.collect_list(F.when(F.col("repeats"), F.col("place"))).alias("whole"), F.collect_list(F.when(~F.col("repeats"), F.col("place"))).alias("places")
        )
        marks = materialize(marks, "marked-places")
    kept_tables = [scratch.pop()]
    release(spark, scratch)
    with collecting(scratch):
        open_texts = materialize(packed.select("id", "packed").join(marks.filter(F.size("places") > 0).select("id", "places"), "id"), "open-texts")
        half, ends = judge(materialize(parse_sections(open_texts, views), "sections"), "section-dictionary")
        parts = ends.groupBy("id").agg(F.collect_list("place").alias("parts"))
        left = materialize(section_parts(open_texts.select("id", "packed").join(parts, "id"), views), "section-parts")
        single = equal_neighbours(suffix_order(left, {v.number: v.unit for v in views})).groupBy("id").agg(F.collect_list(F.struct("view", "start")).alias("starts"))
        half = half.groupBy("id").agg(F.collect_list("place").alias("parts"))
        both = marks.select("id", "whole").join(half, "id", "left").join(single, "id", "left")
        found = materialize(both.select("id", F.concat("whole", F.coalesce("parts", F.array().cast("array<bigint>"))).alias("places"), "starts"), "found-places")
    note(scratch.pop())
    release(spark, scratch + kept_tables)
    return _cut(packed.join(found, "id", "left"), views, carry, keep)


def runs(view: View, places: list[int] | None, starts: list[dict] | None) -> list[tuple[int, int]]:
    """Maximal runs (first, end) of the units covered by strings that repeat: those of whole phrases and sections, and single ones."""
    ranges = [(first, last + view.length) for _, first, last in of_view(places, view)]
    ranges += [(x["start"], x["start"] + view.length) for x in starts or () if x["view"] == view.number]
    out: list[tuple[int, int]] = []
    for first, end in sorted(ranges):
        if out and first <= out[-1][1]:
            out[-1] = (out[-1][0], max(end, out[-1][1]))
        else:
            out.append((first, end))
    return out


def without(text: bytes, spans: list[tuple[int, int]]) -> bytes:
    """The text without spans (first, end), which may overlap."""
    rest, upto = [], 0
    for first, end in sorted(spans):
        rest.append(text[upto : max(first, upto)])
        upto = max(end, upto)
    return b"".join([*rest, text[upto:]])


def _cut(marked: DataFrame, views: tuple[View, ...], carry: tuple[str, ...], keep: str) -> DataFrame:
    n, worded, as_text = len(carry), len(views) > 1, keep == "text"
    spans = pa.list_(pa.struct([("offset", pa.int64()), ("length", pa.int64())]))
    fields = [("n_bytes", pa.int64()), ("n_removed", pa.int64()), ("spans", spans), ("kept", pa.string() if as_text else pa.binary()), *([("n_passage_words", pa.int64()), ("passages", spans)] if worded else [])]

    def told(pairs: list[tuple[int, int]]) -> list[dict]:
        return [{"offset": a, "length": b - a} for a, b in pairs]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        unpacker = zstandard.ZstdDecompressor()
        for batch in batches:
            for begin in range(0, batch.num_rows, ROWS_AT_ONCE):
                part = batch.slice(begin, ROWS_AT_ONCE)
                rows = []
                for packed, places, starts in zip(*(part.column(n + i).to_pylist() for i in range(3))):
                    text = unpacker.decompress(packed)
                    gone = [runs(v, places, starts) for v in views]
                    said = []
                    if worded:
                        at = [m.span() for m in WORD.finditer(text)] if gone[1] else []
                        said = [(at[a][0], at[b - 1][1]) for a, b in gone[1]]
                    left = without(text, gone[0] + said).decode("utf-8", "ignore") if as_text else without(text, gone[0])
                    rows.append((len(text), sum(b - a for a, b in gone[0]), told(gone[0]), left, *([sum(b - a for a, b in gone[1]), told(said)] if worded else [])))
                columns = list(zip(*rows)) or [()] * len(fields)
                yield pa.RecordBatch.from_arrays([*part.columns[:n], *(pa.array(c, t) for c, (_, t) in zip(columns, fields))], names=[*carry, *(f for f, _ in fields)])

    listed = "array<struct<offset: bigint, length: bigint>>"
    schema = f"{_types(marked, carry)}, n_bytes long, n_removed long, spans {listed}, kept {'string' if as_text else 'binary'}" + (f", n_passage_words long, passages {listed}" if worded else "")
    return marked.select(*carry, "packed", "places", "starts").mapInArrow(run, schema)


def digest(cleaned: DataFrame) -> DataFrame:
    """Counts and the hash of what is left of every document; with passages, their number and words."""
    more = ["n_passage_words", F.size("passages").cast("long").alias("n_passages")] if "passages" in cleaned.columns else []
    return cleaned.select("doc_id", "n_bytes", "n_removed", F.size("spans").cast("long").alias("n_spans"), F.sha2("kept", 256).alias("kept_sha256"), *more)


def plain(texts: list[bytes], length: int = LENGTH) -> list[tuple[int, int, int, str]]:
    """Brute force, for tests: (n_bytes, n_removed, n_spans, kept_sha256) of every text."""
    seen: dict[bytes, int] = {}
    for t in texts:
        for i in range(len(t) - length + 1):
            seen[t[i : i + length]] = seen.get(t[i : i + length], 0) + 1
    out = []
    for t in texts:
        starts = [i for i in range(len(t) - length + 1) if seen[t[i : i + length]] > 1]
        keep = [True] * len(t)
        for i in starts:
            keep[i : i + length] = [False] * length
        runs = sum(1 for i, k in enumerate(keep) if not k and (i == 0 or keep[i - 1]))
        out.append((len(t), keep.count(False), runs, hashlib.sha256(bytes(b for b, k in zip(t, keep) if k)).hexdigest()))
    return out
