"""Sharding by histogram sort, with DataFrame functions only.

Rows get a 62-bit sort key: a hash of the text above hashes of the doc_id and of the row's number in the written table,
so equal texts lie together and yet have keys of their own: a group of copies that is larger than a shard is split, and
one that lies at a splitter may be, as the law is about bytes. The splitters between shards are found by counting: each round counts the exact bytes of the key
ranges that still hold a wanted splitter, ranges 512 times finer than the round before, until the bytes below every
splitter are within tolerance of its quota or the key has no more digits. Then rows are exchanged once.

The driver holds the counts of the probed ranges only: 512 for each of the shards' splitters at most. Slots are
gapless numbers inside a shard: sums over cells of hashed keys first, ranks inside cells then.

The law is ``bytes``: shards hold nearly equal bytes. A null text has no bytes and the checksum of the empty text. A
null doc_id is hashed like any other value. Rows that are equal in all of doc_id and text are told apart by their number.
An empty table gives no rows. Extra columns are not read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from assocmine.plans.materialize import materialize

SHARDS, OVERHEAD = 24, 8
KEY_BITS, LOW_BITS, ROW_BITS, DIGIT = 62, 24, 8, 9
#: Bytes by which a splitter may miss its quota, as a share of a shard's bytes; and rows of a cell, about.
TOLERANCE, CELL_ROWS = 1e-4, 4096


def keyed(docs: DataFrame) -> DataFrame:
    """``doc_id``, ``size``, ``text_crc32`` and the sort ``key`` of every row; to be written before it is read twice."""
    text = F.coalesce(F.col("text"), F.lit(""))
    high = F.shiftleft(F.pmod(F.xxhash64("text"), F.lit(1 << (KEY_BITS - LOW_BITS))), LOW_BITS)
    return docs.select("doc_id", (F.octet_length(text) + OVERHEAD).cast("long").alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"), (high + F.shiftleft(F.pmod(F.xxhash64("doc_id"), F.lit(1 << (LOW_BITS - ROW_BITS))), ROW_BITS) + F.pmod(F.xxhash64(F.monotonically_increasing_id()), F.lit(1 << ROW_BITS))).alias("key"))


def splitters(rows: DataFrame, shards: int = SHARDS, tolerance: float = TOLERANCE) -> tuple[list[int], int]:
    """Keys that begin shards 1, 2, ..., and the number of rows."""
    digits, shift = 1, KEY_BITS - DIGIT
    counts = {r["c"]: (r["s"], r["n"]) for r in rows.groupBy(F.shiftright("key", shift).alias("c")).agg(F.sum("size").alias("s"), F.count("*").alias("n")).collect()}
    total, n = sum(s for s, _ in counts.values()), sum(k for _, k in counts.values())
    #: for each splitter: (key range that holds it, bytes below the range)
    found: dict[int, int] = {}
    below = {0: 0}
    wanted = {j: 0 for j in range(1, shards)}
    while wanted:
        ranges: dict[int, list[int]] = {}
        for cell in sorted(counts):
            ranges.setdefault(cell >> DIGIT if digits > 1 else 0, []).append(cell)
        active, next_below = {}, {}
        for j, held in wanted.items():
            quota, at, last = total * j / shards, below[held], None
            for cell in ranges.get(held, []):
                if at + counts[cell][0] > quota:
                    last = cell
                    break
                at += counts[cell][0]
            if last is None:
                found[j] = (((held + 1) << DIGIT) if digits > 1 else 1 << DIGIT) << shift
            elif quota - at <= tolerance * total / shards or shift == 0:
                later = at + counts[last][0]
                found[j] = (last if quota - at <= later - quota or quota - at <= tolerance * total / shards else last + 1) << shift
            elif at + counts[last][0] - quota <= tolerance * total / shards:
                found[j] = (last + 1) << shift
            else:
                active[j], next_below[last] = last, at
        wanted, below = active, next_below
        if wanted:
            finer = max(0, shift - DIGIT)
            probe = rows.filter(F.shiftright("key", shift).isin(sorted(set(wanted.values()))))
            width = shift - finer
            counts = {r["c"]: (r["s"], 0) for r in probe.groupBy(F.shiftright("key", finer).alias("c")).agg(F.sum("size").alias("s")).collect()}
            if width < DIGIT:  # the last round has fewer digits: keep ranges aligned to DIGIT
                counts = {((c >> width) << DIGIT) + (c & ((1 << width) - 1)): v for c, v in counts.items()}
                found |= _last_round(counts, wanted, below, total, shards, width)
                break
            shift, digits = finer, digits + 1
    return [found[j] for j in range(1, shards)], n


def _last_round(counts: dict, wanted: dict, below: dict, total: int, shards: int, width: int) -> dict[int, int]:
    """Splitters at single keys, the nearest to their quotas."""
    found = {}
    for j, held in wanted.items():
        quota, at = total * j / shards, below[held]
        key = (held + 1) << width
        for cell in sorted(c for c in counts if c >> DIGIT == held):
            plain = (held << width) + (cell & ((1 << DIGIT) - 1))
            if at + counts[cell][0] > quota:
                key = plain if quota - at <= at + counts[cell][0] - quota else plain + 1
                break
            at += counts[cell][0]
        found[j] = key
    return found


def shard_of(key: Column, cuts: list[int]) -> Column:
    shard = F.lit(0)
    for cut in cuts:
        shard = shard + (key >= F.lit(cut).cast("long")).cast("int")
    return shard


def shards(docs: DataFrame, n_shards: int = SHARDS) -> DataFrame:
    """``doc_id``, ``size``, ``text_crc32``, ``law``, ``shard``, ``slot`` and ``grown_shard`` of every document."""
    rows = materialize(keyed(docs), "shard-keys")
    cuts, n = splitters(rows, n_shards)
    cells = max(1, n // (n_shards * CELL_ROWS))
    placed = rows.withColumn("shard", shard_of(F.col("key"), cuts)).withColumn("cell", F.pmod(F.xxhash64("key"), F.lit(cells)))
    counts = placed.groupBy("shard", "cell").agg(F.count("*").alias("n"))
    base = counts.select("shard", "cell", F.coalesce(F.sum("n").over(Window.partitionBy("shard").orderBy("cell").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("base"))
    inside = Window.partitionBy("shard", "cell").orderBy("key", "doc_id", "text_crc32", "size")
    slot = F.col("base") + F.row_number().over(inside) - 1
    return placed.join(base, ["shard", "cell"]).select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", slot.alias("slot"), F.lit(None).cast("int").alias("grown_shard"))
