"""SimHash near-duplicates by meet-in-the-middle ball hashing.

Two 64-bit fingerprints within ``radius`` bits of each other share a variant within half the radius of both, so every
distinct fingerprint emits all its variants within radius 1 (itself and 64 single flips, for the radius of 2), and the
variants are shuffled. At most 65 distinct fingerprints lie within one bit of a variant, whatever the data: no bucket
can grow hot. Every two members of a bucket differ by 2 bits at most, which the join's filter verifies again; linking
each member to the smallest one keeps every link's connection. Components follow from alternating large-star and
small-star steps over the edges.

Nulls and texts without words have fingerprint zero and are linked like any other. Equal texts have equal
fingerprints and are collapsed before anything is emitted. Null doc_ids never become a component id unless a component
holds nothing else. Empty tables give empty results. Extra columns are never read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from assocmine.llm.bpe import small, utf8_values
from assocmine.llm.components import connected
from assocmine.plans.materialize import materialize, ship_package

SEED = 42
PIECE = 1 << 15


def fingerprint(text: bytes, width: int = 3) -> int:
    """SimHash of a UTF-8 text: XXH64 of its word shingles, a bit set if it is in over half of them."""
    words = text.lower().split()
    n = len(words)
    if n == 0:
        return 0
    digest = xxhash.xxh64_intdigest
    if n < width:
        shingles = [b" ".join(words)]
    else:
        shingles = map(b" ".join, zip(*(words[i:] for i in range(width))))
    hashes = np.fromiter((digest(s, SEED) for s in shingles), dtype="<u8", count=max(1, n - width + 1))
    ones = np.zeros(64, dtype=np.int64)
    for start in range(0, len(hashes), PIECE):
        bits = np.unpackbits(hashes[start : start + PIECE].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
        ones += bits.sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * ones > len(hashes), bitorder="little").view("<u8")[0])


def fingerprints(docs: DataFrame, key: str = "doc_id", text: str = "text", width: int = 3) -> DataFrame:
    """``doc_id`` and ``fp``: the fingerprint's 64 bits as a signed long."""
    ship_package(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small(batches):
            found = np.array([fingerprint(t, width) for t in utf8_values(batch.column(1))], dtype=np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(found, pa.int64())], names=["doc_id", "fp"])

    narrow = docs.select(F.col(key).alias("doc_id"), F.col(text).alias("text"))
    return narrow.mapInArrow(run, f"doc_id {narrow.schema['doc_id'].dataType.simpleString()}, fp long")


def links(distinct: DataFrame, radius: int = 2) -> DataFrame:
    """Edges (``a`` < ``b``) that connect all fingerprints of ``distinct`` (column ``fp``) within 2 bits of each other."""
    if radius != 2:
        raise ValueError("variants within half the radius are built for a radius of 2")
    flips = F.array(F.lit(0).cast("long"), *[F.lit(1 << b if b < 63 else -(1 << 63)).cast("long") for b in range(64)])
    tasks = int(distinct.sparkSession.conf.get("spark.sql.shuffle.partitions"))  # every row becomes 65: tasks are not coalesced by the size of what they read
    variants = distinct.repartition(tasks, "fp").select("fp", F.explode(F.transform(flips, lambda f: F.col("fp").bitwiseXOR(f))).alias("v"))
    least = variants.groupBy("v").agg(F.min("fp").alias("a"), F.collect_list("fp").alias("all")).filter(F.size("all") > 1)
    pairs = least.select("a", F.explode("all").alias("b")).filter("a <> b and bit_count(a ^ b) <= 2")
    return pairs.distinct()


def components(prints: DataFrame) -> DataFrame:
    """``doc_id``, ``fp`` and ``component_id`` of rows of :func:`fingerprints`, which must be a written table."""
    distinct = prints.groupBy("fp").agg(F.min("doc_id").alias("least"))
    label = connected(materialize(links(distinct.select("fp")), "simhash-links"))
    class_of = distinct.join(label.withColumnRenamed("node", "fp"), "fp", "left").withColumn("root", F.coalesce("root", "fp"))
    smallest = class_of.groupBy("root").agg(F.min("least").alias("component_id"))
    named = class_of.select("fp", "root").join(smallest, "root").select("fp", "component_id")
    return prints.join(named, "fp").select("doc_id", "fp", "component_id")


def near_duplicates(docs: DataFrame) -> DataFrame:
    """One row per document: ``doc_id``, ``fingerprint`` (16 hex digits) and ``component_id``."""
    prints = materialize(fingerprints(docs), "simhash-prints")
    hexed = F.lower(F.lpad(F.hex("fp"), 16, "0"))
    return components(prints).select("doc_id", hexed.alias("fingerprint"), "component_id")
