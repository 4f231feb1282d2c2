"""Mixing sources to target weights by a low-discrepancy schedule, with DataFrame functions only.

Slots of equal numbers of words follow a golden-ratio sequence; each point falls into the interval of a source on the
scale of cumulative targets. The slots of a source are ranked, and slot r takes block r of the source's stream: its
documents in hashed order, twice over, cut into blocks of equal words. A document's share of the mix is what the taken
blocks hold of it, so none is taken more than twice.

Ranks and stream offsets are sums over buckets first and inside buckets then, so a source with a third of all rows is
spread over tasks. Only four numbers about all sources reach the driver.

Null texts count as empty; documents without words are in no block and are taken 0 times. Rows without a source form one
source, which comes last. Repeated rows are documents of their own. An empty table gives no rows. Extra columns are
not read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from assocmine.plans.materialize import materialize

WEIGHTS, SHARE, MOST_TIMES = (3, 1, 2), 1.5, 2
#: A mix has about this many slots, or slots of so many words if those are fewer.
SLOTS, MOST_WORDS = 1 << 15, 256
#: Documents of a bucket, slots of a run, and cells of the scale on which slots meet sources.
BUCKET_ROWS, RUN, CELLS = 1024, 1 << 16, 1 << 12
GOLDEN = 0.6180339887498949
#: Fixed value: the fractional part of 2**20 times the golden ratio's.
GOLDEN_20 = 0.6077874097403509


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")


def targets(sizes: DataFrame) -> DataFrame:
    """Adds ``sid``, ``weight`` and ``target`` to one row per source (``source``, ``source_size``).

    Targets share the mix by weight but stop at the cap; what is cut off is shared again. All targets follow from one
    level: the largest of (mix - caps of the sources that fill up before) / (weights of the others).
    """
    w = Window.orderBy(F.col("source").asc_nulls_last())
    cycle = F.array(*[F.lit(x) for x in WEIGHTS])
    ranked = sizes.withColumn("sid", F.row_number().over(w).cast("int")).withColumn("weight", F.element_at(cycle, (F.col("sid") - 1) % len(WEIGHTS) + 1))
    filled = Window.orderBy(F.col("source_size") / F.col("weight"), "sid")
    before = F.coalesce(F.sum(MOST_TIMES * F.col("source_size")).over(filled.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    others = F.sum("weight").over(filled.rowsBetween(0, Window.unboundedFollowing))
    everything = Window.partitionBy()
    levels = ranked.withColumn("mix", SHARE * F.sum("source_size").over(everything)).withColumn("level", (F.col("mix") - before) / others)
    level = F.max("level").over(everything)
    return levels.withColumn("target", F.least((MOST_TIMES * F.col("source_size")).cast("double"), F.col("weight") * level)).drop("level")


def schedule(goals: DataFrame, block_words: int, n_slots: int) -> DataFrame:
    """``slot``, ``sid`` and ``block``: which source every slot takes, and the rank of the slot among that source's."""
    spark = goals.sparkSession
    order = Window.orderBy("sid")
    total = F.sum("target").over(Window.partitionBy())
    share = goals.withColumn("hi", F.sum("target").over(order.rowsBetween(Window.unboundedPreceding, 0)) / total)
    share = share.withColumn("lo", F.coalesce(F.lag("hi").over(order), F.lit(0.0))).filter("hi > lo")
    cells = share.select("sid", "lo", "hi", F.explode(F.sequence(F.floor(F.col("lo") * CELLS), F.least(F.floor(F.col("hi") * CELLS), F.lit(CELLS - 1).cast("long")))).alias("cell"))
    high, low = F.floor(F.col("id") / (1 << 20)), F.col("id") % (1 << 20)
    point = F.pmod(F.pmod(high * GOLDEN_20, F.lit(1.0)) + low * GOLDEN + 0.5, F.lit(1.0))
    slots = spark.range(n_slots).select(F.col("id").alias("slot"), point.alias("u")).withColumn("cell", F.least(F.floor(F.col("u") * CELLS), F.lit(CELLS - 1).cast("long")))
    owned = slots.join(cells, "cell").filter("u >= lo and u < hi").select("slot", "sid", F.floor(F.col("slot") / RUN).alias("run"))
    counts = owned.groupBy("sid", "run").agg(F.count("*").alias("n"))
    base = counts.select("sid", "run", F.coalesce(F.sum("n").over(Window.partitionBy("sid").orderBy("run").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("base"))
    inside = Window.partitionBy("sid", "run").orderBy("slot")
    return owned.join(base, ["sid", "run"]).select("slot", "sid", (F.col("base") + F.row_number().over(inside) - 1).alias("block"))


def mix(docs: DataFrame) -> DataFrame:
    """``doc_id``, ``h``, ``size``, ``source_size``, ``target`` and ``taken`` of every document."""
    return taken(*prepare(docs))


def prepare(docs: DataFrame) -> tuple[DataFrame, DataFrame, int, int]:
    """Documents placed in their source's stream, sources with targets, words of a block, and number of slots."""
    sized = docs.select(F.col("doc_id"), F.col("source"), word_count(F.col("text")).alias("size"), F.xxhash64("doc_id", "text", "source").alias("h"))
    sized = materialize(sized, "mix-sizes")
    sources = sized.groupBy("source").agg(F.sum("size").alias("source_size"), F.count("*").alias("n"))
    goals = materialize(targets(sources), "mix-targets")
    most, total = goals.agg(F.max("n"), F.sum("target")).first()
    total = total or 0.0
    block_words = int(max(1, min(MOST_WORDS, total // SLOTS)))
    bits = max(0, ((most or 0) // BUCKET_ROWS).bit_length())
    bucket = F.shiftrightunsigned("h", 64 - bits) if bits else F.lit(0).cast("long")
    placed = sized.join(goals.withColumnRenamed("source", "__source").drop("n", "mix", "weight"), F.col("source").eqNullSafe(F.col("__source"))).withColumn("bucket", bucket)
    sums = placed.groupBy("sid", "bucket").agg(F.sum("size").alias("s"))
    base = sums.select("sid", "bucket", F.coalesce(F.sum("s").over(Window.partitionBy("sid").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("base"))
    inside = Window.partitionBy("sid", "bucket").orderBy("h", "doc_id", "size")
    placed = placed.join(base, ["sid", "bucket"])
    upto = F.sum("size").over(inside.rowsBetween(Window.unboundedPreceding, 0))
    placed = placed.withColumn("at", F.col("base") + upto - F.col("size")).withColumn("nth", F.row_number().over(inside))
    return placed.select("doc_id", "h", "size", "source_size", "target", "sid", "bucket", "at", "nth"), goals, block_words, int(-(-total // block_words))


def taken(placed: DataFrame, goals: DataFrame, block_words: int, n_slots: int) -> DataFrame:
    """Words of every document in the scheduled blocks."""
    passes = placed.withColumn("pass", F.explode(F.array(*[F.lit(p) for p in range(MOST_TIMES)]))).withColumn("a", F.col("pass") * F.col("source_size") + F.col("at"))
    first, last = F.floor(F.col("a") / block_words), F.floor((F.col("a") + F.col("size") - 1) / block_words)
    pieces = passes.withColumn("block", F.explode(F.when(F.col("size") > 0, F.sequence(first, last)).otherwise(F.array(F.lit(-1).cast("long")))))
    held = F.least(F.col("a") + F.col("size"), (F.col("block") + 1) * block_words) - F.greatest(F.col("a"), F.col("block") * block_words)
    chosen = schedule(goals, block_words, n_slots).select("sid", "block", "slot")
    joined = pieces.withColumn("held", held).join(chosen, ["sid", "block"], "left")
    keys = ["sid", "bucket", "nth", "doc_id", "h", "size", "source_size", "target"]
    summed = joined.groupBy(*keys).agg(F.sum(F.when(F.col("slot").isNotNull(), F.col("held")).otherwise(0)).alias("taken"))
    return summed.select("doc_id", "h", "size", "source_size", "target", F.col("taken").cast("long").alias("taken"))
