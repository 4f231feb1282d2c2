"""Associations of windows of a stream: cell counts are additive, so windowed counts with a watermark are the state.

Rows later than the watermark are dropped and counted by Spark's progress metrics. Mining of higher orders is left to a
schedule over the emitted counts; pairs and zones are cheap enough for every batch.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from assocmine.functions.expressions import entropy_bits
from assocmine.plans.materialize import fresh_path


def event_stream(spark: SparkSession, path: str) -> DataFrame:
    """A file table, a folder or a single file, as a stream with the table's schema."""
    reader = spark.readStream.schema(spark.read.parquet(path).schema)
    target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    if target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(target).isDirectory():
        return reader.parquet(path)
    folder, _, name = path.rpartition("/")
    return reader.option("pathGlobFilter", name).parquet(folder)


def run_to_end(stream: DataFrame, mode: str) -> DataFrame:
    """What a stream has put out when all that is there has been read; written in the shared folder. In mode "complete" the last batch counts."""
    spark = stream.sparkSession
    out, state = fresh_path(spark, "stream-out"), fresh_path(spark, "stream-state")

    def each(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite" if mode == "complete" else "append").parquet(out)

    query = stream.writeStream.outputMode(mode).foreachBatch(each).option("checkpointLocation", state).trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.schema(stream.schema).parquet(out)


def cell_counts(rows: DataFrame, attributes: dict[str, Column], sets: list[tuple[str, ...]], ts: str = "ts", length: str = "1 day", slide: str | None = None, watermark: str = "1 hour") -> DataFrame:
    """``window_start``, ``set_id``, ``cell``, ``n``, for a stream (append mode) or a table alike."""
    columns = F.array(*[F.struct(F.lit(",".join(s)).alias("set_id"), F.concat_ws("|", *[attributes[c].cast("string") for c in s]).alias("cell")) for s in sets])
    rows = rows.withColumn(ts, F.col(ts).cast("timestamp"))
    timed = rows.withWatermark(ts, watermark) if rows.isStreaming else rows
    window = F.window(ts, length, slide) if slide else F.window(ts, length)
    return timed.select(window.alias("window"), F.explode(columns).alias("x")).groupBy("window", "x.set_id", "x.cell").agg(F.count("*").alias("n")).select(F.col("window.start").alias("window_start"), "set_id", "cell", "n")


def session_counts(rows: DataFrame, key: str, attributes: dict[str, Column], ts: str = "ts", gap: str = "30 minutes", watermark: str = "1 hour") -> DataFrame:
    """Sessions of a key as rows: ``key``, session bounds, events, and the first value of each attribute."""
    rows = rows.withColumn(ts, F.col(ts).cast("timestamp"))
    timed = rows.withWatermark(ts, watermark) if rows.isStreaming else rows
    grouped = timed.select(key, ts, *[c.alias(n) for n, c in attributes.items()]).groupBy(key, F.session_window(ts, gap).alias("w"))
    return grouped.agg(F.count("*").alias("events"), *[F.min(n).alias(n) for n in attributes]).select(key, F.col("w.start").alias("session_start"), F.col("w.end").alias("session_end"), "events", *attributes)


def window_tc(cells: DataFrame) -> DataFrame:
    """TC of every window and pair from cell counts that hold the pairs and their members."""
    ent = cells.groupBy("window_start", "set_id").agg(entropy_bits(F.col("n")).alias("h"), F.sum("n").alias("n"))
    pairs = ent.filter(F.col("set_id").contains(",")).withColumn("a", F.split("set_id", ",")[0]).withColumn("b", F.split("set_id", ",")[1])
    one = ent.select("window_start", F.col("set_id").alias("a"), F.col("h").alias("ha"))
    two = ent.select("window_start", F.col("set_id").alias("b"), F.col("h").alias("hb"))
    return pairs.join(one, ["window_start", "a"]).join(two, ["window_start", "b"]).select("window_start", "set_id", "n", (F.col("ha") + F.col("hb") - F.col("h")).alias("tc"))


def mine_continuously(cells: DataFrame, sink_path: str, checkpoint: str, with_zones):
    """Start a query that appends every batch's TC with zones to Parquet; ``with_zones`` adds them to a batch."""
    def each(batch: DataFrame, number: int) -> None:
        with_zones(window_tc(batch)).withColumn("batch", F.lit(number)).write.mode("append").parquet(sink_path)

    return cells.writeStream.outputMode("append").foreachBatch(each).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


DRIFT_OUT = "set_id string, window_start timestamp, tc double, before double, drift boolean"


def drift(windows: DataFrame, threshold: float) -> DataFrame:
    """Streaming flag of windows whose TC moved by more than ``threshold`` bits since the set's window before."""
    def step(key: tuple, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        before = state.get[0] if state.exists else None
        for batch in batches:
            rows = []
            for r in batch.sort_values("window_start").itertuples():
                rows.append((key[0], r.window_start, r.tc, before, before is not None and abs(r.tc - before) > threshold))
                before = r.tc
            if rows:
                yield pd.DataFrame(rows, columns=["set_id", "window_start", "tc", "before", "drift"]).astype({"before": "float64"})
        if before is not None:
            state.update((float(before),))

    return windows.groupBy("set_id").applyInPandasWithState(step, DRIFT_OUT, "last double", "append", "NoTimeout")
