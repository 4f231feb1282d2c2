"""Accuracy and cost measures of the experiments."""

from __future__ import annotations

import time
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from assocmine.operators import interactions, local, redundancy
from assocmine.operators.mining import Mined, check_local, mine, shape_of, sub_frame
from assocmine.plans.materialize import ship_package
from assocmine.sources.discretize import random_removal
from assocmine.sources.frame import Frame


def _truth(results: DataFrame, truth: Iterable[tuple[int, ...]]) -> DataFrame:
    return results.sparkSession.createDataFrame([(sorted(t),) for t in truth], "members array<int>")


def detection_rate(results: DataFrame, truth: Iterable[tuple[int, ...]], groups: DataFrame) -> DataFrame:
    """Share of the planted sets that every data set's result holds; ``groups`` lists the data sets (``g``)."""
    planted = groups.join(F.broadcast(_truth(results, truth)))
    hit = results.select("g", "members").distinct().withColumn("hit", F.lit(1))
    return planted.join(hit, ["g", "members"], "left").groupBy("g").agg(F.avg(F.coalesce("hit", F.lit(0))).alias("detected"))


def false_rate(results: DataFrame, truth: Iterable[tuple[int, ...]], groups: DataFrame) -> DataFrame:
    """Share of a data set's reported sets that were not planted; 0 where nothing is reported."""
    wrong = results.select("g", "members").distinct().join(F.broadcast(_truth(results, truth)).withColumn("true", F.lit(0)), "members", "left")
    return groups.join(wrong.groupBy("g").agg(F.avg(F.when(F.col("true").isNull(), 1.0).otherwise(0.0)).alias("r")), "g", "left").select("g", F.coalesce("r", F.lit(0.0)).alias("false_rate"))


def noise_curve(results: DataFrame, truth: Iterable[tuple[int, ...]], groups: DataFrame, noise: tuple[float, ...], per: int = 1000) -> DataFrame:
    """Mean detection and false rate for every noise level; data sets are numbered ``per`` * level + repeat."""
    truth = list(truth)
    rates = detection_rate(results, truth, groups).join(false_rate(results, truth, groups), "g")
    levels = F.array(*map(F.lit, noise))
    return rates.groupBy(levels[F.floor(F.col("g") / per).cast("int")].alias("noise")).agg(F.avg("detected").alias("detected"), F.avg("false_rate").alias("false_rate"), F.count("*").alias("repeats"))


def spectrum(result: DataFrame) -> DataFrame:
    """Sets in the order in which a spectrum plots them."""
    return result.orderBy("g", F.size("members"), F.desc("bits"), F.col("members").cast("string"))


MODES = ("none", "redundancy", "bounds", "both")


def ablation(frame: Frame, mode: str, prune: str, delta: float = redundancy.DELTA, **options) -> tuple[Mined, Frame]:
    """One run with a choice of prunings; the sample rule is always on."""
    if prune not in MODES:
        raise ValueError(f"prune is one of {MODES}")
    reduced = redundancy.apply(frame, redundancy.representatives(frame, delta)) if prune in ("redundancy", "both") else frame
    return mine(reduced, mode, bounds=prune in ("bounds", "both"), **options), reduced


RUNTIME = "removed int, rep int, prune string, attributes int, after_redundancy int, children long, exact long, sets long, interactions long, seconds double, members array<string>"


def runtime_curve(frame: Frame, removals: Iterable[int], repeats: int, mode: str = "tc", delta: float = redundancy.DELTA, max_order: int | None = None, modes: tuple[str, ...] = MODES, timed: bool = True) -> DataFrame:
    """Seconds and cost of search and interaction miner for every number of removed attributes, repeat and choice of prunings.

    Attributes are removed in the order of md5 hashes. Repeat r takes the frame's data set number r, from the first again
    when all are used; there are as many repeats as data sets at least. A run over one data set makes all choices of
    prunings, each timed by itself; tasks take several runs where there are many. Without ``timed`` the choices share the
    entropies that they count and the redundant attributes, and ``seconds`` is null.
    """
    check_local(frame)
    ship_package(frame.spark)
    shape = shape_of(frame)
    groups = [r[0] for r in frame.rows.select("g").distinct().orderBy("g").collect()]
    if not groups:
        return frame.spark.createDataFrame([], RUNTIME)
    grid = [(groups[rep % len(groups)], k, rep) for k in removals for rep in range(max(repeats, len(groups)))]
    asked = frame.spark.createDataFrame(grid, "g long, removed int, rep int")
    packs = frame.rows.groupBy("g").agg(F.collect_list(F.struct("a", "w")).alias("rows"))
    fields = pa.schema([("removed", pa.int32()), ("rep", pa.int32()), ("prune", pa.string()), ("attributes", pa.int32()), ("after_redundancy", pa.int32()), ("children", pa.int64()), ("exact", pa.int64()), ("sets", pa.int64()), ("interactions", pa.int64()), ("seconds", pa.float64()), ("members", pa.list_(pa.string()))])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for rows, g, removed, rep in zip(batch.column(0), *(c.to_pylist() for c in batch.columns[1:])):
                w = np.asarray(rows.values.field("w"), dtype=np.int64)
                x = np.asarray(rows.values.field("a").flatten(), dtype=np.int64).reshape(len(w), -1).T.copy()
                made = _runs(shape, g, x, w, removed, rep, modes, mode, delta, max_order, timed)
                yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*made), fields)], schema=fields)

    spread = asked.join(packs, "g").select("rows", "g", "removed", "rep").repartition(curve_tasks(len(grid), frame.spark.sparkContext.defaultParallelism))
    return spread.mapInArrow(run, RUNTIME)


def curve_tasks(runs: int, cores: int) -> int:
    """Tasks that runs are dealt to: one a run while they are few, then several a core, and never more than 64 runs in one."""
    return max(min(runs, 16 * cores), -(-runs // 64))


def _runs(shape: Frame, g: int, x: np.ndarray, w: np.ndarray, removed: int, rep: int, modes: tuple[str, ...], mode: str, delta: float, max_order: int | None, timed: bool) -> list[tuple]:
    """A row for each choice of prunings."""
    kept = set(random_removal([shape.names[i] for i in shape.predictors], removed, rep))
    index = [i for i, name in enumerate(shape.names) if name in kept or (i == shape.class_at and mode == "cac")]
    part, x = sub_frame(shape, index), x[index]
    if timed:
        return [(removed, rep, prune, *_run(part, g, x, w, prune, mode, delta, max_order)) for prune in modes]
    known = local.Known(len(part.names))
    reps = redundancy.representatives_of(part, x, w, delta) if {"redundancy", "both"} & set(modes) else None
    return [(removed, rep, prune, *(row := _run(part, g, x, w, prune, mode, delta, max_order, reps, known))[:6], None, row[7]) for prune in modes]


def _timed(shape: Frame, g: int, x: np.ndarray, w: np.ndarray, removed: int, rep: int, prune: str, mode: str, delta: float, max_order: int | None) -> tuple:
    return _runs(shape, g, x, w, removed, rep, (prune,), mode, delta, max_order, True)[0]


def _run(part: Frame, g: int, x: np.ndarray, w: np.ndarray, prune: str, mode: str, delta: float, max_order: int | None, reps: Iterable[int] | None = None, known: local.Known | None = None) -> tuple:
    began = time.time()
    own, index = part, list(range(len(part.names)))
    if prune in ("redundancy", "both"):
        reps = redundancy.representatives_of(part, x, w, delta) if reps is None else reps
        index = sorted([*reps, *([part.class_at] if part.class_at is not None else [])])
        own, x = sub_frame(part, index), x[index]
    place = np.array([i for i in index if mode != "cac" or i != part.class_at], dtype=np.int64)
    found = local.mine(own, mode, g, x, w, known=known, place=place, bounds=prune in ("bounds", "both"), max_order=max_order)
    attributes, order = interactions.universe(found)
    if attributes and interactions.fits(own, attributes, order):
        ii = sum(len(values) for _, values in local.interactions(x, w, own, attributes, order, 5.0))
    else:
        ii = len(interactions.mine_in_memory(x, w, own, attributes, order)) if attributes else 0
    members = sorted(",".join(own.names[i] for i in s) for s in found.result[g])
    return len(part.predictors), len(own.predictors), sum(v.children for v in found.levels), sum(v.exact for v in found.levels), len(members), ii, time.time() - began, members


def bound_gap(bounds: DataFrame) -> DataFrame:
    """Mean distance of the best bounds from the true TC, by order."""
    low, high = F.greatest("lower_ancestor", "lower_monotone", "lower_sibling"), F.least("upper_parent", "upper_sibling")
    return bounds.groupBy(F.size("s").alias("ord")).agg(F.avg(high - F.col("tc")).alias("upper_gap"), F.avg(F.col("tc") - low).alias("lower_gap"), F.count("*").alias("sets"))


def check_monotone(values: DataFrame, column: str) -> DataFrame:
    """Pairs of a set and a subset with one member fewer where the metric falls; empty if the property holds."""
    from assocmine.functions.expressions import immediate_subsets

    small = values.select("g", F.col("s").alias("t"), F.col(column).alias("small"))
    big = values.select("g", "s", F.col(column).alias("big"), F.explode(immediate_subsets(F.col("s"))).alias("t"))
    return big.join(small, ["g", "t"]).filter(F.col("small") > F.col("big") + 1e-9)


def recovered(found: DataFrame, planted: Iterable[int]) -> DataFrame:
    """How many planted attributes lie in any significant set."""
    wanted = list(planted)
    members = found.select("g", F.explode("s").alias("i")).filter(F.col("i").isin(wanted)).distinct()
    return members.groupBy("g").agg(F.count("*").alias("recovered"), F.lit(len(wanted)).alias("planted"))
