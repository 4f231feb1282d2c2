"""Interaction miner: II of all subsets of the mined attributes, up to an order the sample size allows."""

from __future__ import annotations

import math
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from assocmine.operators import local, metrics, permutation, redundancy
from assocmine.operators.mining import Mined, check_local, dealt, in_memory, shape_of, sub_frame
from assocmine.operators.mining import mine as search
from assocmine.plans import counts
from assocmine.plans.materialize import materialize, ship_package
from assocmine.sources.frame import Frame


def universe(result: Mined, g: int | None = None) -> tuple[list[int], int]:
    """Attributes of the mined sets (with the class, if there is one) and the largest mined order."""
    sets = [s for gg, found in result.result.items() if g is None or gg == g for s in found]
    attributes = sorted({i for s in sets for i in s} | ({result.frame.class_at} if result.metric == "CAC" and sets else set()))
    return attributes, max(map(len, sets), default=0)


def allowed(frame: Frame, s: tuple[int, ...], min_ratio: float = 5.0) -> bool:
    return frame.n >= min_ratio * math.prod(frame.states[i] for i in s)


def mine(frame: Frame, attributes: list[int], order: int, method: str = "signs", min_ratio: float = 5.0, most: int = 1_000_000) -> DataFrame:
    """``g``, ``s``, ``ii`` for all subsets of two or more; with a class in the universe, ``order`` counts predictors and
    only sets with the class are returned. ``method`` "signs": one join of sets with signed subsets; "sweep": one
    self-join an attribute, in place, which ends at minus II."""
    c = frame.class_at if frame.class_at in attributes else None
    predictors = [i for i in attributes if i != c]
    if sum(math.comb(len(predictors), k) for k in range(1, order + 1)) > most:
        raise RuntimeError(f"more than {most} subsets; mine fewer attributes or a smaller order")
    sets = metrics.all_sets(predictors, 1, order)
    if c is not None:
        sets = [*sets, (c,), *(tuple(sorted((*s, c))) for s in sets)]
    sets = [s for s in sets if len(s) == 1 or allowed(frame, s, min_ratio)]
    ent = materialize(counts.entropies(frame, sets), "interaction-entropies")
    goals = [s for s in sets if (len(s) > 1 and (c is None or c in s))]
    if not goals:
        return frame.spark.createDataFrame([], "g long, s array<int>, ii double")
    wanted = metrics.table(frame, goals)
    if method == "signs":
        return metrics.interaction_info(ent, wanted).select("g", "s", "ii")
    held = ent.select("g", "s", F.col("h").alias("v"))
    for i in attributes:
        smaller = held.filter(~F.array_contains("s", i)).select("g", F.array_sort(F.array_append("s", F.lit(i))).alias("s"), F.col("v").alias("less"))
        held = held.join(smaller, ["g", "s"], "left").select("g", "s", F.when(F.array_contains("s", i), F.col("v") - F.coalesce("less", F.lit(0.0))).otherwise(F.col("v")).alias("v"))
    return held.select("g", "s", (-F.col("v")).alias("ii")).join(wanted, ["g", "s"], "left_semi")


def significant(frame: Frame, mined: DataFrame, nperm: int = permutation.NPERM, alpha_ii: float = permutation.ALPHA_II, seed: int = 0, tail: str = "upper") -> DataFrame:
    """II with permutation p below a level; ``relation`` names its sign."""
    sets = [tuple(r[0]) for r in mined.select("s").distinct().collect()]
    tested = permutation.fast(frame, sets, nperm, seed, tail=tail, early_stop=alpha_ii)
    return tested.withColumn("relation", metrics.ii_kind(F.col("ii"))).filter(F.col("p") < alpha_ii)


def pipeline(frame: Frame, mode: str = "tc", delta: float | None = redundancy.DELTA, nperm: int = permutation.NPERM, alpha_ii: float = permutation.ALPHA_II, **options) -> tuple[Mined, DataFrame, dict[int, list[int]]]:
    """Redundancy removal, search, then II of the mined attributes only: result, significant II, and cover groups.

    Members of result and II are indexes of the reduced frame; cover groups are indexes of the given one.
    """
    groups = {i: [i] for i in frame.predictors}
    reduced = frame
    if delta is not None:
        groups = redundancy.representatives(frame, delta)
        reduced = redundancy.apply(frame, groups)
    found = search(reduced, mode, **options)
    attributes, order = universe(found)
    if not attributes:
        return found, frame.spark.createDataFrame([], "g long, s array<int>, ii double, p double, nperm int, cells_touched long, relation string"), groups
    return found, significant(reduced, mine(reduced, attributes, order), nperm, alpha_ii), groups


def recover(frame: Frame, reduced: Frame, sets: list[tuple[int, ...]], groups: dict[int, list[int]], nperm: int = permutation.NPERM, alpha_ii: float = permutation.ALPHA_II) -> DataFrame:
    """II of the sets that covered attributes form in place of their representatives, tested again."""
    index = [frame.names.index(n) for n in reduced.names]
    original = [tuple(sorted(index[i] for i in s)) for s in sets]
    again = [s for s in redundancy.expand(original, groups) if allowed(frame, s)]
    if not again:
        return frame.spark.createDataFrame([], "g long, s array<int>, ii double, p double, nperm int, cells_touched long")
    return permutation.fast(frame, again, nperm, early_stop=alpha_ii).filter(F.col("p") < alpha_ii)


def mine_in_memory(x: np.ndarray, w: np.ndarray, frame: Frame, attributes: list[int], order: int, min_ratio: float = 5.0) -> dict[tuple[int, ...], float]:
    """II as :func:`mine`, of one small data set: in arrays, or by the sweep over named sets, in place, if they are too many for arrays."""
    c = frame.class_at if frame.class_at in attributes else None
    predictors = [i for i in attributes if i != c]
    if fits(frame, attributes, order, min_ratio):
        full = lambda s: tuple(sorted((*s, c))) if c is not None else tuple(s)
        return {full(s): v for members, ii in local.interactions(x, w, frame, attributes, order, min_ratio) for s, v in zip(members.tolist(), ii.tolist())}
    sets = [s for s in metrics.all_sets(predictors, 1, order)]
    if c is not None:
        sets = [*sets, (c,), *(tuple(sorted((*s, c))) for s in sets)]
    held = {s: h for s, h, _ in counts.entropies_of(x, w, frame.states, [s for s in sets if len(s) == 1 or allowed(frame, s, min_ratio)])}
    for i in attributes:
        for s in held:
            if i in s and len(s) > 1:
                held[s] -= held[tuple(j for j in s if j != i)]
    return {s: -v for s, v in held.items() if len(s) > 1 and (c is None or c in s)}


def fits(frame: Frame, attributes: list[int], order: int, min_ratio: float = 5.0) -> bool:
    """Whether the subsets are few enough for arrays."""
    return local.fits(sub_frame(frame, sorted(attributes)), "cac" if frame.class_at in attributes else "tc", order, min_ratio, local.MOST_SETS)


II_SCHEMA = "g long, s array<int>, ii double, p double, nperm int, relation string"


def pipeline_each(frame: Frame, mode: str = "tc", delta: float | None = redundancy.DELTA, nperm: int = permutation.NPERM, alpha_ii: float = permutation.ALPHA_II, seed: int = 0, **options) -> DataFrame:
    """Significant II of the two-step strategy for every data set, one task each; members are indexes of the given frame.

    Draws for a set end when p cannot fall below the level any more.
    """
    check_local(frame)
    ship_package(frame.spark)
    shape, stop = shape_of(frame), int(alpha_ii * nperm) + 1
    schema = pa.schema([("g", pa.int64()), ("s", pa.list_(pa.int32())), ("ii", pa.float64()), ("p", pa.float64()), ("nperm", pa.int32()), ("relation", pa.string())])

    def run(table: pa.Table) -> pa.Table:
        g, x, w = in_memory(table)
        kept = list(range(len(shape.names)))
        if delta is not None:
            reps = redundancy.representatives_of(shape, x, w, delta)
            kept = sorted([*reps, *([shape.class_at] if shape.class_at is not None else [])])
        own = sub_frame(shape, kept)
        x = x[kept]
        attributes, order = universe(local.mine(own, mode, g, x, w, **options))
        rows = []
        for s, ii in mine_in_memory(x, w, own, attributes, order).items() if attributes else ():
            cube = np.zeros(tuple(own.states[i] for i in s), dtype=np.int64)
            np.add.at(cube, tuple(x[i] for i in s), w)
            rng = np.random.default_rng([seed, g & 0x7FFFFFFF, *s])
            _, hits, done = permutation.count_hits(cube, s.index(permutation.pick_shuffle_attr(own, s)), nperm, rng, stop=stop)
            if hits / done < alpha_ii:
                rows.append((g, [kept[i] for i in s], ii, hits / done, done, "synergy" if ii > 1e-9 else "redundancy" if ii < -1e-9 else "none"))
        return pa.table([pa.array(c, f.type) for c, f in zip(list(zip(*rows)) or [()] * len(schema), schema)], schema=schema)

    return dealt(frame).applyInArrow(run, II_SCHEMA)


def cumulative_spectrum(mined: DataFrame) -> DataFrame:
    """Spectrum by order and size with the running sum of II, which ends at the TC of the universe if all sets are there."""
    from pyspark.sql import Window

    order = Window.partitionBy("g").orderBy(F.size("s"), F.desc("ii"), F.col("s").cast("string"))
    return mined.withColumn("running", F.sum("ii").over(order.rowsBetween(Window.unboundedPreceding, 0)))


def pairs_of(attributes: list[int]) -> list[tuple[int, ...]]:
    return list(combinations(attributes, 2))
