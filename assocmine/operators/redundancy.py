"""Redundant attributes: pair scores, cover groups, a greedy choice of representatives, and recovery after mining."""

from __future__ import annotations

import warnings
from collections import defaultdict
from itertools import combinations, product

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from assocmine.operators.metrics import _singles, interaction_info
from assocmine.plans import counts
from assocmine.plans.materialize import materialize, ship_package
from assocmine.sources.frame import Frame

DELTA = 0.75


def pair_entropies(frame: Frame, context: str = "none") -> DataFrame:
    """Entropies that pair scores need, from one pass."""
    p = frame.predictors
    sets = [(i,) for i in range(len(frame.names))] + list(combinations(p, 2))
    if context == "class":
        c = frame.class_at
        sets += [tuple(sorted((i, c))) for i in p] + [tuple(sorted((*s, c))) for s in combinations(p, 2)]
    return counts.entropies(frame, sets)


def scores(frame: Frame, ent: DataFrame, context: str = "none") -> DataFrame:
    """``g``, ``i`` < ``j``, ``score``: the II of the pair with one of them repeated, over the smaller entropy; or, in the
    context of the class, the II of the pair and the class over the class entropy. Redundancy is negative."""
    if context == "class":
        c = frame.class_at
        if c is None:
            raise ValueError("the class context needs a class attribute")
        sets = frame.spark.createDataFrame([(list(s), i, j) for i, j in combinations(frame.predictors, 2) for s in [tuple(sorted((i, j, c)))]], "s array<int>, i int, j int")
        wanted = sets.join(frame.rows.select("g").distinct())
        hc = _singles(ent).filter(F.col("i") == c).select("g", F.col("h1").alias("hc"))
        return wanted.join(interaction_info(ent, wanted.select("g", "s")), ["g", "s"]).join(hc, "g").select("g", "i", "j", (F.col("ii") / F.col("hc")).alias("score"))
    one = _singles(ent)
    pairs = ent.filter(F.size("s") == 2).select("g", F.col("s")[0].alias("i"), F.col("s")[1].alias("j"), F.col("h").alias("hij"))
    if frame.class_at is not None:
        pairs = pairs.filter((F.col("i") != frame.class_at) & (F.col("j") != frame.class_at))
    joined = pairs.join(one.withColumnRenamed("h1", "hi"), ["g", "i"]).join(one.select("g", F.col("i").alias("j"), F.col("h1").alias("hj")), ["g", "j"])
    return joined.select("g", "i", "j", (-(F.col("hi") + F.col("hj") - F.col("hij")) / F.least("hi", "hj")).alias("score"))


def covers(frame: Frame, scored: DataFrame, delta: float = DELTA) -> DataFrame:
    """``g``, ``rep``, ``covered``: every predictor with the attributes redundant with it, itself included."""
    hit = scored.filter(F.col("score") <= -delta)
    both = hit.select("g", F.col("i").alias("rep"), F.col("j").alias("x")).unionByName(hit.select("g", F.col("j").alias("rep"), F.col("i").alias("x")))
    own = frame.rows.select("g").distinct().withColumn("rep", F.explode(F.array(*map(F.lit, frame.predictors)))).withColumn("x", F.col("rep"))
    return both.unionByName(own).groupBy("g", "rep").agg(F.array_sort(F.collect_set("x")).alias("covered"))


def reduce(groups: dict[int, set[int]], greedy: str = "residual") -> dict[int, list[int]]:
    """Representatives in order of choice with what each covers: the largest group first, or what it adds; ties to the
    smallest index. ``groups`` has one entry an attribute."""
    left = set(groups)
    chosen: dict[int, list[int]] = {}
    while left:
        rest = [i for i in groups if i not in chosen and groups[i] & left]
        size = (lambda i: len(groups[i] & left)) if greedy == "residual" else (lambda i: len(groups[i]))
        best = min(rest, key=lambda i: (-size(i), i))
        chosen[best] = sorted(groups[best])
        left -= groups[best]
    return chosen


def representatives_each(frame: Frame, delta: float = DELTA, context: str = "none", greedy: str = "residual") -> DataFrame:
    """``g``, ``nth``, ``rep``, ``covered``: the representatives of every data set in order of choice. A task holds one entry an attribute."""
    ship_package(frame.spark)
    scored = materialize(scores(frame, pair_entropies(frame, context), context), "redundancy-scores")
    if context == "class":
        least = scored.agg(F.min("score")).first()[0]
        if least is not None and least > -delta:
            warnings.warn(f"no pair reaches the threshold {-delta} in the class context (least score {least:.4f})", stacklevel=2)

    def choose(table: pa.Table) -> pa.Table:
        chosen = reduce({r["rep"]: set(r["covered"]) for r in table.to_pylist()}, greedy)
        return pa.table([pa.array([table.column("g")[0].as_py()] * len(chosen), pa.int64()), pa.array(range(len(chosen)), pa.int32()), pa.array(list(chosen), pa.int32()), pa.array(list(chosen.values()), pa.list_(pa.int32()))], names=["g", "nth", "rep", "covered"])

    return covers(frame, scored, delta).groupBy("g").applyInArrow(choose, "g long, nth int, rep int, covered array<int>")


def representatives(frame: Frame, delta: float = DELTA, context: str = "none", greedy: str = "residual") -> dict[int, list[int]]:
    """Cover groups of the representatives of a frame. Data sets whose representatives differ have to be reduced each by itself."""
    by_group: dict[int, dict[int, list[int]]] = defaultdict(dict)
    for r in representatives_each(frame, delta, context, greedy).orderBy("g", "nth").collect():  # one row an attribute and data set
        by_group[r["g"]][r["rep"]] = list(r["covered"])
    found = list(by_group.values())
    if any(set(x) != set(found[0]) for x in found):
        raise ValueError("the data sets of this frame have different representatives; use representatives_each or mine_each")
    return found[0] if found else {}


def representatives_of(frame: Frame, x: np.ndarray, w: np.ndarray, delta: float = DELTA, greedy: str = "residual") -> dict[int, list[int]]:
    """The same for one data set in memory, without class context."""
    p = frame.predictors
    h = np.array([bits for _, bits, _ in counts.entropies_of(x, w, frame.states, [*((i,) for i in p), *combinations(p, 2)])])
    first, second = np.triu_indices(len(p), 1)  # pairs in the order of combinations
    with np.errstate(invalid="ignore", divide="ignore"):  # an attribute with one value in this data set is redundant with none
        hit = -(h[first] + h[second] - h[len(p) :]) / np.minimum(h[first], h[second]) <= -delta
    groups = {i: {i} for i in p}
    for i, j in zip(first[hit].tolist(), second[hit].tolist()):
        groups[p[i]].add(p[j])
        groups[p[j]].add(p[i])
    return reduce(groups, greedy)


def apply(frame: Frame, reps: dict[int, list[int]] | list[int]) -> Frame:
    """Only the representatives and the class."""
    return frame.select([*reps, *([frame.class_at] if frame.class_at is not None else [])])


def expand(result: list[tuple[int, ...]], covered: dict[int, list[int]], most: int = 100_000) -> list[tuple[int, ...]]:
    """Sets with members replaced by what they cover, to be tested again; the given sets are left out."""
    out: set[tuple[int, ...]] = set()
    for s in result:
        for t in product(*(covered.get(i, [i]) for i in s)):
            if len(set(t)) == len(s):
                out.add(tuple(sorted(t)))
        if len(out) > most:
            raise RuntimeError(f"more than {most} recovered sets")
    return sorted(out - {tuple(sorted(s)) for s in result})


def by_name(frame: Frame, reps: dict[int, list[int]]) -> dict[str, list[str]]:
    out: dict[str, list[str]] = defaultdict(list)
    for r, xs in reps.items():
        out[frame.names[r]] = [frame.names[x] for x in xs]
    return dict(out)
