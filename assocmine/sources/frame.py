"""Discrete data: rows of dense integer codes, with weights, for one data set or many at once.

``rows`` has the columns ``g`` (which data set: repeats of an experiment are mined together), ``a`` (codes in the order
of ``names``) and ``w`` (how many equal rows this one stands for). All data sets of a frame have the same number of rows.
"""

from __future__ import annotations

import dataclasses
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from assocmine.plans.materialize import materialize

#: Most values that an attribute may have; dictionaries of encoding are held by the driver.
MAX_STATES = 10_000


@dataclass(frozen=True)
class Frame:
    rows: DataFrame
    names: tuple[str, ...]
    states: tuple[int, ...]
    n: int
    class_at: int | None = None
    dropped: tuple[str, ...] = field(default=())

    @property
    def spark(self) -> SparkSession:
        return self.rows.sparkSession

    @property
    def predictors(self) -> tuple[int, ...]:
        return tuple(i for i in range(len(self.names)) if i != self.class_at)

    def select(self, keep: list[int]) -> Frame:
        """Only these attributes, renumbered in ascending order; a class that is left out stops being one."""
        keep = sorted(keep)
        array = F.array(*[F.col("a")[i] for i in keep])
        at = keep.index(self.class_at) if self.class_at in keep else None
        rows = self.rows.select(*[c for c in self.rows.columns if c != "a"], array.alias("a"))
        return dataclasses.replace(self, rows=rows, names=tuple(self.names[i] for i in keep), states=tuple(self.states[i] for i in keep), class_at=at)

    def collapse(self) -> Frame:
        """Equal rows become one with their summed weight; every metric depends on counts only."""
        return dataclasses.replace(self, rows=materialize(self.rows.groupBy("g", "a").agg(F.sum("w").alias("w")), "collapsed"))

    def attributes(self) -> DataFrame:
        """Catalogue: ``idx``, ``name``, ``states``."""
        return self.spark.createDataFrame(list(zip(range(len(self.names)), self.names, self.states)), "idx int, name string, states long")


def encode(df: DataFrame, names: list[str], class_name: str | None = None, group: Column | None = None, weight: Column | None = None, keep: list[str] | None = None, max_states: int = MAX_STATES) -> Frame:
    """Dense codes by value order; attributes with one value are dropped and reported. The coded rows are written once.

    Nulls must have been treated (see ``discretize``); a null that is left becomes a value of its own, code 0.
    """
    if class_name is not None and class_name not in names:
        names = [*names, class_name]
    group, weight = group if group is not None else F.lit(0), weight if weight is not None else F.lit(1)
    base = df.select(group.cast("long").alias("g"), weight.cast("long").alias("w"), *(keep or []), *(F.col(c).alias(f"__{i}") for i, c in enumerate(names)))
    guess = base.agg(*(F.approx_count_distinct(f"__{i}").alias(str(i)) for i in range(len(names)))).first()
    wide = [c for i, c in enumerate(names) if guess[i] > 1.2 * max_states]
    if wide:
        raise ValueError(f"too many values to be discrete: {wide}")
    values = base.agg(*(F.array_sort(F.collect_set(f"__{i}")).alias(f"v{i}") for i in range(len(names))), *(F.max(F.col(f"__{i}").isNull()).alias(f"n{i}") for i in range(len(names)))).first()
    codes, states, used, dropped = [], [], [], []
    for i, name in enumerate(names):
        known, gap = list(values[f"v{i}"] or []), int(bool(values[f"n{i}"]))
        if len(known) > max_states:
            raise ValueError(f"too many values to be discrete: {name}")
        if len(known) + gap < 2:
            dropped.append(name)
            continue
        dense = all(isinstance(v, int) and not isinstance(v, bool) for v in known) and known == list(range(len(known)))
        column = F.col(f"__{i}")
        code = column if dense else F.array_position(F.array(*[F.lit(v) for v in known]), column) - 1
        codes.append((F.coalesce(code + gap, F.lit(0)) if gap else code).cast("int"))
        states.append(len(known) + gap)
        used.append(name)
    rows = base.select("g", *(keep or []), F.array(*codes).alias("a") if codes else F.array().cast("array<int>").alias("a"), "w")
    rows = materialize(rows, "frame")
    return Frame(rows, tuple(used), tuple(states), _size(rows), used.index(class_name) if class_name in used else None, tuple(dropped))


def _size(rows: DataFrame) -> int:
    size = rows.groupBy("g").agg(F.sum("w").alias("n")).agg(F.min("n"), F.max("n")).first()
    if size[0] != size[1]:
        raise ValueError(f"data sets of one frame differ in size: {size[0]} to {size[1]} rows")
    return int(size[0] or 0)


def dense(df: DataFrame, names: list[str], class_name: str | None = None, group: Column | None = None, keep: list[str] | None = None) -> Frame:
    """A frame of columns that hold dense codes already, without nulls; an attribute has as many states as its largest code tells.

    Attributes with one value are dropped and reported.
    """
    names = [*names, class_name] if class_name is not None and class_name not in names else names
    group = group if group is not None else F.lit(0)
    rows = df.select(group.cast("long").alias("g"), *(keep or []), F.array(*[F.col(c).cast("int") for c in names]).alias("a"), F.lit(1).cast("long").alias("w"))
    rows = materialize(rows, "frame")
    most = rows.agg(*(F.max(F.col("a")[i]).alias(f"m{i}") for i in range(len(names)))).first()
    states = tuple(int(m or 0) + 1 for m in most)
    frame = Frame(rows, tuple(names), states, _size(rows), names.index(class_name) if class_name is not None else None)
    single = [i for i, k in enumerate(states) if k < 2]
    if not single:
        return frame
    return dataclasses.replace(frame.select([i for i in range(len(names)) if i not in single]), dropped=tuple(names[i] for i in single))
