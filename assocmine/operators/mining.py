"""Level-wise search for core and extension sets, with or without a class attribute.

The data are touched by one counting pass a level (and a small one for subsets that the tree never visited), for all data
sets of the frame at once. Between the passes the lattice is attribute metadata: its size depends on the number of
attributes, never on the number of rows, and is guarded by ``max_sets``. Beyond that :mod:`assocmine.operators.lattice`
keeps the lattice in tables.

An experiment's many small data sets are mined by :func:`mine_each`, one task a data set, with the same rules in arrays
(:mod:`assocmine.operators.local`).
"""

from __future__ import annotations

import math
from collections import defaultdict
from collections.abc import Callable, Iterable
from dataclasses import dataclass, field
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, GroupedData

from assocmine.functions.gamma import critical_bits, log_p
from assocmine.operators import bounds as B
from assocmine.operators import redundancy
from assocmine.operators.significance import ALPHA_HIGH, ALPHA_LOW, SLACK, check_alphas
from assocmine.plans import counts
from assocmine.plans.materialize import ship_package
from assocmine.sources.frame import Frame

Members = tuple[int, ...]
#: Counts the sets wanted in each data set: (data set, set, entropy in bits, cells).
Count = Callable[[dict[int, list[Members]]], Iterable[tuple[int, Members, float, int]]]
#: Most rows of a data set that one task mines.
LOCAL_ROWS = 1_000_000
STRONG, MIDDLE, WEAK = "STRONG", "MIDDLE", "WEAK"
RESULT_SCHEMA = "g long, members array<int>, names array<string>, metric string, bits double, df double, p double, neg_log10_p double, zone string, kind string"
REPORT_SCHEMA = "level int, children long, cut_samples long, decided_by_bound map<string,long>, exact long, side_exact long, kept long, frontier long"
CASES = {(STRONG, STRONG): "1", (STRONG, MIDDLE): "2", (STRONG, WEAK): "3", (MIDDLE, WEAK): "4", (WEAK, WEAK): "5", (MIDDLE, MIDDLE): "6"}


@dataclass
class Level:
    order: int
    children: int = 0
    cut_samples: int = 0
    exact: int = 0
    side_exact: int = 0
    kept: int = 0
    frontier: int = 0
    decided: dict[str, int] = field(default_factory=lambda: defaultdict(int))


@dataclass
class Found:
    bits: float
    df: float
    kind: str


@dataclass
class Mined:
    frame: Frame
    metric: str
    result: dict[int, dict[Members, Found]]
    levels: list[Level]

    def rows(self) -> list[tuple]:
        rows = []
        for g, sets in self.result.items():
            for s, f in sets.items():
                lp = log_p(f.bits, f.df, self.frame.n)
                rows.append((g, list(s), [self.frame.names[i] for i in s], self.metric, f.bits, f.df, math.exp(lp), -lp / math.log(10.0), STRONG, f.kind))
        return rows

    def table(self) -> DataFrame:
        return self.frame.spark.createDataFrame(self.rows(), RESULT_SCHEMA)

    def level_rows(self) -> list[tuple]:
        return [(v.order, v.children, v.cut_samples, {k: int(n) for k, n in v.decided.items()}, v.exact, v.side_exact, v.kept, v.frontier) for v in self.levels]

    def report(self) -> DataFrame:
        return self.frame.spark.createDataFrame(self.level_rows(), REPORT_SCHEMA)


class Search:
    """Shared state of one run: exact entropies by data set, zones, and counting passes."""

    def __init__(self, frame: Frame, mode: str, alpha_high: float, alpha_low: float, v_mode: str, min_ratio: float, max_sets: int, tight: bool = True, groups: list[int] | None = None, count: Count | None = None):
        check_alphas(alpha_high, alpha_low)
        if mode == "cac" and frame.class_at is None:
            raise ValueError("class-associated search needs a class attribute")
        self.frame, self.mode, self.high, self.low = frame, mode, alpha_high, alpha_low
        self.v_mode, self.min_ratio, self.max_sets = v_mode, min_ratio, max_sets
        self.c = frame.class_at if mode == "cac" else None
        self.attributes = [i for i in range(len(frame.names)) if i != self.c]
        self.groups = groups if groups is not None else [r[0] for r in frame.rows.select("g").distinct().orderBy("g").collect()]
        self.count = count or self._pass
        self.ent = {g: B.Entropies({}, tight) for g in self.groups}
        self.cells: dict[tuple[int, Members], int] = {}
        self.zones: dict[int, dict[Members, str]] = {g: {} for g in self.groups}
        self.hi: dict[int, dict[Members, float]] = {g: {} for g in self.groups}
        self.lo: dict[int, dict[Members, float]] = {g: {} for g in self.groups}
        self.passes = 0

    def full(self, s: Members) -> Members:
        return tuple(sorted((*s, self.c))) if self.c is not None else s

    def evaluate(self, needed: dict[int, set[Members]]) -> None:
        """Exact entropies of the sets (and, with a class, of the sets with it) in one pass over the data."""
        wanted: dict[int, list[Members]] = {}
        for g, sets in needed.items():
            more = {t for s in sets for t in ((s, self.full(s)) if self.c is not None else (s,)) if t and t not in self.ent[g].exact}
            if self.c is not None and (self.c,) not in self.ent[g].exact:
                more.add((self.c,))
            if more:
                wanted[g] = sorted(more)
        total = sum(map(len, wanted.values()))
        if total > self.max_sets:
            raise RuntimeError(f"{total} candidate sets exceed max_sets = {self.max_sets}; lower max_order, remove redundant attributes, or mine with lattice.mine")
        if not wanted:
            return
        self.passes += 1
        for g, s, h, cells in self.count(wanted):
            self.ent[g].exact[s] = h
            self.cells[g, s] = cells

    def _pass(self, wanted: dict[int, list[Members]]) -> Iterable[tuple[int, Members, float, int]]:
        lists = list(wanted.values())
        same = len(wanted) == len(self.groups) and all(x == lists[0] for x in lists)
        for r in counts.entropies_by_group(self.frame, {None: lists[0]} if same else wanted).collect():
            yield r["g"], tuple(r["s"]), r["h"], r["cells"]

    def is_exact(self, g: int, s: Members) -> bool:
        return self.full(s) in self.ent[g].exact and s in self.ent[g].exact

    def bits(self, g: int, s: Members) -> float:
        h = self.ent[g].exact
        if self.c is None:
            return sum(h[(i,)] for i in s) - h[s]
        return h[s] + h[(self.c,)] - h[self.full(s)]

    def df(self, s: Members) -> float:
        r = [self.frame.states[i] for i in s]
        if self.c is None:
            return float(math.prod(r) - sum(r) + len(r) - 1)
        return float((math.prod(r) - 1) * (self.frame.states[self.c] - 1))

    def df_gain(self, x: Members, k: int) -> float:
        joint = math.prod(self.frame.states[i] for i in x)
        if self.c is None:
            return float((joint - 1) * (self.frame.states[k] - 1))
        return float(joint * (self.frame.states[k] - 1) * (self.frame.states[self.c] - 1))

    def zone_of(self, bits: float, df: float) -> str:
        if bits > critical_bits(df, self.frame.n, self.high) + SLACK:
            return STRONG
        return WEAK if bits <= critical_bits(df, self.frame.n, self.low) + SLACK else MIDDLE

    def settle(self, g: int, s: Members) -> str:
        """Zone of a counted set; remembered."""
        bits = self.bits(g, s)
        self.hi[g][s] = self.lo[g][s] = bits
        zone = self.zones[g][s] = self.zone_of(bits, self.df(s))
        return zone

    def enough(self, s: Members) -> bool:
        """Sample rule: rows for each possible combination of values, the class included."""
        return self.frame.n >= self.min_ratio * math.prod(self.frame.states[i] for i in self.full(s))

    def enough_observed(self, g: int, s: Members) -> bool:
        return self.frame.n >= self.min_ratio * self.cells.get((g, self.full(s)), 0)

    def limits(self, g: int, parent: Members, s: Members, sibling: Members | None) -> tuple[float, float]:
        """Largest lower and smallest upper bound of a child's metric."""
        ent = self.ent[g]
        h = ent.exact
        new = s[-1]
        subsets = [t for t in combinations(s, len(s) - 1) if t]
        low = max([0.0, *(self.lo[g][t] for t in subsets if t in self.lo[g])])
        if self.c is not None:
            low = max(low, max(self.bits(g, (i,)) for i in s))
            return low, B.cac_upper(ent.upper(s), h[(self.c,)])
        sum_h = sum(h[(i,)] for i in s)
        low = max(low, B.tc_lower_ancestor(sum_h, ent.upper(s)))
        high = B.tc_upper_parent(self.hi[g][parent], ent.upper(parent), h[(new,)])
        if sibling is not None:
            i, hs = sibling[-1], h[sibling]
            low = max(low, B.tc_lower_sibling(sum_h, hs, min(ent.given(new, t) for t in parent)))
            high = min(high, B.tc_upper_sibling(sum_h, hs, ent.given(i, new), min(ent.given(i, t) for t in parent)))
        return low, max(low, high)


def mine(
    frame: Frame,
    mode: str = "tc",
    alpha_high: float = ALPHA_HIGH,
    alpha_low: float = ALPHA_LOW,
    max_order: int | None = None,
    rule: str = "tree",
    bounds: bool = True,
    siblings: bool = False,
    subset_check: str = "immediate",
    first_order: int = 1,
    v_mode: str = "product",
    min_ratio: float = 5.0,
    min_bits: float = 0.0,
    max_sets: int = 3_000_000,
    tight: bool = True,
    groups: list[int] | None = None,
    count: Count | None = None,
) -> Mined:
    """Core and extension sets. ``rule`` "tree" tests a set by what its tree parent is; "definition" tests every set.

    ``subset_check`` "immediate" looks at subsets with one member fewer, "all" at every subset of two or more (or, with
    a class, of one or more). ``first_order`` holds with a class: 1 begins with single predictors, 2 with pairs.
    ``groups`` and ``count`` replace the frame's rows by another way to count.
    """
    run = Search(frame, mode, alpha_high, alpha_low, v_mode, min_ratio, max_sets, tight, groups, count)
    start = first_order if mode == "cac" else 2
    top = max_order if max_order is not None else len(run.attributes)
    result: dict[int, dict[Members, Found]] = {g: {} for g in run.groups}
    singles, pairs = [(i,) for i in run.attributes], list(combinations(run.attributes, 2))
    first = [*singles, *(pairs if bounds or start == 2 else [])]
    usable = {s for s in first if len(s) == 1 or run.enough(s) or bounds}
    run.evaluate({g: usable for g in run.groups})
    levels = [Level(start)]
    frontier: dict[int, list[Members]] = {g: [] for g in run.groups}
    for g in run.groups:
        for s in singles if start == 1 else pairs:
            levels[0].children += 1
            if not run.enough(s) or (v_mode == "observed" and not run.enough_observed(g, s)):
                levels[0].cut_samples += 1
                continue
            levels[0].exact += 1
            zone = run.settle(g, s)
            if zone == STRONG and run.bits(g, s) >= min_bits:
                result[g][s] = Found(run.bits(g, s), run.df(s), "core")
            if zone != MIDDLE or rule == "definition":
                frontier[g].append(s)
        if start == 2 and mode == "cac":
            for s in singles:
                run.settle(g, s)
        if bounds and start == 1:
            for s in pairs:
                if run.is_exact(g, s):
                    run.lo[g][s] = run.hi[g][s] = run.bits(g, s)
    levels[0].kept = sum(map(len, result.values()))
    levels[0].frontier = sum(map(len, frontier.values()))
    for order in range(start + 1, top + 1):
        if not any(frontier.values()):
            break
        levels.append(_level(run, order, frontier, result, rule, bounds, siblings, subset_check, min_bits))
    return Mined(frame, "TC" if mode == "tc" else "CAC", result, levels)


def _level(run: Search, order: int, frontier: dict[int, list[Members]], result: dict[int, dict[Members, Found]], rule: str, bounds: bool, siblings: bool, subset_check: str, min_bits: float) -> Level:
    level = Level(order)
    last_attribute = max(run.attributes)
    least = math.prod(sorted(run.frame.states[i] for i in run.attributes)[:order]) * (run.frame.states[run.c] if run.c is not None else 1)
    if run.frame.n < run.min_ratio * least:  # no set of this order has enough samples: count the children, make none
        later = {j: sum(i > j for i in run.attributes) for j in run.attributes}
        level.children = level.cut_samples = sum(later[p[-1]] for nodes in frontier.values() for p in nodes)
        for g in frontier:
            frontier[g] = []
        return level
    children: dict[int, list[tuple[Members, Members]]] = {}
    for g, nodes in frontier.items():
        children[g] = []
        for p in nodes:
            for j in range(p[-1] + 1, last_attribute + 1):
                if j == run.c:
                    continue
                s = (*p, j)
                level.children += 1
                if run.enough(s):
                    children[g].append((p, s))
                else:
                    level.cut_samples += 1
    exact_first: dict[int, set[Members]] = defaultdict(set)
    sibling_of: dict[tuple[int, Members], Members] = {}
    if bounds and siblings and run.c is None:
        for g, pairs in children.items():
            for p, s in pairs:
                sibling_of.setdefault((g, p), s)
            exact_first[g] = {s for (gg, _), s in sibling_of.items() if gg == g}
        run.evaluate(exact_first)
    zone: dict[tuple[int, Members], str] = {}
    saturated: set[tuple[int, Members]] = set()
    needed: dict[int, set[Members]] = defaultdict(set)
    for g, pairs in children.items():
        for p, s in pairs:
            if not bounds or s in exact_first[g]:
                needed[g].add(s)
                continue
            sibling = sibling_of.get((g, p))
            low, high = run.limits(g, p, s, sibling)
            df = run.df(s)
            at_high, at_low = run.zone_of(high, df), run.zone_of(low, df)
            level.decided[CASES[at_high, at_low]] += 1
            if at_high != at_low:
                needed[g].add(s)
                continue
            zone[g, s] = run.zones[g][s] = at_high
            run.lo[g][s], run.hi[g][s] = low, high
            if run.c is not None and at_high == WEAK and high >= run.ent[g].exact[(run.c,)] - 1e-12:
                saturated.add((g, s))
    level.exact = sum(map(len, needed.values()))
    run.evaluate(needed)
    for g, sets in needed.items():
        for s in sets:
            zone[g, s] = run.settle(g, s)
        run.ent[g].forget()
    # subsets of STRONG sets that the tree has not judged, and STRONG sets known by bounds only
    side: dict[int, set[Members]] = defaultdict(set)
    least = 1 if run.c is not None else 2
    for (g, s), z in zone.items():
        if z == STRONG:
            if not run.is_exact(g, s):
                side[g].add(s)
            sizes = range(least, order) if subset_check == "all" else (order - 1,)
            side[g] |= {t for k in sizes for t in combinations(s, k) if t not in run.zones[g] or not run.is_exact(g, t)}
    level.side_exact = sum(map(len, side.values()))
    run.evaluate(side)
    for g, sets in side.items():
        for s in sets:
            run.settle(g, s)
    grown: dict[int, list[Members]] = {g: [] for g in frontier}
    for g, pairs in children.items():
        for p, s in pairs:
            z = zone[g, s]
            if run.v_mode == "observed" and run.is_exact(g, s) and not run.enough_observed(g, s):
                level.cut_samples += 1
                continue
            kind = None
            if z == STRONG and run.bits(g, s) >= min_bits:
                kind = judge(run, g, s, p in result[g] if rule == "tree" else None, subset_check)
                if kind:
                    result[g][s] = Found(run.bits(g, s), run.df(s), kind)
                    level.kept += 1
            if kind or (z == WEAK and (g, s) not in saturated) or rule == "definition":
                grown[g].append(s)
    for g in frontier:
        frontier[g] = grown[g]
    level.frontier = sum(map(len, grown.values()))
    return level


def judge(run: Search, g: int, s: Members, parent_kept: bool | None, subset_check: str = "immediate") -> str | None:
    """Whether a STRONG set is a core set, an extension set, or neither; by its parent, or by definition if that is None."""
    below = list(combinations(s, len(s) - 1))
    strong = [t for t in below if run.zones[g][t] == STRONG]
    weak = [t for t in below if run.zones[g][t] == WEAK]
    if parent_kept is not True and len(weak) == len(below):
        least = 1 if run.c is not None else 2
        if subset_check == "immediate" or all(run.zones[g][t] == WEAK for k in range(least, len(s)) for t in combinations(s, k)):
            return "core"
    if parent_kept is not False and len(strong) == 1 and len(weak) == len(below) - 1:
        x = strong[0]
        (k,) = set(s) - set(x)
        gain, df = run.bits(g, s) - run.bits(g, x), run.df_gain(x, k)
        if gain > critical_bits(df, run.frame.n, run.high) + SLACK:
            return "extension"
    return None


_ARROW = pa.schema(
    [("g", pa.int64()), ("members", pa.list_(pa.int32())), ("names", pa.list_(pa.string())), ("metric", pa.string()), ("bits", pa.float64()), ("df", pa.float64()), ("p", pa.float64()), ("neg_log10_p", pa.float64()), ("zone", pa.string()), ("kind", pa.string())]
)


def in_memory(table: pa.Table) -> tuple[int, np.ndarray, np.ndarray]:
    """Number, codes (a row an attribute) and weights of one data set of a frame's rows."""
    w = np.asarray(table.column("w").combine_chunks(), dtype=np.int64)
    codes = np.asarray(table.column("a").combine_chunks().flatten(), dtype=np.int64).reshape(len(w), -1)
    return table.column("g")[0].as_py(), codes.T.copy(), w


def counter(g: int, x: np.ndarray, w: np.ndarray, states: tuple[int, ...]) -> Count:
    return lambda wanted: ((g, s, h, cells) for s, h, cells in counts.entropies_of(x, w, states, wanted[g]))


def shape_of(frame: Frame) -> Frame:
    """The frame without its rows, for tasks."""
    return Frame(None, frame.names, frame.states, frame.n, frame.class_at, frame.dropped)


def sub_frame(shape: Frame, kept: list[int]) -> Frame:
    """Some attributes of a frame without rows, in ascending order."""
    return Frame(None, tuple(shape.names[i] for i in kept), tuple(shape.states[i] for i in kept), shape.n, kept.index(shape.class_at) if shape.class_at in kept else None)


def check_local(frame: Frame) -> None:
    if frame.n > LOCAL_ROWS:
        raise ValueError(f"data sets of {frame.n} rows are mined by passes over the frame, not by one task each")


def dealt(frame: Frame) -> GroupedData:
    """The rows by data set, in as many tasks as the session shuffles to: few bytes a data set are much work, so tasks are not merged by size."""
    spark = frame.spark
    tasks = max(int(spark.conf.get("spark.sql.shuffle.partitions")), 4 * spark.sparkContext.defaultParallelism)
    return frame.rows.select("g", "a", "w").repartition(tasks, "g").groupBy("g")


def mine_each(frame: Frame, mode: str = "tc", delta: float | None = None, greedy: str = "residual", **options) -> DataFrame:
    """Results (as :meth:`Mined.table`) of every data set of the frame, each mined by one task.

    With ``delta`` each data set is first reduced by its own redundant attributes; members are indexes of the given frame.
    Bounds are off unless asked for: they change no result, and in memory a count costs less than the bounds that may save it.
    """
    from assocmine.operators import local

    options = {"bounds": bool(options.get("siblings")), **options}
    check_local(frame)
    ship_package(frame.spark)
    shape = shape_of(frame)

    def run(table: pa.Table) -> pa.Table:
        g, x, w = in_memory(table)
        kept = list(range(len(shape.names)))
        if delta is not None:
            reps = redundancy.representatives_of(shape, x, w, delta, greedy)
            kept = sorted([*reps, *([shape.class_at] if shape.class_at is not None else [])])
        own = sub_frame(shape, kept)
        found = local.mine(own, mode, g, x[kept], w, **options)
        rows = [(g_, [kept[i] for i in s], *rest) for g_, s, *rest in found.rows()]
        return pa.table([pa.array(c, f.type) for c, f in zip(list(zip(*rows)) or [()] * len(_ARROW), _ARROW)], schema=_ARROW)

    return dealt(frame).applyInArrow(run, RESULT_SCHEMA)


_ZONES = pa.schema([("g", pa.int64()), ("s", pa.list_(pa.int32())), ("bits", pa.float64()), ("zone", pa.string())])


def zones_each(frame: Frame, sets: list[Members], mode: str = "tc", alpha_high: float = ALPHA_HIGH, alpha_low: float = ALPHA_LOW) -> DataFrame:
    """``g``, ``s``, ``bits``, ``zone`` of those of the given sets that are not WEAK, in every data set, one task each: no cells are shuffled."""
    check_local(frame)
    ship_package(frame.spark)
    shape, wanted = shape_of(frame), sorted({tuple(sorted(s)) for s in sets})

    def run(table: pa.Table) -> pa.Table:
        g, x, w = in_memory(table)
        search = Search(shape, mode, alpha_high, alpha_low, "product", 0.0, 2 * len(wanted) + len(shape.names) + 1, groups=[g], count=counter(g, x, w, shape.states))
        search.evaluate({g: {*wanted, *((i,) for i in search.attributes)}})
        rows = [(g, s, search.bits(g, s), zone) for s in wanted if (zone := search.settle(g, s)) != WEAK]
        return pa.table([pa.array(c, f.type) for c, f in zip(list(zip(*rows)) or [()] * len(_ZONES), _ZONES)], schema=_ZONES)

    return dealt(frame).applyInArrow(run, "g long, s array<int>, bits double, zone string")


def mine_correlation(frame: Frame, **options) -> Mined:
    return mine(frame, "tc", **options)


def mine_class_correlation(frame: Frame, **options) -> Mined:
    return mine(frame, "cac", **options)


def exhaustive(frame: Frame, mode: str = "tc", max_order: int = 4, alpha_high: float = ALPHA_HIGH, alpha_low: float = ALPHA_LOW, first_order: int = 1, min_ratio: float = 5.0, subset_check: str = "immediate", max_sets: int = 3_000_000) -> Mined:
    """Every set up to an order, judged by definition without any pruning but the sample rule: the oracle of the search."""
    run = Search(frame, mode, alpha_high, alpha_low, "product", min_ratio, max_sets)
    start = first_order if mode == "cac" else 2
    sets = [s for k in range(1, max_order + 1) for s in combinations(run.attributes, k) if k == 1 or run.enough(s)]
    run.evaluate({g: set(sets) for g in run.groups})
    result: dict[int, dict[Members, Found]] = {g: {} for g in run.groups}
    levels = {k: Level(k) for k in range(start, max_order + 1)}
    for g in run.groups:
        for s in sets:
            if len(s) < (1 if mode == "cac" else 2):
                continue
            zone = run.settle(g, s)
            if len(s) < start:
                continue
            levels[len(s)].children += 1
            levels[len(s)].exact += 1
            kind = "core" if zone == STRONG and len(s) == start else judge(run, g, s, None, subset_check) if zone == STRONG else None
            if kind:
                result[g][s] = Found(run.bits(g, s), run.df(s), kind)
                levels[len(s)].kept += 1
    return Mined(frame, "TC" if mode == "tc" else "CAC", result, list(levels.values()))


def differences(a: Mined, b: Mined) -> DataFrame:
    """Sets that only one of two results holds."""
    keys = lambda m: m.table().select("g", "members", "kind")
    from pyspark.sql import functions as F

    left, right = keys(a).withColumn("in_a", F.lit(True)), keys(b).withColumn("in_b", F.lit(True))
    return left.join(right, ["g", "members", "kind"], "full").filter("in_a is null or in_b is null")
