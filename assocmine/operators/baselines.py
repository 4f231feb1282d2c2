"""Published baselines to compare with: a subset miner with fixed cut-offs, and a relevance-redundancy selector."""

from __future__ import annotations

from itertools import combinations

import pyarrow as pa
from pyspark.sql import DataFrame

from assocmine.operators import local
from assocmine.operators.mining import LOCAL_ROWS, Search, check_local, counter, dealt, in_memory
from assocmine.operators.significance import ALPHA_HIGH, ALPHA_LOW
from assocmine.plans import counts
from assocmine.plans.materialize import ship_package
from assocmine.sources.frame import Frame


SETS_SCHEMA = "g long, members array<int>, names array<string>, bits double"


def _hard_threshold(run: Search, alpha: float, beta: float, max_order: int) -> list[tuple]:
    names = run.frame.names
    weak = {g: {(i,) for i in run.attributes} for g in run.groups}
    run.evaluate({g: set(s) for g, s in weak.items()})
    found = []
    for order in range(2, max_order + 1):
        children = {
            g: {s for p in sets for j in range(p[-1] + 1, len(names)) if run.enough(s := (*p, j)) and all(t in weak[g] for t in combinations(s, order - 1))} for g, sets in ((g, [s for s in weak[g] if len(s) == order - 1]) for g in run.groups)
        }
        run.evaluate(children)
        if not any(children.values()):
            break
        for g, sets in children.items():
            for s in sets:
                bits = run.bits(g, s)
                if bits >= beta:
                    found.append((g, list(s), [names[i] for i in s], bits))
                elif bits <= alpha:
                    weak[g].add(s)
    return found


def hard_threshold(frame: Frame, alpha: float = 0.2, beta: float = 0.8, max_order: int = 4, min_ratio: float = 5.0, max_sets: int = 3_000_000) -> DataFrame:
    """Sets with TC of ``beta`` bits or more whose proper subsets have ``alpha`` bits or less. Supersets of a strong set,
    and of a set between the cut-offs, are not explored. A class counts as one more attribute."""
    plain = Frame(frame.rows, frame.names, frame.states, frame.n)
    return frame.spark.createDataFrame(_hard_threshold(Search(plain, "tc", ALPHA_HIGH, ALPHA_LOW, "product", min_ratio, max_sets), alpha, beta, max_order), SETS_SCHEMA)


def hard_threshold_each(frame: Frame, alpha: float = 0.2, beta: float = 0.8, max_order: int = 4, min_ratio: float = 5.0, max_sets: int = 3_000_000) -> DataFrame:
    """The same, one task a data set."""
    check_local(frame)
    ship_package(frame.spark)
    shape = Frame(None, frame.names, frame.states, frame.n)
    schema = pa.schema([("g", pa.int64()), ("members", pa.list_(pa.int32())), ("names", pa.list_(pa.string())), ("bits", pa.float64())])

    def one(table: pa.Table) -> pa.Table:
        g, x, w = in_memory(table)
        if local.fits(shape, "tc", max_order, min_ratio, min(local.MOST_SETS, max_sets)):
            rows = [(g, list(s), [shape.names[i] for i in s], bits) for s, bits in local.hard_threshold(x, w, shape, alpha, beta, max_order, min_ratio)]
            return pa.table([pa.array(c, f.type) for c, f in zip(list(zip(*rows)) or [()] * len(schema), schema)], schema=schema)
        rows = _hard_threshold(Search(shape, "tc", ALPHA_HIGH, ALPHA_LOW, "product", min_ratio, max_sets, groups=[g], count=counter(g, x, w, shape.states)), alpha, beta, max_order)
        return pa.table([pa.array(c, f.type) for c, f in zip(list(zip(*rows)) or [()] * len(schema), schema)], schema=schema)

    return dealt(frame).applyInArrow(one, SETS_SCHEMA)


RELEVANCE_SCHEMA = "g long, target string, rank int, attribute string, idx int, relevance double, score double"
_RELEVANCE = pa.schema([("g", pa.int64()), ("target", pa.string()), ("rank", pa.int32()), ("attribute", pa.string()), ("idx", pa.int32()), ("relevance", pa.float64()), ("score", pa.float64())])


def _pair_sets(frame: Frame) -> list[tuple[int, ...]]:
    n = len(frame.names)
    return [(i,) for i in range(n)] + list(combinations(range(n), 2))


def _choose(g: int, h: dict[tuple[int, ...], float], names: tuple[str, ...], targets: dict[int, int], form: str) -> list[tuple]:
    """The selector's rows for one data set, from the entropies of its attributes and pairs."""
    mi = {(i, j): h[(i,)] + h[(j,)] - h[(i, j)] for i, j in combinations(range(len(names)), 2)}
    of = lambda i, j: mi[(min(i, j), max(i, j))]
    rows = []
    for c, most in targets.items():
        chosen: list[int] = []
        while len(chosen) < min(most, len(names) - 1):
            best = None
            for i in range(len(names)):
                if i == c or i in chosen:
                    continue
                mean = sum(of(i, j) for j in chosen) / len(chosen) if chosen else 0.0
                score = of(i, c) - mean if form == "difference" else of(i, c) / (mean + 1e-12) if chosen else of(i, c)
                if best is None or score > best[0] + 1e-12:
                    best = (score, i)
            chosen.append(best[1])
            rows.append((g, names[c], len(chosen), names[best[1]], best[1], of(best[1], c), best[0]))
    return rows


def relevance_targets(frame: Frame, targets: dict[int, int], form: str = "difference") -> DataFrame:
    """``g``, ``target``, ``rank``, ``attribute``, ``idx``, ``relevance``, ``score``: for each target as the class, with the number
    of attributes to choose, greedy choice by information with it, less (or over) the mean information with what is
    chosen already. Ties go to the smallest index. Each data set is one task's, which counts it if it is small, else gets
    its entropies: n squared numbers for n attributes. Nothing reaches the driver."""
    if form not in ("difference", "quotient"):
        raise ValueError("form is difference or quotient")
    ship_package(frame.spark)
    names, states, sets = frame.names, frame.states, _pair_sets(frame)

    def chosen(g: int, h: dict[tuple[int, ...], float]) -> pa.Table:
        rows = _choose(g, h, names, targets, form)
        return pa.table([pa.array(c, f.type) for c, f in zip(list(zip(*rows)) or [()] * len(_RELEVANCE), _RELEVANCE)], schema=_RELEVANCE)

    def count(table: pa.Table) -> pa.Table:
        g, x, w = in_memory(table)
        return chosen(g, {s: bits for s, bits, _ in counts.entropies_of(x, w, states, sets)})

    def given(table: pa.Table) -> pa.Table:
        return chosen(table.column("g")[0].as_py(), dict(zip(map(tuple, table.column("s").to_pylist()), table.column("h").to_pylist())))

    if frame.n <= LOCAL_ROWS:
        return frame.rows.select("g", "a", "w").groupBy("g").applyInArrow(count, RELEVANCE_SCHEMA)
    return counts.entropies(frame, sets).select("g", "s", "h").groupBy("g").applyInArrow(given, RELEVANCE_SCHEMA)


def relevance_redundancy(frame: Frame, class_at: int | None = None, n_select: int = 3, form: str = "difference") -> DataFrame:
    """The selector with one class: ``g``, ``rank``, ``attribute``, ``idx``, ``relevance``, ``score``."""
    return relevance_targets(frame, {frame.class_at if class_at is None else class_at: n_select}, form).drop("target")
