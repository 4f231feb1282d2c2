"""Significance of interaction information by permutations of one attribute.

``naive`` shuffles the attribute over all rows; the shuffle is the order of md5 hashes, so SQL can repeat it. ``fast``
counts the contingency table once and redraws it with both margins fixed, so the cost of a permutation depends on the
number of cells and not on the number of rows. Only subsets that hold the shuffled attribute change. ``naive`` is the
baseline: its rank of all rows is one window, and so one task, a data set; at scale ``fast`` is the way.
"""

from __future__ import annotations

import functools
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from assocmine.functions.expressions import plogp
from assocmine.operators.metrics import all_sets, interaction_info, table
from assocmine.plans import counts
from assocmine.plans.materialize import materialize, ship_package
from assocmine.sources.frame import Frame

NPERM, ALPHA_II = 10_000, 1e-4
#: Permutations of one task.
BLOCK = 2_000


def pick_shuffle_attr(frame: Frame, s: tuple[int, ...]) -> int:
    """The class if the set holds it, else the member with fewest states (ties: the smallest index)."""
    if frame.class_at in s:
        return frame.class_at
    return min(s, key=lambda i: (frame.states[i], i))


def naive_values(frame: Frame, s: tuple[int, ...], nperm: int, seed: int = 0, key: str = "key") -> DataFrame:
    """``g``, ``perm``, ``ii`` for permutations 0 (the data as they are) to nperm."""
    x = pick_shuffle_attr(frame, s)
    # rows and values meet by rank; the window is one data set of one permutation, which is what naive means
    base = frame.rows.select("g", F.col(key).alias("k"), "a").withColumn("rank", F.row_number().over(Window.partitionBy("g").orderBy("k")))
    perms = base.withColumn("perm", F.explode(F.sequence(F.lit(0), F.lit(nperm))))
    order = F.when(F.col("perm") == 0, F.lit("")).otherwise(F.md5(F.concat(F.lit(f"{seed}:"), F.col("perm").cast("string"), F.lit(":"), F.col("k").cast("string")).cast("binary")))
    values = perms.select("g", "perm", F.row_number().over(Window.partitionBy("g", "perm").orderBy(order, "k")).alias("rank"), F.col("a")[x].alias("x"))
    shuffled = perms.join(values, ["g", "perm", "rank"])
    codes = F.array(*[F.col("x") if i == x else F.col("a")[i] for i in s])
    moved = shuffled.select((F.col("g") * (nperm + 1) + F.col("perm")).alias("g"), codes.alias("a"), F.lit(1).alias("w"))
    local = Frame(moved, tuple(frame.names[i] for i in s), tuple(frame.states[i] for i in s), frame.n)
    members = tuple(range(len(s)))
    ent = counts.entropies(local, all_sets(members, 1, len(s)), "cube")
    ii = interaction_info(ent, ent.filter(F.size("s") == len(s)).select("g", "s"))
    return ii.select(F.floor(F.col("g") / (nperm + 1)).alias("g"), (F.col("g") % (nperm + 1)).cast("int").alias("perm"), "ii")


def share(values: DataFrame, add_one: bool = False, tail: str = "upper", eps: float = 1e-12) -> DataFrame:
    """p of every data set: share of permutations with an II at least as large (``lower``: as small) as the actual one."""
    actual = values.filter("perm = 0").select("g", F.col("ii").alias("t"))
    hit = (F.col("ii") >= F.col("t") - eps) if tail == "upper" else (F.col("ii") <= F.col("t") + eps)
    counted = values.filter("perm > 0").join(actual, "g").groupBy("g", "t").agg(F.sum(hit.cast("int")).alias("k"), F.count("*").alias("m"))
    p = (F.col("k") + 1) / (F.col("m") + 1) if add_one else F.col("k") / F.col("m")
    return counted.select("g", F.col("t").alias("ii"), p.alias("p"), F.col("m").cast("int").alias("nperm"))


#: Rows from which numpy refuses to draw a column at once.
MOST_COLOURS = 10**9


def resample(tables: np.ndarray, n_tables: int, rng: np.random.Generator) -> np.ndarray:
    """Random tables with the margins of ``tables`` (rows x columns), drawn cell by cell from hypergeometric laws."""
    rows, columns = tables.shape
    if columns == 2 and tables.sum() < MOST_COLOURS:  # the first column decides the second: one call draws it
        totals = tables.sum(axis=1)
        first = rng.multivariate_hypergeometric(totals, int(tables[:, 0].sum()), size=n_tables)
        return np.stack([first, totals - first], axis=2)
    left = np.broadcast_to(tables.sum(axis=0), (n_tables, columns)).copy()
    out = np.zeros((n_tables, rows, columns), dtype=np.int64)
    for r in range(rows):
        need = np.full(n_tables, int(tables[r].sum()))
        rest = left.sum(axis=1)
        for c in range(columns - 1):
            rest = rest - left[:, c]
            drawn = rng.hypergeometric(left[:, c], rest, need)
            out[:, r, c] = drawn
            need = need - drawn
        out[:, r, columns - 1] = need
        left -= out[:, r, :]
    return out


def _plogp(x: np.ndarray) -> np.ndarray:
    return np.where(x > 0, x * np.log2(np.maximum(x, 1)), 0.0)


#: Most rows of tables whose n log2 n are looked up.
LOOKED_UP = 1 << 20


@functools.lru_cache(maxsize=8)
def _plogp_to(n: int) -> np.ndarray:
    return _plogp(np.arange(n + 1))


@functools.lru_cache(maxsize=1024)
def _signs(shape: tuple[int, ...]) -> np.ndarray:
    """1 for cells and -1 for sums along an axis, multiplied over the axes."""
    out = np.ones(1)
    for r in shape:
        out = np.multiply.outer(out, np.append(np.ones(r), -1.0)).ravel()
    return out


def table_ii(tables: np.ndarray, shape: tuple[int, ...]) -> np.ndarray:
    """II of count tables (many x cells) whose axes are the members of the set.

    Each axis gets its sum as one more place, so that all margins are cells of one table: II is the signed sum of their
    n log2 n, over n.
    """
    n = int(tables[0].sum())
    cube = tables.reshape((-1, *shape))
    for axis in range(1, len(shape) + 1):
        cube = np.concatenate([cube, cube.sum(axis=axis, keepdims=True)], axis=axis)
    flat = cube.reshape(len(cube), -1)
    return (_plogp_to(n)[flat] if n <= LOOKED_UP else _plogp(flat)) @ _signs(shape) / n


#: Tables drawn at once: few at first, as hopeless sets stop early, then more.
FIRST_DRAW, MOST_DRAWN = 16, 250


def count_hits(cube: np.ndarray, x: int, todo: int, rng: np.random.Generator, tail: str = "upper", stop: int | None = None) -> tuple[float, int, int]:
    """II of a count table, how many of the random tables with its margins reach it, and how many were drawn; ``x`` is the
    shuffled member's axis. Drawing ends when there are ``stop`` hits."""
    cube = np.moveaxis(cube, x, -1)
    wide = cube.reshape(-1, cube.shape[-1])
    used = wide.sum(axis=1) > 0
    actual = float(table_ii(cube.reshape(1, -1), cube.shape)[0])
    hits = done = 0
    while done < todo and (stop is None or hits < stop):
        m = min(FIRST_DRAW if not done and stop is not None else MOST_DRAWN, todo - done)
        full = np.zeros((m, *wide.shape), dtype=np.int64)
        full[:, used, :] = resample(wide[used], m, rng)
        values = table_ii(full.reshape(m, -1), cube.shape)
        hits += int((values >= actual - 1e-12).sum() if tail == "upper" else (values <= actual + 1e-12).sum())
        done += m
    return actual, hits, done


def fast(frame: Frame, sets: list[tuple[int, ...]], nperm: int = NPERM, seed: int = 0, add_one: bool = False, tail: str = "upper", early_stop: float | None = None) -> DataFrame:
    """``g``, ``s``, ``ii``, ``p``, ``nperm``, ``cells_touched`` for every set of order 2 or more.

    The data are scanned once. Each task gets the table of one set and a block of permutations with a seed of its own.
    ``early_stop``: a block ends when its hits alone put p above this level. Tables have a cell for each combination of
    values, so sets with more than ``counts.CELL_BUDGET`` combinations are refused.
    """
    ship_package(frame.spark)
    wanted = sorted({tuple(sorted(s)) for s in sets if len(s) > 1})
    large = [s for s in wanted if counts.cells_of(frame, s) > counts.CELL_BUDGET]
    if large:
        raise ValueError(f"tables of more than {counts.CELL_BUDGET} cells: {large[:3]}")
    states, shuffled = frame.states, {s: pick_shuffle_attr(frame, s) for s in wanted}
    cells = None
    for start in range(0, len(wanted), counts.CHUNK_SETS):
        part = counts.count_cells(frame, {None: wanted[start : start + counts.CHUNK_SETS]})
        cells = part if cells is None else cells.unionByName(part)
    if cells is None:
        return frame.spark.createDataFrame([], "g long, s array<int>, ii double, p double, nperm int, cells_touched long")
    tables = cells.groupBy("g", "s").agg(F.collect_list(F.struct("cell", "n")).alias("t"))
    blocks = tables.withColumn("block", F.explode(F.sequence(F.lit(0), F.lit(max(0, -(-nperm // BLOCK) - 1)))))
    stop = None if early_stop is None else int(early_stop * nperm) + 1

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            out = []
            for g, s, t, block in zip(batch["g"], batch["s"], batch["t"], batch["block"]):
                s = tuple(int(i) for i in s)
                shape = tuple(states[i] for i in s)
                flat = np.zeros(int(np.prod(shape)), dtype=np.int64)
                for cell in t:
                    flat[cell["cell"]] = cell["n"]
                rng = np.random.default_rng([seed, int(g) & 0x7FFFFFFF, int(block), *s])
                actual, hits, done = count_hits(flat.reshape(shape), s.index(shuffled[s]), min(BLOCK, nperm - int(block) * BLOCK), rng, tail, stop)
                out.append((int(g), list(s), actual, hits, done, done * int(flat.size)))
            yield pd.DataFrame(out, columns=["g", "s", "ii", "hits", "done", "cells_touched"])

    parts = int(frame.spark.conf.get("spark.sql.shuffle.partitions"))
    drawn = blocks.repartition(parts, "g", "s", "block").mapInPandas(run, "g long, s array<int>, ii double, hits long, done long, cells_touched long")
    summed = drawn.groupBy("g", "s").agg(F.first("ii").alias("ii"), F.sum("hits").alias("k"), F.sum("done").alias("m"), F.sum("cells_touched").alias("cells_touched"))
    p = (F.col("k") + 1) / (F.col("m") + 1) if add_one else F.col("k") / F.col("m")
    return summed.select("g", "s", "ii", p.alias("p"), F.col("m").cast("int").alias("nperm"), "cells_touched")


def exact_pairs(frame: Frame, pairs: list[tuple[int, int]]) -> DataFrame:
    """``g``, ``s``, ``ii``, ``p`` for pairs of binary attributes: all tables with the margins are enumerated, so p is what the draws approach."""
    if any(frame.states[i] != 2 for s in pairs for i in s):
        raise ValueError("exact p-values are for pairs of binary attributes")
    cells = materialize(counts.count_cells(frame, {None: sorted(pairs)}), "pair-cells")
    n = F.lit(float(frame.n))
    known = cells.groupBy("g", "s").agg(*(F.sum(F.when(F.col("cell") == k, F.col("n")).otherwise(0)).cast("double").alias(f"n{k}") for k in range(4)))
    known = known.withColumn("r", F.col("n2") + F.col("n3")).withColumn("c", F.col("n1") + F.col("n3"))

    def bits(k: Column) -> Column:
        inside = sum((plogp(x) for x in (k, F.col("r") - k, F.col("c") - k, n - F.col("r") - F.col("c") + k)), F.lit(0.0))
        margins = sum((plogp(x) for x in (F.col("r"), n - F.col("r"), F.col("c"), n - F.col("c"))), F.lit(0.0))
        return (inside - margins) / n + F.log2(n)

    def choose(a: Column, b: Column) -> Column:
        return _log_factorial(a) - _log_factorial(b) - _log_factorial(a - b)

    low, high = F.greatest(F.lit(0.0), F.col("r") + F.col("c") - n), F.least("r", "c")
    each = known.withColumn("k", F.explode(F.sequence(low.cast("int"), high.cast("int")))).withColumn("k", F.col("k").cast("double"))
    chance = F.exp(choose(F.col("r"), F.col("k")) + choose(n - F.col("r"), F.col("c") - F.col("k")) - choose(n, F.col("c")))
    reached = F.when(bits(F.col("k")) >= bits(F.col("n3")) - 1e-12, chance).otherwise(0.0)
    return each.groupBy("g", "s", bits(F.col("n3")).alias("ii")).agg(F.sum(reached).alias("p"))


def _log_factorial(x: Column) -> Column:
    """ln x! by Stirling's series above 20, by the product up to there."""
    small = F.aggregate(F.sequence(F.lit(1), F.greatest(F.lit(1), F.least(x, F.lit(20.0)).cast("int"))), F.lit(0.0), lambda acc, i: acc + F.log(i.cast("double")))
    y = F.greatest(x, F.lit(20.0))
    stirling = (y + 0.5) * F.log(y) - y + 0.9189385332046727 + 1 / (12 * y) - 1 / (360 * y * y * y) + 1 / (1260 * F.pow(y, F.lit(5.0)))
    return F.when(x > 20, stirling).otherwise(small)


def naive(frame: Frame, s: tuple[int, ...], nperm: int, seed: int = 0, **options) -> DataFrame:
    return share(materialize(naive_values(frame, s, nperm, seed), "naive-permutations"), **options)


def actual_ii(frame: Frame, sets: list[tuple[int, ...]]) -> DataFrame:
    ent = counts.entropies(frame, {t for s in sets for t in all_sets(s, 1, len(s))})
    return interaction_info(ent, table(frame, sets))
