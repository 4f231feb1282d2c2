"""The search over one small data set in memory, a level at a time in arrays: results and report of :func:`mining.mine`.

A set of k attributes is a row of indexes and has a number, its rank among the sets of that order, so that what is known
of its subsets is looked up at once for a whole level. Every value of an attribute is a bit vector over the rows; the
cells of a set are counted by AND and popcount, for many sets at once, and only for the sets that the search asks for.
"""

from __future__ import annotations

import math
from itertools import combinations

import numpy as np

from assocmine.functions.gamma import critical_bits
from assocmine.operators.mining import CASES, MIDDLE, STRONG, WEAK, Found, Level, Members, Mined, counter
from assocmine.operators.mining import mine as mine_by_sets
from assocmine.operators.significance import ALPHA_HIGH, ALPHA_LOW, SLACK, check_alphas
from assocmine.plans import counts
from assocmine.sources.frame import Frame

#: Most sets of all orders that a search could meet here; beyond, sets are kept by name in :func:`mining.mine`.
MOST_SETS = 1_000_000
#: Possible cells of a set up to which they are counted by bit vectors, and words of bit vectors at once.
BIT_CELLS, WORDS = 256, 1 << 15
_ZONES = (WEAK, MIDDLE, STRONG)
_WEAK, _MIDDLE, _STRONG = range(3)


class Known:
    """Entropies that searches of one data set have counted, by rank among ``p`` attributes: searches over some of these share them."""

    def __init__(self, p: int):
        self.choose = _binomials(p)
        self.p, self.order = p, {}

    def entropies(self, cells: Cells, members: np.ndarray, place: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """As :meth:`Cells.count`, which is asked for the sets that are not known; ``place`` has the number of each attribute here."""
        k = members.shape[1]
        if k not in self.order:
            self.order[k] = np.full((2, math.comb(self.p, k)), np.nan)
        known, rank = self.order[k], _rank(self.choose, place[members])
        new = np.isnan(known[0, rank])
        if new.any():
            known[:, rank[new]] = cells.count(members[new])
        return known[0, rank], known[1, rank]


def _binomials(p: int) -> np.ndarray:
    binomial = [[math.comb(v, k) for v in range(p + 1)] for k in range(1, min(p, 24) + 2)]
    return np.array([[min(v, 1 << 40) for v in row] for row in binomial], dtype=np.int64)


def _rank(choose: np.ndarray, members: np.ndarray) -> np.ndarray:
    out = np.zeros(len(members), dtype=np.int64)
    for j in range(members.shape[1]):
        out += choose[j, members[:, j]]
    return out


class Cells:
    """Entropies of sets of a data set's attributes; with a class, of the sets with it as well.

    With ``known``, entropies are taken from there where they are known, ``place`` being the attributes' numbers in it.
    """

    def __init__(self, x: np.ndarray, w: np.ndarray, states: tuple[int, ...], class_at: int | None = None, known: Known | None = None, place: np.ndarray | None = None):
        self.known, self.place = known, place
        self.attributes = np.array([i for i in range(len(states)) if i != class_at], dtype=np.int64)
        self.c, self.states = class_at, np.array(states, dtype=np.int64)
        self.r = self.states[self.attributes]
        self.rc = int(self.states[class_at]) if class_at is not None else 1
        self.p, self.n = len(self.attributes), int(w.sum())
        self.x, self.w = x, w
        rows = np.repeat(x, w, axis=1) if (w != 1).any() else x
        self.bits = _bits(rows[self.attributes], int(self.r.max(initial=1)))
        self.class_bits = _bits(rows[[class_at]], self.rc)[:, :, :1] if class_at is not None else None
        n = np.arange(self.n + 1, dtype=np.float64)
        self.plogp = n * np.log2(np.maximum(n, 1.0))
        self.kind = np.uint8 if self.n < 1 << 8 else np.uint16 if self.n < 1 << 16 else np.int32
        self.choose = _binomials(self.p)
        self.hc = float(self._entropy(self._counts(np.empty((1, 0), dtype=np.int64), ()))[1][0]) if class_at is not None else 0.0

    def sets(self, k: int) -> np.ndarray:
        """All sets of an order, in lexicographic order."""
        flat = np.fromiter((i for s in combinations(range(self.p), k) for i in s), dtype=np.int64, count=k * math.comb(self.p, k))
        return flat.reshape(-1, k)

    def rank(self, members: np.ndarray) -> np.ndarray:
        return _rank(self.choose, members)

    def below(self, members: np.ndarray) -> list[np.ndarray]:
        """Ranks of the subsets with one member fewer, in the order of ``combinations``: the last member goes first."""
        k = members.shape[1]
        return [self.rank(np.delete(members, j, axis=1)) for j in range(k - 1, -1, -1)]

    def possible(self, members: np.ndarray) -> np.ndarray:
        """Possible combinations of values, those of the class not included."""
        return self.r[members].prod(axis=1)

    def entropies(self, members: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Entropies of sets of one order and, with a class, of the sets with it."""
        return self.count(members) if self.known is None else self.known.entropies(self, members, self.place)

    def count(self, members: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The same, counted."""
        h, hc = np.empty(len(members)), np.empty(len(members))
        if not len(members):
            return h, hc
        radix = self.r[members]
        same = (radix == radix[0]).all()
        patterns, which = (radix[:1], None) if same else np.unique(radix, axis=0, return_inverse=True)
        for i, pattern in enumerate(patterns.tolist()):
            at = slice(None) if same else np.flatnonzero(which.ravel() == i)
            h[at], hc[at] = self._of_pattern(members[at], tuple(pattern))
        return h, hc

    def _of_pattern(self, members: np.ndarray, pattern: tuple[int, ...]) -> tuple[np.ndarray, np.ndarray]:
        cells = math.prod(pattern) * self.rc
        if cells > BIT_CELLS:
            return self._by_rows(members)
        step = max(1, WORDS // (cells * self.bits.shape[1]))
        parts = [self._entropy(self._counts(members[i : i + step], pattern)) for i in range(0, len(members), step)]
        return tuple(map(np.concatenate, zip(*parts)))

    def _by_rows(self, members: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        own = [tuple(s) for s in self.attributes[members].tolist()]
        full = [tuple(sorted((*s, self.c))) for s in own] if self.c is not None else []
        known = {s: h for s, h, _ in counts.entropies_of(self.x, self.w, tuple(self.states.tolist()), [*own, *full])}
        return np.array([known[s] for s in own]), np.array([known[s] for s in full]) if full else np.empty(len(own))

    def _counts(self, members: np.ndarray, pattern: tuple[int, ...]) -> np.ndarray:
        """Rows of every cell (first axis: the class last and fastest) of sets of one order."""
        words = self.bits.shape[1]
        held = None
        for j, r in enumerate(pattern):
            own = np.take(self.bits[:r], members[:, j], axis=2)
            held = own if held is None else (held[:, None] & own).reshape(-1, words, len(members))
        if self.c is not None:
            held = np.broadcast_to(self.class_bits, (self.rc, words, len(members))) if held is None else (held[:, None] & self.class_bits).reshape(-1, words, len(members))
        ones = np.bitwise_count(held)
        n = ones[:, 0].astype(self.kind)
        for word in range(1, words):
            n += ones[:, word]
        return n

    def _entropy(self, n: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        if self.c is None:
            return self._bits_of(n), np.empty(n.shape[1])
        without = n.reshape(-1, self.rc, n.shape[1]).sum(axis=1, dtype=self.kind)
        return self._bits_of(without), self._bits_of(n)

    def _bits_of(self, n: np.ndarray) -> np.ndarray:
        """Summed as :func:`counts.entropies_of` does where cells are few: bounds compare entropies of pairs, which may tie."""
        plogp = self.plogp[n]
        total = np.add.reduceat(plogp.T.ravel(), np.arange(0, plogp.size, len(n))) if len(n) <= 16 else plogp.sum(axis=0)
        return math.log2(self.n) - total / self.n


def _bits(x: np.ndarray, states: int) -> np.ndarray:
    """Bit vectors over the rows: value, word, attribute."""
    words = -(-x.shape[1] // 64)
    held = np.zeros((states, len(x), 8 * words), dtype=np.uint8)
    for v in range(states):
        packed = np.packbits(x == v, axis=1)
        held[v, :, : packed.shape[1]] = packed
    return np.ascontiguousarray(held.view(np.uint64).transpose(0, 2, 1))


class _Order:
    """What is known of all sets of one order, by rank."""

    def __init__(self, size: int):
        self.h, self.bits, self.lo, self.hi = (np.full(size, np.nan) for _ in range(4))
        self.zone, self.kept = np.full(size, -1, dtype=np.int8), np.zeros(size, dtype=bool)


class _Run:
    def __init__(self, cells: Cells, high: float, low: float, min_ratio: float):
        self.cells, self.high, self.low, self.min_ratio = cells, high, low, min_ratio
        self.order: dict[int, _Order] = {}

    def at(self, k: int) -> _Order:
        if k not in self.order:
            self.order[k] = _Order(math.comb(self.cells.p, k))
        return self.order[k]

    def evaluate(self, members: np.ndarray) -> None:
        """Entropies and bits of the sets that have none yet."""
        k, cells = members.shape[1], self.cells
        known, rank = self.at(k), cells.rank(members)
        new = np.isnan(known.h[rank])
        if not new.any():
            return
        members, rank = members[new], rank[new]
        h, full = cells.entropies(members)
        known.h[rank] = h
        known.bits[rank] = h + cells.hc - full if cells.c is not None else self.sum_h(members) - h

    def sum_h(self, members: np.ndarray) -> np.ndarray:
        total = np.zeros(len(members))
        for j in range(members.shape[1]):
            total = total + self.at(1).h[members[:, j]]
        return total

    def df(self, members: np.ndarray) -> np.ndarray:
        possible = self.cells.possible(members)
        if self.cells.c is not None:
            return ((possible - 1) * (self.cells.rc - 1)).astype(np.float64)
        return (possible - self.cells.r[members].sum(axis=1) + members.shape[1] - 1).astype(np.float64)

    def critical(self, df: np.ndarray, alpha: float) -> np.ndarray:
        if not len(df):
            return df
        values, which = (df[:1], None) if (df == df[0]).all() else np.unique(df, return_inverse=True)
        cut = np.array([critical_bits(float(v), self.cells.n, alpha) for v in values]) + SLACK
        return np.broadcast_to(cut, df.shape) if which is None else cut[which]

    def zone_of(self, bits: np.ndarray, df: np.ndarray) -> np.ndarray:
        zone = np.where(bits <= self.critical(df, self.low), _WEAK, _MIDDLE)
        return np.where(bits > self.critical(df, self.high), _STRONG, zone).astype(np.int8)

    def settle(self, members: np.ndarray) -> np.ndarray:
        known, rank = self.at(members.shape[1]), self.cells.rank(members)
        known.lo[rank] = known.hi[rank] = known.bits[rank]
        zone = known.zone[rank] = self.zone_of(known.bits[rank], self.df(members))
        return zone

    def enough(self, members: np.ndarray) -> np.ndarray:
        return self.cells.n >= self.min_ratio * (self.cells.possible(members) * self.cells.rc)

    def upper(self, members: np.ndarray) -> np.ndarray:
        """Upper bounds of the entropies: exact where counted, else from the pair of largest entropy and the two sets without either."""
        k, single, pairs = members.shape[1], self.at(1).h, self.at(2).h
        exact = self.at(k).h[self.cells.rank(members)] if k in self.order else np.full(len(members), np.nan)
        if k < 3 or not np.isnan(exact).any():
            return exact
        by_rank = pairs
        if k > 3:
            smaller = self.cells.sets(k - 1)
            by_rank = np.empty(len(smaller))
            by_rank[self.cells.rank(smaller)] = self.upper(smaller)
        rows = np.arange(len(members))
        best, first, second = np.full(len(members), -np.inf), np.zeros(len(members), dtype=np.int64), np.zeros(len(members), dtype=np.int64)
        given = np.full((k, len(members)), np.inf)
        for i, j in combinations(range(k), 2):
            h = pairs[self.cells.rank(members[:, [i, j]])]
            more = h >= best
            best, first, second = np.where(more, h, best), np.where(more, i, first), np.where(more, j, second)
            given[i] = np.minimum(given[i], h - single[members[:, j]])
            given[j] = np.minimum(given[j], h - single[members[:, i]])
        without = np.stack([by_rank[r] for r in self.cells.below(members)[::-1]])
        a, b = without[first, rows], without[second, rows]
        bound = np.minimum((a + b + best) / 2, (a + b + given[first, rows] + given[second, rows]) / 2)
        return np.where(np.isnan(exact), bound, exact)

    def limits(self, members: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Largest lower and smallest upper bound of the children's metric."""
        k, less = members.shape[1], self.at(members.shape[1] - 1)
        low = np.zeros(len(members))
        for rank in self.cells.below(members):
            low = np.fmax(low, less.lo[rank])
        upper = self.upper(members)
        if self.cells.c is not None:
            for j in range(k):
                low = np.maximum(low, self.at(1).bits[members[:, j]])
            return low, np.minimum(upper, self.cells.hc)
        low = np.maximum(low, self.sum_h(members) - upper)
        parent = members[:, :-1]
        high = less.hi[self.cells.rank(parent)] + np.minimum(self.upper(parent), self.at(1).h[members[:, -1]])
        return low, np.maximum(low, high)


def _children(frontier: np.ndarray, p: int) -> np.ndarray:
    """Every set of the frontier with every later attribute."""
    later = p - 1 - frontier[:, -1]
    ends = np.cumsum(later)
    new = np.arange(later.sum()) - np.repeat(ends - later, later) + np.repeat(frontier[:, -1] + 1, later)
    return np.column_stack([np.repeat(frontier, later, axis=0), new])


def fits(frame: Frame, mode: str, max_order: int | None, min_ratio: float, most: int) -> bool:
    """Whether the sets of all orders that have enough samples are few enough for arrays."""
    c = frame.class_at if mode == "cac" else None
    states = sorted(r for i, r in enumerate(frame.states) if i != c)
    total, possible = 0, frame.states[c] if c is not None else 1
    for k, r in enumerate(states[: max_order if max_order is not None else None], 1):
        possible *= r
        if k > 2 and frame.n < min_ratio * possible:
            break
        total += 2 * math.comb(len(states), k)
        if total > most or k > 20 or possible > counts.MOST_CELLS:
            return False
    return bool(states) and frame.n > 0


def mine(frame: Frame, mode: str, g: int, x: np.ndarray, w: np.ndarray, known: Known | None = None, place: np.ndarray | None = None, **options) -> Mined:
    """One data set's search: in arrays, or set by set where that is asked for or there are too many sets for arrays.

    Searches in arrays share what they count through ``known`` (see :class:`Cells`); it must be of this data set and mode.
    """
    plain = dict(rule="tree", siblings=False, subset_check="immediate", v_mode="product", tight=True)
    limits = dict(max_order=None, min_ratio=5.0, max_sets=3_000_000) | {k: options[k] for k in ("max_order", "min_ratio", "max_sets") if k in options}
    if (mode == "cac" and frame.class_at is None) or any(options.get(k, v) != v for k, v in plain.items()) or not fits(frame, mode, limits["max_order"], limits["min_ratio"], min(MOST_SETS, limits["max_sets"])):
        return mine_by_sets(frame, mode, groups=[g], count=counter(g, x, w, frame.states), **options)
    return _mine(frame, mode, g, x, w, known=known, place=place, **{k: v for k, v in options.items() if k not in plain and k != "max_sets"})


def _mine(frame: Frame, mode: str, g: int, x: np.ndarray, w: np.ndarray, alpha_high: float = ALPHA_HIGH, alpha_low: float = ALPHA_LOW, max_order: int | None = None, bounds: bool = True, first_order: int = 1, min_ratio: float = 5.0, min_bits: float = 0.0, known: Known | None = None, place: np.ndarray | None = None) -> Mined:
    check_alphas(alpha_high, alpha_low)
    cells = Cells(x, w, frame.states, frame.class_at if mode == "cac" else None, known, place)
    run, p = _Run(cells, alpha_high, alpha_low, min_ratio), cells.p
    start = first_order if mode == "cac" else 2
    top = max_order if max_order is not None else p
    result: dict[Members, Found] = {}

    def keep(members: np.ndarray, kinds: list[str]) -> None:
        known, rank = run.at(members.shape[1]), cells.rank(members)
        known.kept[rank] = True
        for s, bits, df, kind in zip(cells.attributes[members].tolist(), known.bits[rank].tolist(), run.df(members).tolist(), kinds):
            result[tuple(s)] = Found(bits, df, kind)

    singles, pairs = cells.sets(1), cells.sets(2)
    run.evaluate(singles)
    if bounds or start == 2:
        run.evaluate(pairs if bounds else pairs[run.enough(pairs)])
    first = singles if start == 1 else pairs
    level = Level(start, children=len(first))
    usable = first[run.enough(first)]
    level.cut_samples, level.exact = len(first) - len(usable), len(usable)
    zone = run.settle(usable)
    strong = usable[(zone == _STRONG) & (run.at(start).bits[cells.rank(usable)] >= min_bits)]
    keep(strong, ["core"] * len(strong))
    frontier = usable[zone != _MIDDLE]
    if start == 2 and mode == "cac":
        run.settle(singles)
    if bounds and start == 1:
        run.at(2).lo[:] = run.at(2).hi[:] = run.at(2).bits
    level.kept, level.frontier = len(strong), len(frontier)
    levels, least = [level], np.sort(cells.r)
    for order in range(start + 1, top + 1):
        if not len(frontier):
            break
        level = Level(order)
        levels.append(level)
        if cells.n < min_ratio * math.prod(least[:order].tolist()) * cells.rc:  # no set of this order has enough samples
            level.children = level.cut_samples = int((p - 1 - frontier[:, -1]).sum())
            frontier = frontier[:0]
            continue
        children = _children(frontier, p)
        level.children = len(children)
        children = children[run.enough(children)]
        level.cut_samples = level.children - len(children)
        known, rank = run.at(order), cells.rank(children)
        zone, saturated = np.full(len(children), -1, dtype=np.int8), np.zeros(len(children), dtype=bool)
        needed = np.ones(len(children), dtype=bool)
        if bounds and len(children):
            low, high = run.limits(children)
            df = run.df(children)
            at_high, at_low = run.zone_of(high, df), run.zone_of(low, df)
            for case, n in zip(*np.unique(3 * at_high + at_low, return_counts=True)):
                level.decided[CASES[_ZONES[case // 3], _ZONES[case % 3]]] += int(n)
            needed = at_high != at_low
            sure = ~needed
            zone[sure] = known.zone[rank[sure]] = at_high[sure]
            known.lo[rank[sure]], known.hi[rank[sure]] = low[sure], high[sure]
            if cells.c is not None:
                saturated = sure & (at_high == _WEAK) & (high >= cells.hc - 1e-12)
        level.exact = int(needed.sum())
        run.evaluate(children[needed])
        zone[needed] = run.settle(children[needed])
        strong = np.flatnonzero(zone == _STRONG)
        level.side_exact = _judge_sides(run, children[strong])
        grown = (zone == _WEAK) & ~saturated
        strong = strong[known.bits[rank[strong]] >= min_bits]
        kinds = _kinds(run, children[strong])
        kept = [i for i, kind in enumerate(kinds) if kind]
        keep(children[strong[kept]], [kinds[i] for i in kept])
        grown[strong[kept]] = True
        frontier = children[grown]
        level.kept, level.frontier = len(kept), len(frontier)
    return Mined(frame, "TC" if mode == "tc" else "CAC", {g: result}, levels)


def _judge_sides(run: _Run, strong: np.ndarray) -> int:
    """Counts STRONG sets that are known by bounds only, and subsets of STRONG sets that the tree has not judged or counted; how many they were."""
    if not len(strong):
        return 0
    k, known = strong.shape[1], run.at(strong.shape[1])
    own = strong[np.isnan(known.h[run.cells.rank(strong)])]
    less = np.concatenate([np.delete(strong, j, axis=1) for j in range(k)])
    rank, at = np.unique(run.cells.rank(less), return_index=True)
    less = less[at[(run.at(k - 1).zone[rank] < 0) | np.isnan(run.at(k - 1).h[rank])]]
    for sets in (own, less):
        run.evaluate(sets)
        run.settle(sets)
    return len(own) + len(less)


def _kinds(run: _Run, strong: np.ndarray) -> list[str | None]:
    """As :func:`mining.judge` by the tree rule, for STRONG sets of one order."""
    if not len(strong):
        return []
    k, cells = strong.shape[1], run.cells
    less, below = run.at(k - 1), np.stack(cells.below(strong))
    zones = less.zone[below]
    n_strong, n_weak = (zones == _STRONG).sum(axis=0), (zones == _WEAK).sum(axis=0)
    parent_kept = less.kept[below[0]]
    core = ~parent_kept & (n_weak == k)
    which = (zones == _STRONG).argmax(axis=0)  # the subset without member k - 1 - which
    rows = np.arange(len(strong))
    r_new = cells.r[strong[rows, k - 1 - which]]
    joint = cells.possible(strong) // r_new
    df = (joint * (r_new - 1) * (cells.rc - 1) if cells.c is not None else (joint - 1) * (r_new - 1)).astype(np.float64)
    gain = run.at(k).bits[cells.rank(strong)] - less.bits[below[which, rows]]
    extension = parent_kept & (n_strong == 1) & (n_weak == k - 1) & (gain > run.critical(df, run.high))
    return ["core" if c else "extension" if e else None for c, e in zip(core.tolist(), extension.tolist())]


def hard_threshold(x: np.ndarray, w: np.ndarray, frame: Frame, alpha: float, beta: float, max_order: int, min_ratio: float) -> list[tuple[Members, float]]:
    """Sets of ``baselines.hard_threshold`` with their bits, for one data set."""
    run = _Run(Cells(x, w, frame.states), ALPHA_HIGH, ALPHA_LOW, min_ratio)
    cells = run.cells
    weak = {1: np.ones(cells.p, dtype=bool)}
    frontier, found = cells.sets(1), []
    run.evaluate(frontier)
    for order in range(2, max_order + 1):
        children = _children(frontier, cells.p)
        children = children[run.enough(children)]
        children = children[np.all([weak[order - 1][rank] for rank in cells.below(children)], axis=0)]
        if not len(children):
            break
        run.evaluate(children)
        bits = run.at(order).bits[cells.rank(children)]
        found += [(tuple(s), b) for s, b in zip(children[bits >= beta].tolist(), bits[bits >= beta].tolist())]
        frontier = children[(bits <= alpha) & (bits < beta)]
        weak[order] = np.zeros(math.comb(cells.p, order), dtype=bool)
        weak[order][cells.rank(frontier)] = True
    return found


def interactions(x: np.ndarray, w: np.ndarray, frame: Frame, attributes: list[int], order: int, min_ratio: float) -> list[tuple[np.ndarray, np.ndarray]]:
    """II of all subsets of the attributes that have enough samples, with the class if it is among them: by order of
    predictors, their indexes (a row a set, without the class) and values."""
    c = frame.class_at if frame.class_at in attributes else None
    kept = sorted(attributes)
    cells = Cells(x[kept], w, tuple(frame.states[i] for i in kept), kept.index(c) if c is not None else None)
    run = _Run(cells, ALPHA_HIGH, ALPHA_LOW, min_ratio)
    value: dict[int, np.ndarray] = {}
    out = []
    for k in range(1, min(order, cells.p) + 1):
        members = cells.sets(k)
        if k > 1 or c is not None:
            members = members[run.enough(members)]
        if not len(members):
            break
        h, full = cells.entropies(members)
        value[k] = np.full(math.comb(cells.p, k), np.nan)
        value[k][cells.rank(members)] = full - h if c is not None else h
        total = np.full(len(members), (-1.0) ** k * cells.hc if c is not None else 0.0)
        for size in range(1, k + 1):
            for at in combinations(range(k), size):
                total += (-1.0) ** (k - size) * value[size][cells.rank(members[:, list(at)])]
        if k > 1 or c is not None:
            out.append((np.array(kept)[cells.attributes[members]], -total))
    return out
