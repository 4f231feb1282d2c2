"""DuckDB SQL that repeats the experiments from their definitions: planted tables, zones and searches, for comparison only.

Nothing is taken from the engine: critical values come from bisection of the gamma tail in SQL, entropies from counted
cells, and the search from joins level by level. A row of a data set is one number, two or three bits an attribute, so
that a set is a bit mask and a cell is ``code & mask``.
"""

from __future__ import annotations

import math
from itertools import combinations

NOISE = (0.0, 0.1, 0.15, 0.2, 0.25, 0.3)
XOR_SETS = ((0, 1, 2), (5, 6, 7, 8), (10, 11, 12, 13))
TERNARY = (3,) * 15


def u(tag: str) -> str:
    return f"(('0x' || substr(md5('{tag}:' || rep || ':' || key), 1, 8))::bigint / 4294967296.0)"


def geno(tag: str) -> str:
    return f"(case when {u(tag)} < 0.25 then 0 when {u(tag)} < 0.75 then 1 else 2 end)"


def keyed(size: int) -> str:
    """CTEs that cut the orders into ranges of keys, in as many repeats as give a hundred data sets: keyed(key, rep, g)."""
    return f"""parts as (select o_orderkey // {size} as part from orders group by 1 having count(*) = {size}),
 times as (select greatest(1, cast(ceil(100.0 / count(*)) as bigint)) as t from parts),
 keyed as (select o_orderkey as key, rep, rep * 1000000000 + part as g from orders join parts on o_orderkey // {size} = part cross join times cross join range(0, 200) r(rep) where rep < t)"""


def packed(names: list[str], bits: int) -> str:
    return " | ".join(f"({n}::bigint << {bits * i})" for i, n in enumerate(names))


def xor_cte(levels: tuple[int, ...] = tuple(range(len(NOISE)))) -> str:
    """d(g, code) of noisy exclusive-or at the given noise levels; 15 attributes of one bit each, two bits wide."""
    plain = ", ".join(f"({u(f'a{i}')} < 0.5)::int as a{i}" for i in (2, 3, 4, 5, 7, 8, 9, 10, 12, 13, 14, 15))
    flips = ", ".join(f"{u(f'f{i}')} as f{i}" for i in (1, 6, 11))
    noise = ", ".join(f"({i}, {NOISE[i]})" for i in levels)
    targets = "xor(xor(a2, a3), (f1 < noise)::int) as a1, xor(xor(xor(a7, a8), a9), (f6 < noise)::int) as a6, xor(xor(xor(a12, a13), a14), (f11 < noise)::int) as a11"
    return f"""{keyed(200)}, base as (select g, {plain}, {flips} from keyed), flipped as (select g + level * 1000000000000 as g, base.* exclude (g), {targets} from base cross join (values {noise}) n(level, noise)),
 d as (select g, {packed([f"a{i}" for i in range(1, 16)], 2)} as code from flipped)"""


def epistasis_cte(strong: bool = False) -> str:
    """d(g, code): 15 ternary attributes and the trait."""
    if strong:
        a1, a2 = f"floor(3 * {u('a1')})::int", f"case when t = 1 or {u('mix')} < 0.6 then a1 else (a1 + 1) % 3 end"
    else:
        a1 = f"case when t = 1 then [0, 1, 1, 2][floor(4 * {u('cell')})::int + 1] else {geno('a1')} end"
        a2 = f"case when t = 1 then [1, 0, 2, 1][floor(4 * {u('cell')})::int + 1] else {geno('a2')} end"
    rest = ", ".join(f"{geno(f'a{i}')} as a{i}" for i in range(3, 16))
    return f"""{keyed(200)}, one as (select *, (key % 2)::int as t from keyed), two as (select *, {a1} as a1 from one), three as (select *, {a2} as a2, {rest} from two),
 d as (select g, {packed([f"a{i}" for i in range(1, 16)] + ["t"], 2)} as code from three)"""


def gain_cte() -> str:
    """d(g, code): 15 ternary attributes and the class, 300 rows of each."""
    base = ", ".join(f"{geno(f'a{i}')} as a{i}" for i in range(1, 16))
    chance = "[0.25, 0.5, 0.75][a1 + 1] + case when (a1 + a2) % 2 = 0 then 0.25 else -0.25 end"
    return f"""{keyed(700)}, one as (select *, {base} from keyed), two as (select *, ({u('c')} < {chance})::int as c from one), {balanced('two', 300)},
 d as (select g, {packed([f"a{i}" for i in range(1, 16)] + ["c"], 2)} as code from kept)"""


def copies_cte() -> str:
    """d(g, code): 15 ternary attributes, three of them copies with errors, and the class, 800 rows of each."""
    base = ", ".join(f"{geno(f'a{i}')} as a{i}" for i in (1, 2, 3, 4, 5, 9, 10, 11, 12, 13, 14, 15))
    copies = ", ".join(f"case when {u(f'e{i + 5}')} < 0.05 then (a{i} + 1) % 3 else a{i} end as a{i + 5}" for i in (1, 2, 3))
    chance = "0.05 + case when a1 = 2 or a3 = 2 then 0.3 else 0.0 end + 0.3 * ((a1 + a2) % 2) + 0.3 * ((a1 + a2 + a3) % 2)"
    return f"""{keyed(1900)}, one as (select *, {base} from keyed), two as (select *, {copies}, ({u('c')} < {chance})::int as c from one), {balanced('two', 800)},
 d as (select g, {packed([f"a{i}" for i in range(1, 16)] + ["c"], 2)} as code from kept)"""


def balanced(table: str, each: int) -> str:
    return f"""ranked as (select *, row_number() over (partition by g, c order by key) as nth from {table}), drawn as (select * from ranked where nth <= {each}),
 kept as (select * from drawn where g in (select g from drawn group by g having count(*) = {2 * each}))"""


def mask(s, bits: int = 2) -> int:
    return sum(((1 << bits) - 1) << (bits * i) for i in s)


def name_of(s) -> str:
    return ",".join(map(str, s))


def values(rows) -> str:
    return ", ".join("(" + ", ".join(f"'{x}'" if isinstance(x, str) else str(x) for x in r) + ")" for r in rows)


def entropies(masks, given: str = "d") -> str:
    """CTE e(g, mask, h) of a table given(g, code)."""
    return f"""m(mask) as (values {values((x,) for x in sorted(set(masks)))}),
 e as (select g, mask, log2(sum(n)) - sum(n * log2(n)) / sum(n) as h from (select g, mask, code & mask as cell, count(*) as n from {given} cross join m group by 1, 2, 3) group by g, mask)"""


def tail(shape: str, x: str) -> str:
    """Upper tail of the gamma distribution: one minus the series of the lower."""
    return f"(1 - list_sum(list_transform(range(0, 400), lambda j: exp(-({x}) + ({shape} + j) * ln({x}) - lgamma({shape} + j + 1)))))"


def cuts(dfs, n: int | str) -> str:
    """CTE cut(df, strong_at, weak_at) in bits, by bisection."""
    rows = values((float(d), a) for d in sorted(set(map(float, dfs))) for a in (1e-8, 1e-2))
    middle = "((lo + hi) / 2)"
    inside = f"{tail('df / 2', middle)} > alpha"
    return f"""bis as (with recursive b(df, alpha, i, lo, hi) as (select df, alpha, 0, 0e0, df + 60e0 from (values {rows}) v(df, alpha)
  union all select df, alpha, i + 1, case when {inside} then {middle} else lo end, case when {inside} then hi else {middle} end from b where i < 70) select df, alpha, hi from b where i = 70),
 cut as (select df, max(case when alpha < 1e-5 then hi end) / ({n} * ln(2)) + 1e-12 as strong_at, max(case when alpha > 1e-5 then hi end) / ({n} * ln(2)) + 1e-12 as weak_at from bis group by df)"""


class Lattice:
    """Sets up to an order that the sample rule allows, with their degrees of freedom, as VALUES."""

    def __init__(self, states: tuple[int, ...], n: int, order: int, class_at: int | None = None, only=None, bits: int = 2, first_order: int = 1):
        self.states, self.n, self.c, self.bits = states, n, class_at, bits
        self.attributes = [i for i in (only if only is not None else range(len(states))) if i != class_at]
        self.start = 2 if class_at is None else first_order
        with_c = states[class_at] if class_at is not None else 1
        self.sets = [s for k in range(1, order + 1) for s in combinations(self.attributes, k) if k == 1 or n >= 5 * with_c * math.prod(states[i] for i in s)]
        self.order = max(map(len, self.sets))

    def mask(self, s) -> int:
        return mask(s, self.bits)

    def df(self, s) -> int:
        r = [self.states[i] for i in s]
        return math.prod(r) - sum(r) + len(r) - 1 if self.c is None else (math.prod(r) - 1) * (self.states[self.c] - 1)

    def df_gain(self, x, k) -> int:
        joint = math.prod(self.states[i] for i in x)
        return (joint - 1) * (self.states[k] - 1) if self.c is None else joint * (self.states[k] - 1) * (self.states[self.c] - 1)

    def zones(self) -> str:
        """CTE z(g, mask, ord, bits, zone) over d."""
        judged = [s for s in self.sets if len(s) >= (2 if self.c is None else 1)]
        every = {self.mask(s) for s in self.sets}
        gains = {self.df_gain([i for i in s if i != k], k) for s in judged if len(s) > 1 for k in s}
        if self.c is None:
            members = values((self.mask(s), self.mask((i,))) for s in judged for i in s)
            bits = f"t as (select mm.mask, e.g, sum(e.h) as sum_h from (values {members}) mm(mask, one) join e on e.mask = mm.one group by 1, 2), b as (select t.g, t.mask, sum_h - h as bits from t join e on e.g = t.g and e.mask = t.mask)"
        else:
            c = self.mask((self.c,))
            every |= {x | c for x in every} | {c}
            bits = f"b as (select x.g, x.mask, x.h + k.h - y.h as bits from e x join e y on y.g = x.g and y.mask = x.mask | {c} join e k on k.g = x.g and k.mask = {c} where x.mask & {c} = 0)"
        listed = values((self.mask(s), name_of(s), len(s), float(self.df(s))) for s in judged)
        return f"""{entropies(every)}, {cuts([*(self.df(s) for s in judged), *gains], self.n)}, {bits}, sets(mask, set_id, ord, df) as (values {listed}),
 z as (select b.g, b.mask, sets.set_id, sets.ord, b.bits, case when bits > strong_at then 'STRONG' when bits <= weak_at then 'WEAK' else 'MIDDLE' end as zone from b join sets on sets.mask = b.mask join cut on cut.df = sets.df)"""

    def search(self) -> str:
        """CTEs from d to found(g, set_id, kind, bits): the tree rule, level by level."""
        out = [self.zones()]
        subs = values((self.mask(s), self.mask([i for i in s if i != k]), float(self.df_gain([i for i in s if i != k], k))) for s in self.sets if len(s) > self.start for k in s) if self.order > self.start else ""
        out.append(f"l{self.start} as (select g, mask, set_id, bits, case when zone = 'STRONG' then 'core' end as kind, zone <> 'MIDDLE' as front from z where ord = {self.start})")
        if subs:
            out.append(f"subs(mask, sub, df) as (values {subs})")
            out.append(
                """below as (select s.mask, z.g, count(case when zone = 'STRONG' then 1 end) as strong, count(case when zone = 'WEAK' then 1 end) as weak, count(*) as k,
  max(case when zone = 'STRONG' then z.bits end) as sub_bits, max(case when zone = 'STRONG' then cut.strong_at end) as gain_at from subs s join z on z.mask = s.sub join cut on cut.df = s.df group by 1, 2)"""
            )
        for k in range(self.start + 1, self.order + 1):
            tree = values((self.mask(s), self.mask(s[:-1])) for s in self.sets if len(s) == k)
            out.append(
                f"""k{k} as (select z.g, z.mask, z.set_id, z.bits, z.zone, case when z.zone <> 'STRONG' then null when p.kind is null and weak = k then 'core' when p.kind is not null and strong = 1 and weak = k - 1 and z.bits - sub_bits > gain_at then 'extension' end as kind
  from z join (values {tree}) t(mask, parent) on t.mask = z.mask join l{k - 1} p on p.g = z.g and p.mask = t.parent and p.front join below w on w.g = z.g and w.mask = z.mask),
 l{k} as (select g, mask, set_id, bits, kind, kind is not null or zone = 'WEAK' as front from k{k})"""
            )
        out.append("found as (" + " union all ".join(f"select g, set_id, kind, bits from l{k} where kind is not null" for k in range(self.start, self.order + 1)) + ")")
        return ",\n ".join(out)

    def hard_threshold(self) -> str:
        """CTE found(g, set_id, bits) of the baseline with fixed cut-offs, up to order 4, over z."""
        subs = values((self.mask(s), self.mask([i for i in s if i != k])) for s in self.sets if 2 < len(s) <= 4 for k in s)
        out = ["w2 as (select g, mask from z where ord = 2 and bits <= 0.2)", f"hs(mask, sub) as (values {subs})"] if subs else []
        parts = ["select g, set_id, bits from z where ord = 2 and bits >= 0.8"]
        for k in range(3, min(4, self.order) + 1):
            out.append(f"h{k} as (select z.g, z.mask, z.set_id, z.bits from z join hs on hs.mask = z.mask join w{k - 1} w on w.g = z.g and w.mask = hs.sub where z.ord = {k} group by all having count(*) = {k})")
            out.append(f"w{k} as (select g, mask from h{k} where bits <= 0.2)")
            parts.append(f"select g, set_id, bits from h{k} where bits >= 0.8")
        return ",\n ".join([self.zones(), *out, "found as (" + " union all ".join(parts) + ")"])


F1 = Lattice((2,) * 15, 200, 5)
F2 = Lattice((*TERNARY, 2), 200, 3)
F3 = Lattice((*TERNARY, 2), 600, 3, 15)
F3_PAIRS = Lattice((*TERNARY, 2), 600, 3, 15, first_order=2)
F4 = Lattice((*TERNARY, 2), 1600, 4, 15, only=[0, 1, 2, 3, 4, 8, 9, 10, 11, 12, 13, 14])


def selector(n_attributes: int, targets: dict[int, int], bits: int = 2, form: str = "difference") -> str:
    """CTE chosen(g, target, rank, i, relevance, score) over d: greedy choice for every target and its number of attributes; ties to the smaller index."""
    ones, pairs = [(i,) for i in range(n_attributes)], list(combinations(range(n_attributes), 2))
    listed = values((mask(p, bits), *p) for p in pairs)
    less = lambda mean: f"r.mi - {mean}" if form == "difference" else f"r.mi / ({mean} + 1e-12)"
    ctes = [
        entropies([mask(s, bits) for s in ones + pairs]),
        f"h1 as (select g, i, h from e join (values {values((mask((i,), bits), i) for i in range(n_attributes))}) o(mask, i) using (mask))",
        f"half as (select e.g, p.i, p.j, a.h + b.h - e.h as mi from e join (values {listed}) p(mask, i, j) using (mask) join h1 a on a.g = e.g and a.i = p.i join h1 b on b.g = e.g and b.i = p.j)",
        "mi as (select g, i, j, mi from half union all select g, j, i, mi from half)",
        f"goal(target, most) as (values {values(targets.items())})",
        "r as (select mi.g, goal.target, goal.most, mi.i, mi.mi from mi join goal on goal.target = mi.j)",
        "s1 as (select g, target, 1 as rank, i, mi, mi as score, [i] as picked from r qualify row_number() over (partition by g, target order by round(mi, 11) desc, i) = 1)",
    ]
    for k in range(2, max(targets.values()) + 1):
        mean = f"(list_sum(list(b.mi)) / {k - 1})"
        ctes.append(f"t{k} as (select r.g, r.target, r.i, any_value(r.mi) as mi, avg(b.mi) as mean, any_value(s.picked) as picked from r join s{k - 1} s on s.g = r.g and s.target = r.target and not list_contains(s.picked, r.i) and r.most >= {k} join mi b on b.g = r.g and b.i = r.i and list_contains(s.picked, b.j) group by 1, 2, 3)")
        ctes.append(f"s{k} as (select g, target, {k} as rank, i, mi, {less('mean').replace('r.mi', 'mi')} as score, list_append(picked, i) as picked from t{k} qualify row_number() over (partition by g, target order by round({less('mean').replace('r.mi', 'mi')}, {11 if form == 'difference' else 6}) desc, i) = 1)")
    ctes.append("chosen as (" + " union all ".join(f"select g, target, rank, i, mi as relevance, score from s{k}" for k in range(1, max(targets.values()) + 1)) + ")")
    return ",\n ".join(ctes)
