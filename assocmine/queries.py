"""Registered queries of the association engine and their DuckDB oracles.

Every float leaves rounded to six digits on both sides. Sets are named by attribute indexes, comma-separated.
"""

from __future__ import annotations

from collections.abc import Callable
from itertools import combinations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from assocmine import experiments
from assocmine import oracle as o
from assocmine.functions.expressions import immediate_subsets, rounded, set_id, subsets, zone_of
from assocmine.operators import baselines, bounds, evaluation, interactions, lattice, metrics, mining, redundancy, significance
from assocmine.plans import counts
from assocmine.plans.materialize import materialize
from assocmine.sources import discretize, planted, views
from assocmine.sources.frame import Frame

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}
V1_NAMES = views.VIEWS["lineitem"][0]
#: States of the lineitem view by construction (FIXTURES.md), in attribute order; oracles need them as numbers.
V1_STATES = (3, 2, 7, 5, 5, 3, 3, 7, 4)
N1, PAIRS, TRIPLES = 60_000, list(combinations(range(9), 2)), list(combinations(range(9), 3))


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql is not None:
            ORACLES[name] = sql
        return f

    return add


def r6(x: str) -> str:
    return f"round({x}, 6) + 0.0"


def name_of(s) -> str:
    return ",".join(map(str, s))


def mask(s, used: list[int]) -> int:
    """GROUPING() of a set: bit 1 for every used attribute that is grouped away, first attribute highest."""
    return sum(1 << (len(used) - 1 - k) for k, i in enumerate(used) if i not in s)


def entropy_cte(view: str, names: list[str], sets) -> str:
    """CTE ``e``(set_id, ord, h, cells) of a view's sets."""
    sets = sorted(set(sets), key=lambda s: (len(s), s))
    used = sorted({i for s in sets for i in s})
    grouping = ", ".join("(" + ", ".join(names[i] for i in s) + ")" for s in sets)
    listed = ", ".join(f"({mask(s, used)}, '{name_of(s)}', {len(s)})" for s in sets)
    return f"""v as ({view}), cells as (select grouping({', '.join(names[i] for i in used)}) as gid, count(*) as n from v group by grouping sets ({grouping})),
 e as (select set_id, ord, log2(sum(n)) - sum(n * log2(n)) / sum(n) as h, count(*) as cells from cells join (values {listed}) t(gid, set_id, ord) using (gid) group by set_id, ord)"""


def v1_cte(sets) -> str:
    return entropy_cte(views.view_sql("lineitem"), V1_NAMES, sets)


def subset_values(sets, least: int = 1, sign: bool = True) -> str:
    """VALUES (set_id, subset id, sign of the subset in minus the alternating sum)."""
    rows = []
    for s in sets:
        for k in range(least, len(s) + 1):
            rows += [f"('{name_of(s)}', '{name_of(t)}', {-((-1) ** (len(s) - k))})" for t in combinations(s, k)]
    return ", ".join(rows)


def v1(spark: SparkSession, sf: str) -> Frame:
    return views.frame(spark, sf, "lineitem")


def named(df: DataFrame, *values: str) -> DataFrame:
    return df.select(set_id(F.col("s")).alias("set_id"), *[rounded(F.col(v)).alias(v) for v in values])


# --- entropies and metrics -------------------------------------------------------------------------------------

SINGLES = [(i,) for i in range(9)]


@query("q_entropy_attrs", f"with {v1_cte(SINGLES)} select set_id, {r6('h')} as h, cells from e")
def q_entropy_attrs(spark, sf):
    e = counts.entropies(v1(spark, sf), SINGLES)
    return e.select(set_id(F.col("s")).alias("set_id"), rounded(F.col("h")).alias("h"), "cells")


@query("q_entropy_pairs", f"with {v1_cte(PAIRS)} select set_id, {r6('h')} as h, cells from e")
def q_entropy_pairs(spark, sf):
    e = counts.entropies(v1(spark, sf), PAIRS, "arrays")
    return e.select(set_id(F.col("s")).alias("set_id"), rounded(F.col("h")).alias("h"), "cells")


for _strategy in ("cube", "explode", "arrays", "maximal"):
    QUERIES[f"q_count_{_strategy}"] = lambda spark, sf, k=_strategy: counts.entropies(v1(spark, sf), PAIRS, k).select(set_id(F.col("s")).alias("set_id"), rounded(F.col("h")).alias("h"), "cells")
    ORACLES[f"q_count_{_strategy}"] = f"with {v1_cte(PAIRS)} select set_id, {r6('h')} as h, cells from e"


@query("q_count_collapsed", f"with {v1_cte(TRIPLES)} select set_id, {r6('h')} as h, cells from e")
def q_count_collapsed(spark, sf):
    e = counts.entropies(v1(spark, sf).collapse(), TRIPLES, "arrays")
    return e.select(set_id(F.col("s")).alias("set_id"), rounded(F.col("h")).alias("h"), "cells")


@query(
    "q_cond_entropy",
    f"""with {v1_cte(SINGLES + PAIRS)}, p(a, b, ab) as (values {", ".join(f"({a}, {b}, '{name_of(sorted((a, b)))}')" for a in range(9) for b in range(9) if a != b)})
select a, b, {r6('x.h - y.h')} as h_cond from p join e x on x.set_id = ab join e y on y.set_id = cast(b as varchar)""",
)
def q_cond_entropy(spark, sf):
    frame = v1(spark, sf)
    ent = counts.entropies(frame, SINGLES + PAIRS)
    rows = spark.createDataFrame([(0, a, b) for a in range(9) for b in range(9) if a != b], "g long, a int, b int")
    return metrics.conditional(ent, rows).select("a", "b", rounded(F.col("h_cond")).alias("h_cond"))


def tc_sql(sets) -> str:
    members = ", ".join(f"('{name_of(s)}', '{i}')" for s in sets for i in s)
    return f"""with {v1_cte([*SINGLES, *sets])}, m(set_id, i) as (values {members}), t as (select m.set_id, sum(h) as sum_h from m join e on e.set_id = m.i group by m.set_id)
select set_id, {r6('sum_h - h')} as tc from t join e using (set_id)"""


@query("q_tc_pairs", tc_sql(PAIRS))
def q_tc_pairs(spark, sf):
    frame = v1(spark, sf)
    return named(metrics.total_correlation(counts.entropies(frame, SINGLES + PAIRS), metrics.table(frame, PAIRS)), "tc")


@query("q_tc_triples_cube", tc_sql(TRIPLES))
def q_tc_triples_cube(spark, sf):
    """All triples in one pass; 93 sets are counted by arrays, as choose() has it (q_count_cube counts by grouping sets)."""
    frame = v1(spark, sf)
    return named(metrics.total_correlation(counts.entropies(frame, SINGLES + TRIPLES), metrics.table(frame, TRIPLES)), "tc")


@query(
    "q_tc_direct",
    f"""with v as ({views.view_sql('lineitem')}), c as (select year, quarter, count(*) as n from v group by 1, 2), m as (
select *, sum(n) over (partition by year) as my, sum(n) over (partition by quarter) as mq, sum(n) over () as t from c)
select '7,8' as set_id, {r6('sum(n / t * log2((n / t) / ((my / t) * (mq / t))))')} as tc from m""",
)
def q_tc_direct(spark, sf):
    return named(metrics.total_correlation_direct(v1(spark, sf), (7, 8)), "tc")


@query("q_mutual_information", tc_sql(PAIRS).replace("as tc", "as mi"))
def q_mutual_information(spark, sf):
    frame = v1(spark, sf)
    return named(metrics.mutual_information(counts.entropies(frame, SINGLES + PAIRS), metrics.table(frame, PAIRS)), "mi")


C0 = 0  # class attribute of the lineitem view: the return flag
PRED = list(range(1, 9))
P1, P2 = [(i,) for i in PRED], list(combinations(PRED, 2))


def cac_sql(sets, select: str = f"set_id, {r6('hs + hc - hsc')} as cac") -> str:
    rows = ", ".join(f"('{name_of(s)}', '{name_of(sorted((C0, *s)))}')" for s in sets)
    every = {*sets, *(tuple(sorted((C0, *s))) for s in sets), (C0,)}
    return f"""with {v1_cte(every)}, p(set_id, sc) as (values {rows}),
 k as (select p.set_id, a.h as hs, b.h as hsc, z.h as hc from p join e a on a.set_id = p.set_id join e b on b.set_id = p.sc join e z on z.set_id = '{C0}')
select {select} from k"""


def v1_class(spark, sf) -> Frame:
    return views.frame(spark, sf, "lineitem", "returnflag")


def with_class(sets) -> list[tuple[int, ...]]:
    return [*sets, *(tuple(sorted((C0, *s))) for s in sets), (C0,)]


@query("q_cac_singles", cac_sql(P1))
def q_cac_singles(spark, sf):
    frame = v1_class(spark, sf)
    return named(metrics.class_correlation(counts.entropies(frame, with_class(P1)), metrics.table(frame, P1), C0), "cac")


@query("q_cac_pairs", cac_sql(P2))
def q_cac_pairs(spark, sf):
    frame = v1_class(spark, sf)
    return named(metrics.class_correlation(counts.entropies(frame, with_class(P2)), metrics.table(frame, P2), C0), "cac")


@query("q_cac_direct", cac_sql([(1, 3)]))
def q_cac_direct(spark, sf):
    return named(metrics.class_correlation_direct(v1_class(spark, sf), (1, 3), C0), "cac")


def ii_sql(sets, extra: str = "") -> str:
    every = {t for s in sets for k in range(1, len(s) + 1) for t in combinations(s, k)}
    return f"""with {v1_cte(every)}, p(set_id, t, sign) as (values {subset_values(sets)})
select p.set_id, {r6('sum(sign * h)')} as ii{extra} from p join e on e.set_id = p.t group by p.set_id"""


@query("q_ii_triples", ii_sql(TRIPLES))
def q_ii_triples(spark, sf):
    frame = v1(spark, sf)
    ent = counts.entropies(frame, SINGLES + PAIRS + TRIPLES)
    return named(metrics.interaction_info(ent, metrics.table(frame, TRIPLES)), "ii")


@query("q_ii_class", ii_sql([(C0, *s) for s in P2]))
def q_ii_class(spark, sf):
    frame = v1_class(spark, sf)
    sets = [(C0, *s) for s in P2]
    ent = counts.entropies(frame, {t for s in sets for t in metrics.all_sets(s, 1, 3)})
    return named(metrics.interaction_info(ent, metrics.table(frame, sets)), "ii")


@query("q_ii_kind", ii_sql(PAIRS, ", case when sum(sign * h) > 1e-9 then 'synergy' when sum(sign * h) < -1e-9 then 'redundancy' else 'none' end as kind"))
def q_ii_kind(spark, sf):
    frame = v1(spark, sf)
    ii = metrics.interaction_info(counts.entropies(frame, SINGLES + PAIRS), metrics.table(frame, PAIRS))
    return ii.select(set_id(F.col("s")).alias("set_id"), rounded(F.col("ii")).alias("ii"), metrics.ii_kind(F.col("ii")).alias("kind"))


@query("q_tc_identity", tc_sql(TRIPLES).replace("as tc from", "as \"left\", " + r6("sum_h - h") + " as \"right\" from"))
def q_tc_identity(spark, sf):
    return named(metrics.decompositions(v1(spark, sf), TRIPLES), "left", "right")


@query("q_cac_identity", cac_sql(P2, f"set_id, {r6('hs + hc - hsc')} as \"left\", {r6('hs + hc - hsc')} as \"right\""))
def q_cac_identity(spark, sf):
    return named(metrics.decompositions(v1_class(spark, sf), P2, C0), "left", "right")


@query(
    "q_chi2_two_way",
    f"""with v as ({views.view_sql('lineitem')}), c as (select linestatus, quantity, returnflag, count(*) as n from v group by 1, 2, 3),
a as (select linestatus, quantity, count(*) as na from v group by 1, 2), b as (select returnflag, count(*) as nc from v group by 1), t as (select count(*) as t from v)
select '1,3' as set_id, round(sum(power(coalesce(n, 0) - na * nc / t, 2) / (na * nc / t)), 4) + 0.0 as chi2,
 {r6('sum(power(coalesce(n, 0) - na * nc / t, 2) / (na * nc / t)) / (2 * any_value(t) * ln(2))')} as cac_approx
from a cross join b cross join t left join c using (linestatus, quantity, returnflag)""",
)
def q_chi2_two_way(spark, sf):
    c = metrics.cac_chi2_approx(v1_class(spark, sf), (1, 3), C0)
    return c.select(set_id(F.col("s")).alias("set_id"), rounded(F.col("chi2"), 4).alias("chi2"), rounded(F.col("cac_approx")).alias("cac_approx"))


GAINS = [((1, 3, 7), (1, 3)), ((2, 7, 8), (2, 7)), ((7, 8), (7,)), ((1, 2), (2,))]


def _gain_rows(spark) -> DataFrame:
    return spark.createDataFrame([(0, list(s), list(x)) for s, x in GAINS], "g long, s array<int>, x array<int>")


@query(
    "q_tc_gain",
    f"""with {v1_cte([*SINGLES, *(s for s, _ in GAINS), *(x for _, x in GAINS)])}, p(set_id, x, k) as (values {", ".join(f"('{name_of(s)}', '{name_of(x)}', '{(set(s) - set(x)).pop()}')" for s, x in GAINS)})
select p.set_id, p.x as sub, {r6('a.h + b.h - c.h')} as gain from p join e a on a.set_id = p.k join e b on b.set_id = p.x join e c on c.set_id = p.set_id""",
)
def q_tc_gain(spark, sf):
    ent = counts.entropies(v1(spark, sf), [*SINGLES, *(s for s, _ in GAINS), *(x for _, x in GAINS)])
    return metrics.tc_gain(ent, _gain_rows(spark)).select(set_id(F.col("s")).alias("set_id"), set_id(F.col("x")).alias("sub"), rounded(F.col("gain")).alias("gain"))


_big = cac_sql([s for s, _ in GAINS] + [x for _, x in GAINS], "set_id, hs + hc - hsc as cac")
CAC_GAIN_SQL = f"""with q as ({_big}), p(set_id, x) as (values {", ".join(f"('{name_of(s)}', '{name_of(x)}')" for s, x in GAINS)})
select p.set_id, p.x as sub, {r6('a.cac - b.cac')} as gain from p join q a on a.set_id = p.set_id join q b on b.set_id = p.x"""


@query("q_cac_gain", CAC_GAIN_SQL)
def q_cac_gain(spark, sf):
    ent = counts.entropies(v1_class(spark, sf), with_class([*(s for s, _ in GAINS), *(x for _, x in GAINS)]))
    return metrics.cac_gain(ent, _gain_rows(spark), C0).select(set_id(F.col("s")).alias("set_id"), set_id(F.col("x")).alias("sub"), rounded(F.col("gain")).alias("gain"))


@query("q_cac_gain_stratified", f"select sub, gain from ({CAC_GAIN_SQL}) where set_id = '1,3,7'")
def q_cac_gain_stratified(spark, sf):
    return metrics.cac_gain_stratified(v1_class(spark, sf), (1, 3), 7, C0).select(F.lit("1,3").alias("sub"), rounded(F.col("gain")).alias("gain"))


def monotone_sql(body: str, value: str, sets) -> str:
    """Pairs of a set and a subset with one member fewer, and in how many the value falls."""
    inside = ", ".join(f"('{name_of(s)}', '{name_of(t)}')" for s in sets for t in combinations(s, len(s) - 1) if len(t) >= (2 if value == "tc" else 1))
    return f"""with x as ({body}), sub(set_id, t) as (values {inside})
select count(*) as pairs, count(case when y.{value} > x.{value} + 1e-9 then 1 end) as violations from sub join x on x.set_id = sub.set_id join x y on y.set_id = sub.t"""


def _monotone(values: DataFrame, column: str, pairs: int) -> DataFrame:
    return evaluation.check_monotone(values, column).agg(F.lit(pairs).cast("long").alias("pairs"), F.count("*").alias("violations"))


@query("q_monotone", monotone_sql(tc_sql(PAIRS + TRIPLES).replace("round(sum_h - h, 6) + 0.0 as tc", "sum_h - h as tc"), "tc", TRIPLES))
def q_monotone(spark, sf):
    frame = v1(spark, sf)
    ent = counts.entropies(frame, SINGLES + PAIRS + TRIPLES)
    return _monotone(metrics.total_correlation(ent, metrics.table(frame, PAIRS + TRIPLES)), "tc", 3 * len(TRIPLES))


@query("q_monotone_class", monotone_sql(cac_sql(P1 + P2, "set_id, hs + hc - hsc as cac"), "cac", P2))
def q_monotone_class(spark, sf):
    frame = v1_class(spark, sf)
    ent = counts.entropies(frame, with_class(P1 + P2))
    return _monotone(metrics.class_correlation(ent, metrics.table(frame, P1 + P2), C0), "cac", 2 * len(P2))


@query(
    "q_ii_entropy_bound",
    f"""with x as ({ii_sql(TRIPLES).replace("round(sum(sign * h), 6) + 0.0 as ii", "sum(sign * h) as ii")}), {v1_cte(SINGLES)}, m(set_id, i) as (values {", ".join(f"('{name_of(s)}', '{i}')" for s in TRIPLES for i in s)})
select x.set_id, {r6('any_value(ii)')} as ii, {r6('min(h)')} as least_h, any_value(ii) <= min(h) + 1e-9 as holds from x join m using (set_id) join e on e.set_id = m.i group by x.set_id""",
)
def q_ii_entropy_bound(spark, sf):
    """II of three attributes is at most the smallest of their entropies."""
    frame = v1(spark, sf)
    ent = counts.entropies(frame, SINGLES + PAIRS + TRIPLES)
    bound = metrics.ii_entropy_bound(ent, metrics.table(frame, TRIPLES))
    return bound.select(set_id(F.col("s")).alias("set_id"), rounded(F.col("ii")).alias("ii"), rounded(F.col("least_h")).alias("least_h"), (F.col("ii") <= F.col("least_h") + 1e-9).alias("holds"))


# --- significance ----------------------------------------------------------------------------------------------

EVEN = [s for s in PAIRS if (V1_STATES[s[0]] - 1) * (V1_STATES[s[1]] - 1) % 2 == 0]


@query(
    "q_pvalue_even_df",
    f"""with q as ({tc_sql(EVEN).replace('round(sum_h - h, 6) + 0.0 as tc', 'greatest(sum_h - h, 1e-300) as tc')}), n as (select count(*) as n from lineitem),
d(set_id, df) as (values {", ".join(f"('{name_of(s)}', {(V1_STATES[s[0]] - 1) * (V1_STATES[s[1]] - 1)})" for s in EVEN)})
select set_id, cast(df as double) as df, {r6("sum(exp(-tc * n * ln(2) + j * ln(tc * n * ln(2)) - lgamma(j + 1)))")} as p
from q join d using (set_id) cross join n cross join range(0, 40) r(j) where j < df // 2 group by set_id, df""",
)
def q_pvalue_even_df(spark, sf):
    frame = v1(spark, sf)
    tc = metrics.total_correlation(counts.entropies(frame, SINGLES + PAIRS), metrics.table(frame, EVEN)).withColumn("df", significance.df_tc(frame, F.col("s")))
    p, _ = significance.tail(F.col("tc"), F.col("df"), frame.n)
    return tc.select(set_id(F.col("s")).alias("set_id"), "df", rounded(p).alias("p"))


def df_of(s) -> int:
    import math

    r = [V1_STATES[i] for i in s]
    return math.prod(r) - sum(r) + len(r) - 1


ROWS = "(select count(*) from lineitem)"


def zone_cte(sets, more=()) -> str:
    """CTEs cut(df, strong_at, weak_at) and z(set_id, tc, zone); critical values by bisection in SQL, also of further degrees of freedom."""
    body = tc_sql(sets).replace("round(sum_h - h, 6) + 0.0 as tc", "sum_h - h as tc")
    rows = ", ".join(f"('{name_of(s)}', {float(df_of(s))})" for s in sets)
    return f"""{o.cuts([*(df_of(s) for s in sets), *more], ROWS)},
 z as (select set_id, tc, case when tc > strong_at then 'STRONG' when tc <= weak_at then 'WEAK' else 'MIDDLE' end as zone from ({body}) join (values {rows}) c(set_id, df) using (set_id) join cut using (df))"""


@query("q_zone_pairs", f"with {zone_cte(PAIRS)} select set_id, {r6('tc')} as tc, zone from z")
def q_zone_pairs(spark, sf):
    frame = v1(spark, sf)
    tc = metrics.total_correlation(counts.entropies(frame, SINGLES + PAIRS), metrics.table(frame, PAIRS)).withColumn("df", significance.df_tc(frame, F.col("s")))
    return significance.with_zone(tc, "tc", frame.n).select(set_id(F.col("s")).alias("set_id"), rounded(F.col("tc")).alias("tc"), "zone")


@query("q_zone_counts", f"with {zone_cte(PAIRS + TRIPLES)} select zone, count(*) as sets from z group by zone")
def q_zone_counts(spark, sf):
    frame = v1(spark, sf)
    tc = metrics.total_correlation(counts.entropies(frame, SINGLES + PAIRS + TRIPLES), metrics.table(frame, PAIRS + TRIPLES)).withColumn("df", significance.df_tc(frame, F.col("s")))
    return significance.with_zone(tc, "tc", frame.n).groupBy("zone").agg(F.count("*").alias("sets"))


# --- redundancy ------------------------------------------------------------------------------------------------


@query(
    "q_redundancy",
    f"""with {v1_cte(SINGLES + PAIRS)}, p(i, j, s) as (values {", ".join(f"({i}, {j}, '{i},{j}')" for i, j in PAIRS)})
select i, j, {r6('-(a.h + b.h - c.h) / least(a.h, b.h)')} as score from p join e a on a.set_id = cast(i as varchar) join e b on b.set_id = cast(j as varchar) join e c on c.set_id = s""",
)
def q_redundancy(spark, sf):
    frame = v1(spark, sf)
    return redundancy.scores(frame, redundancy.pair_entropies(frame)).select("i", "j", rounded(F.col("score")).alias("score"))


@query(
    "q_redundancy_class",
    f"""with x as ({ii_sql([(C0, *s) for s in P2]).replace('round(sum(sign * h), 6) + 0.0', 'sum(sign * h)')}), {v1_cte([(C0,)])}
select cast(split_part(set_id, ',', 2) as int) as i, cast(split_part(set_id, ',', 3) as int) as j, {r6('ii / (select h from e)')} as score from x""",
)
def q_redundancy_class(spark, sf):
    frame = v1_class(spark, sf)
    return redundancy.scores(frame, redundancy.pair_entropies(frame, "class"), "class").select("i", "j", rounded(F.col("score")).alias("score"))


# --- bounds ----------------------------------------------------------------------------------------------------


def bounds_sql(sets) -> str:
    rows = []
    for s in sets:
        others = [i for i in range(9) if i not in s]
        new, parent = s[-1], s[:-1]
        sib = next((i for i in others if i > new), others[0])
        rows.append((s, parent, new, sib, [x for x in s if x != s[0]], [x for x in s if x != s[1]], s[:2], sorted((*parent, sib))))
    need = {*SINGLES, *PAIRS, *sets, *(tuple(x) for r in rows for x in (r[1], r[4], r[5], r[6], r[7]))}
    listed = ", ".join(f"('{name_of(r[0])}', '{name_of(r[1])}', '{r[2]}', '{r[3]}', '{name_of(r[4])}', '{name_of(r[5])}', '{name_of(r[6])}', '{name_of(r[7])}', '{name_of(sorted((r[2], r[3])))}')" for r in rows)
    members = ", ".join(f"('{name_of(s)}', '{i}')" for s in sets for i in s)
    given = ", ".join(f"('{name_of(r[0])}', '{t}', '{name_of(sorted((r[2], t)))}', '{name_of(sorted((r[3], t)))}')" for r in rows for t in r[1])
    return f"""with {v1_cte(need)}, l(set_id, parent, new, sib, wa, wb, ab, ps, pij) as (values {listed}), m(set_id, i) as (values {members}), gv(set_id, t, jt, it) as (values {given}),
 sm as (select m.set_id, sum(h) as sum_h from m join e on e.set_id = m.i group by m.set_id),
 cd as (select gv.set_id, min(j.h - t.h) as j_t, min(i.h - t.h) as i_t from gv join e j on j.set_id = gv.jt join e i on i.set_id = gv.it join e t on t.set_id = gv.t group by gv.set_id),
 x as (select l.set_id, sum_h, j_t, i_t, s.h as hs, p.h as hp, n.h as hn, wa.h as hwa, wb.h as hwb, ab.h as hab, ps.h as hps, pij.h - n.h as i_j from l join sm using (set_id) join cd using (set_id)
  join e s on s.set_id = l.set_id join e p on p.set_id = l.parent join e n on n.set_id = l.new join e wa on wa.set_id = l.wa join e wb on wb.set_id = l.wb join e ab on ab.set_id = l.ab join e ps on ps.set_id = l.ps join e pij on pij.set_id = l.pij)"""


BOUND_SETS = TRIPLES
BOUND_COLUMNS = {
    "tc": "sum_h - hs",
    "lower_ancestor": "sum_h - (hwa + hwb + hab) / 2",
    "lower_monotone": "sum_h - hn - hp",
    "upper_parent": "sum_h - hn - hp + least(hp, hn)",
    "lower_sibling": "sum_h - hps - j_t",
    "upper_sibling": "sum_h - hps + least(i_j, i_t)",
}


def _bounds(spark, sf):
    frame = v1(spark, sf)
    return bounds.bound_table(frame, materialize(counts.entropies(frame, SINGLES + PAIRS + BOUND_SETS + [tuple(sorted((*s[:-1], o))) for s in BOUND_SETS for o in range(9) if o not in s]), "bound-entropies"), BOUND_SETS)


@query("q_bounds_tc", f"{bounds_sql(BOUND_SETS)} select set_id, " + ", ".join(f"{r6(BOUND_COLUMNS[c])} as {c}" for c in ("tc", "lower_ancestor", "lower_monotone", "upper_parent")) + " from x")
def q_bounds_tc(spark, sf):
    return named(_bounds(spark, sf), "tc", "lower_ancestor", "lower_monotone", "upper_parent")


@query("q_sibling_bounds", f"{bounds_sql(BOUND_SETS)} select set_id, " + ", ".join(f"{r6(BOUND_COLUMNS[c])} as {c}" for c in ("tc", "lower_sibling", "upper_sibling")) + " from x")
def q_sibling_bounds(spark, sf):
    return named(_bounds(spark, sf), "tc", "lower_sibling", "upper_sibling")


_low, _high = (f"{f}({', '.join(BOUND_COLUMNS[c] for c in cs)})" for f, cs in (("greatest", ("lower_ancestor", "lower_monotone", "lower_sibling")), ("least", ("upper_parent", "upper_sibling"))))


@query("q_bound_violations", f"{bounds_sql(BOUND_SETS)} select count(case when {_low} > sum_h - hs + 1e-9 or {_high} < sum_h - hs - 1e-9 then 1 end) as violations from x")
def q_bound_violations(spark, sf):
    b = _bounds(spark, sf)
    low, high = F.greatest("lower_ancestor", "lower_monotone", "lower_sibling"), F.least("upper_parent", "upper_sibling")
    return b.filter((low > F.col("tc") + 1e-9) | (high < F.col("tc") - 1e-9)).agg(F.count("*").alias("violations"))


@query("q_bound_gap", f"{bounds_sql(BOUND_SETS)} select 3 as ord, {r6(f'avg({_high} - (sum_h - hs))')} as upper_gap, {r6(f'avg((sum_h - hs) - {_low})')} as lower_gap, count(*) as sets from x")
def q_bound_gap(spark, sf):
    return evaluation.bound_gap(_bounds(spark, sf)).select("ord", rounded(F.col("upper_gap")).alias("upper_gap"), rounded(F.col("lower_gap")).alias("lower_gap"), "sets")


def cac_bounds_sql() -> str:
    rows = ", ".join(f"('{i},{j}', '{C0},{i},{j}', '{i}', '{j}', '{C0},{i}', '{C0},{j}')" for i, j in P2)
    every = {*with_class(P2), *with_class(P1)}
    return f"""with {v1_cte(every)}, p(set_id, sc, i, j, ci, cj) as (values {rows}), z as (select h as hc from e where set_id = '{C0}')
select p.set_id, {r6('s.h + hc - sc.h')} as cac, {r6('greatest(i.h + hc - ci.h, j.h + hc - cj.h)')} as lower_single, {r6('least((i.h + j.h + s.h) / 2, hc)')} as upper
from p join e s on s.set_id = p.set_id join e sc on sc.set_id = p.sc join e i on i.set_id = p.i join e j on j.set_id = p.j join e ci on ci.set_id = p.ci join e cj on cj.set_id = p.cj cross join z"""


@query("q_bounds_cac", cac_bounds_sql())
def q_bounds_cac(spark, sf):
    frame = v1_class(spark, sf)
    ent = materialize(counts.entropies(frame, {*with_class(P2), *with_class(P1)}), "class-bound-entropies")
    return named(bounds.class_bound_table(frame, ent, P2), "cac", "lower_single", "upper")


# --- lattice ---------------------------------------------------------------------------------------------------

LARGE = list(combinations(range(9), 5))


def _product_sql(s) -> str:
    import math

    return str(math.prod(V1_STATES[i] for i in s))


@query("q_sample_rule", "select set_id from (values " + ", ".join(f"('{name_of(s)}', {_product_sql(s)})" for s in LARGE) + ") t(set_id, v) where (select count(*) from lineitem) >= 5 * v")
def q_sample_rule(spark, sf):
    frame = v1(spark, sf)
    sets = spark.createDataFrame([(list(s),) for s in LARGE], "s array<int>")
    return sets.filter(lattice.enough_samples(frame, F.col("s"))).select(set_id(F.col("s")).alias("set_id"))


@query("q_children", "with p as (select a, b from range(0, 9) x(a) join range(0, 9) y(b) on a < b) select a || ',' || b as parent, a || ',' || b || ',' || c as set_id from p join range(0, 9) z(c) on c > b")
def q_children(spark, sf):
    frame = v1(spark, sf)
    grown = lattice.children(metrics.table(frame, PAIRS).select("g", "s"), frame.attributes())
    return grown.select(set_id(F.col("parent")).alias("parent"), set_id(F.col("s")).alias("set_id"))


@query("q_subsets", "select set_id, count(*) as subsets, cast(3 as bigint) as immediate from (values " + subset_values(TRIPLES) + ") t(set_id, t, sign) group by set_id")
def q_subsets(spark, sf):
    sets = metrics.table(v1(spark, sf), TRIPLES)
    return sets.select(set_id(F.col("s")).alias("set_id"), F.size(subsets(F.col("s"))).cast("long").alias("subsets"), F.size(immediate_subsets(F.col("s"))).cast("long").alias("immediate"))


def definition_sql(kind: str) -> str:
    """Core or extension sets of order two and three of the lineitem view, from zones of all subsets."""
    gain_df = lambda s, t: (V1_STATES[t[0]] * V1_STATES[t[1]] - 1) * (V1_STATES[(set(s) - set(t)).pop()] - 1)
    trip = ", ".join(f"('{name_of(s)}', '{name_of(t)}', {float(gain_df(s, t))})" for s in TRIPLES for t in combinations(s, 2))
    counted = f"""with {zone_cte(PAIRS + TRIPLES, [gain_df(s, t) for s in TRIPLES for t in combinations(s, 2)])}, sub(set_id, t, df) as (values {trip}),
 k as (select sub.set_id, count(case when y.zone = 'STRONG' then 1 end) as strong, count(case when y.zone = 'WEAK' then 1 end) as weak, max(case when y.zone = 'STRONG' then y.tc end) as sub_tc, max(case when y.zone = 'STRONG' then cut.strong_at end) as gain_at
  from sub join z y on y.set_id = sub.t join cut using (df) group by sub.set_id)"""
    if kind == "core":
        return f"{counted} select z.set_id, {r6('tc')} as bits from z left join k using (set_id) where zone = 'STRONG' and (k.set_id is null or weak = 3)"
    return f"{counted} select z.set_id, {r6('tc')} as bits from z join k using (set_id) where zone = 'STRONG' and strong = 1 and weak = 2 and tc - sub_tc > gain_at"


def _kept(m: mining.Mined, kind: str) -> DataFrame:
    return m.table().filter(F.col("kind") == kind).select(set_id(F.col("members")).alias("set_id"), rounded(F.col("bits")).alias("bits"))


@query("q_core_sets", definition_sql("core"))
def q_core_sets(spark, sf):
    return _kept(mining.exhaustive(v1(spark, sf), max_order=3), "core")


@query("q_mine_definition", definition_sql("core"))
def q_mine_definition(spark, sf):
    return _kept(mining.mine_correlation(v1(spark, sf), max_order=3, rule="definition"), "core")


V1_CODES = f"""v as ({views.view_sql('lineitem')}), r as (select {", ".join(f"dense_rank() over (order by {n}) - 1 as {n}" for n in V1_NAMES)} from v), d as (select 0 as g, {o.packed(V1_NAMES, 3)} as code from r)"""
V1_LATTICE = o.Lattice(V1_STATES, N1, 3, bits=3)
NATURAL_SQL = f"with {V1_CODES},\n {V1_LATTICE.search()}\nselect set_id, kind, {r6('bits')} as bits from found"


@query("q_mine_natural", NATURAL_SQL)
def q_mine_natural(spark, sf):
    return mining.mine_correlation(v1(spark, sf), max_order=3).table().select(set_id(F.col("members")).alias("set_id"), "kind", rounded(F.col("bits")).alias("bits"))


@query("q_mine_lattice", NATURAL_SQL)
def q_mine_lattice(spark, sf):
    """The same search with its lattice in tables."""
    return lattice.mine(v1(spark, sf), max_order=3)[0].select(set_id(F.col("members")).alias("set_id"), "kind", rounded(F.col("bits")).alias("bits"))


@query(
    "q_mine_report",
    f"""with {V1_CODES},\n {V1_LATTICE.search()},
 below2 as (select count(*) as children, count(*) as fit, count(case when kind is not null then 1 end) as kept, count(case when front then 1 end) as frontier from l2),
 below3 as (select count(*) as children, count(*) as fit, count(case when kind is not null then 1 end) as kept, count(case when front then 1 end) as frontier from l3)
select 2 as level, children, cast(0 as bigint) as cut_samples, fit as judged, kept, frontier from below2 union all select 3, children, cast(0 as bigint), fit, kept, frontier from below3""",
)
def q_mine_report(spark, sf):
    """Cost of the search by level; every child is cut by the sample rule, decided by a bound, or counted."""
    report = mining.mine_correlation(v1(spark, sf), max_order=3, bounds=False).report()
    return report.select("level", "children", "cut_samples", F.col("exact").alias("judged"), "kept", "frontier")


@query("q_bound_decisions")
def q_bound_decisions(spark, sf):
    """How many children of each level bounds decide, by case, and how many are counted."""
    return mining.mine_correlation(v1(spark, sf), max_order=3).report().withColumn("decided_by_bound", F.to_json("decided_by_bound"))


@query("q_tree_vs_definition", "select cast(count(*) as bigint) as differences from range(0)")
def q_tree_vs_definition(spark, sf):
    """In pure epistasis the tree rule and the definition give the same sets in every data set."""
    frame = planted.epistasis(spark, sf, None)
    keys = ["g", "members", "kind"]
    tree, whole = (materialize(mining.mine_each(frame, max_order=3, rule=rule).select(*keys), f"{rule}-sets") for rule in ("tree", "definition"))
    return tree.exceptAll(whole).unionByName(whole.exceptAll(tree)).agg(F.count("*").alias("differences"))


@query("q_siblings_same_result", "select cast(count(*) as bigint) as differences from range(0)")
def q_siblings_same_result(spark, sf):
    """Sibling bounds change no result, in any data set of noisy exclusive-or."""
    frame = planted.noisy_xor(spark, sf, None)
    keys = ["g", "members", "kind"]
    with_siblings, plain = (materialize(mining.mine_each(frame, max_order=4, **options).select(*keys), "found-sets") for options in ({"siblings": True}, {"bounds": False}))
    return with_siblings.exceptAll(plain).unionByName(plain.exceptAll(with_siblings)).agg(F.count("*").alias("differences"))


# --- interactions and permutations ---------------------------------------------------------------------------------


@query("q_ii_mine", ii_sql(list(combinations((1, 6, 7, 8), 2)) + list(combinations((1, 6, 7, 8), 3))))
def q_ii_mine(spark, sf):
    return named(interactions.mine(v1(spark, sf), [1, 6, 7, 8], 3), "ii")


@query("q_ii_mine_sweep", ii_sql(list(combinations((1, 6, 7, 8), 2)) + list(combinations((1, 6, 7, 8), 3))))
def q_ii_mine_sweep(spark, sf):
    return named(interactions.mine(v1(spark, sf), [1, 6, 7, 8], 3, method="sweep"), "ii")


@query("q_ii_mine_class", ii_sql([tuple(sorted((C0, *s))) for k in (1, 2) for s in combinations((1, 7, 8), k)]))
def q_ii_mine_class(spark, sf):
    return named(interactions.mine(v1_class(spark, sf), [0, 1, 7, 8], 2), "ii")


# --- baselines and measures ------------------------------------------------------------------------------------


_inside = ", ".join(f"('{name_of(s)}', '{name_of(t)}')" for s in TRIPLES for t in combinations(s, 2))


@query(
    "q_hard_threshold",
    f"""with q as ({tc_sql(PAIRS + TRIPLES).replace('round(sum_h - h, 6) + 0.0 as tc', 'sum_h - h as tc')}), sub(set_id, t) as (values {_inside}),
 open as (select sub.set_id from sub join q on q.set_id = sub.t group by sub.set_id having max(tc) <= 0.0049)
select set_id, {r6('tc')} as bits from q where tc >= 0.005 and (length(set_id) = 3 or set_id in (select set_id from open))""",
)
def q_hard_threshold(spark, sf):
    """Low cut-offs, so that the natural view has a strong pair; supersets of it are not explored."""
    return baselines.hard_threshold(v1(spark, sf), alpha=0.0049, beta=0.005, max_order=3).select(set_id(F.col("members")).alias("set_id"), rounded(F.col("bits")).alias("bits"))


# --- views, treatment of gaps, streams -----------------------------------------------------------------------------


def _view_tc(view: str):
    names = views.VIEWS[view][0]
    pairs = list(combinations(range(len(names)), 2))
    singles = [(i,) for i in range(len(names))]
    members = ", ".join(f"('{name_of(s)}', '{i}')" for s in pairs for i in s)
    sql = f"""with {entropy_cte(views.view_sql(view), names, singles + pairs)}, m(set_id, i) as (values {members}), t as (select m.set_id, sum(h) as sum_h from m join e on e.set_id = m.i group by m.set_id)
select set_id, {r6('sum_h - h')} as tc from t join e using (set_id)"""

    def run(spark, sf):
        frame = views.frame(spark, sf, view)
        return named(metrics.total_correlation(counts.entropies(frame, singles + pairs), metrics.table(frame, pairs)), "tc")

    return run, sql


for _view in ("star", "part", "documents", "events"):
    QUERIES[f"q_{_view}_view"], ORACLES[f"q_{_view}_view"] = _view_tc(_view)


@query(
    "q_embedding_signs",
    f"""with x as (select vec_id, label, i, cast(embedding[i + 1] >= 0 as int) as bit from embeddings cross join range(0, 58) r(i)),
 hl as (select log2(sum(n)) - sum(n * log2(n)) / sum(n) as h from (select label, count(*) as n from embeddings group by label)),
 hb as (select i, log2(sum(n)) - sum(n * log2(n)) / sum(n) as h from (select i, bit, count(*) as n from x group by 1, 2) group by i),
 hj as (select i, log2(sum(n)) - sum(n * log2(n)) / sum(n) as h from (select i, bit, label, count(*) as n from x group by 1, 2, 3) group by i)
select i || ',58' as set_id, {r6('hb.h + hl.h - hj.h')} as mi from hb join hj using (i) cross join hl""",
)
def q_embedding_signs(spark, sf):
    frame = views.embedding_signs(spark, sf, 58)
    sets = [(i, frame.class_at) for i in frame.predictors]
    return named(metrics.mutual_information(counts.entropies(frame, [*[(i,) for i in range(len(frame.names))], *sets]), metrics.table(frame, sets)), "mi")


@query(
    "q_impute_mode",
    """with n as (select o_orderkey, case when o_orderkey % 7 = 0 then null else o_orderstatus end as status, case when o_orderkey % 5 = 0 then null else o_orderpriority end as priority from orders),
 a as (select status from n where status is not null group by 1 order by count(*) desc, 1 limit 1), b as (select priority from n where priority is not null group by 1 order by count(*) desc, 1 limit 1)
select coalesce(n.status, a.status) as status, coalesce(n.priority, b.priority) as priority, count(*) as n from n cross join a cross join b group by 1, 2""",
)
def q_impute_mode(spark, sf):
    orders = spark.read.parquet(f"{sf}/orders.parquet")
    gaps = orders.select(F.when(F.col("o_orderkey") % 7 != 0, F.col("o_orderstatus")).alias("status"), F.when(F.col("o_orderkey") % 5 != 0, F.col("o_orderpriority")).alias("priority"))
    return discretize.impute_mode(gaps, ["status", "priority"]).groupBy("status", "priority").agg(F.count("*").alias("n"))


@query(
    "q_bins",
    """select cast(floor(l_quantity / 10.001e0) as int) as width, cast((l_extendedprice >= 1000) as int) + cast((l_extendedprice >= 30000) as int) + cast((l_extendedprice >= 60000) as int) as edge,
 case when l_linenumber in (select l_linenumber from lineitem group by 1 order by count(*) desc, l_linenumber limit 3) then l_linenumber else -1 end as top, count(*) as n
from lineitem group by 1, 2, 3""",
)
def q_bins(spark, sf):
    line = spark.read.parquet(f"{sf}/lineitem.parquet").select("l_quantity", "l_extendedprice", "l_linenumber")
    top = discretize.top_values(line, "l_linenumber", 3, "top", -1)
    binned = top.select(discretize.equal_width(F.col("l_quantity"), 10.001).alias("width"), discretize.explicit_edges(F.col("l_extendedprice"), (1000, 30000, 60000)).alias("edge"), F.col("top").cast("int").alias("top"))
    return binned.groupBy("width", "edge", "top").agg(F.count("*").alias("n"))


@query(
    "q_windowed_tc",
    f"""with x as (select date_trunc('day', ts) as w, event_type as a, cast(floor(hour(ts) / 6e0) as int) as b from events),
 c as (select w, 'a' as s, a as v, count(*) as n from x group by all union all select w, 'b', cast(b as varchar), count(*) from x group by all union all select w, 'ab', a || '|' || b, count(*) from x group by all),
 h as (select w, s, log2(sum(n)) - sum(n * log2(n)) / sum(n) as h, sum(n) as n from c group by w, s)
select w as window_start, cast(max(n) as bigint) as n, {r6("sum(case when s = 'ab' then -h else h end)")} as tc from h group by w""",
)
def q_windowed_tc(spark, sf):
    from assocmine.streaming import windows

    events = spark.read.parquet(f"{sf}/events.parquet")
    attributes = {"a": F.col("event_type"), "b": F.floor(F.hour("ts") / 6)}
    cells = windows.cell_counts(events, attributes, [("a",), ("b",), ("a", "b")])
    return windows.window_tc(cells).select("window_start", "n", rounded(F.col("tc")).alias("tc"))


@query(
    "q_sessions",
    """with x as (select *, case when ts - lag(ts) over (partition by user_id order by ts) < interval 30 minutes then 0 else 1 end as fresh from events),
 y as (select *, sum(fresh) over (partition by user_id order by ts rows unbounded preceding) as nth from x)
select user_id, min(ts) as session_start, max(ts) + interval 30 minutes as session_end, count(*) as events, min(event_type) as event_type from y group by user_id, nth""",
)
def q_sessions(spark, sf):
    from assocmine.streaming import windows

    return windows.session_counts(spark.read.parquet(f"{sf}/events.parquet"), "user_id", {"event_type": F.col("event_type")})


@query("q_stream_tc", ORACLES["q_windowed_tc"])
def q_stream_tc(spark, sf):
    """Windowed TC by a stream over the events, run until all of them are read."""
    from assocmine.streaming import windows

    attributes = {"a": F.col("event_type"), "b": F.floor(F.hour("ts") / 6)}
    cells = windows.run_to_end(windows.cell_counts(windows.event_stream(spark, f"{sf}/events.parquet"), attributes, [("a",), ("b",), ("a", "b")]), "complete")
    return windows.window_tc(cells).select("window_start", "n", rounded(F.col("tc")).alias("tc"))


@query("q_stream_drift", f"with w as ({ORACLES['q_windowed_tc']}), x as (select window_start, tc, lag(tc) over (order by window_start) as before from w) select window_start, before, tc, coalesce(abs(tc - before) > 0.01, false) as drift from x")
def q_stream_drift(spark, sf):
    """Windows whose TC moved by more than 0.01 bits since the window before, by a stream with state."""
    from assocmine.streaming import windows

    tc = materialize(q_stream_tc(spark, sf).withColumn("set_id", F.lit("a,b")), "window-tc")
    stream = spark.readStream.schema(tc.schema).parquet(tc.inputFiles()[0].rsplit("/", 1)[0])
    return windows.run_to_end(windows.drift(stream, 0.01), "append").select("window_start", rounded(F.col("before")).alias("before"), "tc", "drift")


@query("q_association_scan", tc_sql([s for s in combinations((0, 1, 8), 2)]))
def q_association_scan(spark, sf):
    """The SQL table function over collapsed rows of three attributes; names are positions in the handed-in array."""
    from assocmine.functions import udfs

    udfs.register(spark)
    frame = v1(spark, sf).select([0, 1, 8]).collapse()
    frame.rows.select(F.explode(F.array_repeat("a", F.col("w").cast("int"))).alias("codes")).coalesce(1).createOrReplaceTempView("v1_codes")
    out = spark.sql("select * from association_scan(table(select codes, 2 as max_order from v1_codes) with single partition)")
    real = F.create_map(*[F.lit(x) for x in ("0,1", "0,1", "0,2", "0,8", "1,2", "1,8")])
    return out.select(real[F.col("set_id")].alias("set_id"), rounded(F.col("tc")).alias("tc"))


QUERIES |= experiments.QUERIES
ORACLES |= experiments.ORACLES
flagship = experiments.flagship
