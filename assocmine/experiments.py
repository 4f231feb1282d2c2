"""The experiments as queries, each over every data set that the whole table gives (see ``planted``), and their oracles."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from assocmine import oracle as o
from assocmine.functions.expressions import rounded, set_id
from assocmine.operators import baselines, evaluation, interactions, metrics, mining, permutation, redundancy
from assocmine.plans import counts
from assocmine.plans.materialize import materialize
from assocmine.sources import planted

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql is not None:
            ORACLES[name] = sql
        return f

    return add


def r6(x: str) -> str:
    return f"round({x}, 6) + 0.0"


def listed(found: DataFrame) -> DataFrame:
    return found.select("g", set_id(F.col("members")).alias("set_id"), "kind", rounded(F.col("bits")).alias("bits"))


def search_sql(data: str, lattice: o.Lattice) -> str:
    return f"with {data},\n {lattice.search()}\nselect g, set_id, kind, {r6('bits')} as bits from found"


def threshold_sql(data: str, lattice: o.Lattice) -> str:
    return f"with {data},\n {lattice.hard_threshold()}\nselect g, set_id, {r6('bits')} as bits from found"


def closed(lattice: o.Lattice, sets) -> o.Lattice:
    """The lattice of the given sets and all their subsets: enough to say whether the search reaches them."""
    from itertools import combinations

    lattice.sets = sorted({t for s in sets for k in range(1, len(s) + 1) for t in combinations(s, k)}, key=lambda s: (len(s), s))
    lattice.order = max(map(len, lattice.sets))
    return lattice


# --- without class: noisy exclusive-or, pure epistasis ---------------------------------------------------------------


@query("q_mine_tree", search_sql(o.xor_cte((1,)), o.F1))
def q_mine_tree(spark, sf):
    """All sets found in noisy exclusive-or at flip probability 0.1."""
    return listed(mining.mine_each(planted.noisy_xor(spark, sf, None)).withColumn("g", F.col("g") + F.lit(planted.LEVEL)))


XOR_FAMILY = closed(o.Lattice((2,) * 15, 200, 5), o.XOR_SETS)
PARTNERS = {s[0]: s[1:] for s in o.XOR_SETS}
_sets = o.values((o.name_of(s),) for s in o.XOR_SETS)
_noise = "[" + ", ".join(f"{x}e0" for x in o.NOISE) + "][cast(g // 1000000000000 as int) + 1]"
NOISE_SQL = f"""with {o.xor_cte()}, groups as (select distinct g from d), want(set_id) as (values {_sets}),
a as (with {XOR_FAMILY.search()} select 'search' as method, g, set_id from found semi join want using (set_id)),
b as (with {XOR_FAMILY.hard_threshold()} select 'hard threshold' as method, g, set_id from found semi join want using (set_id)),
c as (with {o.selector(15, {t: len(p) for t, p in PARTNERS.items()})} select 'relevance selector' as method, g, string_agg(cast(i as varchar), ',' order by i) as set_id from (select g, target, i from chosen union all select distinct g, target, target from chosen) group by g, target),
hit as (select * from a union all select * from b union all select c.* from c semi join want using (set_id)),
methods(method) as (values ('search'), ('hard threshold'), ('relevance selector')),
per as (select method, g, (select count(*) from want) as planted, count(hit.set_id) as found from methods cross join groups left join hit using (method, g) group by method, g)
select method, {_noise} as noise, {r6('avg(found / planted)')} as detected, count(*) as data_sets from per group by 1, 2"""


def _shares(found: DataFrame, groups: DataFrame, method: str) -> DataFrame:
    per = evaluation.detection_rate(found, planted.XOR_TRUTH, groups)
    level = F.array(*map(F.lit, planted.NOISE))[F.floor(F.col("g") / planted.LEVEL).cast("int")]
    return per.groupBy(F.lit(method).alias("method"), level.alias("noise")).agg(rounded(F.avg("detected")).alias("detected"), F.count("*").alias("data_sets"))


@query("q_noise_curve", NOISE_SQL)
def q_noise_curve(spark, sf):
    """Share of the planted sets that search, fixed cut-offs and selector find at every flip probability."""
    frame = planted.noisy_xor(spark, sf, None, planted.NOISE)
    groups = materialize(frame.rows.select("g").distinct(), "groups")
    chosen = baselines.relevance_targets(frame, {t: len(p) for t, p in PARTNERS.items()})
    at = F.create_map(*[x for t in PARTNERS for x in (F.lit(frame.names[t]), F.lit(t))])[F.col("target")]
    sets = chosen.groupBy("g", "target").agg(F.array_sort(F.array_append(F.collect_list("idx"), F.first(at))).alias("members"))
    methods = (("search", mining.mine_each(frame)), ("hard threshold", baselines.hard_threshold_each(frame)), ("relevance selector", sets))
    parts = [_shares(materialize(found.select("g", "members"), "found-sets"), groups, name) for name, found in methods]
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


@query("q_hard_threshold_xor", threshold_sql(o.xor_cte((0,)), o.Lattice((2,) * 15, 200, 4)))
def q_hard_threshold_xor(spark, sf):
    """Without noise the fixed cut-offs find the planted sets."""
    return baselines.hard_threshold_each(planted.noisy_xor(spark, sf, None, (0.0,))).select("g", set_id(F.col("members")).alias("set_id"), rounded(F.col("bits")).alias("bits"))


@query("q_false_rates")
def q_false_rates(spark, sf):
    """Share of reported sets that were not planted, for search and fixed cut-offs at every flip probability."""
    frame = planted.noisy_xor(spark, sf, None, planted.NOISE)
    groups = materialize(frame.rows.select("g").distinct(), "groups")
    out = None
    for name, found in (("search", mining.mine_each(frame)), ("hard threshold", baselines.hard_threshold_each(frame))):
        rates = evaluation.false_rate(materialize(found.select("g", "members"), "found-sets"), planted.XOR_TRUTH, groups)
        level = F.array(*map(F.lit, planted.NOISE))[F.floor(F.col("g") / planted.LEVEL).cast("int")]
        one = rates.groupBy(F.lit(name).alias("method"), level.alias("noise")).agg(rounded(F.avg("false_rate")).alias("false_rate"), F.count("*").alias("data_sets"))
        out = one if out is None else out.unionByName(one)
    return out


@query("q_mine_epistasis", search_sql(o.epistasis_cte(), o.F2))
def q_mine_epistasis(spark, sf):
    return listed(mining.mine_each(planted.epistasis(spark, sf, None)))


@query("q_mine_strong_pair", search_sql(o.epistasis_cte(True), o.F2))
def q_mine_strong_pair(spark, sf):
    return listed(mining.mine_each(planted.epistasis(spark, sf, None, strong=True)))


@query("q_hard_threshold_strong_pair", threshold_sql(o.epistasis_cte(True), o.F2))
def q_hard_threshold_strong_pair(spark, sf):
    """The strong pair without its extension, which the search finds."""
    return baselines.hard_threshold_each(planted.epistasis(spark, sf, None, strong=True)).select("g", set_id(F.col("members")).alias("set_id"), rounded(F.col("bits")).alias("bits"))


@query("q_extension_sets", search_sql(o.epistasis_cte(), o.F2) + " where kind = 'extension'")
def q_extension_sets(spark, sf):
    """Extension sets, judged by the gain over their one strong subset."""
    return listed(mining.mine_each(planted.epistasis(spark, sf, None)).filter("kind = 'extension'"))


# --- with class --------------------------------------------------------------------------------------------------------


@query("q_class_mine", search_sql(o.gain_cte(), o.F3))
def q_class_mine(spark, sf):
    return listed(mining.mine_each(planted.class_gain(spark, sf, None), "cac"))


@query("q_class_mine_pairs_first", search_sql(o.gain_cte(), o.F3_PAIRS))
def q_class_mine_pairs_first(spark, sf):
    """The literal variant, which begins with two predictors and the class."""
    return listed(mining.mine_each(planted.class_gain(spark, sf, None), "cac", first_order=2))


@query("q_hard_threshold_class", threshold_sql(o.gain_cte(), o.Lattice((*o.TERNARY, 2), 600, 3)))
def q_hard_threshold_class(spark, sf):
    """Fixed cut-offs with the class as one more attribute find nothing here."""
    return baselines.hard_threshold_each(planted.class_gain(spark, sf, None), max_order=3).select("g", set_id(F.col("members")).alias("set_id"), rounded(F.col("bits")).alias("bits"))


@query("q_class_mine_copies", search_sql(o.copies_cte(), o.F4))
def q_class_mine_copies(spark, sf):
    """Every data set is reduced by its own representatives; the copies go, and the planted sets are found."""
    return listed(mining.mine_each(planted.class_copies(spark, sf, None), "cac", delta=redundancy.DELTA))


@query("q_class_mine_unreduced", search_sql(o.copies_cte(), o.Lattice((*o.TERNARY, 2), 1600, 3, 15)))
def q_class_mine_unreduced(spark, sf):
    """The same without removal of redundant attributes, up to three predictors: copies join the reported sets."""
    return listed(mining.mine_each(planted.class_copies(spark, sf, None), "cac", max_order=3))


@query("q_hard_threshold_copies", threshold_sql(o.copies_cte(), o.Lattice((*o.TERNARY, 2), 1600, 3)))
def q_hard_threshold_copies(spark, sf):
    """Up to order three: only copies with their originals reach the fixed cut-off."""
    return baselines.hard_threshold_each(planted.class_copies(spark, sf, None), max_order=3).select("g", set_id(F.col("members")).alias("set_id"), rounded(F.col("bits")).alias("bits"))


_pairs = [(i, j) for i in range(15) for j in range(i + 1, 15)]
COVERS = f"""{o.copies_cte()}, {o.entropies([o.mask(s) for s in [*((i,) for i in range(15)), *_pairs]])},
 p(mask, i, j, mi, mj) as (values {o.values((o.mask(s), *s, o.mask(s[:1]), o.mask(s[1:])) for s in _pairs)}),
 s as (select e.g, p.i, p.j, -(x.h + y.h - e.h) / least(x.h, y.h) as score from e join p on p.mask = e.mask join e x on x.g = e.g and x.mask = p.mi join e y on y.g = e.g and y.mask = p.mj),
 b as (select g, i as rep, j as x from s where score <= -0.75 union select g, j, i from s where score <= -0.75 union select g, i, i from (select distinct g from s) cross join range(0, 15) r(i)),
 cov as (select g, cast(rep as int) as rep, string_agg(cast(x as varchar), ',' order by x) as covered, min(x) as least from b group by g, rep)"""


@query("q_cover_groups", f"with {COVERS} select g, rep, covered from cov")
def q_cover_groups(spark, sf):
    frame = planted.class_copies(spark, sf, None)
    scored = materialize(redundancy.scores(frame, redundancy.pair_entropies(frame)), "scores")
    return redundancy.covers(frame, scored).select("g", "rep", set_id(F.col("covered")).alias("covered"))


@query("q_reduce", f"with {COVERS} select g, rep, covered from cov where rep = least")
def q_reduce(spark, sf):
    """Greedy representatives of every data set. Cover groups here do not overlap, so each group's smallest member is chosen."""
    return redundancy.representatives_each(planted.class_copies(spark, sf, None)).select("g", "rep", set_id(F.col("covered")).alias("covered"))


def rates_sql() -> str:
    """Detection of each planted set and the share of false sets, by workload."""
    parts = []
    for name, data, lattice, truth in (
        ("epistasis", o.epistasis_cte(), o.F2, ("0,1", "0,1,15")), ("strong pair", o.epistasis_cte(True), o.F2, ("0,1", "0,1,15")),
        ("class gain", o.gain_cte(), o.F3, ("0", "0,1")), ("class copies", o.copies_cte(), o.F4, ("0", "2", "0,1")),
    ):
        want = o.values((t,) for t in truth)
        parts.append(
            f"""select * from (with {data}, {lattice.search()}, want(set_id) as (values {want}), groups as (select count(distinct g) as n from d),
 wrong as (select avg(r) as false_rate from (select g, coalesce(avg(case when f.set_id is null then null when w.set_id is null then 1 else 0 end), 0) as r from (select distinct g from d) left join found f using (g) left join want w using (set_id) group by g))
 select '{name}' as workload, want.set_id, {r6('count(found.g) / any_value(groups.n)')} as detected, {r6('any_value(wrong.false_rate)')} as false_rate, any_value(groups.n) as data_sets from want cross join groups cross join wrong left join found using (set_id) group by want.set_id)"""
        )
    return " union all ".join(parts)


@query("q_detection_rate", rates_sql())
def q_detection_rate(spark, sf):
    """Detection ability and false sets of the four workloads that are mined whole."""
    out = None
    for name, frame, mode, delta, truth in (
        ("epistasis", planted.epistasis(spark, sf, None), "tc", None, ((0, 1), (0, 1, 15))), ("strong pair", planted.epistasis(spark, sf, None, True), "tc", None, ((0, 1), (0, 1, 15))),
        ("class gain", planted.class_gain(spark, sf, None), "cac", None, ((0,), (0, 1))), ("class copies", planted.class_copies(spark, sf, None), "cac", redundancy.DELTA, ((0,), (2,), (0, 1))),
    ):
        found = materialize(mining.mine_each(frame, mode, delta=delta).select("g", "members"), "found-sets")
        groups = materialize(frame.rows.select("g").distinct(), "groups")
        n = groups.count()
        wrong = evaluation.false_rate(found, truth, groups).agg(F.avg("false_rate")).first()[0] or 0.0  # one number a workload
        want = spark.createDataFrame([(list(t),) for t in truth], "members array<int>")
        hits = want.join(found.groupBy("members").agg(F.count("*").alias("k")), "members", "left")
        one = hits.select(F.lit(name).alias("workload"), set_id(F.col("members")).alias("set_id"), rounded(F.coalesce("k", F.lit(0)) / max(1, n)).alias("detected"), rounded(F.lit(float(wrong))).alias("false_rate"), F.lit(n).cast("long").alias("data_sets"))
        out = one if out is None else out.unionByName(one)
    return out


# --- the selector and weak information of planted attributes -----------------------------------------------------------


def selector_sql(data: str, targets: dict[int, int], form: str = "difference", score: bool = True) -> str:
    score_column = f", {r6('score')} as score" if score else ""
    return f"with {data},\n {o.selector(16, targets, form=form)}\nselect g, cast(rank as int) as rank, case when i = 15 then 't' else 'a' || (i + 1) end as attribute, {r6('relevance')} as relevance{score_column} from chosen"


@query("q_relevance_redundancy", selector_sql(o.copies_cte(), {15: 3}))
def q_relevance_redundancy(spark, sf):
    return baselines.relevance_redundancy(planted.class_copies(spark, sf, None)).select("g", "rank", "attribute", rounded(F.col("relevance")).alias("relevance"), rounded(F.col("score")).alias("score"))


@query("q_relevance_redundancy_quotient", selector_sql(o.gain_cte(), {15: 2}, "quotient", score=False))
def q_relevance_redundancy_quotient(spark, sf):
    return baselines.relevance_redundancy(planted.class_gain(spark, sf, None), n_select=2, form="quotient").select("g", "rank", "attribute", rounded(F.col("relevance")).alias("relevance"))


@query("q_relevance_targets", f"with {o.xor_cte((0,))},\n {o.selector(15, {t: len(p) for t, p in PARTNERS.items()})}\nselect g, 'a' || (target + 1) as target, cast(rank as int) as rank, 'a' || (i + 1) as attribute, {r6('relevance')} as relevance from chosen")
def q_relevance_targets(spark, sf):
    """One run for each planted target of noisy exclusive-or as the class, without noise."""
    frame = planted.noisy_xor(spark, sf, None, (0.0,))
    return baselines.relevance_targets(frame, {t: len(p) for t, p in PARTNERS.items()}).select("g", "target", "rank", "attribute", rounded(F.col("relevance")).alias("relevance"))


_weak = [(i, 15) for i in (0, 1, 2)]
INFORMATION_SQL = " union all ".join(
    f"""select '{name}' as workload, set_id, {r6('avg(mi)')} as mi, count(*) as data_sets from (with {data}, {o.entropies([o.mask(s) for s in [(0,), (1,), (2,), (15,), *_weak]])},
 p(mask, set_id, mi_, mc) as (values {o.values((o.mask(s), o.name_of(s), o.mask(s[:1]), o.mask(s[1:])) for s in _weak)}) select e.g, p.set_id, x.h + y.h - e.h as mi from e join p on p.mask = e.mask join e x on x.g = e.g and x.mask = p.mi_ join e y on y.g = e.g and y.mask = p.mc) group by set_id"""
    for name, data in (("epistasis", o.epistasis_cte()), ("class gain", o.gain_cte()), ("class copies", o.copies_cte()))
)


@query("q_planted_information", INFORMATION_SQL)
def q_planted_information(spark, sf):
    """Mean mutual information of the planted attributes with the trait or class: weak, as the experiments need."""
    out = None
    for name, frame in (("epistasis", planted.epistasis(spark, sf, None)), ("class gain", planted.class_gain(spark, sf, None)), ("class copies", planted.class_copies(spark, sf, None))):
        mi = metrics.mutual_information(counts.entropies(frame, [(0,), (1,), (2,), (15,), *_weak]), metrics.table(frame, _weak))
        one = mi.groupBy(F.lit(name).alias("workload"), set_id(F.col("s")).alias("set_id")).agg(rounded(F.avg("mi")).alias("mi"), F.count("*").alias("data_sets"))
        out = one if out is None else out.unionByName(one)
    return out


# --- significance of interactions --------------------------------------------------------------------------------------


def naive_sql(nperm: int) -> str:
    parts = {"a1": 1, "a2": 1, "x": 1, "a1 * 3 + a2": -1, "a1 * 3 + x": -1, "a2 * 3 + x": -1, "(a1 * 3 + a2) * 3 + x": 1}
    union = " union all ".join(f"select g, perm, {k} as part, {sign} as sign, {expr} as v, count(*) as n from m group by all" for k, (expr, sign) in enumerate(parts.items()))
    return f"""with {o.copies_cte()}, b as (select g, key, a1, a2, c, row_number() over (partition by g order by key) as rank from kept),
 p as (select b.*, perm from b cross join range(0, {nperm + 1}) r(perm)),
 q as (select g, perm, c as x, row_number() over (partition by g, perm order by case when perm = 0 then '' else md5('0:' || perm || ':' || key) end, key) as rank from p),
 m as (select p.g, p.perm, a1, a2, x from p join q using (g, perm, rank)),
 h as (select g, perm, part, sign, log2(sum(n)) - sum(n * log2(n)) / sum(n) as h from ({union}) group by 1, 2, 3, 4)
select g, cast(perm as int) as perm, {r6('-sum(sign * h)')} as ii from h group by g, perm"""


@query("q_perm_naive", naive_sql(4))
def q_perm_naive(spark, sf):
    frame = planted.class_copies(spark, sf, None)
    return permutation.naive_values(frame, (0, 1, frame.class_at), 4).select("g", "perm", rounded(F.col("ii")).alias("ii"))


@query("q_perm_fast")
def q_perm_fast(spark, sf):
    """p of four sets with the class in every data set, by 10,000 draws that end early where p is not small."""
    frame = planted.class_copies(spark, sf, None)
    c = frame.class_at
    out = permutation.fast(frame, [(0, c), (1, c), (0, 1, c), (0, 1, 2, c)], 10_000, early_stop=0.05)
    return out.select("g", set_id(F.col("s")).alias("set_id"), rounded(F.col("ii")).alias("ii"), (F.col("p") < 1e-4).alias("significant"), "nperm", "cells_touched")


_xor_pairs = [(0, 1), (0, 2), (5, 6), (10, 14)]
EXACT_SQL = f"""with {o.xor_cte((1,))}, p(set_id, i, j) as (values {o.values((o.name_of(s), *s) for s in _xor_pairs)}),
 t as (select g, set_id, sum((code >> (2 * i)) & 1) as r, sum((code >> (2 * j)) & 1) as c, sum(((code >> (2 * i)) & 1) * ((code >> (2 * j)) & 1)) as k, count(*) as n from d cross join p group by g, set_id),
 x as (select t.*, v from t cross join range(0, 201) q(v) where v >= greatest(0, r + c - n) and v <= least(r, c)),
 y as (select *, list_sum([case when z > 0 then z * log2(z) else 0 end for z in [v, r - v, c - v, n - r - c + v]]) as cells, list_sum([case when z > 0 then z * log2(z) else 0 end for z in [k, r - k, c - k, n - r - c + k]]) as own,
  lgamma(r + 1) - lgamma(v + 1) - lgamma(r - v + 1) + lgamma(n - r + 1) - lgamma(c - v + 1) - lgamma(n - r - c + v + 1) - lgamma(n + 1) + lgamma(c + 1) + lgamma(n - c + 1) as chance from x)
select g, set_id, {r6('sum(case when cells >= own - 1e-9 then exp(chance) else 0 end)')} as p, true as draws_agree from y group by g, set_id"""


@query("q_perm_exact", EXACT_SQL)
def q_perm_exact(spark, sf):
    """Exact p of pairs by enumeration, and whether 2,000 draws come within five standard errors of it."""
    frame = planted.noisy_xor(spark, sf, None)
    drawn = permutation.fast(frame, _xor_pairs, 2_000).select("g", "s", F.col("p").alias("q"))
    both = permutation.exact_pairs(frame, _xor_pairs).join(drawn, ["g", "s"])
    near = F.abs(F.col("p") - F.col("q")) <= 5 * F.sqrt(F.greatest(F.col("p") * (1 - F.col("p")), F.lit(1e-3)) / 2_000)
    return both.select((F.col("g") + F.lit(planted.LEVEL)).alias("g"), set_id(F.col("s")).alias("set_id"), rounded(F.col("p")).alias("p"), near.alias("draws_agree"))


@query("q_ii_significant")
def q_ii_significant(spark, sf):
    """The two-step strategy on noisy exclusive-or at 0.1: how many data sets have a set among their significant II, 10,000 draws at 1e-4."""
    frame = planted.noisy_xor(spark, sf, None)
    found = interactions.pipeline_each(frame, delta=None)
    return found.groupBy(set_id(F.col("s")).alias("set_id")).agg(F.count("*").alias("data_sets"), rounded(F.avg("ii"), 4).alias("mean_ii"))


@query("q_spectrum", f"with {o.epistasis_cte()},\n {o.F2.zones()}\nselect g, set_id, {r6('bits')} as bits, zone from z where zone <> 'WEAK'")
def q_spectrum(spark, sf):
    """TC of every set of two and three attributes that is not weak, in all data sets of pure epistasis."""
    frame = planted.epistasis(spark, sf, None)
    sets = [s for s in metrics.all_sets(range(16), 2, 3) if counts.cells_of(frame, s) * 5 <= frame.n]
    return mining.zones_each(frame, sets).select("g", set_id(F.col("s")).alias("set_id"), rounded(F.col("bits")).alias("bits"), "zone")


# --- run time of the prunings, and the case study ----------------------------------------------------------------------

REMOVALS, REPEATS = (10, 20, 30, 40), 10


def cost(runs: DataFrame) -> DataFrame:
    """Means over the repeats, without the seconds, which differ from run to run."""
    return runs.groupBy("prune", "attributes").agg(
        F.count("*").alias("runs"), rounded(F.avg("after_redundancy"), 4).alias("after_redundancy"), rounded(F.avg("children"), 4).alias("children"), rounded(F.avg("exact"), 4).alias("exact"),
        rounded(F.avg("sets"), 4).alias("sets"), rounded(F.avg("interactions"), 4).alias("interactions"),
    )


@query("q_pruning_modes")
def q_pruning_modes(spark, sf):
    """Search and interaction miner under the four choices of prunings, 58 attributes less 10 to 40, without class."""
    return cost(evaluation.runtime_curve(planted.runtime_small(spark, sf, None), REMOVALS, REPEATS))


@query("q_pruning_modes_class")
def q_pruning_modes_class(spark, sf):
    return cost(evaluation.runtime_curve(planted.runtime_small(spark, sf, None), REMOVALS, REPEATS, "cac"))


@query("q_runtime_large")
def q_runtime_large(spark, sf):
    """The same for 103 attributes."""
    return cost(evaluation.runtime_curve(planted.runtime_large(spark, sf, None), REMOVALS, REPEATS))


@query("q_runtime_large_class")
def q_runtime_large_class(spark, sf):
    return cost(evaluation.runtime_curve(planted.runtime_large(spark, sf, None), REMOVALS, REPEATS, "cac", timed=False))


@query("q_runtime_seconds")
def q_runtime_seconds(spark, sf):
    """Mean seconds of search and interaction miner by choice of prunings and number of attributes, 58 attributes less 10 to 40."""
    runs = evaluation.runtime_curve(planted.runtime_small(spark, sf, None), REMOVALS, REPEATS)
    return runs.groupBy("prune", "attributes").agg(F.avg("seconds").alias("seconds"), F.count("*").alias("runs"))


@query("q_pruning_same_sets", "select cast(count(*) as bigint) as differences from range(0)")
def q_pruning_same_sets(spark, sf):
    """Bounds change no result: runs that differ in nothing else find the same sets."""
    runs = materialize(evaluation.runtime_curve(planted.runtime_small(spark, sf, None), REMOVALS, REPEATS, "cac", timed=False), "runs")
    key = ["removed", "rep", "reduced"]
    plain, bounded = (runs.filter(F.col("prune").isin(*names)).select("removed", "rep", (F.col("prune").isin("redundancy", "both")).alias("reduced"), F.col("members").alias(out)) for names, out in ((("none", "redundancy"), "a"), (("bounds", "both"), "b")))
    return plain.join(bounded, key, "full").filter(~F.col("a").eqNullSafe(F.col("b"))).agg(F.count("*").alias("differences"))


@query("q_case_study")
def q_case_study(spark, sf):
    """Both analyses of the case study: sets with significant II, sets that covered attributes form in place of their
    representatives, and how many of the two planted attributes are found, themselves or by a cover group."""
    whole_frame = planted.case_study(spark, sf)
    out = None
    for mode in ("tc", "cac"):
        frame = whole_frame if mode == "cac" else whole_frame.select(list(whole_frame.predictors))
        found, significant, groups = interactions.pipeline(frame, mode, alpha_high=1e-4)
        reduced = redundancy.apply(frame, groups)
        significant = materialize(significant, "significant")
        sets = [tuple(r["s"]) for r in significant.select("s").collect()]
        back = interactions.recover(frame, reduced, sets, groups)
        names, short = F.array(*[F.lit(n) for n in frame.names]), F.array(*[F.lit(n) for n in reduced.names])
        spell = lambda s, table: F.array_join(F.transform(s, lambda i: F.element_at(table, i + 1)), ",")
        rows = significant.select(F.lit(mode).alias("analysis"), F.lit("significant").alias("step"), spell(F.col("s"), short).alias("members"), rounded(F.col("ii")).alias("value"))
        rows = rows.unionByName(back.select(F.lit(mode).alias("analysis"), F.lit("recovered").alias("step"), spell(F.col("s"), names).alias("members"), rounded(F.col("ii")).alias("value")))
        index = [frame.names.index(n) for n in reduced.names]
        at = F.create_map(*[x for k, i in enumerate(index) for x in (F.lit(k), F.lit(i))])
        whole = significant.select("g", F.transform("s", lambda i: at[i]).alias("s")).unionByName(back.select("g", "s"))
        leaders = [frame.names.index(n) for n in ("a1", "a5") if n in frame.names]
        count = evaluation.recovered(whole, leaders)
        rows = rows.unionByName(count.select(F.lit(mode).alias("analysis"), F.lit("planted attributes found").alias("step"), F.lit("").alias("members"), F.col("recovered").cast("double").alias("value")))
        out = rows if out is None else out.unionByName(rows)
    return out


@query("q_scale_sweep")
def q_scale_sweep(spark, sf):
    """Cells and sets of the star view by number of attributes, all pairs: what grows with attributes is the work, not the rows shuffled."""
    from assocmine.sources import views

    frame = views.frame(spark, sf, "star")
    out = None
    for k in range(5, len(frame.names) + 1):
        ent = counts.entropies(frame.select(list(range(k))), metrics.all_sets(range(k), 1, 2))
        one = ent.agg(F.lit(k).alias("attributes"), F.lit(frame.n).cast("long").alias("rows"), F.count("*").alias("sets"), F.sum("cells").alias("cells"))
        out = one if out is None else out.unionByName(one)
    return out


FLAGSHIP_SQL = f"with {o.epistasis_cte()},\n {o.F2.search()}\nselect g, set_id, 'TC' as metric, {r6('bits')} as bits, kind from found"


def flagship(spark: SparkSession, sf: str) -> DataFrame:
    """Sets found in pure epistasis, in every data set of the table."""
    found = mining.mine_each(planted.epistasis(spark, sf, None))
    return found.select("g", set_id(F.col("members")).alias("set_id"), "metric", rounded(F.col("bits")).alias("bits"), "kind")


QUERIES["q_flagship"] = flagship
ORACLES["q_flagship"] = FLAGSHIP_SQL
