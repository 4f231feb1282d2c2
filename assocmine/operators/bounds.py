"""Bounds on joint entropy, TC and CAC from entropies of smaller sets.

The arithmetic is written once and works on numbers (the search holds intervals of its lattice nodes) and on columns (a
table of bounds for given sets).
"""

from __future__ import annotations

from itertools import combinations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from assocmine.sources.frame import Frame


def _least(*xs):
    return F.least(*xs) if isinstance(xs[0], Column) else min(xs)


def h_upper_half(h_without_a, h_without_b, h_ab):
    """H(S) from two subsets that lack one member each, and that pair."""
    return (h_without_a + h_without_b + h_ab) / 2


def h_upper_tight(h_without_a, h_without_b, a_given, b_given):
    """The same with the smallest conditional entropies of the two members: never looser (ours)."""
    return (h_without_a + h_without_b + a_given + b_given) / 2


def tc_lower_ancestor(sum_h, h_upper):
    return sum_h - h_upper


def tc_upper_parent(tc_parent, h_parent, h_new):
    return tc_parent + _least(h_parent, h_new)


def tc_lower_sibling(sum_h_with_j, h_sibling, least_j_given_t):
    """TC(S, j) from the joint entropy of the sibling (S, i)."""
    return sum_h_with_j - h_sibling - least_j_given_t


def tc_upper_sibling(sum_h_with_j, h_sibling, i_given_j, least_i_given_t):
    """TC(S, j) from its sibling (S, i): H(S, j) is at least H(S, i) less what i may hold beyond j or beyond S."""
    return sum_h_with_j - h_sibling + _least(i_given_j, least_i_given_t)


def sibling_upper_as_printed(sum_h_with_j, h_sibling, i_given_j, least_j_given_t):
    """The form as printed, which can fall below the true value; for a test that shows it, never for pruning."""
    return sum_h_with_j - h_sibling + _least(i_given_j, least_j_given_t)


def cac_lower_single(h_c, least_c_given_i):
    return h_c - least_c_given_i


def cac_upper(h_upper, h_c):
    return _least(h_upper, h_c)


class Entropies:
    """Exact joint entropies and intervals of one data set, with upper bounds for sets that were never counted."""

    def __init__(self, exact: dict[tuple[int, ...], float], tight: bool = True):
        self.exact, self.tight = exact, tight
        self.memo: dict[tuple[int, ...], float] = {}

    def pair(self, a: int, b: int) -> float:
        return self.exact[(a, b) if a < b else (b, a)]

    def given(self, a: int, b: int) -> float:
        """H(a given b)."""
        return self.pair(a, b) - self.exact[(b,)]

    def upper(self, s: tuple[int, ...]) -> float:
        """Upper bound of H(s): exact if counted, else from its pair of largest entropy and the two sets without either."""
        if s in self.exact:
            return self.exact[s]
        known = self.memo.get(s)
        if known is None:
            a, b = max(combinations(s, 2), key=lambda p: (self.exact[p], p))
            without_a, without_b = tuple(x for x in s if x != a), tuple(x for x in s if x != b)
            known = h_upper_half(self.upper(without_a), self.upper(without_b), self.exact[(a, b)])
            if self.tight:
                known = min(known, h_upper_tight(self.upper(without_a), self.upper(without_b), min(self.given(a, t) for t in without_a), min(self.given(b, t) for t in without_b)))
            self.memo[s] = known
        return known

    def forget(self) -> None:
        self.memo.clear()


def bound_table(frame: Frame, ent: DataFrame, sets: list[tuple[int, ...]]) -> DataFrame:
    """All TC bounds of given sets of order 3 or more, next to the true value; one join for each entropy that is used.

    The last member is the newest one (the parent lacks it); the sibling replaces it by the attribute after it, or the
    one before the parent's last if there is none.
    """
    spark, n_attributes = frame.spark, len(frame.names)
    rows = []
    for s in sets:
        parent, new = s[:-1], s[-1]
        others = [i for i in range(n_attributes) if i not in s]
        sibling = next((i for i in others if i > new), others[0] if others else None)
        a, b = s[0], s[1]
        rows.append((list(s), list(parent), new, sibling, list(x for x in s if x != a), list(x for x in s if x != b), [a, b], sorted([*parent, sibling]) if sibling is not None else None))
    listed = spark.createDataFrame(rows, "s array<int>, parent array<int>, new int, sibling int, wa array<int>, wb array<int>, ab array<int>, ps array<int>").join(frame.rows.select("g").distinct())

    def h(name: str, out: str, left: DataFrame) -> DataFrame:
        return left.join(ent.select("g", F.col("s").alias(name), F.col("h").alias(out)), ["g", name], "left")

    for name, out in (("s", "h_s"), ("parent", "h_parent"), ("wa", "h_wa"), ("wb", "h_wb"), ("ab", "h_ab"), ("ps", "h_ps")):
        listed = h(name, out, listed)
    one = ent.filter(F.size("s") == 1).select("g", F.col("s")[0].alias("i"), "h")
    pairs = ent.filter(F.size("s") == 2).select("g", F.col("s").alias("p"), "h")
    sums = listed.select("g", "s", F.explode("s").alias("i")).join(one, ["g", "i"]).groupBy("g", "s").agg(F.sum("h").alias("sum_h"), F.max_by("h", F.array_position("s", F.col("i"))).alias("h_new"))
    given = listed.select("g", "s", "new", "sibling", F.explode("parent").alias("t"))
    j = given.withColumn("p", F.array_sort(F.array("new", "t"))).join(pairs, ["g", "p"]).join(one.select("g", F.col("i").alias("t"), F.col("h").alias("ht")), ["g", "t"]).groupBy("g", "s").agg(F.min(F.col("h") - F.col("ht")).alias("j_given_t"))
    i = given.filter("sibling is not null").withColumn("p", F.array_sort(F.array("sibling", "t"))).join(pairs, ["g", "p"]).join(one.select("g", F.col("i").alias("t"), F.col("h").alias("ht")), ["g", "t"]).groupBy("g", "s").agg(F.min(F.col("h") - F.col("ht")).alias("i_given_t"))
    i_j = listed.filter("sibling is not null").withColumn("p", F.array_sort(F.array("sibling", "new"))).join(pairs, ["g", "p"]).join(one.select("g", F.col("i").alias("new"), F.col("h").alias("hj")), ["g", "new"]).select("g", "s", (F.col("h") - F.col("hj")).alias("i_given_j"))
    full = listed.join(sums, ["g", "s"]).join(j, ["g", "s"]).join(i, ["g", "s"], "left").join(i_j, ["g", "s"], "left")
    c = F.col
    tc = c("sum_h") - c("h_s")
    lower = tc_lower_ancestor(c("sum_h"), h_upper_half(c("h_wa"), c("h_wb"), c("h_ab")))
    return full.select(
        "g",
        "s",
        tc.alias("tc"),
        lower.alias("lower_ancestor"),
        (c("sum_h") - c("h_new") - c("h_parent")).alias("lower_monotone"),
        tc_upper_parent(c("sum_h") - c("h_new") - c("h_parent"), c("h_parent"), c("h_new")).alias("upper_parent"),
        tc_lower_sibling(c("sum_h"), c("h_ps"), c("j_given_t")).alias("lower_sibling"),
        tc_upper_sibling(c("sum_h"), c("h_ps"), c("i_given_j"), c("i_given_t")).alias("upper_sibling"),
        sibling_upper_as_printed(c("sum_h"), c("h_ps"), c("i_given_j"), c("j_given_t")).alias("upper_sibling_as_printed"),
    )


def class_bound_table(frame: Frame, ent: DataFrame, sets: list[tuple[int, ...]]) -> DataFrame:
    """CAC bounds of given sets of two predictors or more, next to the true value."""
    from assocmine.operators.metrics import class_correlation, table

    k = frame.class_at
    wanted = table(frame, sets)
    true = class_correlation(ent, wanted, k)
    singles = class_correlation(ent, wanted.select("g", F.explode("s").alias("i")).select("g", F.array("i").alias("s")).distinct(), k).select("g", F.col("s")[0].alias("i"), "cac")
    least = wanted.select("g", "s", F.explode("s").alias("i")).join(singles, ["g", "i"]).groupBy("g", "s").agg(F.max("cac").alias("best"))
    wa, wb, ab = F.slice("s", 2, F.size("s") - 1), F.concat(F.slice("s", 1, 1), F.slice("s", 3, F.size("s"))), F.slice("s", 1, 2)
    rows = true.join(least, ["g", "s"]).withColumns({"wa": wa, "wb": wb, "ab": ab})
    for name in ("wa", "wb", "ab"):
        rows = rows.join(ent.select("g", F.col("s").alias(name), F.col("h").alias(f"h_{name}")), ["g", name])
    c = F.col
    return rows.select("g", "s", "cac", cac_lower_single(c("hc"), c("hc") - c("best")).alias("lower_single"), cac_upper(h_upper_half(c("h_wa"), c("h_wb"), c("h_ab")), c("hc")).alias("upper"))
