"""Association metrics as joins over a table of joint entropies (``g``, ``s``, ``h``).

H joint entropy, II interaction information (signed: what a set holds as a whole and no proper subset does), TC total
correlation, CAC class-associated correlation (what the joint of a set tells about the class), and gains of TC and CAC
over a subset. Everything is in bits.
"""

from __future__ import annotations

from itertools import combinations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from assocmine.functions.expressions import plogp, subsets
from assocmine.plans import counts
from assocmine.sources.frame import Frame


def all_sets(attributes: list[int] | tuple[int, ...], least: int, most: int) -> list[tuple[int, ...]]:
    return [s for k in range(least, most + 1) for s in combinations(sorted(attributes), k)]


def table(frame: Frame, sets: list[tuple[int, ...]]) -> DataFrame:
    """Sets as rows, for every data set of the frame."""
    wanted = frame.spark.createDataFrame([(list(s),) for s in sets], "s array<int>")
    return wanted.join(frame.rows.select("g").distinct())


def _singles(ent: DataFrame) -> DataFrame:
    return ent.filter(F.size("s") == 1).select("g", F.col("s")[0].alias("i"), F.col("h").alias("h1"))


def conditional(ent: DataFrame, pairs: DataFrame) -> DataFrame:
    """H(a given b) of rows (``g``, ``a``, ``b``)."""
    joint = ent.select("g", F.col("s").alias("__s"), F.col("h").alias("hab"))
    one = _singles(ent).select("g", F.col("i").alias("b"), F.col("h1").alias("hb"))
    keyed = pairs.withColumn("__s", F.array_sort(F.array("a", "b")))
    return keyed.join(joint, ["g", "__s"]).join(one, ["g", "b"]).select("g", "a", "b", (F.col("hab") - F.col("hb")).alias("h_cond"))


def interaction_info(ent: DataFrame, sets: DataFrame) -> DataFrame:
    """II of rows (``g``, ``s``): alternating sum over all subsets, in one join of sets with their signed subsets."""
    parts = sets.select("g", "s", F.explode(subsets(F.col("s"))).alias("t"))
    sign = F.when((F.size("s") - F.size("t")) % 2 == 0, -1.0).otherwise(1.0)
    joined = parts.join(ent.select("g", F.col("s").alias("t"), "h"), ["g", "t"])
    return joined.groupBy("g", "s").agg(F.sum(sign * F.col("h")).alias("ii"))


def ii_kind(ii: Column, eps: float = 1e-9) -> Column:
    return F.when(ii > eps, "synergy").when(ii < -eps, "redundancy").otherwise("none")


def ii_entropy_bound(ent: DataFrame, sets: DataFrame) -> DataFrame:
    """II of rows (``g``, ``s``) with ``least_h``, the smallest entropy of a member, which II of three attributes cannot exceed."""
    least = sets.select("g", "s", F.explode("s").alias("i")).join(_singles(ent), ["g", "i"]).groupBy("g", "s").agg(F.min("h1").alias("least_h"))
    return interaction_info(ent, sets).join(least, ["g", "s"])


def total_correlation(ent: DataFrame, sets: DataFrame) -> DataFrame:
    """TC of rows (``g``, ``s``): sum of the members' entropies minus the joint's."""
    members = sets.select("g", "s", F.explode("s").alias("i")).join(_singles(ent), ["g", "i"]).groupBy("g", "s").agg(F.sum("h1").alias("sum_h"))
    return members.join(ent.select("g", "s", "h", "cells"), ["g", "s"]).select("g", "s", (F.col("sum_h") - F.col("h")).alias("tc"), "h", "cells", "sum_h")


def class_correlation(ent: DataFrame, sets: DataFrame, c: int) -> DataFrame:
    """CAC of rows (``g``, ``s``; predictors only): H(S) + H(C) - H(S, C)."""
    with_c = sets.withColumn("sc", F.array_sort(F.array_append("s", F.lit(c))))
    joint = ent.select("g", F.col("s").alias("sc"), F.col("h").alias("hsc"))
    hc = _singles(ent).filter(F.col("i") == c).select("g", F.col("h1").alias("hc"))
    return with_c.join(joint, ["g", "sc"]).join(ent.select("g", "s", F.col("h").alias("hs"), "cells"), ["g", "s"]).join(hc, "g").select("g", "s", (F.col("hs") + F.col("hc") - F.col("hsc")).alias("cac"), "hs", "hc", "hsc", "cells")


def mutual_information(ent: DataFrame, sets: DataFrame) -> DataFrame:
    return total_correlation(ent, sets.filter(F.size("s") == 2)).select("g", "s", F.col("tc").alias("mi"))


def tc_gain(ent: DataFrame, rows: DataFrame) -> DataFrame:
    """Gain of TC of ``s`` over ``x`` = s without one member: H(member) + H(x) - H(s)."""
    keyed = rows.withColumn("i", F.array_except("s", "x")[0])
    out = keyed.join(_singles(ent), ["g", "i"]).join(ent.select("g", F.col("s").alias("x"), F.col("h").alias("hx")), ["g", "x"]).join(ent.select("g", "s", "h"), ["g", "s"])
    return out.select("g", "s", "x", (F.col("h1") + F.col("hx") - F.col("h")).alias("gain"))


def cac_gain(ent: DataFrame, rows: DataFrame, c: int) -> DataFrame:
    """Gain of CAC of ``s`` over ``x``, both sets of predictors."""
    big = class_correlation(ent, rows.select("g", "s").distinct(), c).select("g", "s", F.col("cac").alias("big"))
    small = class_correlation(ent, rows.select("g", F.col("x").alias("s")).distinct(), c).select("g", F.col("s").alias("x"), F.col("cac").alias("small"))
    return rows.join(big, ["g", "s"]).join(small, ["g", "x"]).select("g", "s", "x", (F.col("big") - F.col("small")).alias("gain"))


# Direct sums over cells: better conditioned near zero, where differences of entropies lose digits.


def _joint(frame: Frame, s: tuple[int, ...]) -> DataFrame:
    return frame.rows.groupBy("g", *[F.col("a")[i].alias(f"x{i}") for i in s]).agg(F.sum("w").alias("n"))


def total_correlation_direct(frame: Frame, s: tuple[int, ...]) -> DataFrame:
    """TC as the divergence between the joint and the product of its margins."""
    from pyspark.sql import Window

    cells = _joint(frame, s)
    cells = cells.withColumns({f"m{i}": F.sum("n").over(Window.partitionBy("g", f"x{i}")) for i in s})
    ratio = F.log2(F.col("n") / frame.n)
    for i in s:
        ratio = ratio - F.log2(F.col(f"m{i}") / frame.n)
    return cells.groupBy("g").agg(F.sum(F.col("n") / frame.n * ratio).alias("tc")).select("g", F.array(*map(F.lit, s)).alias("s"), "tc")


def _margins(frame: Frame, s: tuple[int, ...], c: int) -> DataFrame:
    from pyspark.sql import Window

    cells = _joint(frame, (*s, c))
    return cells.withColumn("na", F.sum("n").over(Window.partitionBy("g", *[f"x{i}" for i in s]))).withColumn("nc", F.sum("n").over(Window.partitionBy("g", f"x{c}")))


def class_correlation_direct(frame: Frame, s: tuple[int, ...], c: int) -> DataFrame:
    cells = _margins(frame, s, c)
    bits = F.sum(F.col("n") / frame.n * F.log2(F.col("n").cast("double") * frame.n / (F.col("na").cast("double") * F.col("nc"))))
    return cells.groupBy("g").agg(bits.alias("cac")).select("g", F.array(*map(F.lit, s)).alias("s"), "cac")


def cac_gain_stratified(frame: Frame, x: tuple[int, ...], k: int, c: int) -> DataFrame:
    """Gain of CAC of x + {k} over x: CAC of k inside every stratum of x, weighted by the strata's shares."""
    base = [f"x{i}" for i in x]
    cells = _joint(frame, (*x, k, c))
    per = lambda keys: cells.groupBy("g", *keys).agg(F.sum("n").alias("n")).groupBy("g", *base).agg(F.sum(plogp(F.col("n"))).alias("q"))
    joint, by_k, by_c = per([*base, f"x{k}", f"x{c}"]), per([*base, f"x{k}"]), per([*base, f"x{c}"])
    total = cells.groupBy("g", *base).agg(F.sum("n").alias("n"))
    keys = ["g", *base]
    strata = total.join(joint.withColumnRenamed("q", "qj"), keys).join(by_k.withColumnRenamed("q", "qk"), keys).join(by_c.withColumnRenamed("q", "qc"), keys)
    inside = (F.col("qj") - F.col("qk") - F.col("qc") + plogp(F.col("n"))) / F.col("n")
    return strata.groupBy("g").agg(F.sum(F.col("n") / frame.n * inside).alias("gain"))


def cac_chi2_approx(frame: Frame, s: tuple[int, ...], c: int) -> DataFrame:
    """Second-order approximation of CAC and the two-way chi-square; chi2 = 2 n ln 2 times the approximation.

    Empty cells count with their expected number.
    """
    cells = _margins(frame, s, c).withColumn("e", F.col("na").cast("double") * F.col("nc") / frame.n)
    chi2 = F.sum((F.col("n") - F.col("e")) * (F.col("n") - F.col("e")) / F.col("e")) + (frame.n - F.sum("e"))
    return cells.groupBy("g").agg(chi2.alias("chi2")).select("g", F.array(*map(F.lit, s)).alias("s"), "chi2", (F.col("chi2") / (2 * frame.n * 0.6931471805599453)).alias("cac_approx"))


def decompositions(frame: Frame, sets: list[tuple[int, ...]], c: int | None = None) -> DataFrame:
    """Both sides of an identity for every set: TC = sum of II of subsets of two or more, or CAC = sum of II with the class."""
    if c is None:
        ent = counts.entropies(frame, {t for s in sets for t in all_sets(s, 1, len(s))})
        wanted = table(frame, sets)
        parts = wanted.select("g", "s", F.explode(subsets(F.col("s"), 2)).alias("t"))
        left = total_correlation(ent, wanted).select("g", "s", F.col("tc").alias("left"))
    else:
        full = [tuple(sorted((*s, c))) for s in sets]
        ent = counts.entropies(frame, {t for s in full for t in all_sets(s, 1, len(s))})
        wanted = table(frame, sets)
        parts = wanted.select("g", "s", F.explode(F.transform(subsets(F.col("s")), lambda t: F.array_sort(F.array_append(t, F.lit(c))))).alias("t"))
        left = class_correlation(ent, wanted, c).select("g", "s", F.col("cac").alias("left"))
    ii = interaction_info(ent, parts.select("g", F.col("t").alias("s")).distinct()).withColumnRenamed("s", "t")
    right = parts.join(ii, ["g", "t"]).groupBy("g", "s").agg(F.sum("ii").alias("right"))
    return left.join(right, ["g", "s"])
