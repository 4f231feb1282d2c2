"""Significance of TC, CAC and their gains: degrees of freedom, p-values, and zones by critical values.

p is monotone in bits for fixed degrees of freedom, so zones compare bits with two thresholds for each distinct df; the
thresholds are few and made on the driver, and the comparison stays in Catalyst. p itself is computed for printed rows.
"""

from __future__ import annotations

from collections.abc import Iterable

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from assocmine.functions.expressions import product, zone_of
from assocmine.functions.gamma import critical_bits, log_p
from assocmine.plans.materialize import ship_package
from assocmine.sources.frame import Frame

ALPHA_HIGH, ALPHA_LOW = 1e-8, 1e-2
#: Bits by which a metric must exceed a threshold: differences of entropies carry rounding errors of this order.
SLACK = 1e-12


def check_alphas(high: float, low: float) -> None:
    if not 0.0 < high < low:
        raise ValueError("levels need 0 < alpha_high < alpha_low")


def states_array(frame: Frame, s: Column) -> Column:
    known = F.array(*[F.lit(x).cast("long") for x in frame.states])
    return F.transform(s, lambda i: F.element_at(known, i + 1))


def df_tc(frame: Frame, s: Column) -> Column:
    """prod(r) - sum(r) + k - 1."""
    r = states_array(frame, s)
    return product(r) - F.aggregate(r, F.lit(0.0), lambda acc, x: acc + x.cast("double")) + F.size(s) - 1


def df_cac(frame: Frame, s: Column, cells: Column | None = None) -> Column:
    """(states of the joint of S - 1)(states of C - 1); ``cells`` gives observed states instead of the product."""
    joint = product(states_array(frame, s)) if cells is None else cells.cast("double")
    return (joint - 1) * (frame.states[frame.class_at] - 1)


def df_tc_gain(frame: Frame, x: Column, k: Column, cells: Column | None = None) -> Column:
    """Two-way: (states of the joint of X - 1)(r_k - 1)."""
    joint = product(states_array(frame, x)) if cells is None else cells.cast("double")
    return (joint - 1) * (states_array(frame, F.array(k))[0] - 1)


def df_cac_gain(frame: Frame, x: Column, k: Column, cells: Column | None = None) -> Column:
    """One two-way table of A_k and C in every stratum of X."""
    joint = product(states_array(frame, x)) if cells is None else cells.cast("double")
    return joint * (states_array(frame, F.array(k))[0] - 1) * (frame.states[frame.class_at] - 1)


def tail(bits: Column, df: Column, n: int) -> tuple[Column, Column]:
    """p and -log10 p, in Arrow batches over result rows."""
    @F.pandas_udf(T.DoubleType())
    def neg_log10_p(b: pd.Series, d: pd.Series) -> pd.Series:
        return pd.Series([-log_p(x, y, n) / 2.302585092994046 for x, y in zip(b, d)], dtype="float64")

    digits = neg_log10_p(bits.cast("double"), df.cast("double"))
    return F.pow(F.lit(10.0), -digits), digits


def thresholds(spark: SparkSession, dfs: Iterable[float], n: int, high: float = ALPHA_HIGH, low: float = ALPHA_LOW) -> DataFrame:
    """``df``, ``strong_at``, ``weak_at``: bits above which p < alpha_high, and up to which p >= alpha_low."""
    check_alphas(high, low)
    rows = [(float(d), critical_bits(float(d), n, high) + SLACK, critical_bits(float(d), n, low) + SLACK) for d in sorted(set(dfs))]
    return spark.createDataFrame(rows, "df double, strong_at double, weak_at double")


def critical_values(df: Column, n: int, high: float = ALPHA_HIGH, low: float = ALPHA_LOW) -> Column:
    """``strong_at`` and ``weak_at`` of each row's degrees of freedom, in Arrow batches over candidate rows; each distinct one is computed once a worker."""
    check_alphas(high, low)

    @F.pandas_udf("strong_at double, weak_at double")
    def cuts(d: pd.Series) -> pd.DataFrame:
        return pd.DataFrame([(critical_bits(x, n, high) + SLACK, critical_bits(x, n, low) + SLACK) for x in d], columns=["strong_at", "weak_at"], dtype="float64")

    return cuts(df.cast("double"))


def with_zone(rows: DataFrame, bits: str, n: int, high: float = ALPHA_HIGH, low: float = ALPHA_LOW, out: str = "zone") -> DataFrame:
    """Adds a zone to rows with ``df`` and the metric, without a job of its own."""
    ship_package(rows.sparkSession)
    cut = rows.withColumn("__cut", critical_values(F.col("df"), n, high, low))
    return cut.withColumn(out, zone_of(F.col(bits), F.col("__cut.strong_at"), F.col("__cut.weak_at"))).drop("__cut")


def p_even_df(bits: float, df: int, n: float) -> float:
    """Closed form for even degrees of freedom: a finite Poisson sum."""
    import math

    x = bits * n * math.log(2.0)
    return sum(math.exp(-x + j * math.log(x) - math.lgamma(j + 1)) if x > 0 else float(j == 0) for j in range(df // 2))
