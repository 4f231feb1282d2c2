"""Catalyst expressions that the operators share; none of them leaves the JVM."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def rounded(x: Column, digits: int = 6) -> Column:
    """Rounded, without negative zero."""
    return F.round(x, digits) + F.lit(0.0)


def uniform(tag: str, rep: Column, key: Column) -> Column:
    """Deterministic uniform number in [0, 1): first eight hex digits of md5('tag:rep:key') over 2^32."""
    digest = F.md5(F.concat(F.lit(f"{tag}:"), rep.cast("string"), F.lit(":"), key.cast("string")).cast("binary"))
    return F.conv(F.substring(digest, 1, 8), 16, 10).cast("double") / float(1 << 32)


def genotype(u: Column) -> Column:
    """0, 1, 2 with probabilities 1/4, 1/2, 1/4."""
    return F.when(u < 0.25, 0).when(u < 0.75, 1).otherwise(2).cast("int")


def set_id(s: Column) -> Column:
    return F.array_join(F.transform(s, lambda x: x.cast("string")), ",")


def immediate_subsets(s: Column) -> Column:
    """All subsets with one member fewer."""
    return F.transform(s, lambda out: F.filter(s, lambda x: x != out))


def subsets(s: Column, least: int = 1) -> Column:
    """All subsets with ``least`` members or more, from bit masks."""
    masks = F.sequence(F.lit(1), F.pow(F.lit(2.0), F.size(s)).cast("int") - 1)
    every = F.transform(masks, lambda m: F.filter(s, lambda x, i: F.getbit(m, i) == 1))
    return F.filter(every, lambda t: F.size(t) >= least)


def plogp(n: Column) -> Column:
    """n log2 n, zero for empty cells."""
    return F.when(n > 0, n * F.log2(n)).otherwise(F.lit(0.0))


def entropy_bits(n: Column) -> Column:
    """Aggregate: Shannon entropy in bits of cell counts."""
    return F.log2(F.sum(n)) - F.sum(plogp(n)) / F.sum(n)


def product(xs: Column) -> Column:
    """Product of an array of whole numbers, as a double (it may exceed the long range)."""
    return F.aggregate(xs, F.lit(1.0), lambda acc, x: acc * x.cast("double"))


def zone_of(bits: Column, strong_at: Column, weak_at: Column) -> Column:
    """STRONG above the critical bits of alpha_high, WEAK up to those of alpha_low, MIDDLE between."""
    return F.when(bits > strong_at, F.lit("STRONG")).when(bits <= weak_at, F.lit("WEAK")).otherwise(F.lit("MIDDLE"))
