"""Binning and treatment of gaps before encoding."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def equal_width(x: Column, width: float) -> Column:
    return F.floor(x / width).cast("int")


def explicit_edges(x: Column, edges: Sequence[float]) -> Column:
    """Number of edges that are not above the value."""
    return sum(((x >= e).cast("int") for e in edges), F.lit(0)).cast("int")


def equal_depth(df: DataFrame, column: str, bins: int, out: str, relative_error: float = 1e-4) -> DataFrame:
    """Bins of nearly equal counts, by approximate quantiles: one pass, no global sort."""
    cuts = sorted(set(df.select(F.percentile_approx(column, [i / bins for i in range(1, bins)], int(1 / relative_error))).first()[0] or []))
    return df.withColumn(out, F.when(F.col(column).isNotNull(), explicit_edges(F.col(column), cuts)))


def top_values(df: DataFrame, column: str, k: int, out: str, other: str = "other") -> DataFrame:
    """The k most frequent values (ties: the smaller value), all others as one."""
    top = [r[0] for r in df.filter(F.col(column).isNotNull()).groupBy(column).count().orderBy(F.desc("count"), column).limit(k).collect()]
    return df.withColumn(out, F.when(F.col(column).isin(top), F.col(column)).when(F.col(column).isNotNull(), F.lit(other)))


def sign_bit(x: Column) -> Column:
    return (x >= 0).cast("int")


def json_number(x: Column, path: str) -> Column:
    return F.get_json_object(x, path).cast("double")


def impute_mode(df: DataFrame, columns: list[str]) -> DataFrame:
    """Nulls become the most frequent value of their column (ties: the smallest)."""
    long = df.select(F.explode(F.array(*[F.struct(F.lit(c).alias("c"), F.col(c).cast("string").alias("v")) for c in columns])).alias("x")).select("x.c", "x.v").filter("v is not null")
    counts = long.groupBy("c", "v").agg(F.count("*").alias("n"))
    first = counts.groupBy("c").agg(F.min_by("v", F.struct(-F.col("n"), F.col("v"))).alias("v"))
    modes = {r.c: r.v for r in first.collect()}  # one row a column
    return df.withColumns({c: F.coalesce(F.col(c), F.lit(modes.get(c)).cast(df.schema[c].dataType)) for c in columns})


def drop_gap_columns(df: DataFrame, columns: list[str], most: float = 0.0) -> list[str]:
    """Columns whose share of nulls is not above ``most``."""
    share = df.agg(*(F.avg(F.col(c).isNull().cast("double")).alias(c) for c in columns)).first()
    return [c for c in columns if (share[c] or 0.0) <= most]


def drop_gap_rows(df: DataFrame, columns: list[str]) -> DataFrame:
    return df.dropna(subset=columns)


def balanced(df: DataFrame, group: list[str], class_column: str, key: str, counts: dict[int, int] | int) -> DataFrame:
    """The first rows (by key) of every class of every group."""
    rank = F.row_number().over(Window.partitionBy(*group, class_column).orderBy(key))
    ranked = df.withColumn("__rank", rank)
    if isinstance(counts, int):
        return ranked.filter(F.col("__rank") <= counts).drop("__rank")
    limit = F.create_map(*[x for k, v in counts.items() for x in (F.lit(k), F.lit(v))])[F.col(class_column)]
    return ranked.filter(F.col("__rank") <= F.coalesce(limit, F.lit(0))).drop("__rank")


def random_removal(names: list[str], k: int, rep: int, tag: str = "drop") -> list[str]:
    """Names without k that are chosen by the order of md5('tag:rep:name')."""
    import hashlib

    order = sorted(names, key=lambda c: hashlib.md5(f"{tag}:{rep}:{c}".encode()).hexdigest())
    gone = set(order[:k])
    return [c for c in names if c not in gone]
