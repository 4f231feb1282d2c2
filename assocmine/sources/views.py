"""Natural discrete views of the given tables, and the same views as SQL for DuckDB."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession

from assocmine.sources.frame import Frame, encode

#: View name: (attribute names, FROM clause, expressions). The expressions are common to Spark SQL and DuckDB.
VIEWS: dict[str, tuple[list[str], str, list[str]]] = {
    "lineitem": (
        ["returnflag", "linestatus", "linenumber", "quantity", "price", "discount", "tax", "year", "quarter"],
        "lineitem",
        [
            "l_returnflag", "l_linestatus", "l_linenumber", "cast(floor(l_quantity / 10.001e0) as int)", "cast(floor(l_extendedprice / 21000e0) as int)",
            "cast(floor(l_discount * 100e0 / 4e0) as int)", "cast(floor(l_tax * 100e0 / 3e0) as int)", "cast(year(l_shipdate) as int)", "cast(quarter(l_shipdate) as int)",
        ],
    ),
    "star": (
        ["returnflag", "linestatus", "orderstatus", "orderpriority", "segment", "region", "orderyear", "shipyear", "parttype"],
        "lineitem join orders on l_orderkey = o_orderkey join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey join part on l_partkey = p_partkey",
        ["l_returnflag", "l_linestatus", "o_orderstatus", "o_orderpriority", "c_mktsegment", "r_name", "cast(year(o_orderdate) as int)", "cast(year(l_shipdate) as int)", "p_type"],
    ),
    "part": (
        ["word1", "word2", "type", "size", "price"],
        "part",
        ["substring(p_name, 1, 3)", "substring(p_name, length(p_name) - 2, 3)", "p_type", "cast(floor(p_size / 13e0) as int)", "cast(cast(floor(p_retailprice) as bigint) % 2 as int)"],
    ),
    "documents": (
        ["lang", "quality", "toxic", "length", "source4"],
        "documents join labels on documents.doc_id = labels.doc_id",
        ["lang", "quality", "toxic", "cast(least(floor(n_chars / 500e0), 4) as int)", "cast(cast(substring(source, 4, 9) as int) % 4 as int)"],
    ),
    "events": (
        ["event_type", "hour", "weekday", "value", "user4"],
        "events",
        ["event_type", "cast(floor(hour(ts) / 6e0) as int)", "cast(dayofmonth(ts) % 7 as int)", "cast(least(floor(value / 20e0), 3) as int)", "cast(user_id % 4 as int)"],
    ),
}


def tables_of(name: str) -> list[str]:
    words = VIEWS[name][1].replace("(", " ").split()
    return [w for w in words if w in {"region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "labels"}]


def view_sql(name: str) -> str:
    """SELECT with a column for each attribute; ``part`` and others read as plain tables."""
    names, source, expressions = VIEWS[name]
    return "select " + ", ".join(f"{e} as {n}" for n, e in zip(names, expressions)) + f" from {source}"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """The view as a DataFrame; no view of the session is created or replaced."""
    used = tables_of(name)
    source = re.sub(r"^(\w+)|(?<=join )(\w+)", lambda m: f"{{{m[0]}}} as {m[0]}", VIEWS[name][1])
    names, _, expressions = VIEWS[name]
    listed = ", ".join(f"{e} as {n}" for n, e in zip(names, expressions))
    return spark.sql(f"select {listed} from {source}", **{t: spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in used})


def frame(spark: SparkSession, sf_dir: str, name: str, class_name: str | None = None) -> Frame:
    return encode(table(spark, sf_dir, name), list(VIEWS[name][0]), class_name)


def embedding_signs(spark: SparkSession, sf_dir: str, dims: int = 8) -> Frame:
    """Label and sign bits of the first dimensions."""
    vectors = spark.read.parquet(f"{sf_dir}/embeddings.parquet")
    names = [f"s{i}" for i in range(dims)]
    return encode(vectors.selectExpr("label", *(f"cast(embedding[{i}] >= 0 as int) as s{i}" for i in range(dims))), [*names, "label"], "label")
