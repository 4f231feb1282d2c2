"""Planted data sets, derived from the keys of the given tables by md5 uniforms; see FIXTURES.md for the recipes."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from assocmine.functions.expressions import genotype, uniform
from assocmine.plans.materialize import materialize
from assocmine.sources import discretize
from assocmine.sources.frame import Frame, dense, encode

NOISE = (0.0, 0.1, 0.15, 0.2, 0.25, 0.3)


#: Number of a data set: LEVEL * noise level + REPEAT * repeat + number of its key range.
LEVEL, REPEAT = 10**12, 10**9
#: Consecutive keys that give one data set of 300 + 300 or 800 + 800 rows.
GAIN_KEYS, COPY_KEYS = 700, 1_900


def _spread(keys: DataFrame) -> DataFrame:
    """Keys dealt to all cores: a table of keys is a file or two, but each key makes a wide row of md5 uniforms."""
    spark = keys.sparkSession
    tasks = max(int(spark.conf.get("spark.sql.shuffle.partitions")), 4 * spark.sparkContext.defaultParallelism)
    return keys.repartition(tasks, "g", "key")


def _keys(spark: SparkSession, sf_dir: str, table: str, column: str, size: int | None, reps: list[int] | None) -> DataFrame:
    """``key``, ``rep`` and ``g``. With repeats given, the first key range only, g being the repeat. Without, the whole
    table: every range of ``size`` keys is a data set, in as many repeats as it takes to have ``REPEATS`` of them."""
    keys = spark.read.parquet(f"{sf_dir}/{table}.parquet").select(F.col(column).alias("key"))
    if reps is not None:
        keys = keys.filter(F.col("key") < size) if size is not None else keys
        return keys.withColumn("rep", F.explode(F.array(*[F.lit(r) for r in reps]))).withColumn("g", F.col("rep").cast("long"))
    keys = keys.withColumn("part", F.floor(F.col("key") / size))
    full = keys.groupBy("part").agg(F.count("*").alias("n")).filter(F.col("n") == size)
    times = repeats(full.count())
    whole = keys.join(full.select("part"), "part", "left_semi").withColumn("rep", F.explode(F.sequence(F.lit(0), F.lit(times - 1))))
    return _spread(whole.withColumn("g", F.col("rep").cast("long") * F.lit(REPEAT) + F.col("part")).drop("part"))


#: Data sets of an experiment, at least.
REPEATS = 100


def repeats(parts: int) -> int:
    """How often the key ranges of a table are used, each time with other draws."""
    return -(-REPEATS // parts) if parts else 1


def _u(tag: str) -> Column:
    return uniform(tag, F.col("rep"), F.col("key"))


def _attributes(n: int = 15) -> list[str]:
    return [f"a{i}" for i in range(1, n + 1)]


def _noisy_xor(spark: SparkSession, sf_dir: str, reps: list[int] | None, noise: tuple[float, ...]) -> DataFrame:
    """All noise levels, ``level`` being the index: uniforms are made once a key, and only the flips differ."""
    df = _keys(spark, sf_dir, "orders", "o_orderkey", 200, reps)
    flips = {f"f{target}": _u(f"f{target}") for target in (1, 6, 11)}
    df = df.withColumns({c: (_u(c) < 0.5).cast("int") for c in _attributes()} | flips)
    df = df.withColumn("at", F.explode(F.array(*[F.struct(F.lit(i).alias("level"), F.lit(p).alias("noise")) for i, p in enumerate(noise)]))).select("*", "at.level", "at.noise").drop("at")
    for target, parts in ((1, (2, 3)), (6, (7, 8, 9)), (11, (12, 13, 14))):
        value = F.col(f"a{parts[0]}")
        for p in parts[1:]:
            value = value.bitwiseXOR(F.col(f"a{p}"))
        df = df.withColumn(f"a{target}", value.bitwiseXOR((F.col(f"f{target}") < F.col("noise")).cast("int")))
    return df.drop(*flips, "noise")


def noisy_xor_table(spark: SparkSession, sf_dir: str, reps: list[int] | None, noise: float) -> DataFrame:
    """three exclusive-or relations among 15 binary attributes, their targets flipped with probability ``noise``."""
    return _noisy_xor(spark, sf_dir, reps, (noise,)).drop("level")


def noisy_xor(spark: SparkSession, sf_dir: str, reps: list[int] | None, noise: tuple[float, ...] = (0.1,)) -> Frame:
    """F1 for all noise levels at once: data set g = 1000 * (index of the noise level) + repeat, or of the whole table (no
    repeats given) LEVEL * (index) + the number of the data set."""
    df = _noisy_xor(spark, sf_dir, reps, noise)
    return _coded(df.withColumn("g", F.lit(LEVEL if reps is None else 1000) * F.col("level") + F.col("g")), _attributes())


def _coded(df: DataFrame, names: list[str], class_name: str | None = None) -> Frame:
    return dense(df, names, class_name, F.col("g"), keep=["key"])


#: Sets of attribute indexes (from 0) that F1 plants.
XOR_TRUTH = ((0, 1, 2), (5, 6, 7, 8), (10, 11, 12, 13))


def epistasis_table(spark: SparkSession, sf_dir: str, reps: list[int] | None, strong: bool = False) -> DataFrame:
    """F2 and (strong) F2b: a pair of ternary attributes that tells a binary trait only together."""
    df = _keys(spark, sf_dir, "orders", "o_orderkey", 200, reps)
    df = df.withColumns({c: genotype(_u(c)) for c in _attributes()}).withColumn("t", (F.col("key") % 2).cast("int"))
    if strong:
        df = df.withColumn("a1", F.floor(3 * _u("a1")).cast("int"))
        return df.withColumn("a2", F.when((F.col("t") == 1) | (_u("mix") < 0.6), F.col("a1")).otherwise((F.col("a1") + 1) % 3).cast("int"))
    pick = F.floor(4 * _u("cell")).cast("int")
    first, second = F.array(*map(F.lit, (0, 1, 1, 2))), F.array(*map(F.lit, (1, 0, 2, 1)))
    return df.withColumns({"a1": F.when(F.col("t") == 1, first[pick]).otherwise(F.col("a1")), "a2": F.when(F.col("t") == 1, second[pick]).otherwise(F.col("a2"))})


def epistasis(spark: SparkSession, sf_dir: str, reps: list[int] | None, strong: bool = False) -> Frame:
    return _coded(epistasis_table(spark, sf_dir, reps, strong), [*_attributes(), "t"])


def class_gain_table(spark: SparkSession, sf_dir: str, reps: list[int] | None) -> DataFrame:
    """attribute 1 tells the class alone, attribute 2 only together with it; 300 rows of each class."""
    df = _keys(spark, sf_dir, "orders", "o_orderkey", GAIN_KEYS, reps)
    df = df.withColumns({c: genotype(_u(c)) for c in _attributes()})
    even = F.when((F.col("a1") + F.col("a2")) % 2 == 0, 0.25).otherwise(-0.25)
    df = df.withColumn("c", (_u("c") < F.array(*map(F.lit, (0.25, 0.5, 0.75)))[F.col("a1")] + even).cast("int"))
    return _complete(discretize.balanced(df, ["g"], "c", "key", 300), 600)


def class_gain(spark: SparkSession, sf_dir: str, reps: list[int] | None) -> Frame:
    return _coded(class_gain_table(spark, sf_dir, reps), _attributes(), "c")


def class_copies_table(spark: SparkSession, sf_dir: str, reps: list[int] | None) -> DataFrame:
    """three attributes act on the class together, and copies of them have 5% errors; 800 rows of each class."""
    df = _keys(spark, sf_dir, "orders", "o_orderkey", COPY_KEYS, reps)
    df = df.withColumns({c: genotype(_u(c)) for c in _attributes()})
    for i in (1, 2, 3):
        copy = F.when(_u(f"e{i + 5}") < 0.05, (F.col(f"a{i}") + 1) % 3).otherwise(F.col(f"a{i}"))
        df = df.withColumn(f"a{i + 5}", copy.cast("int"))
    two, three = (F.col("a1") + F.col("a2")) % 2, (F.col("a1") + F.col("a2") + F.col("a3")) % 2
    chance = 0.05 + F.when((F.col("a1") == 2) | (F.col("a3") == 2), 0.3).otherwise(0.0) + 0.3 * two + 0.3 * three
    return _complete(discretize.balanced(df.withColumn("c", (_u("c") < chance).cast("int")), ["g"], "c", "key", 800), 1_600)


def _complete(df: DataFrame, size: int) -> DataFrame:
    """The data sets that have got all their rows; a key range with too few rows of a class makes none."""
    full = df.groupBy("g").agg(F.count("*").alias("n")).filter(F.col("n") == size)
    return df.join(full.select("g"), "g", "left_semi")


def class_copies(spark: SparkSession, sf_dir: str, reps: list[int] | None) -> Frame:
    return _coded(class_copies_table(spark, sf_dir, reps), _attributes(), "c")


#: Consecutive customers that give one data set of 26 + 65 and of 144 + 243 rows.
SMALL_KEYS, LARGE_KEYS = 200, 600


def block_table(spark: SparkSession, sf_dir: str, reps: list[int] | None, n_attributes: int, cases: int, controls: int, gaps: float = 0.0, size: int | None = None) -> DataFrame:
    """ternary attributes in blocks of four that copy their leader with growing errors, a class, and gaps."""
    if reps is not None:
        df = _keys(spark, sf_dir, "customer", "c_custkey", None, reps)
    else:
        keys = spark.read.parquet(f"{sf_dir}/customer.parquet").select(F.col("c_custkey").alias("key"))
        df = _spread(keys.withColumn("rep", F.lit(0)).withColumn("g", F.floor(F.col("key") / size)))
    names = _attributes(n_attributes)
    columns = {}
    for i, name in enumerate(names):
        own = genotype(_u(name))
        if i % 4:
            own = F.when(_u(f"x{name}") < (0.05, 0.2, 0.4)[i % 4 - 1], own).otherwise(genotype(_u(names[i - i % 4])))
        columns[name] = own.cast("int")
    df = df.withColumns(columns)
    even = F.when((F.col("a1") + F.col("a5")) % 2 == 0, 0.25).otherwise(-0.25)
    df = df.withColumn("c", (_u("c") < F.array(*map(F.lit, (0.25, 0.5, 0.75)))[F.col("a1")] + even).cast("int"))
    if gaps:
        df = df.withColumns({name: F.when(_u(f"n{i}") >= gaps, F.col(name)) for i, name in enumerate(names, 1)})
    return discretize.balanced(df, ["g"], "c", "key", {1: cases, 0: controls})


def runtime_small(spark: SparkSession, sf_dir: str, rep: int | None = 0) -> Frame:
    """58 attributes, 26 + 65 rows; with None, a data set of every range of customers that has so many of each class."""
    names = _attributes(58)
    if rep is not None:
        return encode(block_table(spark, sf_dir, [rep], 58, 26, 65), names, "c", keep=["key"])
    return _coded(_complete(block_table(spark, sf_dir, None, 58, 26, 65, size=SMALL_KEYS), 91), names, "c")


def runtime_large(spark: SparkSession, sf_dir: str, rep: int | None = 0) -> Frame:
    """103 attributes, 144 + 243 rows, gaps imputed with the mode; with None as :func:`runtime_small`."""
    names = _attributes(103)
    if rep is not None:
        return encode(discretize.impute_mode(block_table(spark, sf_dir, [rep], 103, 144, 243, 0.03), names), names, "c", keep=["key"])
    full = materialize(_complete(block_table(spark, sf_dir, None, 103, 144, 243, 0.03, LARGE_KEYS), 387), "gapped")
    return _coded(discretize.impute_mode(full, names), names, "c")


def case_study(spark: SparkSession, sf_dir: str, attributes: int = 40, cases: int = 58, controls: int = 92) -> Frame:
    """The attributes with fewest gaps, rows without gaps among them, and the experiment's number of cases and controls."""
    names = _attributes(103)
    df = materialize(block_table(spark, sf_dir, [0], 103, 10**6, 10**6, 0.03), "gapped")
    share = df.agg(*(F.sum(F.col(c).isNull().cast("int")).alias(c) for c in names)).first()
    kept = sorted(sorted(names, key=lambda c: (share[c], int(c[1:])))[:attributes], key=lambda c: int(c[1:]))
    complete = discretize.drop_gap_rows(df, kept)
    return encode(discretize.balanced(complete, ["rep"], "c", "key", {1: cases, 0: controls}), kept, "c", keep=["key"])
