"""The search with its lattice in tables: for candidate sets in numbers that the driver does not hold.

A level is a table of sets; children, sample rule, bounds, the six cases and the handlers are joins and expressions over
it. Only exact values touch the data: the sets that need them are counted in chunks of ``counts.CHUNK_SETS``, one pass a
chunk, and no more than a chunk is on the driver at any time. The tree rule, the subset check and the results are those
of :func:`assocmine.operators.mining.mine`; bounds only decide which sets need no exact value.

All tables have ``g`` (data set) and ``s`` (members, ascending). With a class attribute ``s`` holds predictors only.
"""

from __future__ import annotations

from collections import defaultdict
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from assocmine.functions.expressions import immediate_subsets, product, zone_of
from assocmine.operators import significance
from assocmine.operators.significance import ALPHA_HIGH, ALPHA_LOW
from assocmine.plans import counts
from assocmine.plans.materialize import materialize
from assocmine.sources.frame import Frame

REPORT = "level int, children long, cut_samples long, decided long, exact long, side_exact long, kept long, frontier long"


def children(front: DataFrame, attributes: DataFrame) -> DataFrame:
    """``g``, ``parent`` and ``s``: every set of the frontier with each later attribute (``idx``; a row an attribute, broadcast)."""
    later = F.broadcast(attributes.select("idx"))
    return front.select("g", F.col("s").alias("parent")).join(later, F.col("idx") > F.element_at("parent", -1)).select("g", "parent", F.array_append("parent", F.col("idx")).alias("s"))


def enough_samples(frame: Frame, s: Column, min_ratio: float = 5.0) -> Column:
    """Sample rule: rows for each possible combination of values, the class included."""
    cells = product(significance.states_array(frame, s))
    cells = cells * frame.states[frame.class_at] if frame.class_at is not None else cells
    return F.lit(float(frame.n)) >= min_ratio * cells


@dataclass
class Lattice:
    """One run: entropies known so far, and judged sets."""

    frame: Frame
    mode: str
    high: float
    low: float
    entropies: DataFrame | None = None
    levels: list[tuple] = field(default_factory=list)
    passes: int = 0

    @property
    def c(self) -> int | None:
        return self.frame.class_at if self.mode == "cac" else None

    def count(self, sets: DataFrame) -> int:
        """Exact entropies of the sets (``g``, ``s``) that have none yet, and with a class of the sets with it. Returns how many sets were asked for."""
        asked = materialize(sets.select("g", "s").distinct(), "asked-sets")
        wanted = asked
        if self.c is not None:
            wanted = asked.unionByName(asked.select("g", F.array_sort(F.array_append("s", F.lit(self.c))).alias("s"))).unionByName(asked.select("g").distinct().withColumn("s", F.array(F.lit(self.c))))
        if self.entropies is not None:
            wanted = wanted.join(self.entropies, ["g", "s"], "left_anti")
        wanted = materialize(wanted, "wanted-sets")
        n = wanted.count()
        chunks = -(-n // counts.CHUNK_SETS)
        for k in range(chunks):
            by_group: dict[int, list[tuple[int, ...]]] = defaultdict(list)
            for r in wanted.filter(F.pmod(F.xxhash64("g", "s"), F.lit(chunks)) == k).collect():
                by_group[r["g"]].append(tuple(r["s"]))
            if by_group:
                self.passes += 1
                found = materialize(counts.entropies_by_group(self.frame, {g: sorted(x) for g, x in by_group.items()}).select("g", "s", "h"), "entropies")
                self.entropies = found if self.entropies is None else self.entropies.unionByName(found)
        return asked.count()

    def singles(self) -> DataFrame:
        return self.entropies.filter(F.size("s") == 1).select("g", F.col("s")[0].alias("i"), F.col("h").alias("h1"))

    def df(self, s: Column) -> Column:
        return significance.df_tc(self.frame, s) if self.c is None else significance.df_cac(self.frame, s)

    def bits(self, sets: DataFrame) -> DataFrame:
        """The sets with their exact ``bits``, entropy ``h`` and ``zone``; sets must have been counted."""
        h = sets.join(self.entropies.select("g", "s", "h"), ["g", "s"])
        if self.c is None:
            sums = sets.select("g", "s", F.explode("s").alias("i")).distinct().join(self.singles(), ["g", "i"]).groupBy("g", "s").agg(F.sum("h1").alias("sum_h"))
            out = h.join(sums, ["g", "s"]).withColumn("bits", F.col("sum_h") - F.col("h")).drop("sum_h")
        else:
            joint = self.entropies.select("g", F.col("s").alias("sc"), F.col("h").alias("hsc"))
            own = self.singles().filter(F.col("i") == self.c).select("g", F.col("h1").alias("hc"))
            out = h.withColumn("sc", F.array_sort(F.array_append("s", F.lit(self.c)))).join(joint, ["g", "sc"]).join(own, "g")
            out = out.withColumn("bits", F.col("h") + F.col("hc") - F.col("hsc")).drop("sc", "hsc", "hc")
        return self.zoned(out, "bits", "zone")

    def zoned(self, rows: DataFrame, bits: str, out: str) -> DataFrame:
        return significance.with_zone(rows.withColumn("df", self.df(F.col("s"))), bits, self.frame.n, self.high, self.low, out).drop("df")

    def bounded(self, cands: DataFrame, before: DataFrame) -> DataFrame:
        """Candidates with ``lo``, ``hi`` and upper bound ``h_hi`` of their entropy, from the level before and pair entropies."""
        new = F.element_at("s", -1)
        parents = before.select("g", F.col("s").alias("parent"), F.col("hi").alias("p_hi"), F.col("h_hi").alias("p_h"))
        pair = self.entropies.filter(F.size("s") == 2).select("g", F.col("s").alias("pair"), F.col("h").alias("h2"))
        one = self.singles()
        given = cands.select("g", "s", F.explode("parent").alias("i"), new.alias("j")).withColumn("pair", F.array_sort(F.array("i", "j"))).join(pair, ["g", "pair"]).join(one, ["g", "i"])
        given = given.groupBy("g", "s").agg(F.min(F.col("h2") - F.col("h1")).alias("new_given"))
        below = cands.select("g", "s", F.explode(immediate_subsets(F.col("s"))).alias("t")).join(before.select("g", F.col("s").alias("t"), "lo"), ["g", "t"]).groupBy("g", "s").agg(F.max("lo").alias("best"))
        rows = cands.join(parents, ["g", "parent"]).join(given, ["g", "s"]).join(below, ["g", "s"], "left").withColumn("h_hi", F.col("p_h") + F.col("new_given"))
        if self.c is not None:
            own = one.filter(F.col("i") == self.c).select("g", F.col("h1").alias("hc"))
            rows = rows.join(own, "g").withColumn("hi", F.least("h_hi", "hc")).withColumn("lo", F.greatest(F.lit(0.0), F.coalesce("best", F.lit(0.0))))
            return rows.withColumn("full", F.col("hi") >= F.col("hc") - 1e-12).select("g", "parent", "s", "h_hi", "hi", "lo", "full")
        sums = cands.select("g", "s", F.explode("s").alias("i")).join(one, ["g", "i"]).groupBy("g", "s").agg(F.sum("h1").alias("sum_h"))
        newest = one.select("g", F.col("i").alias("__new"), F.col("h1").alias("h_new"))
        rows = rows.withColumn("__new", new).join(newest, ["g", "__new"]).join(sums, ["g", "s"])
        rows = rows.withColumn("lo", F.greatest(F.lit(0.0), F.coalesce("best", F.lit(0.0)), F.col("sum_h") - F.col("h_hi"))).withColumn("hi", F.greatest("lo", F.col("p_hi") + F.least("p_h", "h_new")))
        return rows.select("g", "parent", "s", "h_hi", "hi", "lo", F.lit(False).alias("full"))

    def handled(self, strong: DataFrame, known: DataFrame, kept: DataFrame) -> tuple[DataFrame, int]:
        """``g``, ``s`` and ``kind`` of STRONG sets (with parent and bits) that are core or extension sets, and how many subsets were counted for it."""
        below = materialize(strong.select("g", "s", "bits", "parent", F.explode(immediate_subsets(F.col("s"))).alias("t")), "subsets")
        unseen = below.select("g", F.col("t").alias("s")).distinct().join(known.select("g", "s"), ["g", "s"], "left_anti")
        side = self.count(unseen)
        judged = known.select("g", F.col("s").alias("t"), F.col("bits").alias("sub"), F.col("zone").alias("z"))
        if side:
            judged = judged.unionByName(materialize(self.bits(unseen), "side-sets").select("g", F.col("s").alias("t"), F.col("bits").alias("sub"), F.col("zone").alias("z")))
        is_strong = F.col("z") == "STRONG"
        status = below.join(judged, ["g", "t"]).groupBy("g", "s", "bits", "parent").agg(
            F.count_if(is_strong).alias("strong"), F.count_if(F.col("z") == "WEAK").alias("weak"), F.max(F.when(is_strong, F.col("sub"))).alias("sub"), F.max_by(F.when(is_strong, F.col("t")), F.when(is_strong, 1).otherwise(0)).alias("x")
        )
        x = F.coalesce("x", F.slice("s", 1, F.size("s") - 1))
        k = F.array_except(F.col("s"), x)[0]
        df = significance.df_tc_gain(self.frame, x, k) if self.c is None else significance.df_cac_gain(self.frame, x, k)
        status = status.withColumn("cut", significance.critical_values(df, self.frame.n, self.high, self.low)["strong_at"])
        parents = kept.select("g", F.col("s").alias("parent"), F.lit(True).alias("parent_kept"))
        status = status.join(parents, ["g", "parent"], "left")
        core = F.col("parent_kept").isNull() & (F.col("weak") == F.size("s"))
        extension = F.col("parent_kept").isNotNull() & (F.col("strong") == 1) & (F.col("weak") == F.size("s") - 1) & (F.col("bits") - F.col("sub") > F.col("cut"))
        return status.withColumn("kind", F.when(core, "core").when(extension, "extension")).filter("kind is not null").select("g", "s", "bits", "kind"), side


def mine(frame: Frame, mode: str = "tc", alpha_high: float = ALPHA_HIGH, alpha_low: float = ALPHA_LOW, max_order: int | None = None, min_ratio: float = 5.0, bounds: bool = True, first_order: int = 1) -> tuple[DataFrame, DataFrame]:
    """Core and extension sets (``g``, ``members``, ``bits``, ``kind``) by the tree rule, and a report of the levels."""
    significance.check_alphas(alpha_high, alpha_low)
    run = Lattice(frame, mode, alpha_high, alpha_low)
    attributes = frame.attributes().filter(F.col("idx") != (run.c if run.c is not None else -1))
    groups = materialize(frame.rows.select("g").distinct(), "groups")
    shape = frame if mode == "cac" else Frame(frame.rows, frame.names, frame.states, frame.n)
    ones = groups.join(F.broadcast(attributes.select(F.array("idx").alias("s"))))
    run.count(ones)
    start = first_order if run.c is not None else 2
    pairs = children(ones, attributes)
    level = materialize(ones if start == 1 else pairs.filter(enough_samples(shape, F.col("s"), min_ratio)).select("g", "s"), "first-level")
    if bounds or start == 2:
        run.count(pairs)
    exact = run.count(level)
    nodes = materialize(run.bits(level), "level")
    known = nodes.select("g", "s", "bits", "zone")
    kept = nodes.filter("zone = 'STRONG'").select("g", "s", "bits", F.lit("core").alias("kind"))
    result = kept
    before = nodes.select("g", "s", F.col("bits").alias("lo"), F.col("bits").alias("hi"), F.col("h").alias("h_hi"))
    front = nodes.filter("zone <> 'MIDDLE'").select("g", "s")
    run.levels.append((start, level.count(), 0, 0, exact, 0, kept.count(), front.count()))
    for order in range(start + 1, (max_order or len(frame.names)) + 1):
        grown = materialize(children(front, attributes), "children")
        cands = grown.filter(enough_samples(shape, F.col("s"), min_ratio))
        n, fit = grown.count(), cands.count()
        if not fit:
            break
        if bounds:
            judged = run.zoned(run.zoned(run.bounded(cands, before), "lo", "at_low"), "hi", "at_high")
            judged = materialize(judged, "bounds")
            open_sets, decided = judged.filter("at_low <> at_high"), judged.filter("at_low = at_high")
        else:
            judged = cands.withColumns({"h_hi": F.lit(0.0), "hi": F.lit(0.0), "lo": F.lit(0.0), "full": F.lit(False), "at_low": F.lit("STRONG"), "at_high": F.lit("STRONG")})
            open_sets, decided = judged, judged.limit(0)
        strong_by_bound = decided.filter("at_low = 'STRONG'")
        exact = run.count(open_sets.unionByName(strong_by_bound))
        settled = materialize(run.bits(open_sets.unionByName(strong_by_bound).select("g", "s", "parent")), "level")
        known = known.unionByName(settled.select("g", "s", "bits", "zone"))
        found, side = run.handled(settled.filter("zone = 'STRONG'"), known, kept)
        kept = materialize(found, "kept")
        result = result.unionByName(kept)
        weak = settled.filter("zone = 'WEAK'").select("g", "s").unionByName(decided.filter("at_low = 'WEAK' and not full").select("g", "s"))
        front = materialize(weak.unionByName(kept.select("g", "s")), "frontier")
        rest = decided.filter("at_low <> 'STRONG'").select("g", "s", "lo", "hi", "h_hi")
        before = rest.unionByName(settled.select("g", "s", F.col("bits").alias("lo"), F.col("bits").alias("hi"), F.col("h").alias("h_hi")))
        run.levels.append((order, n, n - fit, fit - open_sets.count(), exact, side, kept.count(), front.count()))
    members = result.select("g", F.col("s").alias("members"), "bits", "kind")
    return materialize(members, "lattice-result"), frame.spark.createDataFrame(run.levels, REPORT)
