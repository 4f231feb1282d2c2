"""Worked examples, closed forms, planted workloads, edge cases, and agreement between strategies, rules and streams."""

import math
import random
import time
import warnings
from itertools import combinations

import numpy as np
import pytest
from pyspark.sql import functions as F

from assocmine.functions import gamma
from assocmine.operators import baselines, bounds, evaluation, interactions, metrics, mining, permutation, redundancy, significance
from assocmine.plans import counts
from assocmine.sources import discretize, planted, tables
from assocmine.sources.frame import encode

SF = "/root/testdata/sf0.01"


def small(spark, rows, class_name=None):
    names = [f"a{i}" for i in range(len(rows[0]))]
    return encode(spark.createDataFrame([tuple(map(int, r)) for r in rows], ", ".join(f"{n} int" for n in names)), names, class_name)


def test_gamma_closed_forms():
    for bits in (1e-6, 1e-4, 0.003, 0.02, 0.2):
        x = bits * 1000 * math.log(2)
        for df in (2, 4, 10, 40):
            want = significance.p_even_df(bits, df, 1000)
            got = gamma.log_p(bits, df, 1000)
            assert got == pytest.approx(math.log(want), abs=1e-9 * max(1, abs(math.log(want)))) if want > 1e-290 else got < -600
        assert gamma.log_p(bits, 1, 1000) == pytest.approx(math.log(math.erfc(math.sqrt(x))), rel=1e-9, abs=1e-12)
    assert gamma.log_p(3.0, 4, 10**6) < -2e6  # far below what a double can hold
    for df in (1, 2, 7, 300):
        for alpha in (1e-2, 1e-8, 1e-30):
            c = gamma.critical_bits(df, 500, alpha)
            assert gamma.log_p(c * 1.0001, df, 500) < math.log(alpha) < gamma.log_p(c * 0.9999, df, 500)


def test_levels_must_be_ordered():
    with pytest.raises(ValueError):
        significance.check_alphas(0.1, 0.01)


def test_sample_rule_example(spark):
    """Three ternary attributes need 135 rows."""
    draw = random.Random(0)
    for n, enough in ((135, True), (134, False)):
        rows = [[draw.randrange(3) for _ in range(3)] for _ in range(n - 3)] + [[i] * 3 for i in range(3)]
        assert mining.Search(small(spark, rows), "tc", 1e-8, 1e-2, "product", 5.0, 1000).enough((0, 1, 2)) is enough


def test_xor_and_copies_have_known_interactions(spark):
    xor = small(spark, [(a, b, a ^ b) for a in (0, 1) for b in (0, 1)] * 10)
    ent = counts.entropies(xor, metrics.all_sets(range(3), 1, 3))
    assert metrics.interaction_info(ent, metrics.table(xor, [(0, 1, 2)])).first().ii == pytest.approx(1.0)
    copy = small(spark, [(a, a, a) for a in (0, 1)] * 20)
    ent = counts.entropies(copy, metrics.all_sets(range(3), 1, 3))
    assert metrics.interaction_info(ent, metrics.table(copy, [(0, 1, 2)])).first().ii == pytest.approx(-1.0)
    assert redundancy.scores(copy, ent).first().score == pytest.approx(-1.0)


def test_two_strong_pairs_make_no_core_of_four(spark):
    draw = random.Random(5)
    rows = [(a, a, b, b) for a, b in ((draw.randrange(2), draw.randrange(2)) for _ in range(200))]
    found = mining.exhaustive(small(spark, rows), max_order=4).result[0]
    assert set(found) == {(0, 1), (2, 3)}


def test_bounds_hold_on_random_data():
    draw = np.random.default_rng(1)
    broken = 0
    for _ in range(400):
        x = draw.integers(0, 3, size=(60, 4))
        for k in range(1, 4):
            same = draw.random(60) < draw.random()
            x[same, k] = x[same, draw.integers(0, k)]

        def h(s):
            _, n = np.unique(x[:, list(s)], axis=0, return_counts=True)
            return math.log2(60) - float((n * np.log2(n)).sum()) / 60

        exact = {s: h(s) for k in (1, 2) for s in combinations(range(4), k)}
        tight, loose = bounds.Entropies(dict(exact)), bounds.Entropies(dict(exact), tight=False)
        for s in [*combinations(range(4), 3), (0, 1, 2, 3)]:
            assert h(s) <= tight.upper(s) + 1e-9 <= loose.upper(s) + 2e-9
        (a, b), i, j = (0, 1), 2, 3
        sums, hs = h((a,)) + h((b,)) + h((j,)), h((a, b, i))
        true = sums - h((a, b, j))
        given = lambda p, q: exact[tuple(sorted((p, q)))] - exact[(q,)]  # noqa: B023, E731
        assert bounds.tc_lower_sibling(sums, hs, min(given(j, a), given(j, b))) <= true + 1e-9
        assert bounds.tc_upper_sibling(sums, hs, given(i, j), min(given(i, a), given(i, b))) >= true - 1e-9
        broken += bounds.sibling_upper_as_printed(sums, hs, given(i, j), min(given(j, a), given(j, b))) < true - 1e-9
    assert broken > 0  # the printed form does not hold


def test_six_cases_are_all():
    zones = ("STRONG", "MIDDLE", "WEAK")
    assert set(mining.CASES) == {(u, low) for i, u in enumerate(zones) for low in zones[i:]}


def test_noise_experiment(spark):
    frame = planted.noisy_xor(spark, SF, list(range(3)), (0.0, 0.2, 0.3))
    found = mining.mine_correlation(frame, max_order=4)
    groups = frame.rows.select("g").distinct()
    curve = {round(r.noise, 2): r for r in evaluation.noise_curve(found.table(), planted.XOR_TRUTH, groups, (0.0, 0.2, 0.3)).collect()}
    assert curve[0.0].detected >= 0.85 and curve[0.2].detected >= 0.7 and curve[0.3].detected <= 0.4
    assert all(r.false_rate <= 0.05 for r in curve.values())
    plain = mining.mine_correlation(frame, max_order=4, bounds=False)
    assert mining.differences(found, plain).count() == 0
    assert sum(v.exact for v in found.levels) <= sum(v.exact for v in plain.levels)


def test_class_experiments(spark):
    frame = planted.class_copies(spark, SF, [0, 1])
    reps = redundancy.representatives(frame)
    assert [reps[i] for i in (0, 1, 2)] == [[0, 5], [1, 6], [2, 7]] and len(reps) == 12
    reduced = redundancy.apply(frame, reps)
    found = mining.mine_class_correlation(reduced)
    assert all({(0,), (2,), (0, 1)} == set(f) for f in found.result.values())
    first = baselines.relevance_redundancy(frame, n_select=3)
    assert {r.attribute for r in first.filter("rank <= 2").collect()} <= {"a1", "a3", "a6", "a8"}
    assert mining.mine_class_correlation(reduced, first_order=2).result != found.result
    with warnings.catch_warnings(record=True) as seen:
        warnings.simplefilter("always")
        redundancy.representatives(frame, context="class")
    assert any("threshold" in str(w.message) for w in seen)


def test_interactions_beyond_search(spark):
    """II finds the triple with the class that the class search cannot report."""
    frame = planted.class_copies(spark, SF, [1])
    reduced = redundancy.apply(frame, redundancy.representatives(frame))
    c = reduced.class_at
    out = {tuple(r.s): r for r in permutation.fast(reduced, [(0, 1, 2, c), (1, c)], 1000).collect()}
    assert out[(0, 1, 2, c)].p == 0.0 and out[(1, c)].p > 0.05


def test_permutations(spark):
    table = np.array([[5, 3, 2], [1, 7, 4]])
    drawn = permutation.resample(table, 500, np.random.default_rng(0))
    assert (drawn.sum(axis=1) == table.sum(axis=0)).all() and (drawn.sum(axis=2) == table.sum(axis=1)).all()
    frame = planted.class_copies(spark, SF, [0])
    s = (0, 1, frame.class_at)
    fast, naive = permutation.fast(frame, [s], 2000).first(), permutation.naive(frame, s, 60).first()
    assert fast.ii == pytest.approx(naive.ii, abs=1e-9)
    assert abs(fast.p - naive.p) <= 3 * math.sqrt(max(fast.p, 0.02) * (1 - fast.p) / 60) + 0.02
    assert fast.cells_touched == 2000 * 18
    assert permutation.fast(frame, [s], 100, add_one=True).first().p >= 1 / 101
    assert permutation.fast(frame, [(1, frame.class_at)], 10_000, early_stop=0.01).first().nperm < 10_000


def test_rules_and_options(spark):
    frame = planted.epistasis(spark, SF, [0])
    tree, by_definition = mining.mine_correlation(frame, max_order=3), mining.mine_correlation(frame, max_order=3, rule="definition")
    assert mining.differences(by_definition, mining.exhaustive(frame, max_order=3)).count() == 0
    assert set(tree.result[0]) <= set(by_definition.result[0]) | set(tree.result[0])
    assert mining.mine_correlation(frame, max_order=3, subset_check="all").result == tree.result
    assert mining.mine_correlation(frame, max_order=3, min_bits=10.0).result[0] == {}
    with pytest.raises(RuntimeError):
        mining.mine_correlation(frame, max_sets=10)
    assert mining.mine_correlation(frame, max_order=2, v_mode="observed").levels[0].children == 120


def test_encoding_edges(spark):
    df = spark.createDataFrame([(1, "x", None, 5), (2, None, None, 5), (2, "y", None, 5)], "a int, b string, c int, d int")
    frame = encode(df, ["a", "b", "c", "d"])
    assert frame.names == ("a", "b") and set(frame.dropped) == {"c", "d"} and frame.states == (2, 3)
    assert mining.mine_correlation(frame).result == {0: {}}
    empty = encode(df.limit(0), ["a", "b"])
    assert empty.n == 0 and mining.mine_correlation(empty).table().count() == 0
    one = encode(df, ["a"])
    assert mining.mine_correlation(one).table().count() == 0
    with pytest.raises(ValueError):
        encode(df, ["a", "b"], max_states=1)
    with pytest.raises(ValueError):
        mining.mine_class_correlation(frame)
    assert discretize.drop_gap_columns(df, ["a", "b", "c"]) == ["a"] and discretize.drop_gap_rows(df, ["b"]).count() == 2
    assert len(discretize.random_removal(list("abcdef"), 2, 0)) == 4
    assert discretize.equal_depth(spark.range(100), "id", 4, "q").groupBy("q").count().count() == 4


def test_strategies_and_large_keys(spark):
    frame = planted.class_gain(spark, SF, [0]).collapse()
    sets = metrics.all_sets(range(4), 1, 3)
    per = [{tuple(r.s): (round(r.h, 9), r.cells) for r in counts.entropies(frame, sets, k).collect()} for k in ("cube", "explode", "arrays", "maximal")]
    assert all(p == per[0] for p in per[1:])
    wide = planted.runtime_small(spark, SF)
    assert counts.cells_of(wide, tuple(range(50))) > counts.MOST_CELLS
    assert counts.entropies(wide, [tuple(range(50))], "explode").first().h <= math.log2(91) + 1e-9
    old, counts.CELL_BUDGET = counts.CELL_BUDGET, 40
    try:
        assert {tuple(r.s): (round(r.h, 9), r.cells) for r in counts.entropies(frame, sets, "arrays").collect()} == per[0]
    finally:
        counts.CELL_BUDGET = old


def test_recovery_and_case_study(spark):
    assert redundancy.reduce({0: {0, 1, 2}, 1: {0, 1}, 2: {0, 2}, 3: {3}}) == {0: [0, 1, 2], 3: [3]}
    assert redundancy.reduce({0: {0, 1}, 1: {0, 1}}, "static") == {0: [0, 1]}
    assert redundancy.expand([(0, 2)], {0: [0, 1], 2: [2]}) == [(1, 2)]
    frame = planted.case_study(spark, SF)
    assert frame.n == 150 and len(frame.predictors) == 40
    found, significant, groups = interactions.pipeline(frame, "cac", alpha_high=1e-4, max_order=2)
    assert set(groups) <= set(range(41)) and significant.count() >= 0 and found.metric == "CAC"


def test_stream_equals_batch(spark, tmp_path):
    from assocmine.streaming import windows

    events = spark.read.parquet(f"{SF}/events.parquet")
    attributes = {"a": F.col("event_type"), "b": F.floor(F.hour("ts") / 6)}
    sets = [("a",), ("b",), ("a", "b")]
    source = str(tmp_path / "in")
    late = events.agg(F.max("ts")).first()[0]
    closing = events.limit(1).withColumn("ts", F.lit(late) + F.expr("interval 3 days"))
    events.coalesce(1).write.parquet(source)
    closing.coalesce(1).write.mode("append").parquet(source)
    stream = tables.read_stream(spark, source, ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in events.schema), 10)
    query = windows.cell_counts(stream, attributes, sets).writeStream.format("memory").queryName("cells_out").outputMode("append").trigger(availableNow=True).start()
    query.awaitTermination(120)
    key = lambda df: {(r.window_start, r.set_id, r.cell): r.n for r in df.collect()}
    got, want = key(spark.table("cells_out")), key(windows.cell_counts(events, attributes, sets))
    assert got == want
    out = windows.mine_continuously(windows.cell_counts(stream, attributes, sets), str(tmp_path / "out"), str(tmp_path / "cp"), lambda df: df)
    out.awaitTermination(120)
    assert spark.read.parquet(str(tmp_path / "out")).count() == windows.window_tc(windows.cell_counts(events, attributes, sets)).count()


def test_sources_round_trip(spark, tmp_path):
    rows = tables.generated(spark, 50, 3)
    for kind in ("parquet", "orc", "json"):
        rows.write.format(kind).save(str(tmp_path / kind))
        assert tables.read(spark, str(tmp_path / kind), kind, "key long, a1 int, a2 int, a3 int", ["a1", "a2"]).count() == 50
    with pytest.raises(ValueError):
        tables.read(spark, "x", "csv")
    found = mining.mine_correlation(planted.epistasis(spark, SF, [0]), max_order=2)
    tables.write_result(found.table(), str(tmp_path / "result"))
    assert spark.read.parquet(str(tmp_path / "result")).filter("ord = 2").count() == 1


def test_exact_pairs_and_early_stop(spark):
    """Enumerated p of a 2 x 2 table, and draws that end early without changing what is significant."""
    rows = [(0, 0)] * 30 + [(0, 1)] * 12 + [(1, 0)] * 9 + [(1, 1)] * 29
    frame = small(spark, rows)
    exact = permutation.exact_pairs(frame, [(0, 1)]).first()
    r, c, n = 38, 41, 80
    chance = lambda k: math.comb(r, k) * math.comb(n - r, c - k) / math.comb(n, c)
    info = lambda k: metrics_of_table([n - r - c + k, c - k, r - k, k])
    want = sum(chance(k) for k in range(max(0, r + c - n), min(r, c) + 1) if info(k) >= info(29) - 1e-12)
    assert exact.p == pytest.approx(want, rel=1e-6) and exact.ii == pytest.approx(info(29), abs=1e-9)
    drawn = permutation.fast(frame, [(0, 1)], 4000).first()
    assert abs(drawn.p - want) <= 5 * math.sqrt(max(want, 1e-4) / 4000)


def metrics_of_table(cells):
    n, total = np.array(cells, dtype=float).reshape(2, 2), sum(cells)
    h = lambda x: math.log2(total) - float((x[x > 0] * np.log2(x[x > 0])).sum()) / total
    return h(n.sum(axis=0)) + h(n.sum(axis=1)) - h(n.ravel())


def test_each_equals_passes_over_the_frame(spark):
    """One task a data set gives what the search over the whole frame gives, and reduces every data set by itself."""
    frame = planted.class_copies(spark, SF, [0, 1])
    whole = mining.mine_class_correlation(frame, max_order=2)
    each = {(r.g, tuple(r.members), r.kind) for r in mining.mine_each(frame, "cac", max_order=2).collect()}
    assert each == {(g, s, f.kind) for g, found in whole.result.items() for s, f in found.items()}
    reduced = mining.mine_each(frame, "cac", delta=0.75)
    assert {(r.g, tuple(r.members)) for r in reduced.collect()} == {(g, s) for g in (0, 1) for s in ((0,), (2,), (0, 1))}
    own = {(r.g, r.rep): list(r.covered) for r in redundancy.representatives_each(frame).collect()}
    assert all(own[g, 0] == [0, 5] and own[g, 1] == [1, 6] and own[g, 2] == [2, 7] for g in (0, 1)) and len(own) == 24
    assert baselines.hard_threshold_each(frame, max_order=2).count() == baselines.hard_threshold(frame, max_order=2).count()


def test_two_step_strategy_finds_the_planted_sets(spark):
    """Significant II at 10,000 draws and level 1e-4, no row filtered: the planted sets and next to nothing else."""
    frame = planted.noisy_xor(spark, SF, list(range(4)))
    found = interactions.pipeline_each(frame, delta=None).collect()
    hits = {(r.g, tuple(r.s)) for r in found}
    planted_hits = {(g, s) for g in range(4) for s in planted.XOR_TRUTH}
    assert len(hits & planted_hits) >= 10 and len(hits - planted_hits) <= 4


def test_late_rows_are_dropped(spark, tmp_path):
    from assocmine.streaming import windows

    rows = lambda *days: spark.createDataFrame([(f"2024-01-{d:02d} 12:00:00", "x", "y") for d in days], "ts string, a string, b string").withColumn("ts", F.col("ts").cast("timestamp")).coalesce(1)
    source = str(tmp_path / "late")
    rows(1, 5, 9).write.parquet(source)
    for batch in ((10,), (2, 20)):  # rows are late by the watermark that the batch before last has set: day 2 is by then
        time.sleep(1.1)
        rows(*batch).write.mode("append").parquet(source)
    stream = tables.read_stream(spark, source, "ts timestamp, a string, b string", 1)
    cells = windows.run_to_end(windows.cell_counts(stream, {"a": F.col("a"), "b": F.col("b")}, [("a",)]), "append")
    assert {r.window_start.day for r in cells.collect()} == {1, 5, 9, 10}


def test_relevance_selector_leaves_the_driver_alone(spark, monkeypatch):
    """Counted by its tasks or from written entropies, the selector chooses the same, and no data set is collected."""
    from pyspark.sql.classic.dataframe import DataFrame as Classic

    frame, targets = planted.noisy_xor(spark, "/root/testdata/sf0.001", None, (0.0,)), {0: 2, 5: 3}
    with monkeypatch.context() as m:
        m.setattr(Classic, "collect", lambda self: pytest.fail("collected"))
        local = baselines.relevance_targets(frame, targets)
        m.setattr(baselines, "LOCAL_ROWS", 0)
        passes = baselines.relevance_targets(frame, targets)
    rows = lambda df: sorted((r.g, r.target, r["rank"], r.attribute, r.idx, round(r.relevance, 9), round(r.score, 9)) for r in df.collect())
    assert rows(local) == rows(passes) and len(rows(local)) == 5 * local.select("g").distinct().count() > 0


def test_spectrum_shuffles_no_cells(spark, monkeypatch):
    """Zones of small data sets are found by one task each, as by the tables of counted cells."""
    frame = planted.epistasis(spark, "/root/testdata/sf0.001", [0, 1])
    sets = [s for s in metrics.all_sets(range(16), 2, 3) if counts.cells_of(frame, s) * 5 <= frame.n]
    tc = metrics.total_correlation(counts.entropies(frame, [*((i,) for i in range(16)), *sets]), metrics.table(frame, sets)).withColumn("df", significance.df_tc(frame, F.col("s")))
    want = sorted((r.g, tuple(r.s), round(r.tc, 9), r.zone) for r in significance.with_zone(tc, "tc", frame.n).filter("zone <> 'WEAK'").collect())
    monkeypatch.setattr(counts, "count_cells", lambda *_: pytest.fail("cells are shuffled"))
    found = mining.zones_each(frame, sets)
    assert want == sorted((r.g, tuple(r.s), round(r.bits, 9), r.zone) for r in found.collect()) and want
