"""The search in arrays: results and reports of the search set by set, and a cost that thousands of data sets can bear."""

import numpy as np
import pytest

from assocmine.operators import baselines, evaluation, interactions, local, mining
from assocmine.operators.significance import ALPHA_HIGH, ALPHA_LOW
from assocmine.sources import planted
from assocmine.sources.frame import Frame


def drawn(seed, n=200):
    """Attributes of two to four values, some of them noisy copies or sums of the ones before."""
    rng = np.random.default_rng(seed)
    states = tuple(rng.integers(2, 5, 7).tolist()) if seed % 2 else (2,) * 8
    x = np.stack([rng.integers(0, r, n) for r in states])
    for i in range(2, len(states)):
        if i % 2:
            x[i] = np.where(rng.random(n) < 0.85, x[i - 1] % states[i], x[i])
        else:
            x[i] = np.where(rng.random(n) < 0.95, (x[i - 1] + x[i - 2]) % states[i], x[i])
    w = rng.integers(1, 4, n) if seed % 3 == 0 else np.ones(n, dtype=np.int64)
    return x, w, states


def plain(found):
    return {s: (f.kind, f.df, round(f.bits, 9)) for s, f in found.result[0].items()}, found.level_rows()


@pytest.mark.parametrize("seed", range(6))
@pytest.mark.parametrize("mode", ["tc", "cac"])
def test_results_and_report_equal_the_search_set_by_set(seed, mode):
    x, w, states = drawn(seed)
    frame = Frame(None, tuple(f"a{i}" for i in range(len(states))), states, int(w.sum()), seed % len(states) if mode == "cac" else None)
    for bounds in (False, True):
        for first_order in (1, 2):
            for min_ratio in (5.0, 1.0):
                options = {"bounds": bounds, "first_order": first_order, "min_ratio": min_ratio, "alpha_high": 1e-4}
                slow = mining.mine(frame, mode, groups=[0], count=mining.counter(0, x, w, states), **options)
                assert plain(local.mine(frame, mode, 0, x, w, **options)) == plain(slow)


@pytest.mark.parametrize("seed", range(4))
def test_interactions_and_fixed_cut_offs_equal_those_set_by_set(seed, monkeypatch):
    x, w, states = drawn(seed)
    names = tuple(f"a{i}" for i in range(len(states)))
    frame = Frame(None, names, states, int(w.sum()))
    slow = baselines._hard_threshold(mining.Search(frame, "tc", ALPHA_HIGH, ALPHA_LOW, "product", 5.0, 10**6, groups=[0], count=mining.counter(0, x, w, states)), 0.2, 0.3, 4)
    fast = local.hard_threshold(x, w, frame, 0.2, 0.3, 4, 5.0)
    assert sorted((tuple(s), round(b, 9)) for _, s, _, b in slow) == sorted((s, round(b, 9)) for s, b in fast)
    for c in (None, 1):
        frame = Frame(None, names, states, int(w.sum()), c)
        fast = interactions.mine_in_memory(x, w, frame, [0, 1, 2, 4, 6], 3)
        monkeypatch.setattr(local, "MOST_SETS", 0)
        slow = interactions.mine_in_memory(x, w, frame, [0, 1, 2, 4, 6], 3)
        monkeypatch.undo()
        assert fast.keys() == slow.keys() and all(abs(fast[s] - slow[s]) < 1e-9 for s in slow)


def test_a_run_handles_levels_and_not_sets(monkeypatch):
    """Before, each of 20,000 sets of a run was looked at by itself, many times: no method of the search by sets is called now."""
    calls = []
    for name in ("settle", "bits", "limits"):
        monkeypatch.setattr(mining.Search, name, lambda self, *a, name=name: calls.append(name) or pytest.fail(name))
    x = np.random.default_rng(1).integers(0, 3, (48, 387))
    frame = Frame(None, tuple(f"a{i}" for i in range(1, 49)), (3,) * 48, 387)
    made = evaluation._timed(frame, 0, x, np.ones(387, dtype=np.int64), 8, 0, "bounds", "tc", 0.75, None)
    assert made[3] == 40 and made[6] > 9_000 and not calls


def test_an_attribute_with_one_value_in_a_data_set_is_redundant_with_none():
    from assocmine.operators import redundancy

    x = np.array([[0, 1, 0, 1], [0, 0, 0, 0], [0, 1, 0, 1]])
    assert redundancy.representatives_of(Frame(None, ("a", "b", "c"), (2, 2, 2), 4), x, np.ones(4, dtype=np.int64)) == {0: [0, 2], 1: [1]}


def test_runs_of_many_data_sets_share_tasks(spark):
    """Before, every run was a task: 16 for each data set, whatever their number."""
    from pyspark.sql import functions as F

    rows = spark.range(300 * 20).select((F.col("id") % 300).alias("g"), F.array(*[(F.col("id") / 300 / k).cast("int") % 2 for k in (1, 2, 4)]).alias("a"), F.lit(1).cast("long").alias("w"))
    curve = evaluation.runtime_curve(Frame(rows, ("a1", "a2", "a3"), (2, 2, 2), 20), (0, 1), 10)
    assert curve.rdd.getNumPartitions() <= 16 * spark.sparkContext.defaultParallelism
    assert curve.count() == 300 * 2 * 4
    assert evaluation.curve_tasks(10**6, 8) * 64 >= 10**6 and evaluation.curve_tasks(40, 8) == 40


def test_noise_levels_share_their_uniforms(spark):
    """Before, the uniforms of a key were made again for each noise level."""
    count = lambda noise: planted._noisy_xor(spark, "/root/testdata/sf0.001", [0], noise)._jdf.queryExecution().optimizedPlan().toString().count("md5")
    assert 0 < count(planted.NOISE) == count((0.1,))


def test_prunings_that_are_not_timed_count_a_set_once(monkeypatch):
    """Rows are those of runs by themselves, for few entropies more than the run without prunings counts alone."""
    draw = np.random.default_rng(8)
    x = draw.integers(0, 3, (13, 387))
    x[4] = np.where(draw.random(387) < 0.05, x[4], x[0])
    x[12] = (x[0] + x[1]) % 2
    w = np.ones(387, dtype=np.int64)
    frame = Frame(None, tuple(f"a{i}" for i in range(12)) + ("c",), (3,) * 12 + (2,), 387, 12)
    counted, count = [], local.Cells._of_pattern
    monkeypatch.setattr(local.Cells, "_of_pattern", lambda self, members, pattern: (counted.append(len(members)), count(self, members, pattern))[1])
    monkeypatch.setattr(local, "interactions", lambda *given: [])
    for mode in ("tc", "cac"):
        alone = [evaluation._timed(frame, 0, x, w, 2, 0, prune, mode, 0.75, None) for prune in evaluation.MODES]
        counted.clear()
        evaluation._timed(frame, 0, x, w, 2, 0, "none", mode, 0.75, None)
        one = sum(counted)
        counted.clear()
        shared = evaluation._runs(frame, 0, x, w, 2, 0, evaluation.MODES, mode, 0.75, None, False)
        assert [r[:9] + r[10:] for r in shared] == [r[:9] + r[10:] for r in alone] and all(r[9] is None for r in shared)
        assert 0 < one <= sum(counted) <= 1.5 * one
