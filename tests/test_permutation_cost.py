"""II and random tables of the fast permutations: equal to the definition, and cheap enough for thousands of data sets."""

import numpy as np
import pytest

from assocmine.operators import permutation


def by_definition(tables, shape):
    """Margin by margin."""
    k, n = len(shape), tables[0].sum()
    cube, ii = tables.reshape((-1, *shape)), np.zeros(len(tables))
    for mask in range(1, 1 << k):
        gone = tuple(i + 1 for i in range(k) if not mask >> i & 1)
        margin = (cube.sum(axis=gone) if gone else cube).reshape(len(cube), -1)
        p = margin / n
        h = -np.where(p > 0, p * np.log2(np.where(p > 0, p, 1.0)), 0.0).sum(axis=1)
        ii -= (-1) ** (k - bin(mask).count("1")) * h
    return ii


@pytest.mark.parametrize("shape", [(2,), (2, 2), (3, 2), (3, 3, 2), (2, 2, 2, 2), (2, 3, 1, 2)])
@pytest.mark.parametrize("most", [1, permutation.LOOKED_UP])
def test_ii_is_the_signed_sum_of_margins(monkeypatch, shape, most):
    monkeypatch.setattr(permutation, "LOOKED_UP", most)
    tables = np.random.default_rng(1).multinomial(200, np.full(int(np.prod(shape)), 1 / np.prod(shape)), size=50)
    assert np.abs(permutation.table_ii(tables, shape) - by_definition(tables, shape)).max() < 1e-12


@pytest.mark.parametrize("most", [0, permutation.MOST_COLOURS])
def test_tables_of_two_columns_keep_margins_and_law(monkeypatch, most):
    """Both ways to draw: a cell's mean and variance are those of the hypergeometric law."""
    monkeypatch.setattr(permutation, "MOST_COLOURS", most)
    table = np.array([[20, 30], [5, 0], [25, 20]])
    drawn = permutation.resample(table, 20_000, np.random.default_rng(2))
    assert (drawn.sum(axis=1) == table.sum(axis=0)).all() and (drawn.sum(axis=2) == table.sum(axis=1)).all() and drawn.min() >= 0
    n, a, b = 100, 50, 50
    for r, m in enumerate(table.sum(axis=1)):
        variance = m * a / n * b / n * (n - m) / (n - 1)
        assert abs(drawn[:, r, 0].mean() - m * a / n) < 5 * (variance / 20_000) ** 0.5
        assert abs(drawn[:, r, 0].var() / variance - 1) < 0.06


def test_draws_of_a_binary_set_are_few_calls(monkeypatch):
    """A batch of tables with two columns is one call of the generator, and its II takes no logarithm once n is known."""
    cube = np.random.default_rng(3).multinomial(200, np.full(16, 1 / 16)).reshape((2,) * 4)
    permutation.table_ii(cube.reshape(1, -1), cube.shape)
    calls = []

    class Counted:
        def __init__(self, rng):
            self.rng = rng

        def __getattr__(self, name):
            calls.append(name)
            return getattr(self.rng, name)

    plogp = permutation._plogp
    monkeypatch.setattr(permutation, "_plogp", lambda x: calls.append("plogp") or plogp(x))
    _, _, done = permutation.count_hits(cube, 0, 1_000, Counted(np.random.default_rng(4)))
    assert done == 1_000 and len(calls) <= 1_000 / permutation.MOST_DRAWN and "plogp" not in calls


def test_small_data_sets_are_not_merged_into_few_tasks(spark):
    """Tasks are as many as the session's partitions, however few bytes the data sets have."""
    from pyspark.sql import functions as F

    from assocmine.operators.mining import dealt
    from assocmine.sources.frame import Frame

    rows = spark.range(64 * 200).select((F.col("id") % 64).alias("g"), F.array(F.lit(0), F.lit(1)).alias("a"), F.lit(1).cast("long").alias("w"))

    def run(table):
        from pyspark import TaskContext
        import pyarrow as pa

        return pa.table({"task": pa.array([TaskContext.get().partitionId()], pa.int32())})

    used = dealt(Frame(rows, ("a", "b"), (2, 2), 200)).applyInArrow(run, "task int").distinct().count()
    assert used >= 8
