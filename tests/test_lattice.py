"""The search in tables against the search on the driver."""

from assocmine.operators import lattice, mining
from assocmine.plans import counts
from assocmine.sources import planted

SF = "/root/testdata/sf0.01"


def rows(df):
    return sorted((r.g, tuple(r.members), round(r.bits, 9), r.kind) for r in df.collect())


def test_same_sets_with_and_without_bounds(spark):
    frame = planted.epistasis(spark, SF, [0, 1, 2])
    want = rows(mining.mine_correlation(frame).table())
    found, report = lattice.mine(frame)
    assert rows(found) == want and want
    plain, full = lattice.mine(frame, bounds=False)
    assert rows(plain) == want
    assert report.agg({"exact": "sum"}).first()[0] <= full.agg({"exact": "sum"}).first()[0]


def test_class_and_small_chunks(spark):
    frame = planted.class_gain(spark, SF, [0, 1])
    old, counts.CHUNK_SETS = counts.CHUNK_SETS, 150
    try:
        assert rows(lattice.mine(frame, "cac")[0]) == rows(mining.mine_class_correlation(frame).table())
    finally:
        counts.CHUNK_SETS = old


def test_sparse_cells(spark):
    """Sets with more possible cells than a task's budget are counted by their distinct cells."""
    frame = planted.noisy_xor(spark, SF, [0])
    old = counts.DENSE_CELLS, counts.CELL_BUDGET
    counts.DENSE_CELLS, counts.CELL_BUDGET = 4, 100
    try:
        assert rows(mining.mine_correlation(frame, max_order=4).table()) == rows(mining.mine_each(frame, max_order=4))
    finally:
        counts.DENSE_CELLS, counts.CELL_BUDGET = old
