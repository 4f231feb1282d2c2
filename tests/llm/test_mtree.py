"""The paged M-tree against brute force: small pages and leaves, so that searches descend, and results of pages are merged."""

import numpy as np
import pytest

from assocmine.llm import mtree
from assocmine.plans.materialize import materialize


def brute(ids, x, k=10):
    out = []
    for q in np.flatnonzero(ids % 100 == 0):
        scores = (x @ x[q]).astype(np.int64)
        best = sorted((-int(s), int(v)) for s, v in zip(scores, ids) if v != ids[q])[:k]
        out += [(int(ids[q]), r, v, -s) for r, (s, v) in enumerate(best, 1)]
    return sorted(out)


def vectors(kind, n=3000, dims=24, seed=3):
    draw = np.random.default_rng(seed)
    if kind == "random":
        x = draw.normal(size=(n, dims))
    else:
        centres = draw.normal(size=(30, dims)) * 4
        x = centres[draw.integers(0, 30, n)] + draw.normal(size=(n, dims)) * 0.05
    if kind == "hot":
        x[: n // 3] = x[0]
    return np.floor(1024 * x / np.linalg.norm(x, axis=1)[:, None])


@pytest.mark.parametrize("kind", ["random", "clustered", "hot"])
def test_small_pages_equal_brute_force(spark, kind):
    x = vectors(kind)
    ids = np.arange(len(x)) * 5
    rows = materialize(spark.createDataFrame([(int(i), v.tolist()) for i, v in zip(ids, x)], "vec_id long, v array<double>"), "test-vectors")
    asked = materialize(rows.filter("vec_id % 100 = 0"), "test-asked")
    options = dict(page=200, leaf=8, fanout=4, wave_bytes=20_000)
    got = sorted(tuple(r) for r in mtree.search(rows, asked, **options).collect())
    assert got == [tuple(r) for r in brute(ids, x)]
    pages, _, _ = mtree.index(rows, page=200, leaf=8, fanout=4)
    assert pages.count() >= 15 and pages.agg({"part": "max"}).first()[0] >= (4 if kind == "hot" else 0)
    cost = mtree.search_cost(rows, asked, **options).agg({"scored": "avg"}).first()[0] / len(x)
    assert cost < {"random": 1.2, "clustered": 0.1, "hot": 0.5}[kind], cost


def test_tree_bounds_hold():
    draw = np.random.default_rng(5)
    for x in (np.floor(draw.normal(size=(500, 7)) * 100), np.ones((300, 3)), np.floor(np.exp(draw.normal(size=(200, 4)) * 6)), np.full((20, 2), 1e200)):
        tree = mtree.Tree(np.arange(len(x)), x, 4, 3)
        import pickle

        tree = pickle.loads(pickle.dumps(tree))
        for q in (x[0], x[-1], -x[3], draw.normal(size=x.shape[1]).round()):
            exact = sorted(((max(-(1 << 63), min((1 << 63) - 1, sum(int(a) * int(b) for a, b in zip(v, q)))), -i) for i, v in zip(tree.ids.tolist(), tree.x)), reverse=True)[:6]
            found, scored = tree.search(-1, q, 6)
            assert found == [(s, -i) for s, i in exact] and scored <= len(x)
            assert tree.root_bounds(q[None])[0] >= exact[0][0]
            assert tree.search(-1, q, 6, exact[2][0])[0][:3] == [(s, -i) for s, i in exact[:3]]
