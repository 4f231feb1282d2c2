"""Exact repeats against brute force over all byte strings."""

import random

import pytest

from assocmine.llm import repeats
from tests.llm.fixtures import frame, mixed_documents


def planted(seed):
    draw = random.Random(seed)
    prose = lambda n: "".join(draw.choice("abcdefgh é\n") for _ in range(n))
    shared, other = prose(700), prose(1500)
    rows = [(i, prose(draw.randrange(0, 900)) + draw.choice([shared, shared[50:], shared[:-80], other, other[300:720], ""]) + prose(draw.randrange(0, 900)), "en", "s", 1) for i in range(60)]
    rows += [(100 + i, other, "en", "s", 1) for i in range(5)]
    rows += [(200, shared + shared, "en", "s", 1), (201, "ab" * 600, "en", "s", 1), (202, "x" * 450, "en", "s", 1), (203, "x" * 399, "en", "s", 1), (204, "x" * 400 + "y", "en", "s", 1)]
    edited = list(other)
    edited[700] = "#"
    rows += [(205, "".join(edited), "en", "s", 1)]
    return rows + [r if r[0] != 10 and r[0] != 9 else r for r in mixed_documents(seed, 10)]


@pytest.mark.parametrize("length", [400, 50])
def test_against_brute_force(spark, length):
    rows = planted(length)
    want = sorted([(r[0], *x) for r, x in zip(rows, repeats.plain([(r[1] or "").encode() for r in rows], length))], key=str)
    got = sorted([tuple(r) for r in repeats.digest(repeats.removed(frame(spark, rows), length)).collect()], key=str)
    assert got == want


def test_empty(spark):
    assert repeats.removed(frame(spark, [])).count() == 0


def test_phrases_cover_all_strings():
    draw = random.Random(1)
    old, repeats.PIECE = repeats.PIECE, 700
    try:
        for n in (0, 399, 400, 401, 1099, 1100, 5000):
            text = bytes(draw.choice(b"abc") for _ in range(n))
            at, first, last = repeats.phrases(repeats.byte_view().units(text), repeats.byte_view())
            covered = [i for a, b in zip(first, last) for i in range(a, b + 1)]
            assert covered == list(range(max(0, n - 399)))
            assert all(i <= t < i + repeats.reach_of(400) for t, a, b in zip(at, first, last) for i in range(a, b + 1))
    finally:
        repeats.PIECE = old


def test_word_passages(spark):
    """Besides the byte strings: passages of 51 words, whatever their bytes, and only whole words of them."""
    draw = random.Random(4)
    word = lambda: "".join(draw.choice("abcdefghij") for _ in range(draw.randrange(1, 9)))
    prose = lambda n: " ".join(word() for _ in range(n))
    short, long = prose(51), prose(90)
    rows = [(1, f"{prose(30)} {short} {prose(20)}", "en", "s", 1), (2, f"{prose(9)}\n{short.replace(' ', '  ', 3)}\t{prose(60)}", "en", "s", 1), (3, prose(200), "en", "s", 1)]
    rows += [(4, f"{prose(5)} {' '.join(short.split()[:50])} {prose(5)}", "en", "s", 1), (5, f"{long} {prose(40)}", "en", "s", 1), (6, f"x{long}y z", "en", "s", 1), (7, None, "en", "s", 1), (8, " ".join(["w"] * 60), "en", "s", 1)]
    got = {r.doc_id: r for r in repeats.removed(frame(spark, rows), words=51, keep="text").collect()}
    seen: dict[tuple, int] = {}
    words = {r[0]: (r[1] or "").split() for r in rows}
    for w in words.values():
        for i in range(len(w) - 50):
            seen[tuple(w[i : i + 51])] = seen.get(tuple(w[i : i + 51]), 0) + 1
    for key, w in words.items():
        hit = {j for i in range(len(w) - 50) if seen[tuple(w[i : i + 51])] > 1 for j in range(i, i + 51)}
        assert got[key].n_passage_words == len(hit), key
        if not got[key].n_removed:
            assert got[key].kept.split() == [x for i, x in enumerate(w) if i not in hit]
    assert [got[k].n_passage_words for k in (1, 2, 3, 4, 7, 8)] == [51, 51, 0, 0, 0, 60] and got[5].n_passage_words == 88


def test_suffix_order_and_hot_class(spark):
    """Equal suffixes are found across tasks, whatever their number, and the order is that of the strings."""
    parts = [(i, 0, 50, 0, 3, b"core" if i % 2 else b"cord", bytes([97 + i % 3]) * 3, b"x" * (i % 5 and 15)) for i in range(3000)]
    schema = "id long, view long, base long, least int, most int, core binary, before binary, behind binary"
    ordered = repeats.suffix_order(spark.createDataFrame(parts, schema), {0: 1})
    rows = ordered.collect()
    keys = [(r.i, bytes(r.before), r.rank, bytes(r.behind)) for r in rows]
    by_task: dict[int, list] = {}
    for r, k in zip(rows, keys):
        by_task.setdefault(r.task, []).append(k)
    assert [k for t in sorted(by_task) for k in by_task[t]] == sorted(keys) and len(by_task) > 1 and len(keys) == 12000
    counts: dict[tuple, int] = {}
    for k in keys:
        counts[k] = counts.get(k, 0) + 1
    want = {(r.id, r.start) for r, k in zip(rows, keys) if counts[k] > 1}
    assert {(r.id, r.start) for r in repeats.equal_neighbours(ordered).collect()} == want
