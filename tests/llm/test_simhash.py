"""SimHash components against brute force over all pairs."""

import random

import xxhash

from assocmine.llm import simhash
from tests.llm.fixtures import frame, mixed_documents


def plain_print(text):
    words = "".join(c.lower() if "A" <= c <= "Z" else c for c in text or "").replace("\t", " ").replace("\n", " ").replace("\r", " ").replace("\x0b", " ").replace("\x0c", " ").split(" ")
    words = [w for w in words if w]
    if not words:
        return 0
    hashes = [xxhash.xxh64_intdigest(" ".join(words[i : i + 3]).encode(), 42) for i in range(max(1, len(words) - 2))]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def plain_components(prints):
    label = list(range(len(prints)))
    changed = True
    while changed:
        changed = False
        for i in range(len(prints)):
            for j in range(len(prints)):
                if (prints[i] ^ prints[j]).bit_count() <= 2 and label[j] > label[i]:
                    label[j], changed = label[i], True
    return label


def test_against_all_pairs(spark):
    draw = random.Random(3)
    rows = mixed_documents()
    vocabulary = ["alpha", "beta", "gamma", "delta", "eps"]
    base = [draw.choice(vocabulary) for _ in range(400)]
    for i in range(40):
        words = list(base)
        words[draw.randrange(len(words))] = "changed"
        rows.append((1000 + i, " ".join(words), "en", "src0", 1))
    rows += [(2000 + i, " ".join(draw.choice(vocabulary) for _ in range(3)), "en", None, 1) for i in range(40)]
    prints = [plain_print(r[1]) for r in rows]
    label = plain_components(prints)
    want = []
    for r, p, own in zip(rows, prints, label):
        want.append((r[0], f"{p:016x}", min(rows[i][0] for i in range(len(rows)) if label[i] == own and rows[i][0] is not None) if any(label[i] == own and rows[i][0] is not None for i in range(len(rows))) else None))
    got = simhash.near_duplicates(frame(spark, rows)).collect()
    assert sorted(map(tuple, got), key=str) == sorted(want, key=str)


def test_empty(spark):
    assert simhash.near_duplicates(frame(spark, [])).count() == 0


def test_long_chain_settles(spark):
    from assocmine.llm.components import connected

    edges = spark.createDataFrame([(i, i + 1) for i in range(300)], "a long, b long")
    assert {r.root for r in connected(edges).collect()} == {0}
