"""Repeated passages of over 50 words, most of them shorter than 400 bytes, against brute force."""

import random
import re

import corpus_pipeline as cp
from assocmine.llm import repeats
from tests.llm.fixtures import SF, frame, mixed_documents


def plain(texts):
    """Of every text what is left without repeated byte strings and without repeated strings of 51 words."""
    seen, words, out = {}, [t.split() for t in texts], []
    for n, parts in ((repeats.LENGTH, texts), (51, words)):
        for k, t in enumerate(parts):
            for i in range(len(t) - n + 1):
                seen.setdefault((n, t[i : i + n] if n > 51 else b" ".join(t[i : i + n])), []).append((k, i))
    keep = [[True] * len(t) for t in texts]
    at = [[m.span() for m in re.finditer(rb"[^ \t\n\r\x0b\x0c]+", t)] for t in texts]
    for (n, _), found in seen.items():
        for k, i in found if len(found) > 1 else ():
            start, end = (i, i + n) if n > 51 else (at[k][i][0], at[k][i + n - 1][1])
            keep[k][start:end] = [False] * (end - start)
    for t, k in zip(texts, keep):
        out.append(bytes(b for b, left in zip(t, k) if left).decode("utf-8", "ignore"))
    return out


def planted(seed=4):
    draw = random.Random(seed)
    prose = lambda n: " ".join("".join(draw.choice("abcdefghé") for _ in range(draw.randrange(1, 9))) for _ in range(n))
    rows = []
    for n in (49, 50, 51, 52, 54, 58, 65):
        shared = prose(n)
        rows += [(100 * n + i, f"{prose(draw.randrange(20, 90))} {shared} {prose(draw.randrange(20, 90))}", "en", "s", 1) for i in range(3)]
        rows += [(100 * n + 9, shared + "\n" + prose(5), "en", "s", 1)]
    rows += [(1 + i, "short " * 80, "en", "s", 1) for i in range(2)] + [(3, "ab" * 600, "en", "s", 1), (4, None, "en", "s", None)]
    return rows + mixed_documents(seed, 10)


def test_stage_against_brute_force(spark):
    for docs in (frame(spark, planted()), spark.read.parquet(f"{SF}/documents.parquet").select(*cp.COLUMNS)):
        source = docs.collect()
        left = plain([(r.text or "").encode() for r in source])
        want = [(r.doc_id, r.text if c == (r.text or "") else c) for r, c in zip(source, left) if c == (r.text or "") or c.strip(" ")]
        got = cp.STAGES[2][1](spark, docs, SF).collect()
        print("documents", len(source), "bytes cut", sum(len((r.text or "").encode()) - len(c.encode()) for r, c in zip(source, left)))
        assert sorted(((r.doc_id, r.text) for r in got), key=str) == sorted(want, key=str)
