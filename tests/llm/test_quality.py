"""Statistics by brute force, learning on a planted rule, and held-out agreement with the labels."""

import re

import numpy as np
from pyspark.sql import functions as F

from assocmine.llm import quality
from tests.llm.fixtures import SF, frame, mixed_documents


def plain_stats(text):
    text = text or ""
    words = re.findall(r"[^\x20\x09-\x0D]+", text)
    windows = [tuple(words[i : i + 3]) for i in range(len(words) - 2)]
    repeated = {i + k for i, w in enumerate(windows) if windows.count(w) > 1 for k in range(3)}
    lines = [x for x in text.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    dup = sum(x in lines[:i] for i, x in enumerate(lines))
    return len(words), sum(map(len, words)), len(re.findall(r"[#*$%&|<>]", text)), dup, len(repeated)


def test_statistics(spark):
    rows = [r if len(r[1] or "") < 3000 else (r[0], r[1][:800], *r[2:]) for r in mixed_documents()] + [(90, "a b c d\na b c d\n\nx a b c", "en", "s", 1), (91, "l\nl\n l\nl ", "en", "s", 1)]
    got = quality.statistics(frame(spark, rows)).collect()
    assert sorted([(r.doc_id, r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) for r in got], key=str) == sorted([(r[0], *plain_stats(r[1])) for r in rows], key=str)


def test_learns_planted_conjunction():
    draw = np.random.default_rng(0)
    x = {"a": draw.random(3000), "b": draw.random(3000), "c": draw.random(3000)}
    bad = (x["a"] > 0.7) & (x["b"] <= 0.4)
    rules = quality.learn(x, bad)
    found = np.zeros(3000, bool)
    for rule in rules:
        found |= quality._covers(rule, x, 3000)
    assert (found == bad).mean() > 0.98 and quality.learn(x, bad) == rules


def test_labels_and_edges(spark):
    docs, labels = spark.read.parquet(f"{SF}/documents.parquet"), spark.read.parquet(f"{SF}/labels.parquet")
    judged = quality.judge(docs, labels).join(labels, "doc_id").filter("not base_failed")
    agree = judged.agg(F.avg((F.col("kept") == (F.col("quality") == 1)).cast("int"))).first()[0]
    assert agree > 0.9
    nothing = labels.limit(0)
    assert quality.judge(frame(spark, mixed_documents()), nothing).filter("kept = base_failed").count() == 0
    assert quality.judge(frame(spark, []), labels).count() == 0
    odd = spark.createDataFrame([(None, 1), (1, None), (2, 0), (2, 1)], "doc_id long, quality int")
    assert quality.judge(frame(spark, mixed_documents()), odd).count() == len(mixed_documents())
