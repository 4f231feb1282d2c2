"""Quality rules: a learned decision list over text statistics, applied as ordered Spark conditional expressions.

The statistics of every whole text are computed once. Sequential covering then learns a list of rules from labelled
documents: a rule is grown one threshold at a time on two thirds of the examples (the condition with the largest
information gain), pruned on the remaining third (final conditions go while that does not lower its precision), kept if
it is precise enough, and the examples that it covers are taken away before the next rule is grown. Rules say "reject";
what no rule covers is kept.

The list is fitted on a documented, bounded sample: the ``SAMPLE_ROWS`` labelled documents with the smallest hash of
their id. Statistics and verdicts cover every row.

Nulls count as texts without words. Labels that are null are not used; a document labelled both ways counts as both. With
no labels, or with labels of one kind, the list is empty and the base rules decide alone. A null doc_id has statistics
and a verdict but never a label. Extra columns are not read.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from assocmine.llm.bpe import small, utf8_values
from assocmine.plans.materialize import materialize, ship_package

#: Most labelled rows that the list is fitted on, most rules, most conditions of a rule, and thresholds tried for each feature.
SAMPLE_ROWS, MAX_RULES, MAX_CONDITIONS, THRESHOLDS = 20_000, 12, 4, 64
#: A rule must reject low quality with this share at least, on the examples that did not grow it, and cover this many.
MIN_PRECISION, MIN_COVER = 0.95, 3
MIN_WORDS, MAX_REPEAT_PERCENT = 50, 50

SYMBOLS = b"#*$%&|<>"
SPACE = b" \t\n\x0b\x0c\r"
UPPER = re.compile(r"[^\W\d_a-zß-öø-ÿ]")
STATS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines", "n_distinct_words", "n_upper", "n_digits", "n_marks")


def repeat_words(words: list[bytes]) -> int:
    """Words that lie in a window of three words found twice or more in the text, the first find included."""
    if len(words) < 4:
        return 0
    windows = list(zip(words, words[1:], words[2:]))
    counts = Counter(windows)
    if len(counts) == len(windows):
        return 0
    covered = until = 0
    for i, window in enumerate(windows):
        if counts[window] > 1:
            covered += i + 3 - max(i, until)
            until = i + 3
    return covered


def text_stats(text: bytes) -> tuple[int, ...]:
    """The statistics named in ``STATS`` of one UTF-8 text."""
    words = text.split()
    lines = [line for line in text.split(b"\n") if line.strip(SPACE)]
    decoded = text.decode("utf-8")
    return (
        len(words),
        len(decoded) - (len(text) - len(text.translate(None, SPACE))),
        len(text) - len(text.translate(None, SYMBOLS)),
        len(lines) - len(set(lines)),
        repeat_words(words),
        len(lines),
        len(set(words)),
        len(UPPER.findall(decoded)),
        len(text) - len(text.translate(None, b"0123456789")),
        len(text) - len(text.translate(None, b"!?.,;:")),
    )


def statistics(docs: DataFrame, carry: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """The carried columns and the statistics of every document."""
    ship_package(docs.sparkSession)
    n = len(carry)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small(batches):
            rows = [text_stats(t) for t in utf8_values(batch.column(n))]
            columns = zip(*rows) if rows else [[] for _ in STATS]
            yield pa.RecordBatch.from_arrays([*batch.columns[:n], *(pa.array(c, pa.int64()) for c in columns)], names=[*carry, *STATS])

    narrow = docs.select(*carry, F.col("text").alias("__text"))
    return narrow.mapInArrow(run, ", ".join([*(f"`{c}` {narrow.schema[c].dataType.simpleString()}" for c in carry), *(f"{s} long" for s in STATS)]))


def base_failed() -> Column:
    return (F.col("n_words") < MIN_WORDS) | (100 * F.col("n_repeat_words") > MAX_REPEAT_PERCENT * F.col("n_words"))


def features() -> dict[str, Column]:
    """Ratios that the rules test; a text without words has zeros."""
    def per(a: str, b: str) -> Column:
        return F.when(F.col(b) > 0, F.col(a) / F.col(b)).otherwise(F.lit(0.0))

    return {
        "words": F.col("n_words").cast("double"),
        "mean_word": per("word_chars", "n_words"),
        "symbol_share": per("n_symbols", "word_chars"),
        "dup_line_share": per("n_dup_lines", "n_lines"),
        "repeat_share": per("n_repeat_words", "n_words"),
        "distinct_share": per("n_distinct_words", "n_words"),
        "upper_share": per("n_upper", "word_chars"),
        "digit_share": per("n_digits", "word_chars"),
        "mark_share": per("n_marks", "n_words"),
    }


@dataclass(frozen=True)
class Condition:
    feature: str
    above: bool
    threshold: float

    def holds(self, x: dict[str, np.ndarray]) -> np.ndarray:
        return x[self.feature] > self.threshold if self.above else x[self.feature] <= self.threshold

    def expression(self) -> Column:
        column = features()[self.feature]
        return column > self.threshold if self.above else column <= self.threshold

    def __str__(self) -> str:
        return f"{self.feature} {'>' if self.above else '<='} {self.threshold:.6g}"


def _covers(rule: tuple[Condition, ...], x: dict[str, np.ndarray], n: int) -> np.ndarray:
    held = np.ones(n, dtype=bool)
    for condition in rule:
        held &= condition.holds(x)
    return held


def _grow(x: dict[str, np.ndarray], bad: np.ndarray) -> tuple[Condition, ...]:
    rule: tuple[Condition, ...] = ()
    held = np.ones(len(bad), dtype=bool)
    while len(rule) < MAX_CONDITIONS and held.any() and not bad[held].all():
        p0, n0 = int(bad[held].sum()), int((~bad[held]).sum())
        if p0 == 0:
            break
        best, best_gain = None, 1e-9
        for name, values in x.items():
            order = np.argsort(values[held], kind="stable")
            v, b = values[held][order], bad[held][order]
            cuts = np.nonzero(v[1:] > v[:-1])[0]
            if len(cuts) > THRESHOLDS:
                cuts = cuts[np.linspace(0, len(cuts) - 1, THRESHOLDS).astype(int)]
            below = np.cumsum(b)
            for above in (False, True):
                p = p0 - below[cuts] if above else below[cuts]
                total = len(v) - cuts - 1 if above else cuts + 1
                with np.errstate(divide="ignore", invalid="ignore"):
                    gain = np.where(p > 0, p * (np.log2(p / total) - np.log2(p0 / (p0 + n0))), -1.0)
                if len(gain) and gain.max() > best_gain:
                    k = int(gain.argmax())
                    best, best_gain = Condition(name, above, float((v[cuts[k]] + v[cuts[k] + 1]) / 2)), float(gain[k])
        if best is None:
            break
        rule += (best,)
        held &= best.holds(x)
    return rule


def _prune(rule: tuple[Condition, ...], x: dict[str, np.ndarray], bad: np.ndarray) -> tuple[Condition, ...]:
    def worth(r: tuple[Condition, ...]) -> float:
        held = _covers(r, x, len(bad))
        p, n = int((bad & held).sum()), int((~bad & held).sum())
        return (p - n) / (p + n) if p + n else -1.0

    while len(rule) > 1 and worth(rule[:-1]) >= worth(rule):
        rule = rule[:-1]
    return rule


def learn(x: dict[str, np.ndarray], bad: np.ndarray) -> list[tuple[Condition, ...]]:
    """Ordered rejection rules by sequential covering; examples in a fixed order give a fixed list."""
    rules: list[tuple[Condition, ...]] = []
    left = np.ones(len(bad), dtype=bool)
    while len(rules) < MAX_RULES and bad[left].any() and not bad[left].all():
        at = np.nonzero(left)[0]
        third = np.arange(len(at)) % 3 == 2
        grow, check = at[~third], at[third]
        rule = _grow({k: v[grow] for k, v in x.items()}, bad[grow])
        if not rule:
            break
        rule = _prune(rule, {k: v[check] for k, v in x.items()}, bad[check])
        held = _covers(rule, x, len(bad)) & left
        seen = held[check]
        precise = bad[check][seen].mean() >= MIN_PRECISION if seen.sum() >= MIN_COVER else bad[held].mean() >= MIN_PRECISION and held.sum() >= MIN_COVER
        if not precise:
            break
        rules.append(rule)
        left &= ~held
    return rules


def fit(stats: DataFrame, labels: DataFrame) -> list[tuple[Condition, ...]]:
    """The decision list from at most ``SAMPLE_ROWS`` labelled documents; base failures need no rule and are left out."""
    chosen = labels.select("doc_id", "quality").filter("doc_id is not null and quality is not null").distinct().orderBy(F.xxhash64("doc_id"), "doc_id", "quality").limit(SAMPLE_ROWS)
    wanted = features()
    joined = stats.join(F.broadcast(chosen), "doc_id").filter(~base_failed())
    rows = joined.select("doc_id", "quality", *(c.alias(n) for n, c in wanted.items())).orderBy(F.xxhash64("doc_id"), "doc_id", "quality", *wanted).limit(SAMPLE_ROWS).collect()
    bad = np.array([r["quality"] == 0 for r in rows], dtype=bool)
    return learn({n: np.array([r[n] for r in rows], dtype=float) for n in wanted}, bad)


def verdict(rules: list[tuple[Condition, ...]]) -> Column:
    """Number of the first rule that rejects (from 1), or 0: an ordered conditional expression."""
    found = F.when(F.lit(False), F.lit(0))
    for number, rule in enumerate(rules, 1):
        held = rule[0].expression()
        for condition in rule[1:]:
            held = held & condition.expression()
        found = found.when(held, F.lit(number))
    return found.otherwise(F.lit(0))


def judge(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """Statistics, ``base_failed``, ``rule`` (0: none) and ``kept`` of every document."""
    stats = materialize(statistics(docs), "quality-statistics")
    rule = verdict(fit(stats, labels))
    judged = stats.withColumn("base_failed", base_failed()).withColumn("rule", rule)
    return judged.withColumn("kept", ~F.col("base_failed") & (F.col("rule") == 0))
