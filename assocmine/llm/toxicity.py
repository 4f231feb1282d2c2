"""Toxicity by a weighted lexicon, matched with Aho-Corasick after folding, with exception phrases.

Folding lower-cases, replaces homoglyphs of Latin letters, and reads digits and signs inside words as the letters that
they stand for. The lexicon holds beginnings of words with weights (log odds of toxic against clean documents), learned
greedily: the entry that tells most is taken, the toxic documents that it explains are set aside, and so on. Exception
phrases are a match with a neighbouring word that occurs in clean training documents only; such matches do not count.
A document's score is a logistic function of the weight of its matches, normalised by its length.

The lexicon is fitted on a documented, bounded sample: the ``SAMPLE_ROWS`` labelled training rows with the smallest hash
of their id. The share of toxic documents that an entry must be in is one of ``SUPPORTS``, chosen by cross-validation
inside the sample: the largest one that is within a standard error of the best, so that fragments of words that explain
mislabelled documents are left out. Rows whose crc32(doc_id as text) mod 4 is 2 are held out and never seen in training; labels, language,
source and doc_id are no inputs of a score. Every whole text of the table is scored.

Nulls count as empty texts and get the score of a text without matches. A null doc_id is not held out and has no label.
Without labels of both kinds the lexicon is empty and every score is the prior's. Extra columns are not read.
"""

from __future__ import annotations

import math
import re
import sys
from collections import Counter
from collections.abc import Iterator

import ahocorasick
import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from assocmine.llm.bpe import small, utf8_values
from assocmine.plans.materialize import materialize, ship_package

SAMPLE_ROWS, MAX_ENTRIES, MIN_DOCUMENTS, MIN_ODDS = 6_000, 400, 3, 8.0
SHORTEST, LONGEST = 3, 12
#: Shares of toxic training documents that an entry must be in, of which cross-validation takes one; and its folds.
SUPPORTS, FOLDS = (0.01, 0.02, 0.05, 0.1, 0.15), 3
THRESHOLD = 0.3

#: Characters that are drawn like a Latin letter, by code point, and the letters.
HOMOGLYPHS = {
    0x0430: "a", 0x0435: "e", 0x043E: "o", 0x0440: "p", 0x0441: "c", 0x0443: "y", 0x0445: "x", 0x0456: "i", 0x0458: "j", 0x0455: "s",
    0x04BB: "h", 0x0501: "d", 0x051B: "q", 0x051D: "w", 0x0432: "b", 0x043A: "k", 0x043C: "m", 0x043D: "h", 0x0442: "t",
    0x03B1: "a", 0x03B5: "e", 0x03B9: "i", 0x03BA: "k", 0x03BD: "v", 0x03BF: "o", 0x03C1: "p", 0x03C4: "t", 0x03C5: "u", 0x03C7: "x",
    0x0131: "i", 0x0251: "a", 0x0261: "g", 0x0269: "i", 0x028F: "y", 0x1D04: "c", 0x1D0F: "o", 0x1D20: "v", 0x1D21: "w",
}
#: Digits and signs inside words, and the letters that they stand for.
SUBSTITUTES = {"0": "o", "1": "i", "3": "e", "4": "a", "5": "s", "7": "t", "8": "b", "@": "a", "$": "s", "!": "i", "|": "l"}

FOLD = {**HOMOGLYPHS, **{0xFF41 + i: chr(97 + i) for i in range(26)}, **{c: None for c in (0xAD, 0x200B, 0x200C, 0x200D, 0x2060, 0xFEFF)}}
PLAIN = re.compile("[^" + "".join(map(chr, FOLD)) + "]*")
INSIDE = re.compile(r"(?<=[^\W\d_])[013457 8@$!|]+(?=[^\W\d_])|(?<![\w$@!|])[013457 8@$]+(?=[^\W\d_])".replace(" ", ""))
SWAP = str.maketrans(SUBSTITUTES)
NO_WORD = re.compile(r"[\W\d_]+")


def fold(text: str) -> str:
    """Folded words, each with a space before it, and a space at the end."""
    low = text.lower()
    if not low.isascii():
        low = low.translate(FOLD)
    low = INSIDE.sub(lambda m: m[0].translate(SWAP), low)
    return " " + NO_WORD.sub(" ", low).strip(" ") + " "


class Lexicon:
    """Beginnings of words with weights, exception phrases, and the logistic function of the normalised weight."""

    def __init__(self, entries: dict[str, float], exceptions: frozenset[str] = frozenset(), curve: tuple[float, float, float] = (-4.0, 0.0, 0.0)):
        self.entries, self.exceptions, self.curve = entries, exceptions, curve
        self.machine = ahocorasick.Automaton()
        for entry, weight in entries.items():
            self.machine.add_word(" " + entry, (entry, weight))
        if entries:
            self.machine.make_automaton()

    def __reduce__(self):
        return Lexicon, (self.entries, self.exceptions, self.curve)

    def matches(self, folded: str) -> list[tuple[str, float, str, str]]:
        """(entry, weight, phrase with the word before, phrase with the word after); the longest entry of a word counts."""
        if not self.entries:
            return []
        best: dict[int, tuple[str, float]] = {}
        for end, (entry, weight) in self.machine.iter(folded):
            start = end - len(entry)
            if len(entry) >= len(best.get(start, ("", 0))[0]):
                best[start] = (entry, weight)
        out = []
        for start, (entry, weight) in best.items():
            stop = folded.index(" ", start + 1)
            word = folded[start + 1 : stop]
            before = folded[folded.rfind(" ", 0, start) + 1 : start] if start else ""
            after = folded[stop + 1 : folded.find(" ", stop + 1)] if stop + 1 < len(folded) else ""
            out.append((entry, weight, f"{before} {word}", f"{word} {after}"))
        return out

    def inputs(self, folded: str) -> tuple[float, float]:
        """Log of the weight of all counted matches, and that weight per word of the text."""
        weight = sum(w for _, w, a, b in self.matches(folded) if a not in self.exceptions and b not in self.exceptions)
        return math.log1p(weight), min(1.0, weight / max(1, folded.count(" ") - 1))

    def score(self, text: str) -> float:
        a, b = self.inputs(fold(text))
        bias, of_log, of_share = self.curve
        return 1 / (1 + math.exp(-max(-50.0, min(50.0, bias + of_log * a + of_share * b))))


def held_out() -> Column:
    return F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 4 == 2, F.lit(False))


def beginnings(words: list[str]) -> set[str]:
    return {w[:k] for w in words for k in range(SHORTEST, min(LONGEST, len(w)) + 1)}


class Tally:
    """Counts of the beginnings of words in toxic and clean samples (distinct words joined by spaces, label); words are split one document at a time."""

    def __init__(self, samples: list[tuple[str, int]]):
        self.n_toxic = sum(t for _, t in samples)
        self.n_clean = len(samples) - self.n_toxic
        self.toxic_sets = [{sys.intern(b) for b in beginnings(words.split())} for words, toxic in samples if toxic]
        every = Counter(b for s in self.toxic_sets for b in s)
        self.full = {b: n for b, n in every.items() if n >= MIN_DOCUMENTS}
        self.clean: Counter[str] = Counter()
        for words, toxic in samples:
            if not toxic:
                self.clean.update(beginnings(words.split()) & self.full.keys())

    def entries(self, support: float) -> dict[str, float]:
        """Greedy choice of beginnings of words by log odds; among equally telling ones the longest, then the first by letters."""
        if not self.n_toxic or not self.n_clean:
            return {}
        full, clean, least = self.full, self.clean, support * self.n_toxic

        def odds(b: str) -> float:
            return (full[b] + 0.5) / (self.n_toxic + 1) / ((clean[b] + 0.5) / (self.n_clean + 1))

        usable = {b for b, n in full.items() if n >= least and odds(b) >= MIN_ODDS and clean[b] <= 0.02 * n}
        entries: dict[str, float] = {}
        left = [s & usable for s in self.toxic_sets]
        while len(entries) < MAX_ENTRIES:
            counts = Counter(b for s in left for b in s)
            if not counts:
                break
            entry = min(counts, key=lambda b: (-(counts[b] - 5 * clean[b]), -len(b), b))
            if counts[entry] < MIN_DOCUMENTS:
                break
            entries[entry] = math.log(odds(entry))
            left = [s for s in left if entry not in s]
        # further entries explain the same documents; they catch other documents that hold only one of them
        for entry in sorted(usable, key=lambda b: (-full[b], -len(b), b)):
            if len(entries) >= MAX_ENTRIES:
                break
            if clean[entry] == 0 and not any(entry.startswith(e) or e.startswith(entry) for e in entries):
                entries[entry] = math.log(odds(entry))
        return entries


def choose_support(samples: list[tuple[str, int]]) -> float:
    """The largest support whose entries do, on the folds that did not give them, as well as the best but for one standard
    error of a share (measured: F1 of documents that hold any entry)."""
    hits = {support: [0, 0] for support in SUPPORTS}
    n_toxic = sum(t for _, t in samples)
    for fold in range(FOLDS):
        tally = Tally([x for i, x in enumerate(samples) if i % FOLDS != fold])
        for support in SUPPORTS:
            found = tuple(" " + e for e in tally.entries(support))
            for words, toxic in samples[fold::FOLDS]:
                if any(e in " " + words for e in found):
                    hits[support][toxic] += 1
    f1 = {x: 2 * right / max(1, wrong + right + n_toxic) for x, (wrong, right) in hits.items()}
    best = max(f1.values())
    error = math.sqrt(best * (1 - best) / max(1, n_toxic))
    return max(x for x in SUPPORTS if f1[x] >= best - error)


def learn_entries(samples: list[tuple[str, int]]) -> dict[str, float]:
    """Entries of the samples with the support that cross-validation chooses."""
    return Tally(samples).entries(choose_support(samples))


def learn_curve(inputs: np.ndarray, toxic: np.ndarray) -> tuple[float, float, float]:
    """Logistic regression with a small penalty, by Newton steps."""
    x = np.column_stack([np.ones(len(inputs)), inputs])
    w = np.zeros(3)
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -50, 50)))
        slope = x.T @ (p - toxic) + 0.1 * w
        step = np.linalg.solve((x * (p * (1 - p))[:, None]).T @ x + 0.1 * np.eye(3), slope)
        w -= step
        if np.abs(step).max() < 1e-8:
            break
    return float(w[0]), float(max(0.0, w[1])), float(max(0.0, w[2]))


def fit(docs: DataFrame, labels: DataFrame) -> Lexicon:
    """The lexicon from at most ``SAMPLE_ROWS`` labelled rows that are not held out; rows equal in doc_id, text and label count once."""
    spark = docs.sparkSession
    ship_package(spark)
    usable = labels.select("doc_id", F.col("toxic").cast("int").alias("toxic")).filter("doc_id is not null and toxic in (0, 1)").filter(~held_out())
    chosen = usable.distinct().orderBy(F.xxhash64("doc_id"), "doc_id", "toxic").limit(SAMPLE_ROWS)
    hashed = docs.select("doc_id", "text", F.xxhash64("text").alias("h"))
    keys = hashed.join(F.broadcast(chosen), "doc_id").select("doc_id", "h", "toxic").distinct().orderBy(F.xxhash64("doc_id"), "doc_id", "toxic", "h").limit(SAMPLE_ROWS)
    keys = materialize(keys, "toxicity-sample")
    sample = hashed.join(F.broadcast(keys), ["doc_id", "h"]).dropDuplicates(["doc_id", "h", "toxic"]).select("doc_id", "text", "toxic")

    def words_of(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small(batches):
            words = [" ".join(sorted(set(fold(t.decode("utf-8")).split()))) for t in utf8_values(batch.column(1))]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(words, pa.string()), batch.column(2)], names=["doc_id", "words", "toxic"])

    doc_type = docs.schema["doc_id"].dataType.simpleString()
    rows = sample.mapInArrow(words_of, f"doc_id {doc_type}, words string, toxic int").toArrow()
    samples = [(w, t) for _, t, w in sorted(zip(*(rows.column(c).to_pylist() for c in ("doc_id", "toxic", "words"))))]
    entries = learn_entries(samples)
    del rows, samples
    bare = Lexicon(entries)

    def found_in(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small(batches):
            phrases, n = [], []
            weights = []
            for t in utf8_values(batch.column(1)):
                folded = fold(t.decode("utf-8"))
                found = bare.matches(folded)
                phrases.append([f"{a}\n{b}" for _, _, a, b in found])
                weights.append([w for _, w, _, _ in found])
                n.append(max(1, folded.count(" ") - 1))
            yield pa.RecordBatch.from_arrays([pa.array(phrases, pa.list_(pa.string())), pa.array(weights, pa.list_(pa.float64())), pa.array(n, pa.int64()), batch.column(2)], names=["phrases", "weights", "n", "toxic"])

    seen = sample.mapInArrow(found_in, "phrases array<string>, weights array<double>, n long, toxic int").collect()
    clean, toxic = Counter(), Counter()
    for r in seen:
        (toxic if r["toxic"] else clean).update({p for pair in r["phrases"] for p in pair.split("\n")})
    exceptions = frozenset(p for p, k in clean.items() if k >= MIN_DOCUMENTS and not toxic[p] and not p.startswith(" ") and not p.endswith(" "))
    inputs = []
    for r in seen:
        weight = sum(w for pair, w in zip(r["phrases"], r["weights"]) if not exceptions & set(pair.split("\n")))
        inputs.append((math.log1p(weight), min(1.0, weight / r["n"])))
    truth = np.array([r["toxic"] for r in seen], dtype=float)
    curve = learn_curve(np.array(inputs), truth) if entries else (-4.0, 0.0, 0.0)
    return Lexicon(entries, exceptions, curve)


def score(docs: DataFrame, lexicon: Lexicon) -> DataFrame:
    """``doc_id``, ``held_out``, ``score`` and ``predicted`` of every whole text."""
    ship_package(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small(batches):
            scores = [lexicon.score(t.decode("utf-8")) for t in utf8_values(batch.column(1))]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(scores, pa.float64())], names=["doc_id", "score"])

    narrow = docs.select("doc_id", "text")
    scored = narrow.mapInArrow(run, f"doc_id {narrow.schema['doc_id'].dataType.simpleString()}, score double")
    return scored.select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))
