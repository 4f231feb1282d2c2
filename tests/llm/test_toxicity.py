"""Folding, exceptions, edge cases and held-out accuracy."""

from pyspark.sql import functions as F

from assocmine.llm import toxicity
from tests.llm.fixtures import frame, mixed_documents


def test_fold():
    assert toxicity.fold("1D10T id10t, І​dіоt! $tupid") == " idiot idiot idiot stupid "
    assert toxicity.fold("in 2014, 100% of $5") == " in of "
    assert toxicity.fold("") == "  "


def test_exceptions_and_longest_entry():
    lexicon = toxicity.Lexicon({"clown": 3.0, "clownf": 1.0}, frozenset({"clown fish"}), (-3.0, 2.0, 1.0))
    assert lexicon.score("a clown here") > 0.3 > lexicon.score("a clown fish here")
    assert [m[0] for m in lexicon.matches(toxicity.fold("clownfish Clown"))] == ["clownf", "clown"]


def test_held_out_accuracy(spark):
    sf = "/root/testdata/sf0.01"
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    scored = toxicity.score(docs, toxicity.fit(docs, labels)).filter("held_out").join(labels, "doc_id")
    hit = scored.agg(F.sum("toxic"), F.sum(F.expr("toxic * predicted")), F.sum("predicted")).first()
    assert hit[1] / hit[0] > 0.6 and hit[1] / hit[2] > 0.8


def test_edges(spark):
    labels = spark.createDataFrame([(1, 1), (2, 0), (None, 1), (3, None)], "doc_id long, toxic int")
    rows = mixed_documents()
    docs = frame(spark, rows)
    got = toxicity.score(docs, toxicity.fit(docs, labels)).collect()
    assert len(got) == len(rows) and all(0 <= r.score <= 1 and r.held_out is not None for r in got)
    assert toxicity.score(frame(spark, []), toxicity.fit(frame(spark, []), labels.limit(0))).count() == 0
