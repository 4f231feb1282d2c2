"""Workloads run on all of their attributes."""

from assocmine import queries
from assocmine.operators import evaluation
from assocmine.sources import planted

SF = "/root/testdata/sf0.001"


def test_embedding_signs_has_all_dimensions(spark):
    assert queries.QUERIES["q_embedding_signs"](spark, SF).count() == 58


def test_runtime_experiment_on_103_attributes(spark):
    """Bounds change neither sets nor interactions; redundancy removal leaves fewer attributes."""
    frame = planted.runtime_large(spark, "/root/testdata/sf0.01", None)
    assert len(frame.predictors) == 103 and frame.n == 387
    runs = {r.prune: r for r in evaluation.runtime_curve(frame, (40,), 1).filter("rep = 0").collect()}
    assert runs["none"].members == runs["bounds"].members and runs["redundancy"].members == runs["both"].members
    assert runs["bounds"].exact <= runs["none"].exact and runs["both"].after_redundancy < runs["none"].attributes == 63
