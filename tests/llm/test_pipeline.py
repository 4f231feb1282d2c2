"""Every stage on its own input, and the whole pipeline, against brute force."""

import corpus_pipeline as cp
from assocmine.llm import quality, repeats, simhash
from tests.llm.fixtures import SF, frame, mixed_documents


def rows_of(df):
    return sorted((tuple(r) for r in df.collect()), key=str)


def test_stages_one_by_one(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    kept = cp.quality_rules(spark, docs, SF)
    judged = {r.doc_id for r in quality.judge(docs, spark.read.parquet(f"{SF}/labels.parquet")).filter("kept").collect()}
    assert {r.doc_id for r in kept.collect()} == judged and kept.columns == list(cp.COLUMNS)

    single = cp.near_duplicates(spark, docs, SF)
    ids = {r.component_id for r in simhash.near_duplicates(docs).collect()}
    assert sorted(r.doc_id for r in single.collect()) == sorted(ids)

    cut = {r.doc_id: r for r in cp.repeated_passages(spark, docs, SF).collect()}
    source = docs.collect()
    plain = repeats.plain([(r.text or "").encode() for r in source])
    for r, (n_bytes, n_removed, _, _) in zip(source, plain):
        if n_removed == 0:
            assert cut[r.doc_id].text == r.text
        elif n_removed == n_bytes:
            assert r.doc_id not in cut
        else:
            assert n_bytes - n_removed - 6 <= len(cut[r.doc_id].text.encode()) <= n_bytes - n_removed and cut[r.doc_id].n_chars == len(cut[r.doc_id].text)

    mixed = cp.source_mix(spark, docs, SF)
    times = {}
    for r in mixed.collect():
        times[r.doc_id] = times.get(r.doc_id, 0) + 1
    assert max(times.values()) <= 2 and set(times) <= {r.doc_id for r in source} and rows_of(mixed) == rows_of(cp.source_mix(spark, docs, SF))


def test_run_and_edges(spark):
    assert cp.run(spark, SF).count() > 0
    labels = spark.read.parquet(f"{SF}/labels.parquet")
    assert labels.count()
    for rows in ([], mixed_documents()):
        docs = frame(spark, rows)
        for _, stage in cp.STAGES[:-1]:
            out = stage(spark, docs, SF)
            assert out.columns == list(cp.COLUMNS) and out.count() <= 2 * max(1, len(rows))
        assert cp.bpe_ids(spark, docs, SF).count() == len(rows)
