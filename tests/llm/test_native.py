"""Chat formatting, top-k search, mixing and sharding: oracles, laws and edge cases."""

import hashlib
import zlib

import pytest
from pyspark.sql import functions as F

from assocmine.llm import chat, mixing, mtree, registry, sharding
from tests.compare import connect, same
from tests.llm.fixtures import SF, frame, mixed_documents


@pytest.mark.parametrize("name", sorted(registry.ORACLES))
def test_oracles(spark, name):
    same(registry.QUERIES[name](spark, SF), registry.ORACLES[name], connect(SF))


def test_chat_edges(spark):
    rows = [(1, 0, "user", "a\\b<c|\\l"), (1, 1, "assistant", None), (1, 1, "assistant", "<|end|>\n<|x|>\n"), (1, None, None, "n"), (None, 3, "assistant", "z"), (2, 5000, "a|b<\\", "t"), (2, 9, "assistant", "é")]
    turns = chat.stream(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").withColumn("position", F.lit("clash")))
    got = {r.conv_id: r for r in chat.digest(turns).collect()}
    want = "".join(f"{r}\n{t}\n" for r, t in [("", "n"), ("user", "a\\b<c|\\l"), ("assistant", ""), ("assistant", "<|end|>\n<|x|>\n")])
    assert got[1].turns_sha256 == hashlib.sha256(want.encode()).hexdigest() and got[1].loss_chars == 14
    assert got[2].turns_sha256 == hashlib.sha256("assistant\né\na|b<\\\nt\n".encode()).hexdigest()
    assert got[None].loss_chars == 1 and len(got) == 3
    whole = {r.conv_id: r.c for r in turns.filter("conv_id = 1").groupBy("conv_id").agg(F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("position", "formatted"))), lambda t: t["formatted"]), "").alias("c")).collect()}
    rendered = chat.render(turns).filter("conv_id = 1").orderBy("target").collect()
    spans = chat.examples(turns).filter("conv_id = 1").orderBy("target").collect()
    assert len(rendered) == 2 and [r.context + r.reply for r in rendered] == [whole[1][: s.length] for s in spans]
    assert chat.digest(chat.stream(turns.sparkSession.createDataFrame([], "conv_id long, turn long, role string, text string"))).count() == 0


def test_search_edges(spark):
    rows = [(100, [1.0, 2.0]), (1, [0.5, 0.25]), (2, [0.5, 0.25]), (3, None), (4, [float("nan"), 1.0]), (5, [None, 1.0]), (6, []), (7, [1.0]), (None, [1.0, 1.0]), (200, [1.0]), (100, [1.0, 2.0]), (8, [1e30, 0.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>").withColumn("v", F.lit("clash"))
    got = [tuple(r) for r in mtree.top_of_every_hundredth(df).orderBy("query_id", "rank").collect()]
    unit = 512 * 1024 + 256 * 2048
    assert got == [(100, 1, 8, (1 << 63) - 1), (100, 2, 1, unit), (100, 3, 2, unit), (200, 1, 7, 1024 * 1024)]
    assert mtree.top_of_every_hundredth(df.limit(0)).count() == 0
    same_vector = spark.range(0, 300).select(F.col("id").alias("vec_id"), F.array(F.lit(0.5), F.lit(-0.5)).alias("embedding"))
    tied = mtree.top_of_every_hundredth(same_vector).collect()
    assert {r.vec_id for r in tied if r.query_id == 100} == set(range(10)) and len(tied) == 30


def plain_targets(sizes):
    order = sorted(sizes, key=lambda s: (s is None, s or ""))
    weight = {s: (3, 1, 2)[i % 3] for i, s in enumerate(order)}
    total = 1.5 * sum(sizes.values())
    full, out = set(), {}
    while True:
        rest = total - sum(2 * sizes[s] for s in full)
        open_weight = sum(weight[s] for s in order if s not in full)
        out = {s: 2.0 * sizes[s] if s in full else rest * weight[s] / open_weight for s in order}
        over = {s for s in order if s not in full and out[s] > 2 * sizes[s]}
        if not over:
            return out
        full |= over


def test_mix_laws(spark):
    for docs in (spark.read.parquet(f"{SF}/documents.parquet"), frame(spark, mixed_documents(n=200))):
        rows = mixing.mix(docs).join(docs.select("doc_id", "source").distinct(), "doc_id") if "ids" not in docs.columns else mixing.mix(docs)
        result = mixing.mix(docs)
        got = result.collect()
        assert sorted(map(tuple, got), key=str) == sorted(map(tuple, mixing.mix(docs).collect()), key=str)
        assert len(got) == docs.count() and all(0 <= r.taken <= 2 * r.size for r in got)
        source_of = docs.select(F.xxhash64("doc_id", "text", "source").alias("h"), "source").distinct()
        per = result.join(source_of, "h").groupBy("source").agg(F.sum("size").alias("s"), F.sum("taken").alias("t"), F.first("target").alias("g"), F.first("source_size").alias("z")).collect()
        want = plain_targets({r.source: r.s for r in per})
        for r in per:
            assert r.z == r.s and abs(r.g - want[r.source]) < 1e-6 * max(1, r.g)
            assert abs(r.t - r.g) <= max(0.02 * r.g, 3), (r, want)
        assert rows is not None
    assert mixing.mix(frame(spark, [])).count() == 0


def test_shard_laws(spark):
    for docs in (spark.read.parquet("/root/testdata/sf0.01/documents.parquet"), frame(spark, mixed_documents(n=100)), frame(spark, [(i, "same text", "en", "s", 9) for i in range(3000)])):
        got = sharding.shards(docs).collect()
        assert len(got) == docs.count()
        texts = {}
        for r in docs.select("doc_id", "text").collect():
            texts.setdefault(r.doc_id, set()).add(r.text or "")
        slots, total = {}, {}
        for r in got:
            assert 0 <= r.shard < 24 and any(r.size == len(t.encode()) + 8 and r.text_crc32 == zlib.crc32(t.encode()) for t in texts[r.doc_id])
            slots.setdefault(r.shard, []).append(r.slot)
            total[r.shard] = total.get(r.shard, 0) + r.size
        assert all(sorted(s) == list(range(len(s))) for s in slots.values())
        ideal, longest = sum(total.values()) / 24, max(r.size for r in got)
        assert all(abs(total.get(s, 0) - ideal) <= longest * 2 + 0.001 * ideal for s in range(24)), (ideal, total)
    assert sharding.shards(frame(spark, [])).count() == 0
