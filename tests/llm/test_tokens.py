"""BPE automaton and token files against the public library."""

import hashlib
import zlib

import numpy as np
from tokenizers import Tokenizer

from assocmine.llm import bpe, token_files
from assocmine.llm.vocabulary import public_path
from tests.llm.fixtures import frame, mixed_documents


def test_automaton_matches_library(spark):
    path = public_path("word_bpe_49k.json")
    rows = mixed_documents()
    library = Tokenizer.from_file(path)
    got = bpe.digest(bpe.decode(bpe.encode(frame(spark, rows), path, ["doc_id"]), path, ["doc_id"])).collect()
    want = []
    for doc_id, text, *_ in rows:
        ids = library.encode(text or "", add_special_tokens=False).ids
        spelled = library.decode(ids, skip_special_tokens=False)
        want.append((doc_id, len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), hashlib.sha256(spelled.encode()).hexdigest()))
    assert sorted(map(tuple, got), key=str) == sorted(want, key=str)


def test_empty_table(spark):
    path = public_path("word_bpe_49k.json")
    assert bpe.decode(bpe.encode(frame(spark, []), path, ["doc_id"]), path, ["doc_id"]).count() == 0
    assert token_files.write_and_read(frame(spark, []), public_path("byte_bpe_50k.json")).count() == 0


def test_files_match_library(spark):
    path = public_path("byte_bpe_50k.json")
    rows = mixed_documents(11)
    library = Tokenizer.from_file(path)
    got = sorted(map(tuple, token_files.write_and_read(frame(spark, rows), path).collect()), key=lambda r: r[1])
    assert [r[0] for r in got] == sorted((r[0] for r in rows), key=lambda k: (k is not None, k or 0))
    start = 0
    for key, first, n, _ in got:
        assert first == start
        start += n
    want = sorted((r[0] if r[0] is not None else -1, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes())) for r in rows for ids in [library.encode(r[1] or "", add_special_tokens=False).ids + [2]])
    assert sorted((-1 if k is None else k, n, c) for k, _, n, c in got) == want


def test_planes_round_trip():
    for ids in ([], [0], [7, 0, 1], list(range(50_000)), [2**32 - 1, 5]):
        block = np.array(ids, "<u4")
        assert (token_files.Planes.join(token_files.Planes.split(block), len(block)) == block).all()


def test_one_worker_encodes_and_decodes(spark):
    """The pipeline's last stage: equal rows by one Python worker a task instead of two."""
    path = public_path("word_bpe_49k.json")
    docs = frame(spark, mixed_documents())
    one = bpe.encode_and_decode(docs, path, ["doc_id"])
    two = bpe.decode(bpe.encode(docs, path, ["doc_id"]), path, ["doc_id"])
    assert one.columns == two.columns and sorted(one.collect(), key=str) == sorted(two.collect(), key=str)
    assert one._jdf.queryExecution().executedPlan().toString().count("MapInArrow") == 1
