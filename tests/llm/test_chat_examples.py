"""Expanded chat examples, and a digest that is read back from them."""

from pyspark.sql import functions as F

from assocmine.llm import chat

ROWS = [(1, 0, "user", "a<b"), (1, 1, "assistant", "c\\d"), (1, 2, "user", "e"), (1, 3, "assistant", "f|"), (1, 4, "user", "g"), (2, 0, "user", "only"), (3, 0, "assistant", None), (None, 0, "system", "h"), (None, 1, "assistant", "i")]


def test_examples_in_full(spark):
    turns = chat.stream(spark.createDataFrame(ROWS, "conv_id long, turn long, role string, text string"))
    got = {(r.conv_id, r.target): (r.text, None if r.target is None else r.text[r.loss_start : r.loss_end]) for r in chat.expanded(turns).collect()}
    mark = lambda role, text: f"<|{role}|>\n{text}<|end|>\n"
    one = mark("user", "a\\lb") + mark("assistant", "c\\bd")
    assert got == {
        (1, 2): (one, "c\\bd"), (1, 4): (one + mark("user", "e") + mark("assistant", "f|"), "f|"), (1, None): (mark("user", "g"), None),
        (2, None): (mark("user", "only"), None), (3, 1): (mark("assistant", ""), ""), (None, 2): (mark("system", "h") + mark("assistant", "i"), "i"),
    }


def test_digest_reads_examples(spark, monkeypatch):
    turns = chat.stream(spark.createDataFrame(ROWS, "conv_id long, turn long, role string, text string"))
    whole = {r.conv_id: r for r in chat.digest(turns).collect()}
    assert [(whole[k].n_turns, whole[k].n_examples, whole[k].loss_chars) for k in (1, 2, 3, None)] == [(5, 2, 5), (1, 0, 0), (1, 1, 0), (2, 1, 1)]
    full = chat.expanded
    monkeypatch.setattr(chat, "expanded", lambda t: full(t).filter(F.col("target").isNull() | (F.col("target") < 4)))
    less = {r.conv_id: r for r in chat.digest(turns).collect()}
    assert less[1].n_examples == 1 and less[1].n_turns == 3 and less[1].loss_chars == 3 and less[1].example_chars < whole[1].example_chars
