r"""Chat formatting by prefix-target expansion, with DataFrame functions only.

Every assistant turn becomes an example of its own: all preceding turns are its context, and only that reply is
trainable. The turns of a conversation are formatted once, as a stream; an example is a prefix of that stream that ends
with its target turn, together with the span of the reply. :func:`expanded` writes the examples out in full, which
grows with the square of a conversation's turns, and :func:`digest` reads its columns back from them.

A turn is ``<|role|>``, a line feed, the text, ``<|end|>`` and a line feed. Inside roles and texts a backslash becomes
``\b`` and ``<`` becomes ``\l`` (in roles ``|`` also becomes ``\p``), so that no mark can stand in a text, and the
replacement can be undone.

Turns are ordered by turn number (nulls first), role and text; repeated rows are kept. Null roles and texts count as
empty. Rows without conv_id form one conversation whose id is null. Positions and offsets come from sums over buckets
of turns, so a conversation with very many turns is spread over tasks; only the expansion and the digests gather a
conversation, which hashing it in order requires. Empty tables give no rows. Extra columns are not read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

OPEN, SHUT, END = "<|", "|>\n", "<|end|>\n"
#: Turn numbers of one bucket.
BUCKET = 1024


def escape(text: Column, role: bool = False) -> Column:
    out = F.replace(F.replace(text, F.lit("\\"), F.lit("\\b")), F.lit("<"), F.lit("\\l"))
    return F.replace(out, F.lit("|"), F.lit("\\p")) if role else out


def unescape(text: Column) -> Column:
    for short, long in (("\\l", "<"), ("\\p", "|"), ("\\b", "\\")):
        text = F.replace(text, F.lit(short), F.lit(long))
    return text


def stream(conversations: DataFrame) -> DataFrame:
    """One row per turn: conv_id, position (from 1), formatted turn, its offsets in the stream, and the reply's span.

    ``start`` and ``end`` count characters of the conversation's stream; ``loss_start`` and ``loss_end`` are null unless
    the turn is an assistant's.
    """
    text, role = F.coalesce(F.col("text").cast("string"), F.lit("")), F.coalesce(F.col("role").cast("string"), F.lit(""))
    turns = conversations.select("conv_id", F.col("turn").alias("turn"), role.alias("role"), text.alias("text"))
    turns = turns.withColumn("formatted", F.concat(F.lit(OPEN), escape(F.col("role"), True), F.lit(SHUT), escape(F.col("text")), F.lit(END)))
    turns = turns.withColumn("bucket", F.coalesce(F.floor(F.col("turn") / BUCKET), F.lit(-(1 << 62)))).withColumn("chars", F.length("formatted"))
    sums = turns.groupBy("conv_id", "bucket").agg(F.count("*").alias("n"), F.sum("chars").alias("c"))
    earlier = Window.partitionBy("conv_id").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    bases = sums.select(
        F.col("conv_id").alias("__conv"), F.col("bucket").alias("__bucket"), F.coalesce(F.sum("n").over(earlier), F.lit(0)).alias("n0"), F.coalesce(F.sum("c").over(earlier), F.lit(0)).alias("c0")
    )
    joined = turns.join(bases, F.col("conv_id").eqNullSafe(F.col("__conv")) & (F.col("bucket") == F.col("__bucket")))
    inside = Window.partitionBy("conv_id", "bucket").orderBy("turn", "role", "text")
    end = F.col("c0") + F.sum("chars").over(inside.rowsBetween(Window.unboundedPreceding, 0))
    placed = joined.withColumn("position", F.col("n0") + F.row_number().over(inside)).withColumn("end", end).withColumn("start", F.col("end") - F.col("chars"))
    head = F.length(escape(F.col("role"), True)) + len(OPEN) + len(SHUT)
    trained = F.col("role") == "assistant"
    return placed.select(
        "conv_id", "position", "formatted", "start", "end", F.when(trained, F.col("start") + head).alias("loss_start"), F.when(trained, F.col("end") - len(END)).alias("loss_end")
    )


def examples(turns: DataFrame) -> DataFrame:
    """One row per assistant turn: the example is the stream's first ``length`` characters, trainable in the span."""
    return turns.filter("loss_start is not null").select("conv_id", F.col("position").alias("target"), F.col("start").alias("context_chars"), F.col("end").alias("length"), "loss_start", "loss_end")


def render(turns: DataFrame) -> DataFrame:
    """Examples written out: conv_id, target, context and reply turn as texts. Its size is that of all prefixes."""
    goals = turns.filter("loss_start is not null").select(F.col("conv_id").alias("__conv"), F.col("position").alias("target"), F.col("formatted").alias("reply"))
    joined = goals.join(turns.select("conv_id", "position", "formatted"), F.col("conv_id").eqNullSafe(F.col("__conv")) & (F.col("position") <= F.col("target")))
    gathered = joined.groupBy("conv_id", "target", "reply").agg(F.sort_array(F.collect_list(F.when(F.col("position") < F.col("target"), F.struct("position", "formatted")))).alias("before"))
    return gathered.select("conv_id", "target", F.array_join(F.transform("before", lambda t: t["formatted"]), "").alias("context"), "reply")


def expanded(turns: DataFrame) -> DataFrame:
    """Every example in full: conv_id, target, text (all preceding turns, then the reply's turn) and the loss span in it.

    Turns behind a conversation's last reply are nobody's context; they make a row of their own, without target and span.
    The gathered conversation is expanded inside its row, so only the rows that come out grow with the square.
    """
    gathered = turns.groupBy("conv_id").agg(F.sort_array(F.collect_list(F.struct("position", "formatted", "start", "loss_start", "loss_end"))).alias("ts"))
    goals = F.filter("ts", lambda t: t["loss_start"].isNotNull())
    upto = F.coalesce(F.array_max(F.transform(goals, lambda t: t["position"])), F.lit(0)).cast("int")
    rest = F.struct(F.lit(None).cast("long").alias("position"), F.lit(None).cast("string").alias("formatted"), F.lit(None).cast("long").alias("start"), F.lit(None).cast("long").alias("loss_start"), F.lit(None).cast("long").alias("loss_end"))
    asked = gathered.withColumn("upto", upto).select("conv_id", "ts", "upto", F.explode(F.concat(goals, F.when(F.size("ts") > F.col("upto"), F.array(rest)).otherwise(F.array()))).alias("goal"))
    first, count = F.when(F.col("goal.position").isNull(), F.col("upto") + 1).otherwise(1), F.coalesce(F.col("goal.position").cast("int"), F.size("ts") - F.col("upto"))
    text = F.array_join(F.transform(F.slice("ts", first, count), lambda t: t["formatted"]), "")
    return asked.select("conv_id", F.col("goal.position").alias("target"), text.alias("text"), F.col("goal.loss_start").alias("loss_start"), F.col("goal.loss_end").alias("loss_end"))


def digest(turns: DataFrame) -> DataFrame:
    """What the expanded examples hold of each conversation: its turns, its trainable text, and its sizes.

    Everything is read back from the examples' texts: replies are cut by the loss spans, and roles and texts are parsed
    from the longest example and the turns behind it.
    """
    rows = expanded(turns).withColumn("reply", unescape(F.substring(F.col("text"), F.col("loss_start") + 1, F.col("loss_end") - F.col("loss_start"))))
    read = rows.groupBy("conv_id").agg(
        F.max_by(F.when(F.col("target").isNotNull(), F.col("text")), "target").alias("longest"),
        F.max(F.when(F.col("target").isNull(), F.col("text"))).alias("behind"),
        F.array_join(F.transform(F.sort_array(F.collect_list(F.when(F.col("target").isNotNull(), F.struct("target", "reply")))), lambda t: t["reply"]), "").alias("loss"),
        F.count("target").alias("n_examples"),
        F.coalesce(F.sum(F.when(F.col("target").isNotNull(), F.length("text"))), F.lit(0)).alias("example_chars"),
    )
    whole = read.withColumn("whole", F.concat(F.coalesce("longest", F.lit("")), F.coalesce("behind", F.lit(""))))
    split = whole.withColumn("parts", F.split("whole", r"<\|end\|>\n", -1)).withColumn("parts", F.slice("parts", 1, F.size("parts") - 1))
    mark = lambda t: F.substring_index(F.substring(t, len(OPEN) + 1, 1 << 30), SHUT, 1)
    turn = lambda t: F.concat(unescape(mark(t)), F.lit("\n"), unescape(F.substring(t, F.length(mark(t)) + len(OPEN) + len(SHUT) + 1, F.length(t))), F.lit("\n"))
    return split.select(
        "conv_id",
        F.size("parts").cast("long").alias("n_turns"),
        F.sha2(F.array_join(F.transform("parts", turn), "").cast("binary"), 256).alias("turns_sha256"),
        F.length("loss").cast("long").alias("loss_chars"),
        F.sha2(F.col("loss").cast("binary"), 256).alias("loss_sha256"),
        F.length("whole").cast("long").alias("formatted_chars"),
        "n_examples",
        F.col("example_chars").cast("long").alias("example_chars"),
    )


ORACLE = r"""
with t as (
  select conv_id, turn, coalesce(role, '') as role, coalesce(text, '') as text from conversations
  union all select -7, 0, 'user', '\### Assistant: </turn> ok'
  union all select -7, 1, 'assistant', '\### Assistant: </turn> ok'
), f as (
  select *, length(replace(replace(text, '\', '\b'), '<', '\l')) + length(replace(replace(replace(role, '\', '\b'), '<', '\l'), '|', '\p')) + 13 as chars,
    sum(length(replace(replace(text, '\', '\b'), '<', '\l')) + length(replace(replace(replace(role, '\', '\b'), '<', '\l'), '|', '\p')) + 13)
      over (partition by conv_id order by turn nulls first, role, text rows between unbounded preceding and current row) as upto
  from t
)
select conv_id, count(*) as n_turns,
  sha256(string_agg(role || chr(10) || text || chr(10), '' order by turn nulls first, role, text)) as turns_sha256,
  cast(sum(case when role = 'assistant' then length(text) else 0 end) as bigint) as loss_chars,
  sha256(coalesce(string_agg(case when role = 'assistant' then text end, '' order by turn nulls first, role, text), '')) as loss_sha256,
  cast(sum(chars) as bigint) as formatted_chars,
  count(case when role = 'assistant' then 1 end) as n_examples,
  cast(sum(case when role = 'assistant' then upto else 0 end) as bigint) as example_chars
from f group by conv_id
"""
