"""Small inputs with nulls, ties, repeated rows, long texts, extra columns and odd characters."""

import random

SF = "/root/testdata/sf0.001"

ODD = [
    None,
    "",
    " ",
    "\n\n \t",
    "a",
    "aaa aaaa aaaaaaa rrrr",
    "x<|endoftext|>y <|startoftext|> <|end",
    "İstanbul ΣΑΣ Σ \x1c a\x1fb\x0b q z\x85n \n\n k",
    "日本語テスト 'll'd don't WE'VE 12345 ½ é ﬁ ☃️!!??...",
    "ab" * 3000 + "!?" * 100,
    "word " * 4000,
    "tail  \n",
    "  lead",
    "ñandú é Å İ",
]


def mixed_documents(seed: int = 7, n: int = 40) -> list[tuple]:
    """Rows (doc_id, text, lang, source, n_chars) with nulls in every column and repeated rows."""
    draw = random.Random(seed)
    texts = ODD + ["".join(draw.choice("abcdeth ing'<|>é́σςІ\n\t.,1") for _ in range(draw.randrange(1, 400))) for _ in range(n)]
    rows = [(i, t, draw.choice(["en", None]), draw.choice(["src0", "src1", None]), None if t is None else len(t)) for i, t in enumerate(texts)]
    return [*rows, rows[5], rows[5], (None, "no key here", None, None, None), (3, "a second text of key three", "en", "src1", 3)]


SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def frame(spark, rows, extra: bool = True):
    df = spark.createDataFrame(rows, SCHEMA)
    if extra:
        from pyspark.sql import functions as F

        df = df.withColumns({c: F.lit("clash") for c in ("ids", "n_tokens", "fp", "k", "t", "size", "score", "component_id", "__text", "n_words", "shard", "law")})
    return df
