"""Awkward documents for every operator."""

from pyspark.sql import types as T

SCHEMA = T.StructType([
    T.StructField("doc_id", T.LongType()), T.StructField("text", T.StringType()), T.StructField("lang", T.StringType()),
    T.StructField("source", T.StringType()), T.StructField("n_chars", T.LongType()),
    T.StructField("length", T.StringType()), T.StructField("component_id", T.StringType()), T.StructField("score", T.StringType()),
])  # the last three clash with names that operators use inside

LONG = "word soup " * 20_000
ROWS = [
    (1, None, "en", "src0"), (2, "", "en", "src0"), (3, " ", None, None), (4, "a", "en", "src1"), (5, LONG, "en", "src1"),
    (6, "One two three four five six seven eight nine ten eleven.\nSame line here again and again, it is.", "en", "src2"),
    (7, "One two three four five six seven eight nine ten eleven.\nSame line here again and again, it is.", "en", "src2"),
    (7, "One two three four five six seven eight nine ten eleven.\nSame line here again and again, it is.", "en", "src2"),
    (None, "no id at all, mail me at jo.doe@mail.example.com or +1 (212) 555-0100", None, "src3"),
    (9, "été naïve Ωmega 日本語   x\t\ty  z <|endoftext|> \n\n end", "fr", None), (10, "4111 1111 1111 1111 and 10.0.0.255", "en", "src3"),
]


def odd(spark):
    return spark.createDataFrame([(*r, len(r[1] or ""), "x", "y", "z") for r in ROWS], SCHEMA)


def none(spark):
    return spark.createDataFrame([], SCHEMA)
