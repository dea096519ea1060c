"""Small tables with the awkward cases every operator must define."""

from pyspark.sql import types as T

SCHEMA = T.StructType([
    T.StructField("doc_id", T.LongType()), T.StructField("text", T.StringType()), T.StructField("lang", T.StringType()),
    T.StructField("source", T.StringType()), T.StructField("n_chars", T.LongType()),
    # names that operators use inside
    T.StructField("key", T.StringType()), T.StructField("rep", T.LongType()), T.StructField("label", T.StringType()), T.StructField("_kept", T.LongType()),
])

LONG = " ".join(f"word{i % 977} and{i % 13}," for i in range(20_000)) + "."


def docs(spark, rows):
    """rows: (doc_id, text[, lang])"""
    full = [(r[0], r[1], r[2] if len(r) > 2 else None, None, None, "k", 1, "x", 7) for r in rows]
    return spark.createDataFrame(full, SCHEMA)


AWKWARD = [
    (5, None, "en"), (6, "", "en"), (7, "   \n", None), (8, "a", "en"), (9, "the the the the the the", "en"), (10, "the the the the the the", "en"),
    (11, "1234 5678 !!!", None), (12, "naïve café — ﬁ ① 中文 😀 ▁ \x01\x02 x", "fr"), (13, LONG, "en"), (14, LONG + " tail", "en"),
    (15, "MIT License\tmit  license", "en"), (16, "MIT License mit license", "en"), (None, "no id at all here", None), (8, "a", "en"),
]
