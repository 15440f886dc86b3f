import random

from pyspark.sql import types as T

DOCS = T.StructType(
    [T.StructField("doc_id", T.LongType()), T.StructField("text", T.StringType()), T.StructField("lang", T.StringType()), T.StructField("source", T.StringType()), T.StructField("n_chars", T.LongType())]
)


def prose(seed: int, words: int, vocabulary: int = 5000) -> str:
    r = random.Random(seed)
    return " ".join(f"w{r.randrange(vocabulary)}" for _ in range(words))


def odd_docs():
    """Nulls, empty and blank texts, ties, repeated rows and a long text."""
    shared = "This line is shared by many documents and is long enough to count."
    rows = [
        (1, None),
        (2, ""),
        (3, " \n\t\n"),
        (4, prose(4, 80)),
        (5, prose(4, 80)),
        (5, prose(4, 80)),
        (None, prose(6, 60)),
        (7, prose(7, 20_000)),
        (8, "É" * 50 + "\n" + prose(8, 30)),
        (9, "one two three"),
        (10, "ONE two\nthree"),
        (11, "\x1c odd \x1d text   with spaces 'S I'LL"),
        *((20 + i, f"{prose(20 + i, 60)}\n  {shared if i % 2 else shared.upper()}\t\n{prose(90 + i, 10)}") for i in range(8)),
    ]
    return [(i, t, None if i is None else "en", "src0", None if t is None else len(t)) for i, t in rows]


def frame(spark, rows, schema=DOCS):
    return spark.createDataFrame(rows, schema)
