"""Removal of lines that many documents share. DataFrame functions only.

Plan: normalise and explode the lines, keep a 128-bit hash of each long key, count distinct documents per hash
(partial aggregation first), join the few shared hashes back to the line positions, and drop those positions
from each text, which keeps the order of the lines.

Defined cases: a null or empty text is one empty line. A null document id is an id of its own for dropping, but is not
counted and never the one that keeps a line. Rows that repeat an id count once and share the keeping right. An empty
table gives an empty table. Extra columns pass through; one named like a column that is added comes out as in__...
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import ascii_lower, aside, back, join_keys, materialise, named

MIN_CHARS = 40
MIN_DOCS = 5
#: White space that is stripped from a line before it is compared.
BLANKS = " \t\n\x0b\x0c\r"


def line_key(line):
    """The form of a line in which it is compared with others."""
    return ascii_lower(F.btrim(line, F.lit(BLANKS)))


def _hash(*cols):
    return F.xxhash64(*cols), F.xxhash64(F.lit(1), *cols)


def _candidates(df: DataFrame, id_col: str, text_col: str, min_chars: int) -> DataFrame:
    text = F.coalesce(F.col(text_col), F.lit(""))
    h1, h2 = _hash(F.col("__key"))
    return (
        df.select(F.col(id_col).alias("__id"), F.xxhash64(text).alias("__text_hash"), F.posexplode(F.split(text, "\n", -1)).alias("__pos", "__line"))
        .select("__id", "__text_hash", "__pos", line_key(F.col("__line")).alias("__key"))
        .where(F.length("__key") >= min_chars)
        .select("__id", "__text_hash", "__pos", h1.alias("__h1"), h2.alias("__h2"))
    )


def shared_lines(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_chars: int = MIN_CHARS, min_docs: int = MIN_DOCS) -> DataFrame:
    """One row per line hash that at least min_docs documents hold: __h1, __h2, __keeper (largest id), __rows (its lines)."""
    return (
        _candidates(df, id_col, text_col, min_chars)
        .groupBy("__h1", "__h2")
        .agg(F.count_distinct("__id").alias("__docs"), F.max("__id").alias("__keeper"), F.count(F.lit(1)).alias("__rows"))
        .where(F.col("__docs") >= min_docs)
        .drop("__docs")
    )


def dedup_lines(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_chars: int = MIN_CHARS, min_docs: int = MIN_DOCS) -> DataFrame:
    """df with the text cleaned, and two more columns: __n_lines (before) and __n_dropped."""
    df, names = aside(df)
    id_col, text_col = named(id_col, names), named(text_col, names)
    shared = materialise(shared_lines(df, id_col, text_col, min_chars, min_docs), "shared-lines")
    drops = (
        join_keys(_candidates(df, id_col, text_col, min_chars), shared, ["__h1", "__h2"], "__rows")
        .where(~F.col("__id").eqNullSafe(F.col("__keeper")))
        .groupBy(F.col("__id").alias("__drop_id"), F.col("__text_hash").alias("__drop_text"))
        .agg(F.collect_set("__pos").alias("__drops"))
    )
    text = F.coalesce(F.col(text_col), F.lit(""))
    joined = df.withColumn("__text_hash", F.xxhash64(text)).join(
        drops, F.col(id_col).eqNullSafe(F.col("__drop_id")) & (F.col("__text_hash") == F.col("__drop_text")), "left"
    )
    lines = joined.withColumn("__lines", F.split(text, "\n", -1)).withColumn("__n_lines", F.size("__lines").cast("long"))
    kept = F.array_except(F.sequence(F.lit(0), (F.col("__n_lines") - 1).cast("int")), F.col("__drops"))
    rebuilt = F.array_join(F.transform(kept, lambda i: F.col("__lines")[i]), "\n")
    out = lines.select(
        *[(F.when(F.col("__drops").isNull(), text).otherwise(rebuilt).alias(c) if c == text_col else F.col(f"`{c}`")) for c in df.columns],
        "__n_lines",
        F.coalesce(F.size("__drops"), F.lit(0)).cast("long").alias("__n_dropped"),
    )
    return back(out, names)
