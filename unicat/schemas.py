"""Columns that the library reads from the given tables and that its derived tables have; checked where stages meet."""

from __future__ import annotations

from pyspark.sql import DataFrame

GIVEN = {
    "documents": "doc_id bigint, text string, lang string, source string",
    "pages": "page_id bigint, url string, html string",
    "embeddings": "vec_id bigint, embedding array<float>, label int",
    "labels": "doc_id bigint",
    "events": "event_id bigint, user_id bigint, event_type string, value double, props string",
}
RESPONSES = "item_id bigint, feat int, wtype string, r double"
EDGES = "s bigint, t bigint, q double"
LABELS = "item_id bigint"


def checked(df: DataFrame, columns: str, what: str) -> DataFrame:
    """df, if it has these columns (name type, ...) among others; else a ValueError that names what is wrong."""
    have = {n.lower(): t for n, t in df.dtypes}
    wrong = [c for c in columns.split(", ") if have.get(c.split(" ")[0]) != c.split(" ")[1]]
    if wrong:
        raise ValueError(f"{what}: expected {', '.join(wrong)}; it has {', '.join(f'{n} {t}' for n, t in df.dtypes)}")
    return df
