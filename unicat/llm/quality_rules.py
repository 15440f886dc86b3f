"""Quality rules by compression bands: zstandard ratios of whole documents and of fixed chunks.

A text that compresses far better than prose repeats itself; one that hardly compresses is not prose. What is normal
depends on length, so each band of lengths has its own limits, in bytes of UTF-8. Whole texts and every chunk count; the
last chunk is judged by the band of its own length, and one under LAST_BYTES by the chunk that it ends.

Defined cases: a null or empty text has no words and fails the base rules. Lone surrogates can't occur in Arrow
strings. Each row is judged alone, so repeated rows, null ids and empty tables need no rule. Extra columns pass through; one
named like a column that is added comes out as in__...
"""

from __future__ import annotations

from collections import Counter
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from .common import aside, back, named, trim

MIN_WORDS = 50
MAX_REPEAT_PERCENT = 50
#: A shorter last chunk says too little by itself.
LAST_BYTES = 1_000
SYMBOLS = "#*$%&|<>"
_BLANKS = {c: " " for c in range(9, 14)}


@dataclass(frozen=True)
class Bands:
    """(from bytes, least ratio, greatest ratio), ascending; a text falls under the last band that it reaches."""

    whole: tuple[tuple[int, float, float], ...] = ((0, 0.0, 9.0), (200, 0.20, 0.95), (500, 0.20, 0.80), (1_000, 0.18, 0.72), (2_000, 0.18, 0.66), (4_000, 0.15, 0.62), (20_000, 0.12, 0.56), (200_000, 0.08, 0.55))
    chunk_bytes: int = 4_096
    chunk: tuple[float, float] = (0.12, 0.62)
    #: A document goes when more than this share of its bytes is in chunks outside their limits.
    chunk_share: float = 0.2
    level: int = 3


def words_of(text: str) -> list[str]:
    return [w for w in text.translate(_BLANKS).split(" ") if w]


def base_counts(text: str | None) -> tuple[int, int, int, int, int]:
    """n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words."""
    if not text:
        return 0, 0, 0, 0, 0
    w = words_of(text)
    n = len(w)
    lines = [x for x in text.split("\n") if x and x.translate(_BLANKS).strip(" ")]
    repeat = 0
    if n > 3:
        triples = list(zip(w, w[1:], w[2:], strict=False))
        if len(set(triples)) < len(triples):
            seen, covered = Counter(triples), bytearray(n)
            for i, t in enumerate(triples):
                if seen[t] > 1:
                    covered[i] = covered[i + 1] = covered[i + 2] = 1
            repeat = sum(covered)
    return n, sum(map(len, w)), sum(text.count(c) for c in SYMBOLS), len(lines) - len(set(lines)), repeat


def in_bands(raw: bytes, bands: Bands, compress) -> tuple[bool, float]:
    """Whether a text is inside its limits, and its ratio."""
    n = len(raw)
    if not n:
        return True, 1.0
    ratio = len(compress(raw)) / n
    low, high = _limits(n, bands)
    if not low <= ratio <= high:
        return False, ratio
    if n <= bands.chunk_bytes:  # the text is its only chunk
        return True, ratio
    starts = list(range(0, n, bands.chunk_bytes))
    if len(starts) > 1 and n - starts[-1] < LAST_BYTES:
        starts.pop()
    out = 0
    for at, end in zip(starts, [*starts[1:], n], strict=True):
        low, high = bands.chunk if end - at >= bands.chunk_bytes else _limits(end - at, bands)
        if not low <= len(compress(raw[at:end])) / (end - at) <= high:
            out += end - at
    return out <= bands.chunk_share * n, ratio


def _limits(n: int, bands: Bands) -> tuple[float, float]:
    return next((lo, hi) for least, lo, hi in reversed(bands.whole) if n >= least)


#: What judge() adds to each row.
ADDED = T.StructType(
    [T.StructField(f"__{n}", T.LongType()) for n in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")]
    + [T.StructField("__base_failed", T.BooleanType()), T.StructField("__ratio", T.DoubleType()), T.StructField("__kept", T.BooleanType())]
)


def judge(df: DataFrame, text_col: str = "text", bands: Bands = Bands(), rejects: bool = True, drop_text: bool = False) -> DataFrame:
    """Every row with the measures of ADDED; rejects=False leaves out the rows that fail, drop_text leaves out the text."""
    df, names_in = aside(df)
    text_col = named(text_col, names_in)
    names = [c for c in df.columns if not (drop_text and c == text_col)]
    fields = [df.schema[c] for c in names] + list(ADDED)

    def run(batches):
        import zstandard

        compress = zstandard.ZstdCompressor(level=bands.level).compress
        for b in batches:
            rows = []
            for x in b.column(b.schema.get_field_index(text_col)):
                text = x.as_py()
                counts = base_counts(text)
                failed = counts[0] < MIN_WORDS or 100 * counts[4] > MAX_REPEAT_PERCENT * counts[0]
                inside, ratio = in_bands((text or "").encode(), bands, compress)
                rows.append((*counts, failed, ratio, inside and not failed))
            kinds = [pa.int64()] * 5 + [pa.bool_(), pa.float64(), pa.bool_()]
            cols = [pa.array(list(c), k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)] if rows else [pa.array([], k) for k in kinds]
            out = pa.RecordBatch.from_arrays([b.column(b.schema.get_field_index(c)) for c in names] + cols, names + ADDED.names)
            yield out if rejects else out.filter(cols[-1])
        trim()

    return back(df.mapInArrow(run, T.StructType(fields)), names_in)


def drop_rejected(df: DataFrame, text_col: str = "text", bands: Bands = Bands()) -> DataFrame:
    """The rows of df that are kept, with their own columns."""
    own, names = aside(df)
    return back(judge(own, named(text_col, names), bands, rejects=False).drop(*ADDED.names), names)
