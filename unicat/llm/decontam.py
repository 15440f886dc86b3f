"""Benchmark decontamination: which words of a document lie inside an item's passages, by a prefix-filtered set join.

An item is its windows of WINDOW consecutive words. Containment needs every word of a window, so the prefix that a
document must share is one token: the rarest word of the window, by counts over all documents. Each window is indexed
under it with the word's place in the window (positional bound) and the window's length (length bound); a document word
that is such a token is aligned by place, the window must fit inside the document, and all its words are verified.

The windows are held by every worker in blocks of at most BLOCK_WORDS words; more blocks are further narrow passes over
the same rows, without a shuffle, so any number of items works.

Defined cases: null or empty texts have no words, items without words have no windows, items of fewer words than a
window are one window. Repeated items all match; repeated rows are judged alone. An empty table on either side gives
rows without hits, or no rows. Extra columns pass through; one named like a column that is added comes out as in__...
"""

from __future__ import annotations

import hashlib
from collections import Counter

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import aside, back, named, trim

WINDOW = 10
#: Words of benchmark items that one pass holds (about 100 bytes each in a worker).
BLOCK_WORDS = 500_000
#: On UTF-8: A-Z lower-cased, other ASCII than digits and letters to spaces.
_PLAIN = bytes(c + 32 if 65 <= c <= 90 else c if c >= 128 or 48 <= c <= 57 or 97 <= c <= 122 else 32 for c in range(256))


def words_of(text: str | None) -> list[bytes]:
    """Runs of code points other than ASCII without digits and letters, A-Z lower-cased, in UTF-8."""
    return text.encode().translate(_PLAIN).split() if text else []


def windows_of(words: list[bytes], window: int = WINDOW) -> list[tuple[bytes, ...]]:
    return [tuple(words[i : i + window]) for i in range(max(1, len(words) - window + 1))] if words else []


def item_blocks(items: DataFrame, id_col: str, text_col: str, block_words: int = BLOCK_WORDS):
    """Lists of (item id, words) with at most block_words words each (one item at least); read one partition at a time."""
    block, held = [], 0
    for item, text in items.select(id_col, text_col).toLocalIterator():
        words = words_of(text)
        if not words:
            continue
        if block and held + len(words) > block_words:
            yield block
            block, held = [], 0
        block.append((item, words))
        held += len(words)
    if block:
        yield block


def count_words(docs: DataFrame, text_col: str, vocabulary: set[bytes]) -> dict[bytes, int]:
    """Occurrences of the block's words in all documents: at most one number for each word of the block."""
    held = docs.sparkSession.sparkContext.broadcast(vocabulary)

    def count(batches):
        known, total = held.value, Counter()
        for b in batches:
            for x in b.column(0):
                total.update(filter(known.__contains__, words_of(x.as_py())))
        yield pa.RecordBatch.from_arrays([pa.array(list(total), pa.binary()), pa.array(list(total.values()), pa.int64())], ["word", "n"])

    rows = docs.select(text_col).mapInArrow(count, "word binary, n long").groupBy("word").agg(F.sum("n")).collect()
    return {bytes(w): n for w, n in rows}


def prefix_index(block, counts: dict[bytes, int], window: int = WINDOW):
    """(token -> {(place, length)}, window -> [items]); the token is the window's rarest word."""
    tokens: dict[bytes, set[tuple[int, int]]] = {}
    owners: dict[tuple[bytes, ...], list] = {}
    for item, words in block:
        for w in windows_of(words, window):
            if w not in owners:
                place = min(range(len(w)), key=lambda i: (counts.get(w[i], 0), w[i], i))
                tokens.setdefault(w[place], set()).add((place, len(w)))
                owners[w] = []
            if item not in owners[w]:
                owners[w].append(item)
    return {k: sorted(v) for k, v in tokens.items()}, owners


def _hits(words: list[bytes], tokens, owners) -> tuple[list[tuple[int, int]], set]:
    """Spans of words inside windows, and the items they belong to."""
    spans, items, n = [], set(), len(words)
    if tokens.keys().isdisjoint(words):
        return spans, items
    for i, w in enumerate(words):
        for place, length in tokens.get(w, ()):
            start = i - place
            if start >= 0 and start + length <= n and (own := owners.get(tuple(words[start : start + length]))):
                spans.append((start, start + length))
                items.update(own)
    return spans, items


#: What match() adds: the number of words, the spans of hit words (start, end, start, end ...) and the items.
ADDED = T.StructType([T.StructField("__n_words", T.LongType()), T.StructField("__spans", T.ArrayType(T.LongType())), T.StructField("__items", T.ArrayType(T.StringType()))])


def match(docs: DataFrame, items: DataFrame, text_col: str = "text", item_id: str = "item_id", item_text: str = "text", window: int = WINDOW, block_words: int = BLOCK_WORDS) -> DataFrame:
    """Every document row with the columns of ADDED."""
    docs, names = aside(docs)
    text_col = named(text_col, names)
    return back(_match(docs, items, text_col, item_id, item_text, window, block_words), names)


def _or_one(blocks):
    """The blocks, one at a time, or an empty one if there are none."""
    first = next(blocks, [])
    yield first
    yield from blocks


def _match(docs: DataFrame, items: DataFrame, text_col: str, item_id: str, item_text: str, window: int, block_words: int) -> DataFrame:
    sc, source, out = docs.sparkSession.sparkContext, docs, None
    schema = T.StructType([*docs.schema, *ADDED])
    for block in _or_one(item_blocks(items, item_id, item_text, block_words)):
        counts = count_words(source, text_col, {w for _, words in block for w in words}) if block else {}
        held = sc.broadcast(prefix_index(block, counts, window))
        first = out is None

        def scan(batches, held=held, first=first):
            tokens, owners = held.value
            for b in batches:
                at = b.schema.get_field_index
                before = [(s.as_py(), i.as_py()) for s, i in zip(b.column(at("__spans")), b.column(at("__items")), strict=True)] if not first else [([], [])] * b.num_rows
                rows = []
                for x, (spans, found) in zip(b.column(at(text_col)), before, strict=True):
                    words = words_of(x.as_py())
                    new, own = _hits(words, tokens, owners)
                    rows.append((len(words), spans + [p for s in new for p in s], sorted({*found, *map(str, own)})))
                cols = list(zip(*rows, strict=True)) or [(), (), ()]
                keep = [n for n in b.schema.names if n not in ADDED.names]
                yield pa.RecordBatch.from_arrays(
                    [*(b.column(at(n)) for n in keep), pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.list_(pa.int64())), pa.array(cols[2], pa.list_(pa.string()))], [*keep, *ADDED.names]
                )
            trim()

        out = (docs if first else out).mapInArrow(scan, schema)
    return out


def report(docs: DataFrame, items: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """One row per document: id, n_words, n_hit, n_items, items_sha256, contaminated."""

    def digest(batches):
        for b in batches:
            hit = []
            for spans in b.column(2).to_pylist():
                end = total = 0
                for start, stop in sorted(zip(spans[::2], spans[1::2], strict=True)):
                    total += max(0, stop - max(start, end))
                    end = max(end, stop)
                hit.append(total)
            items = b.column(3).to_pylist()
            yield pa.RecordBatch.from_arrays(
                [b.column(0), b.column(1), pa.array(hit, pa.int64()), pa.array([len(x) for x in items], pa.int64()), pa.array([hashlib.sha256(",".join(x).encode()).hexdigest() for x in items]), pa.array([h > 0 for h in hit])],
                ["id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated"],
            )

    kind = docs.schema[id_col].dataType.simpleString()
    found = match(docs.select(id_col, text_col), items, text_col, **options).select(id_col, "__n_words", "__spans", "__items")
    return found.mapInArrow(digest, f"id {kind}, n_words long, n_hit long, n_items long, items_sha256 string, contaminated boolean").withColumnRenamed("id", id_col)


def drop_contaminated(docs: DataFrame, items: DataFrame, text_col: str = "text", **options) -> DataFrame:
    """The documents without any hit, with their own columns."""
    own, names = aside(docs)
    return back(match(own, items, named(text_col, names), **options).where(F.size("__spans") == 0).drop(*ADDED.names), names)
