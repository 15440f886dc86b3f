"""Exact similarity self-join of documents on sets of word shingles, by grouped prefixes, up to connected components.

1. A sketch counts all shingles of all documents in SKETCH buckets. Bucket count, then hash, is the global order: a
   shingle that many documents share comes late. Any order gives exact results; this one keeps the lists short.
2. Documents with equal sets form a class, classes with equal prefixes and sizes a group. Two sets that link must share
   a token of their prefixes.
3. Star round: classes that share a min-hash are compared with the most typical class of the list only. A large group of
   near copies so becomes one component with as many comparisons as it has members.
4. Exact round: of all prefix lists of groups, those that hold one component only are settled. In the others, every pair
   of different components that passes the size, prefix, position and bitmap filters is expanded to classes and
   verified on the whole texts. A pair inside one component can't change the components, so no link between components is lost.

Comparison is on 64-bit hashes of shingles; class keys have 128 bits.

Defined cases: a null, empty or blank text has no shingles, links with nothing and is its own component. Fewer words
than a shingle are one shingle. A row with a null id is listed with the component of equal sets, but a null id can't
name a component. Rows that repeat an id with different texts are one node, whose links add up. An empty table gives
an empty table. Extra columns are not read; keep_one passes them through.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import aside, back, join_keys, materialise, named, trim
from .components import components

SHINGLE = 5
PERCENT = 75
#: Buckets of the rarity sketch, in SEGMENTS rows.
SKETCH, SEGMENTS = 1 << 21, 1 << 11
#: 64-bit words of a set's parity bitmap.
PARITY = 16
STARS = 6
#: Ids of which a broadcast set may consist (16 bytes each); more are shuffled.
BROADCAST_IDS = 1_000_000
SALTS = 64
#: Rows of one token's list that a task joins with at a time; longer lists are split into as many blocks.
LIST_ROWS = 1_000
_MIX = np.uint64(0x9E3779B97F4A7C15)
_FIN = np.uint64(0xD6E8FEB86659FD93)
_STAR_MIX = np.array([(0xBF58476D1CE4E5B9 * (2 * j + 1)) % (1 << 64) | 1 for j in range(STARS)], np.uint64)


class WordHashes(dict):
    """64-bit hashes of words, remembered up to a bound."""

    def __missing__(self, word: bytes) -> int:
        import xxhash

        if len(self) > 100_000:
            self.clear()
        h = self[word] = xxhash.xxh64_intdigest(word)
        return h


def shingle_set(text: str | None, memo: WordHashes, size: int = SHINGLE) -> np.ndarray:
    """Sorted distinct hashes of the word shingles of a text; words end at ASCII white space and A-Z are lower-cased."""
    words = (text or "").encode().lower().split()
    n = len(words)
    if not n:
        return np.empty(0, np.uint64)
    w = np.fromiter(map(memo.__getitem__, words), np.uint64, n)
    k = min(n, size)
    h = np.full(n - k + 1, k, np.uint64)
    for j in range(k):
        h = (h ^ (h >> np.uint64(29))) * _MIX + w[j : n - k + 1 + j]
    h = (h ^ (h >> np.uint64(32))) * _FIN
    return np.unique(h ^ (h >> np.uint64(31)))


def prefix_length(n, percent: int = PERCENT):
    """Tokens of an n-set of which one at least is in any set that links with it."""
    return n - (percent * n + 99) // 100 + 1


def index_length(n, percent: int = PERCENT):
    """The same for partners that are at least as large."""
    return n - (2 * percent * n + 99 + percent) // (100 + percent) + 1


def _int(arr) -> pa.Array:
    return pa.array(np.ascontiguousarray(arr).view(np.int64))


def _bytes(arrays) -> pa.Array:
    return pa.array([a.tobytes() for a in arrays], pa.binary())


def rarity_sketch(docs: DataFrame, size: int = SHINGLE) -> np.ndarray:
    """Counts of all shingles of all documents by the top bits of their hashes; SKETCH numbers at any input size."""
    width = SKETCH // SEGMENTS
    shift = np.uint64(64 - (SKETCH.bit_length() - 1))

    def count(batches):
        memo, total, wait, waiting = WordHashes(), np.zeros(SKETCH, np.int64), [], 0
        for b in batches:
            for x in b.column(0):
                s = shingle_set(x.as_py(), memo, size)
                wait.append(s)
                waiting += len(s)
                if waiting > 500_000:
                    total += np.bincount((np.concatenate(wait) >> shift).astype(np.int64), minlength=SKETCH)
                    wait, waiting = [], 0
        if wait:
            total += np.bincount((np.concatenate(wait) >> shift).astype(np.int64), minlength=SKETCH)
        if total.any():
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(SEGMENTS, dtype=np.int32)), _bytes(total.astype(np.uint32).reshape(SEGMENTS, width))], ["segment", "counts"])
        del memo, total, wait
        trim()

    def add(batches):
        held: dict[int, np.ndarray] = {}
        for b in batches:
            for seg, raw in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                held[seg] = held.get(seg, 0) + np.frombuffer(raw.as_buffer(), np.uint32).astype(np.int64)
        if held:
            yield pa.RecordBatch.from_arrays([pa.array(list(held), pa.int32()), _bytes(held.values())], ["segment", "counts"])

    rows = docs.select("text").mapInArrow(count, "segment int, counts binary").repartition("segment").mapInArrow(add, "segment int, counts binary").collect()
    out = np.zeros((SEGMENTS, width), np.int64)
    for seg, raw in rows:
        out[seg] = np.frombuffer(raw, np.int64)
    return out.reshape(-1)


def _row_key(text):
    return F.xxhash64(F.coalesce(text, F.lit("")))


def signatures(docs: DataFrame, counts: np.ndarray, size: int = SHINGLE, percent: int = PERCENT) -> DataFrame:
    """Per row: id, n, class key s1 s2, group key g1 g2, prefix (hashes in global order), stars (min-hashes), typical,
    parity (bit i: whether an odd number of hashes ends in i), row (a hash of the text)."""
    shift = np.uint64(64 - (SKETCH.bit_length() - 1))
    held = docs.sparkSession.sparkContext.broadcast(np.minimum(counts, np.iinfo(np.uint32).max).astype(np.uint32))

    def sign(batches):
        import xxhash

        memo, rank = WordHashes(), held.value
        for b in batches:
            ns, keys, prefixes, stars, typical, parity = [], [], [], [], [], []
            for x in b.column(1):
                s = shingle_set(x.as_py(), memo, size)
                n = len(s)
                ns.append(n)
                if not n:
                    keys.append(b"\0" * 32)
                    prefixes.append(b"")
                    stars.append([])
                    typical.append(0)
                    parity.append(np.zeros(PARITY, np.int64))
                    continue
                c = rank[(s >> shift).astype(np.int64)]
                p = s[np.lexsort((s, c))[: prefix_length(n, percent)]].tobytes()
                keys.append(xxhash.xxh3_128_digest(s.tobytes()) + xxhash.xxh3_128_digest(p + n.to_bytes(8, "little")))
                prefixes.append(p)
                mixed = s[:, None] * _STAR_MIX[None, :]
                stars.append((mixed ^ (mixed >> np.uint64(31))).min(axis=0).view(np.int64))
                typical.append(int(100 * np.log2(c + 1.0).mean()))
                odd = np.bincount((s & np.uint64(64 * PARITY - 1)).astype(np.int64), minlength=64 * PARITY) & 1
                parity.append(np.packbits(odd.astype(np.uint8)).view(np.int64))
            k = np.frombuffer(b"".join(keys), np.int64).reshape(-1, 4)
            yield pa.RecordBatch.from_arrays(
                [b.column(0), pa.array(ns, pa.int64()), *(pa.array(k[:, j]) for j in range(4)), pa.array(prefixes, pa.binary()), pa.array(stars, pa.list_(pa.int64())), pa.array(typical, pa.int64()), pa.array(parity, pa.list_(pa.int64())), b.column(2)],
                ["id", "n", "s1", "s2", "g1", "g2", "prefix", "stars", "typical", "parity", "row"],
            )
        del memo
        trim()

    return docs.select("id", "text", _row_key(F.col("text")).alias("row")).mapInArrow(sign, "id long, n long, s1 long, s2 long, g1 long, g2 long, prefix binary, stars array<long>, typical long, parity array<long>, row long")


def linked(docs: DataFrame, pairs: DataFrame, size: int = SHINGLE, percent: int = PERCENT) -> DataFrame:
    """Those of the pairs (a, b) of ids whose texts link, judged on the whole texts.

    The texts of a are dealt out by (a, salt), so that one id with very many partners is spread over SALTS tasks."""
    pairs = materialise(pairs.select("a", "b", F.pmod(F.xxhash64("b"), F.lit(SALTS)).alias("salt")), "pairs")
    ids = materialise(pairs.select(F.col("a").alias("id")).union(pairs.select(F.col("b").alias("id"))).distinct(), "ids")
    few = ids.count() <= BROADCAST_IDS
    texts = docs.where(F.col("id").isNotNull()).join(F.broadcast(ids), "id", "left_semi") if few else docs
    left = pairs.select("a", "salt").distinct().join(texts.select(F.col("id").alias("a"), F.col("text").alias("text_a")), "a")
    right = pairs.join(texts.select(F.col("id").alias("b"), F.col("text").alias("text_b")), "b")

    def verify(batches):
        memo, sets = WordHashes(), {}

        def of(key, text):
            if (key, len(text or "")) not in sets:
                if len(sets) >= 64:
                    sets.clear()
                sets[key, len(text or "")] = text, shingle_set(text, memo, size)
            was, s = sets[key, len(text or "")]
            return s if was == text else shingle_set(text, memo, size)

        for batch in batches:
            keep = []
            for a, ta, b, tb in zip(*(batch.column(i) for i in range(4)), strict=True):
                x, y = of(a.as_py(), ta.as_py()), shingle_set(tb.as_py(), memo, size)
                common = len(np.intersect1d(x, y, assume_unique=True))
                keep.append(common > 0 and 100 * common >= percent * (len(x) + len(y) - common))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2)], ["a", "b"]).filter(pa.array(keep, pa.bool_()))
        memo.clear()
        sets.clear()
        trim()

    both = right.join(left, ["a", "salt"]).select("a", "text_a", "b", "text_b")
    return materialise(both.mapInArrow(verify, "a long, b long").distinct(), "links")


def _possible(pairs: DataFrame, classes: DataFrame, percent: int) -> DataFrame:
    """Leaves out pairs whose parity bitmaps differ in more bits than linked sets can have elements of their own.

    Each element that only one of two sets has flips one bit, so the bits that differ are no more than those elements."""
    known = classes.select("rep", "n", "parity")
    ends = pairs.join(known.select(F.col("rep").alias("a"), F.col("n").alias("n_a"), F.col("parity").alias("p_a")), "a").join(known.select(F.col("rep").alias("b"), F.col("n").alias("n_b"), F.col("parity").alias("p_b")), "b")
    differ = F.aggregate(F.zip_with("p_a", "p_b", lambda x, y: F.bit_count(x.bitwiseXOR(y))), F.lit(0), lambda t, x: t + x)
    # 100 * overlap >= percent * union, with overlap = (n_a + n_b - differ) / 2
    return ends.where((100 + percent) * differ <= (100 - percent) * (F.col("n_a") + F.col("n_b"))).select("a", "b")


def _star_pairs(classes: DataFrame) -> DataFrame:
    """(a, b): b shares a min-hash with a, the most typical class of the list."""
    lists = classes.select("rep", "n", "typical", F.posexplode("stars").alias("j", "m"))
    leaders = lists.groupBy("j", "m").agg(F.max(F.struct("typical", (-F.col("rep")).alias("minus"), F.col("n").alias("size"))).alias("top"), F.count(F.lit(1)).alias("rows")).where("rows > 1")
    leaders = materialise(leaders.select("j", "m", (-F.col("top.minus")).alias("a"), F.col("top.size").alias("size"), "rows"), "leaders")
    near = join_keys(lists.select("j", "m", "rep", "n"), leaders, ["j", "m"], "rows")
    return near.where((F.col("rep") != F.col("a")) & (100 * F.least("n", "size") >= PERCENT * F.greatest("n", "size"))).select("a", F.col("rep").alias("b")).distinct()


def _postings(groups: DataFrame, extra: list[str], tokens: DataFrame | None, few: bool) -> DataFrame:
    """One row per token of each group's prefix: token, pos and the extra columns."""
    kinds = {c: t for c, t in groups.dtypes}

    def spread(batches):
        for b in batches:
            raw = b.column(b.schema.get_field_index("prefix"))
            sizes = np.array([len(x.as_buffer()) // 8 for x in raw], np.int64)
            if not sizes.sum():
                continue
            token = np.concatenate([np.frombuffer(x.as_buffer(), np.int64) for x in raw])
            at = np.repeat(np.arange(len(sizes)), sizes)
            pos = np.arange(len(token)) - np.repeat(np.cumsum(sizes) - sizes, sizes)
            own = [b.column(b.schema.get_field_index(c)).take(pa.array(at)) for c in extra]
            for lo in range(0, len(token), 100_000):
                yield pa.RecordBatch.from_arrays([pa.array(token[lo : lo + 100_000]), pa.array(pos[lo : lo + 100_000]), *(o.slice(lo, 100_000) for o in own)], ["token", "pos", *extra])

    out = groups.select("prefix", *extra).mapInArrow(spread, "token long, pos long, " + ", ".join(f"{c} {kinds[c]}" for c in extra))
    if tokens is None:
        return out
    return out.join(F.broadcast(tokens) if few else tokens, "token", "left_semi")


def _cross_pairs(signed: DataFrame, classes: DataFrame, percent: int) -> DataFrame:
    """(a, b): every pair of classes of different components that can link, by shared prefix tokens."""
    spans = classes.groupBy("g1", "g2").agg(F.min("comp").alias("low"), F.max("comp").alias("high"))
    prefixes = signed.where("n > 0").groupBy("g1", "g2").agg(F.first("prefix").alias("prefix"), F.first("n").alias("n"))
    groups = prefixes.join(spans, ["g1", "g2"])
    mixed = _postings(groups, ["low", "high"], None, False).groupBy("token").agg(F.min("low").alias("low"), F.max("high").alias("high")).where("low <> high").select("token")
    mixed = materialise(mixed, "mixed-tokens")
    few = mixed.count() <= BROADCAST_IDS
    lists = _postings(groups, ["g1", "g2"], mixed, few).join(classes.select("g1", "g2", "rep", "comp", "n"), ["g1", "g2"])
    lists = materialise(lists.select("token", "pos", "rep", "comp", "n"), "lists")
    main = lists.groupBy("token", "comp").agg(F.count(F.lit(1)).alias("held")).groupBy("token").agg(F.max(F.struct("held", "comp")).alias("top"), F.sum("held").alias("rows"))
    main = materialise(main.select("token", F.col("top.comp").alias("main"), "rows", F.expr(f"1 + rows div {LIST_ROWS}").alias("blocks")), "list-heads")
    tagged = join_keys(lists, main, ["token"], "rows")
    # A long list is dealt out in blocks: each row is in one block as y, and meets every block as x.
    x = tagged.where("comp <> main").withColumn("block", F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1))).select("token", "block", *[F.col(c).alias(f"x_{c}") for c in ("pos", "rep", "comp", "n")])
    y = tagged.withColumn("block", F.pmod(F.xxhash64("rep"), F.col("blocks"))).select("token", "block", "main", *[F.col(c).alias(f"y_{c}") for c in ("pos", "rep", "comp", "n")])
    small, large = F.least("x_n", "y_n"), F.greatest("x_n", "y_n")
    small_pos = F.when(F.col("x_n") <= F.col("y_n"), F.col("x_pos")).otherwise(F.col("y_pos"))
    small_pos = F.when(F.col("x_n") == F.col("y_n"), F.least("x_pos", "y_pos")).otherwise(small_pos)
    index = small - F.floor((2 * percent * small + (99 + percent)) / (100 + percent)).cast("long") + 1
    most = 1 + F.least(F.col("x_n") - F.col("x_pos") - 1, F.col("y_n") - F.col("y_pos") - 1)
    pairs = x.join(y, ["token", "block"]).where(
        (F.col("x_comp") != F.col("y_comp"))
        & ((F.col("y_comp") == F.col("main")) | (F.col("x_rep") < F.col("y_rep")))
        & (100 * small >= percent * large)
        & (small_pos < index)
        # 100 * overlap >= percent * union, with the most that can still be shared from this token on
        & ((100 + percent) * most >= percent * (small + large))
    )
    return pairs.select(F.col("x_rep").alias("a"), F.col("y_rep").alias("b")).distinct()


def link_components(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", size: int = SHINGLE, percent: int = PERCENT) -> DataFrame:
    """One row per row of df: id, n_shingles, component_id."""
    return _linked_rows(df, id_col, text_col, size, percent).select("id", "n_shingles", "component_id")


def _linked_rows(df: DataFrame, id_col: str, text_col: str, size: int, percent: int) -> DataFrame:
    """One row per row of df: id, n_shingles, component_id, row, s1, s2."""
    docs = df.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text"))
    signed = materialise(signatures(docs, rarity_sketch(docs, size), size, percent), "signatures")
    classes = signed.where("n > 0 and id is not null").groupBy("s1", "s2").agg(
        F.min("id").alias("rep"), F.count(F.lit(1)).alias("rows"), *[F.first(c).alias(c) for c in ("n", "g1", "g2", "typical", "stars", "parity")]
    )
    classes = materialise(classes, "classes")
    first = components(linked(docs, _possible(_star_pairs(classes), classes, percent), size, percent))
    staged = classes.drop("stars", "typical", "parity").join(first.withColumnRenamed("node", "rep"), "rep", "left").withColumn("comp", F.coalesce("label", "rep")).drop("label")
    staged = materialise(staged, "staged")
    links = linked(docs, _possible(_cross_pairs(signed, staged, percent), classes, percent), size, percent)
    comp = staged.select("rep", "comp")
    ends = links.join(comp.select(F.col("rep").alias("a"), F.col("comp").alias("comp_a")), "a").join(comp.select(F.col("rep").alias("b"), F.col("comp").alias("comp_b")), "b")
    second = components(ends.select("comp_a", "comp_b"), "comp_a", "comp_b").withColumnRenamed("node", "comp")
    named = staged.join(second, "comp", "left").select("s1", "s2", "rows", F.coalesce("label", "comp").alias("component_id"))
    named = materialise(named, "components")
    full = signed.where("n > 0").select("id", F.col("n").alias("n_shingles"), "s1", "s2", "row")
    known = join_keys(full, named, ["s1", "s2"], "rows").select("id", "n_shingles", "component_id", "row", "s1", "s2")
    lost = full.where("id is null").join(named, ["s1", "s2"], "left_anti").select("id", "n_shingles", F.lit(None).cast("long").alias("component_id"), "row", "s1", "s2")
    alone = signed.where("n = 0").select("id", F.lit(0).cast("long").alias("n_shingles"), F.col("id").alias("component_id"), "row", "s1", "s2")
    return known.unionByName(alone).unionByName(lost)


def keep_one(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", size: int = SHINGLE, percent: int = PERCENT) -> DataFrame:
    """df with one row of each component: of the rows whose id names it, the one whose text has shingles and the lowest
    hash. Null-id rows whose set no id has are a component for each set, and without words one for each text."""
    df, names_in = aside(df)
    id_col, text_col = named(id_col, names_in), named(text_col, names_in)
    linked_rows = _linked_rows(df, id_col, text_col, size, percent)
    of = F.when(F.col("component_id").isNotNull(), F.struct("component_id", F.lit(0).cast("long").alias("s1"), F.lit(0).cast("long").alias("s2")))
    of = of.otherwise(F.struct("component_id", F.when(F.col("n_shingles") > 0, F.col("s1")).otherwise(F.col("row")).alias("s1"), "s2"))
    distinct = linked_rows.groupBy("id", "component_id", "row").agg(F.max("n_shingles").alias("n_shingles"), F.max("s1").alias("s1"), F.max("s2").alias("s2"), F.count(F.lit(1)).alias("rows"))
    # A row whose id names the component comes first.
    order = F.struct(F.coalesce(F.col("id") != F.col("component_id"), F.lit(True)).alias("other"), (F.col("n_shingles") == 0).alias("blank"), "row", "id", "rows")
    winners = distinct.groupBy(of.alias("__of")).agg(F.min(order).alias("__w"))
    winners = winners.select(F.col("__w.id").alias("__kept_id"), F.col("__w.row").alias("__kept_row"), F.col("__w.rows").alias("__rows")).distinct()
    winners = materialise(winners, "kept-rows")
    names = df.columns
    keyed = df.withColumn("__row", _row_key(F.col(text_col)))

    def rows_of(keys: DataFrame) -> DataFrame:
        few = keys.count() <= BROADCAST_IDS
        return keyed.join(F.broadcast(keys) if few else keys, (F.col("__row") == F.col("__kept_row")) & F.col(id_col).cast("long").eqNullSafe(F.col("__kept_id")), "left_semi")

    single = rows_of(winners.where("__rows = 1")).select(*names)
    repeated = winners.where("__rows > 1")
    if not repeated.limit(1).count():
        return back(single, names_in)
    # Rows that repeat id and text: one of them, by a hash of the whole row.
    whole = [F.col(f"`{f.name}`") for f in df.schema.fields if "map<" not in f.dataType.simpleString()]
    one = rows_of(repeated).groupBy(F.col(id_col).alias("__id"), "__row").agg(F.min_by(F.struct(*[F.col(f"`{c}`") for c in names]), F.xxhash64(*whole)).alias("__one"))
    return back(single.unionByName(one.select("__one.*")), names_in)
