"""URL filter: a blocked Bloom filter of listed canonical URLs passes possible hits to an exact hash join.

An entry is a host and a path prefix, written host + path ("example.org/es/"). It fits a URL whose host is the entry's
or a subdomain of it and whose path starts with the entry's. So a URL has one key for each suffix of its host and each
prefix of its path whose length occurs in the list; a key that passes the filter goes to the join with the entries,
which removes false positives. Entries are of two kinds: rules, matched on the path as it stands, and listed URLs, whose
own canonical form and the URL's have "/" for an empty path. Among rules, and among listed URLs, the longest that fits
wins (then the longer host); a rule outranks listed URLs; without either the default verdict stands.

The filter has blocks of eight 32-bit words, one bit in each. It has at most MAX_BLOCKS blocks (16 MB) whatever the
length of the list: a longer list only passes more false positives, and the join still decides. Entries are repeated
SALTS times in the join, so that a key of very many URLs is dealt over as many tasks.

Defined cases: a null URL, or one without "://", has an empty host and path and fits nothing. An empty host fits no
entry. Repeated rows stay; repeated entries count once, and of equal keys with different verdicts "block" wins. Empty
tables and empty lists work. Extra columns pass through; one named like a column that is added comes out as in__...
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import aside, back, named

MAX_BLOCKS = 1 << 19
BITS_PER_ENTRY = 20
SALTS = 8
RULE, LISTED = "R", "L"
#: The multipliers that choose the bit in each word of a block: any odd numbers do.
_SALT = np.array([(0x9E3779B1 * (2 * i + 1)) & 0xFFFFFFFF | 1 for i in range(8)], np.uint32)


def lower_host(host: str) -> str:
    return host.lower() if host.isascii() else "".join(c.lower() if "A" <= c <= "Z" else c for c in host)


def split_url(url: str | None) -> tuple[str, str]:
    """(host, path): the host after the first "://" with A-Z lower-cased, the path up to "?" or "#"."""
    if url is None or (at := url.find("://")) < 0:
        return "", ""
    rest = url[at + 3 :]
    end = min((i for i in map(rest.find, "?#") if i >= 0), default=len(rest))
    cut = rest.find("/", 0, end)
    cut = end if cut < 0 else cut
    return lower_host(rest[:cut]), rest[cut:end]


def url_keys(host: str, path: str, lengths: dict[str, list[int]]) -> list[str]:
    """The keys under which a URL can be listed."""
    if not host:
        return []
    parts = host.split(".")
    hosts = [".".join(parts[i:]) for i in range(len(parts))]
    paths = [(kind, p[:n]) for kind, p in ((RULE, path), (LISTED, path or "/")) for n in lengths.get(kind, ()) if n <= len(p)]
    return [f"{kind}{h}{p}" for h in hosts if h for kind, p in paths]


def _hashes(keys: list[str]) -> np.ndarray:
    import xxhash

    return np.fromiter((xxhash.xxh64_intdigest(k) for k in keys), np.uint64, len(keys))


def _places(h: np.ndarray, blocks: int) -> tuple[np.ndarray, np.ndarray]:
    """The block of each hash and the eight masks in it."""
    block = ((h >> np.uint64(32)) % np.uint64(blocks)).astype(np.int64)
    low = (h & np.uint64(0xFFFFFFFF)).astype(np.uint32)
    with np.errstate(over="ignore"):
        bits = (low[:, None] * _SALT[None, :]) >> np.uint32(27)
    return block, np.uint32(1) << bits


def build_filter(entries: DataFrame) -> np.ndarray:
    """The filter of a table with a column key, as an array of blocks by eight words."""
    blocks = int(min(MAX_BLOCKS, max(1, entries.count() * BITS_PER_ENTRY // 256 + 1)))

    def bits(batches):
        for b in batches:
            block, mask = _places(_hashes(b.column(0).to_pylist()), blocks)
            yield pa.RecordBatch.from_arrays([pa.array(block), *(pa.array(mask[:, i].view(np.int32)) for i in range(8))], ["block", *(f"w{i}" for i in range(8))])

    words = [f"w{i}" for i in range(8)]
    rows = entries.select("key").mapInArrow(bits, "block long, " + ", ".join(f"{w} int" for w in words)).groupBy("block").agg(*[F.bit_or(w).alias(w) for w in words]).collect()
    out = np.zeros((blocks, 8), np.uint32)
    for block, *w in rows:
        out[block] = np.array(w, np.int32).view(np.uint32)
    return out


def passes(filled: np.ndarray, keys: list[str]) -> np.ndarray:
    if not keys:
        return np.zeros(0, bool)
    block, mask = _places(_hashes(keys), len(filled))
    return ((filled[block] & mask) == mask).all(axis=1)


def entry_table(rules: DataFrame, listed: DataFrame) -> DataFrame:
    """One list of (kind, entry, verdict, key) from rules (entry, verdict) and listed URLs (url or host + path)."""
    split = F.split(F.regexp_replace("url", r"^[^/]*://", ""), r"[?#]").getItem(0)
    host, path = F.regexp_extract(split, r"^([^/]*)", 1), F.regexp_extract(split, r"^[^/]*(.*)$", 1)
    canonical = F.concat(F.translate(host, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"), F.when(path == "", "/").otherwise(path))
    both = rules.select(F.lit(RULE).alias("kind"), "entry", "verdict").unionByName(listed.select(F.lit(LISTED).alias("kind"), canonical.alias("entry"), F.lit("block").alias("verdict")))
    return both.where(F.col("entry").isNotNull()).groupBy("kind", "entry").agg(F.max("verdict").alias("verdict")).withColumn("key", F.concat("kind", "entry"))


def judge(df: DataFrame, entries: DataFrame, url_col: str = "url", default: str = "allow") -> DataFrame:
    """df with __host, __path, __rule (the rule's entry, else null), __listed (the listed entry, else null), __verdict."""
    df, names_in = aside(df)
    url_col = named(url_col, names_in)
    path_length = F.length(F.regexp_extract("entry", r"^[^/]*(.*)$", 1))
    lengths: dict[str, list[int]] = {}
    for kind, n in entries.select("kind", path_length.alias("n")).distinct().sort("kind", "n").collect():  # as many as path lengths
        lengths.setdefault(kind, []).append(n)
    held = df.sparkSession.sparkContext.broadcast(build_filter(entries))
    added = T._parse_datatype_string("__row long, __host string, __path string, __hits array<string>")
    base = df.withColumn("__row", F.monotonically_increasing_id())
    names = base.columns

    def probe(batches):
        filled = held.value
        for b in batches:
            urls = [split_url(u) for u in b.column(b.schema.get_field_index(url_col)).to_pylist()]
            keys = [url_keys(h, p, lengths) for h, p in urls]
            good = passes(filled, [k for own in keys for k in own]).tolist()
            hits, at = [], 0
            for own in keys:
                hits.append([k for k, g in zip(own, good[at : at + len(own)], strict=True) if g])
                at += len(own)
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array([h for h, _ in urls], pa.string()), pa.array([p for _, p in urls], pa.string()), pa.array(hits, pa.list_(pa.string()))], [*names, *added.names[1:]])

    probed = base.mapInArrow(probe, T.StructType([*base.schema, *added.fields[1:]]))
    kept = [*df.columns, "__host", "__path"]
    hits = probed.select("__row", F.struct(*[F.col(f"`{c}`") for c in kept]).alias("__own"), F.explode_outer("__hits").alias("__key"))
    # A URL without a hit meets nothing, so any salt does: its row number spreads such rows over all tasks.
    hits = hits.withColumn("__salt", F.when(F.col("__key").isNull(), F.col("__row")).otherwise(F.pmod("__row", F.lit(SALTS))))
    exact = entries.select(F.col("key").alias("__key"), F.col("kind").alias("__kind"), F.col("entry").alias("__entry"), F.col("verdict").alias("__v"), F.explode(F.array(*[F.lit(i).cast("long") for i in range(SALTS)])).alias("__salt"))
    host_length = F.length("__entry") - F.length(F.regexp_extract("__entry", r"^[^/]*(.*)$", 1))
    rank = F.struct(F.length("__entry").alias("n"), host_length.alias("h"), F.col("__entry").alias("entry"), F.col("__v").alias("verdict"))
    best = [F.max(F.when(F.col("__kind") == k, rank)).alias(n) for k, n in ((RULE, "__r"), (LISTED, "__l"))]
    found = hits.join(exact, ["__key", "__salt"], "left").groupBy("__row").agg(F.first("__own").alias("__own"), *best)
    out = found.select(
        *[F.col(f"__own.`{c}`").alias(c) for c in kept],
        F.col("__r.entry").alias("__rule"),
        F.col("__l.entry").alias("__listed"),
        F.coalesce("__r.verdict", "__l.verdict", F.lit(default)).alias("__verdict"),
    )
    return back(out, names_in)
