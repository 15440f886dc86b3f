"""Personal data: base patterns, and terms that disclose whom they are about. DataFrame functions only.

Base spans are the matches of four patterns per whole text. A pattern's matches and the pieces between them come from
the same regular expression, and running lengths give the places in code points. The patterns below are linear on long
runs: a match can start only where a run starts or where the match before has ended, which gives the same matches.

Information-theoretic part: an entity is a base value. Its contexts are the words within CONTEXT_CHARS on both sides.
For a term t and an entity e, the bits about e that t leaves open are -log2 p(e | t), with p(e | t) = occurrences of t in
contexts of e / occurrences of t in the whole corpus. Both are counted over distinct texts, so copies of a document add
nothing to either. Terms with MIN_SUPPORT distinct contexts at least that leave MAX_BITS at most disclose e: they are
spans of kind "term" in the documents that hold e, and sanitise() removes them, while base values are generalised to
their kind.

Defined cases: a null or empty text has no spans. Rows that repeat an id with different texts are judged by their own
text. An empty table gives an empty table. Extra columns are not read.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import aside, back, join_keys, materialise, named

KINDS = ("email", "ip", "card", "phone")
#: The four patterns, each written so that it is linear.
PATTERNS = {
    "email": r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?:\G|(?<![0-9]))[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"[0-9](?:[\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
_IP_OK = r"^(?:0*(?:25[0-5]|2[0-4][0-9]|1[0-9][0-9]|[0-9]{1,2})(?:\.|$)){4}$"
TERM = r"(?<![\p{L}\p{N}])\p{L}[\p{L}\p{N}]{2,}+"
CONTEXT_CHARS, CONTEXT_TERMS = 80, 6
MIN_SUPPORT, MAX_BITS = 3, 1.0
#: Terms or entities of which a broadcast table may consist (under 20 MB).
BROADCAST_ROWS = 100_000
_CHUNK = 512


def _hint(text, kind: str):
    """Whether a text can hold the kind at all."""
    return F.contains(text, F.lit({"email": "@", "ip": ".", "phone": "+"}[kind])) if kind != "card" else F.lit(True)


def _valid(kind: str, value):
    if kind == "email":
        return F.lit(True)
    if kind == "ip":
        return F.when(F.length(value) <= 64, value.rlike(_IP_OK)).otherwise(F.regexp_replace(value, r"(?<![0-9])0+(?=[0-9])", "").rlike(_IP_OK))
    digits = F.regexp_replace(value, r"[^0-9]", "")
    if kind == "phone":
        return F.length(digits).between(9, 15)
    back = F.reverse(digits)

    def luhn(total, i):
        d = F.substring(back, i, F.lit(1)).cast("int") * F.when(i % 2 == 0, 2).otherwise(1)
        return total + F.when(d > 9, d - 9).otherwise(d)

    return F.when(F.length(digits).between(12, 19), F.aggregate(F.sequence(F.lit(1), F.length(digits)), F.lit(0), luhn) % 10 == 0).otherwise(False)


def _places(pieces, matches):
    """array<struct<start, end, value>> of the matches, from the pieces between them. Running lengths are summed in
    chunks, so that very many matches in a text stay cheap."""
    sizes = F.zip_with(F.slice(pieces, F.lit(1), F.size(matches)), matches, lambda p, m: F.struct(F.length(p).alias("gap"), m.alias("value")))
    chunks = F.transform(F.sequence(F.lit(0), F.floor((F.size(matches) - 1) / _CHUNK).cast("int")), lambda i: F.slice(sizes, i * _CHUNK + 1, F.lit(_CHUNK)))
    empty = F.array().cast("array<struct<start:int,end:int,value:string>>")

    def step(acc, x):
        start = acc["at"] + x["gap"]
        end = start + F.length(x["value"])
        return F.struct(end.alias("at"), F.concat(acc["out"], F.array(F.struct(start.alias("start"), end.alias("end"), x["value"].alias("value")))).alias("out"))

    local = F.transform(chunks, lambda c: F.aggregate(c, F.struct(F.lit(0).alias("at"), empty.alias("out")), step))

    def join(acc, c):
        shifted = F.transform(c["out"], lambda s: F.struct((s["start"] + acc["at"]).alias("start"), (s["end"] + acc["at"]).alias("end"), s["value"].alias("value")))
        return F.struct((acc["at"] + c["at"]).alias("at"), F.concat(acc["out"], F.array(shifted)).alias("out"))

    nested = F.array().cast("array<array<struct<start:int,end:int,value:string>>>")
    return F.flatten(F.aggregate(local, F.struct(F.lit(0).alias("at"), nested.alias("out")), join)["out"])


def _matched(df: DataFrame, text: str, kinds=KINDS) -> DataFrame:
    """df with columns __m_<kind> (all matches) and __p_<kind> (pieces between), null where there is no match."""
    for kind in kinds:
        t = F.col(text)
        df = df.withColumn(f"__m_{kind}", F.when(_hint(t, kind), F.regexp_extract_all(t, F.lit(PATTERNS[kind]), F.lit(0))))
    for kind in kinds:
        df = df.withColumn(f"__p_{kind}", F.when(F.size(f"__m_{kind}") > 0, F.split(F.col(text), PATTERNS[kind], -1)))
    return df


def _checks(kind: str):
    return lambda s: _valid(kind, s["value"])


def _as_spans(places, kind: int):
    return F.transform(places, lambda s: F.struct(s["start"].alias("start"), F.lit(kind).alias("kind"), s["end"].alias("end")))


def _generalised(kind: str):
    return lambda v: F.when(_valid(kind, v), f"[{kind.upper()}]").otherwise(v)


def base_spans(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """__id, __hash (of the text), __base: array<struct<start, kind, end>> with the kind's number, in order."""
    docs = _matched(df.select(F.col(id_col).alias("__id"), F.coalesce(F.col(text_col), F.lit("")).alias("__text")), "__text")
    for n, kind in enumerate(KINDS):
        spans = _as_spans(F.filter(_places(F.col(f"__p_{kind}"), F.col(f"__m_{kind}")), _checks(kind)), n)
        docs = docs.withColumn(f"__s_{kind}", F.when(F.col(f"__p_{kind}").isNotNull(), spans))
    none = F.array().cast("array<struct<start:int,kind:int,end:int>>")
    every = F.concat(*[F.coalesce(F.col(f"__s_{k}"), none) for k in KINDS])
    return docs.select("__id", F.xxhash64("__text").alias("__hash"), F.array_sort(every).alias("__base"))


def how_many(spans, kind: int):
    return F.size(F.filter(spans, lambda s: s["kind"] == kind)).cast("long")


def written(spans, kinds: list[str]):
    """kind:start:end of each span, comma-joined."""
    names = F.array(*map(F.lit, kinds))
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", names[s["kind"]], s["start"].cast("string"), s["end"].cast("string"))), ",")


def _entities(df: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """__id, __hash, __entity, __context, __near: one row per valid base match, with the terms around it as often as they occur."""
    docs = _matched(df.select(F.col(id_col).alias("__id"), F.coalesce(F.col(text_col), F.lit("")).alias("__text")).where(F.col("__text") != ""), "__text")
    docs = docs.withColumn("__hash", F.xxhash64("__text"))
    out = None
    for kind in KINDS:
        m, p = F.col(f"__m_{kind}"), F.col(f"__p_{kind}")
        sides = F.zip_with(F.slice(p, F.lit(1), F.size(m)), F.slice(p, F.lit(2), F.size(m)), lambda a, b: F.struct(F.substring(a, -CONTEXT_CHARS, CONTEXT_CHARS).alias("before"), F.substring(b, 1, CONTEXT_CHARS).alias("after")))
        rows = docs.where(p.isNotNull()).select("__id", "__hash", F.explode(F.arrays_zip(m.alias("value"), sides.alias("side"))).alias("__x"))
        own = rows.select("__id", "__hash", F.col("__x").getField("value").alias("__value"), F.col("__x").getField("side").alias("__side")).where(_valid(kind, F.col("__value")))
        own = own.select("__id", "__hash", F.concat(F.lit(f"{kind}:"), F.lower("__value")).alias("__entity"), F.lower("__side.before").alias("__before"), F.lower("__side.after").alias("__after"))
        out = own if out is None else out.unionByName(own)
    before, after = F.regexp_extract_all("__before", F.lit(TERM), F.lit(0)), F.regexp_extract_all("__after", F.lit(TERM), F.lit(0))
    return out.select("__id", "__hash", "__entity", F.xxhash64("__before", "__after").alias("__context"), F.concat(F.slice(F.reverse(before), F.lit(1), F.lit(CONTEXT_TERMS)), F.slice(after, F.lit(1), F.lit(CONTEXT_TERMS))).alias("__near"))


def _copies(df: DataFrame, text_col: str) -> DataFrame:
    """__hash, __copies of the texts that more than one row holds."""
    own = df.select(F.xxhash64(F.coalesce(F.col(text_col), F.lit(""))).alias("__hash")).groupBy("__hash").agg(F.count(F.lit(1)).alias("__copies"))
    return materialise(own.where("__copies > 1"), "pii-copies")


def _with_copies(texts: DataFrame, copies: DataFrame) -> DataFrame:
    """__text, __copies: how many rows hold the same text."""
    hashed = texts.withColumn("__hash", F.xxhash64(F.coalesce("__text", F.lit(""))))
    if copies.count() <= BROADCAST_ROWS:
        return hashed.join(F.broadcast(copies), "__hash", "left").select("__text", F.coalesce("__copies", F.lit(1)).alias("__copies"))
    single = hashed.join(copies, "__hash", "left_anti").select("__text", F.lit(1).cast("long").alias("__copies"))
    return single.unionByName(join_keys(hashed, copies, ["__hash"], "__copies").select("__text", "__copies"))


def disclosing_terms(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_support: int = MIN_SUPPORT, max_bits: float = MAX_BITS) -> DataFrame:
    """__entity, __term, __bits: terms that leave max_bits at most open about an entity."""
    copies = _copies(df, text_col)
    matches = _entities(df, id_col, text_col).groupBy("__hash", "__entity", "__context").agg(F.first("__near").alias("__near"), F.count(F.lit(1)).alias("__rows"))
    # Every copy has the same matches and words, so the rows of a text are a whole multiple of its copies.
    seen = matches.join(F.broadcast(copies) if copies.count() <= BROADCAST_ROWS else copies, "__hash", "left").withColumn("__seen", F.expr("__rows div coalesce(__copies, 1)"))
    contexts = seen.groupBy("__entity", "__context").agg(F.first("__near").alias("__near"), F.sum("__seen").alias("__seen"))
    times = F.transform(F.array_distinct("__near"), lambda t: F.struct(t.alias("term"), F.size(F.filter("__near", lambda x: x == t)).alias("times")))
    near = contexts.select("__entity", "__seen", F.explode(times).alias("__t")).select("__entity", F.col("__t.term").alias("__term"), (F.col("__seen") * F.col("__t.times")).alias("__n"))
    together = near.groupBy("__entity", "__term").agg(F.count(F.lit(1)).alias("__support"), F.sum("__n").alias("__both")).where(F.col("__support") >= min_support).drop("__support")
    together = materialise(together, "pii-pairs")
    terms = materialise(together.select("__term").distinct(), "pii-terms")
    n = terms.count()
    if not n:
        return together.select("__entity", "__term", F.lit(0.0).alias("__bits"))
    texts = _with_copies(df.select(F.col(text_col).alias("__text")), copies)
    words = texts.select("__copies", F.explode(F.regexp_extract_all(F.lower("__text"), F.lit(TERM), F.lit(0))).alias("__term"))
    counts = words.join(F.broadcast(terms) if n <= BROADCAST_ROWS else terms, "__term", "left_semi").groupBy("__term", "__copies").agg(F.count(F.lit(1)).alias("__rows"))
    counts = counts.groupBy("__term").agg(F.sum(F.expr("__rows div __copies")).alias("__all"))
    bits = -F.log2(F.least(F.lit(1.0), F.col("__both") / F.col("__all")))
    return materialise(together.join(counts, "__term").select("__entity", "__term", bits.alias("__bits")).where(F.col("__bits") <= max_bits), "pii-disclosing")


def _terms_of(df: DataFrame, disclosing: DataFrame, id_col: str, text_col: str) -> DataFrame | None:
    """__id, __hash, __terms: what each document's own entities let disclose; null if nothing discloses anything."""
    by_entity = materialise(disclosing.groupBy("__entity").agg(F.collect_set("__term").alias("__terms")), "pii-by-entity")
    n = by_entity.count()
    if not n:
        return None
    held = _entities(df, id_col, text_col).select("__id", "__hash", "__entity").distinct()
    return held.join(F.broadcast(by_entity) if n <= BROADCAST_ROWS else by_entity, "__entity").groupBy("__id", "__hash").agg(F.array_distinct(F.flatten(F.collect_list("__terms"))).alias("__terms"))


def find(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_support: int = MIN_SUPPORT, max_bits: float = MAX_BITS) -> DataFrame:
    """__id, __base and __all (base and term spans, kind 4 being the terms) of every row."""
    base = base_spans(df, id_col, text_col)
    marked = _terms_of(df, disclosing_terms(df, id_col, text_col, min_support, max_bits), id_col, text_col)
    if marked is None:
        return base.select("__id", "__base", F.col("__base").alias("__all"))
    text = F.coalesce(F.col(text_col), F.lit(""))
    rows = df.select(F.col(id_col).alias("__id"), text.alias("__text"), F.xxhash64(text).alias("__hash"))
    marked = materialise(marked, "pii-documents").withColumnRenamed("__id", "__of")
    few = marked.count() <= BROADCAST_ROWS
    rows = rows.join(F.broadcast(marked) if few else marked, F.col("__id").eqNullSafe(F.col("__of")) & (rows["__hash"] == marked["__hash"])).select("__id", rows["__hash"], "__text", "__terms").distinct()
    rows = rows.withColumn("__m", F.regexp_extract_all("__text", F.lit(TERM), F.lit(0))).where(F.size("__m") > 0).withColumn("__p", F.split("__text", TERM, -1))
    found = F.filter(_places(F.col("__p"), F.col("__m")), lambda s: F.array_contains(F.col("__terms"), F.lower(s["value"])))
    spans = rows.select(F.col("__id").alias("__of"), F.col("__hash").alias("__of_hash"), _as_spans(found, len(KINDS)).alias("__spans"))
    joined = base.join(spans, F.col("__id").eqNullSafe(F.col("__of")) & (F.col("__hash") == F.col("__of_hash")), "left")
    none = F.array().cast("array<struct<start:int,kind:int,end:int>>")
    return joined.select("__id", "__base", F.array_sort(F.concat("__base", F.coalesce("__spans", none))).alias("__all"))


def sanitise(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_support: int = MIN_SUPPORT, max_bits: float = MAX_BITS) -> DataFrame:
    """df with the text cleaned: base values become their kind in brackets, disclosing terms go."""
    df, names = aside(df)
    id_col, text_col = named(id_col, names), named(text_col, names)
    marked = _terms_of(df, disclosing_terms(df, id_col, text_col, min_support, max_bits), id_col, text_col)
    text = F.coalesce(F.col(text_col), F.lit(""))
    out = df.withColumn("__clean", text).withColumn("__own", F.xxhash64(text))
    for kind in KINDS:
        out = _matched(out, "__clean", (kind,))
        ends = F.zip_with(F.col(f"__p_{kind}"), F.concat(F.transform(F.col(f"__m_{kind}"), _generalised(kind)), F.array(F.lit(""))), lambda a, b: F.concat(a, b))
        out = out.withColumn("__clean", F.when(F.col(f"__p_{kind}").isNull(), F.col("__clean")).otherwise(F.array_join(ends, ""))).drop(f"__m_{kind}", f"__p_{kind}")
    if marked is not None:
        out = out.join(marked, F.col(id_col).eqNullSafe(F.col("__id")) & (F.col("__own") == F.col("__hash")), "left")
        m, p = F.regexp_extract_all("__clean", F.lit(TERM), F.lit(0)), F.split("__clean", TERM, -1)
        ends = F.zip_with(p, F.concat(F.transform(m, lambda v: F.when(F.array_contains("__terms", F.lower(v)), "").otherwise(v)), F.array(F.lit(""))), lambda a, b: F.concat(a, b))
        out = out.withColumn("__clean", F.when(F.col("__terms").isNull(), F.col("__clean")).otherwise(F.array_join(ends, "")))
    return back(out.select(*[F.col("__clean").alias(c) if c == text_col else F.col(f"`{c}`") for c in df.columns]), names)
