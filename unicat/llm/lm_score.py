"""Cross-entropy difference: a target and a background n-gram model over one vocabulary score each document.

Bigrams of words. Both models are counted over whole tables: the background over all documents, the target over the
documents that are marked as such. The vocabulary is every word with MIN_WORD occurrences in all documents; the others are
one unknown word. Bigrams with fewer than MIN_BIGRAM occurrences in all documents back off; as a bigram has no more
occurrences than its words, no bigram with an unknown word is kept. Unigrams have add-one smoothing, bigrams Dirichlet
smoothing towards them:

    p(w | v) = (c(v, w) + MU p(w)) / (c(v) + MU)

The target's counts are matched to the background's by its own totals. The score is the mean loss per token under the
target less that under the background: the lower, the closer to the target.

There is one plan for every size, and no table of n-grams is ever held by the driver or broadcast:

1. Documents are read once and gathered in chunks of about CHUNK_TOKENS words (one document at least), which are written
   with their words as places in a list of the chunk's own distinct words.
2. Each chunk's distinct words and bigrams, with their counts in it, are dealt out by the top bits of 64-bit hashes: one
   row of packed arrays for each chunk and bucket. A hot word or bigram is one entry a chunk, so no bucket gets more of it.
3. A bucket sums the counts of its keys and answers each chunk with the totals in the chunk's own order.
4. A chunk's answers meet its words again, which gives the losses of its documents.

Counts are integers all the way. Memory in a worker is a chunk's or a bucket's arrays; the number of buckets follows the tokens.

Defined cases: a null or blank text has no tokens and null losses and score. Without any target document both models are
the background and all scores 0. Rows that repeat an id are scored by themselves; for the target each row counts whose id
is marked. An empty table gives an empty table. Extra columns are not read.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import materialise, trim

MIN_WORD, MIN_BIGRAM = 2, 2
MU = 50.0
#: Words of a chunk (about 60 bytes each while a worker has it), and of which a bucket of keys is made.
CHUNK_TOKENS, BUCKET_TOKENS = 1_000_000, 1_500_000
#: Target ids that are broadcast (16 bytes each); more are joined.
BROADCAST_IDS = 1_000_000
WORDS, BIGRAMS = 0, 1
_MIX = np.uint64(0x9E3779B97F4A7C15)
_START = np.uint64(0x5851F42D4C957F2D)


class WordPlaces(dict):
    """The place of each distinct word in the order in which words first occur."""

    def __missing__(self, word: bytes) -> int:
        i = self[word] = len(self)
        return i


def words_of(text: str | None) -> list[bytes]:
    """Words end at ASCII white space; A-Z are lower-cased."""
    return text.encode().lower().split() if text else []


def bigram_keys(keys: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """A key for each word with the one before it; where a document starts, the start is before it."""
    before = np.empty(len(keys), np.uint64)
    before[1:] = keys[:-1]
    before[starts] = _START
    h = (before ^ (before >> np.uint64(31))) * _MIX + keys
    return (h ^ (h >> np.uint64(29))) * _MIX


class Packer:
    """Arrays of whole numbers as compressed byte planes of the narrowest width that holds them."""

    def __init__(self):
        import zstandard

        self.compress, self.expand = zstandard.ZstdCompressor(level=1).compress, zstandard.ZstdDecompressor().decompress

    def pack(self, a: np.ndarray) -> bytes:
        top = int(a.max()) if len(a) else 0
        width = next(w for w in (1, 2, 4, 8) if top < 1 << (8 * w))
        planes = a.astype(f"<u{width}").view(np.uint8).reshape(-1, width).T
        return bytes([width]) + self.compress(planes.tobytes())

    def unpack(self, raw) -> np.ndarray:
        raw = memoryview(raw)
        planes = np.frombuffer(self.expand(raw[1:]), np.uint8).reshape(raw[0], -1)
        return np.ascontiguousarray(planes.T).reshape(-1).view(f"<u{raw[0]}").astype(np.uint64)


def grouped(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Sorted distinct keys, the place of each key among them, and one place where each occurs."""
    order = np.argsort(keys)
    ordered = keys[order]
    first = np.ones(len(keys), bool)
    first[1:] = ordered[1:] != ordered[:-1]
    inverse = np.empty(len(keys), np.int64)
    inverse[order] = np.cumsum(first) - 1
    return ordered[first], inverse, order[first]


def _chunks(rows: DataFrame, chunk_tokens: int) -> DataFrame:
    """chunk, ids, n, and packed: sizes of documents, marks, words' places, and keys of the distinct words."""
    schema = T.StructType(
        [T.StructField("chunk", T.LongType()), T.StructField("ids", T.ArrayType(rows.schema["id"].dataType)), T.StructField("n", T.LongType())]
        + [T.StructField(x, T.BinaryType()) for x in ("sizes", "marks", "at", "words")]
    )
    id_type = T.ArrayType(rows.schema["id"].dataType)

    def run(batches):
        import xxhash
        from pyspark import TaskContext
        from pyspark.sql.pandas.types import to_arrow_type

        base, packer, made = TaskContext.get().partitionId() << 32, Packer(), 0
        places, ids, sizes, marks, at, held = WordPlaces(), [], [], [], [], 0

        def flush():
            words = np.fromiter(map(xxhash.xxh64_intdigest, places), np.uint64, len(places))
            blobs = [packer.pack(np.array(x)) for x in (sizes, marks)] + [packer.pack(np.concatenate(at)), packer.pack(words)]
            return pa.RecordBatch.from_arrays([pa.array([base + made]), pa.array([ids], to_arrow_type(id_type)), pa.array([held]), *(pa.array([x], pa.binary()) for x in blobs)], schema.names)

        for b in batches:
            for i, x, m in zip(b.column(0).to_pylist(), b.column(1), b.column(2).to_pylist(), strict=True):
                own = words_of(x.as_py())
                ids.append(i)
                sizes.append(len(own))
                marks.append(int(bool(m)))
                at.append(np.fromiter(map(places.__getitem__, own), np.uint32, len(own)))
                held += len(own)
                if held >= chunk_tokens:
                    yield flush()
                    made, held = made + 1, 0
                    places, ids, sizes, marks, at = WordPlaces(), [], [], [], []
        if ids:
            yield flush()
        del places, at
        trim()

    return rows.select("id", "text", "mark").mapInArrow(run, schema)


def _whole(keys_in: np.ndarray, at: np.ndarray, sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Keys of the tokens, and where documents with words start."""
    return keys_in[at], (np.cumsum(sizes) - sizes)[sizes > 0]


def _parts(chunks: DataFrame, bits: int) -> DataFrame:
    """chunk, bucket, and packed: sorted keys, counts in all documents of the chunk, and in marked ones."""

    def run(batches):
        packer = Packer()
        for b in batches:
            for row in b.to_pylist():
                sizes, marks, at, words = (packer.unpack(row[x]) for x in ("sizes", "marks", "at", "words"))
                sizes, at = sizes.astype(np.int64), at.astype(np.int64)
                marked = np.repeat(marks.astype(bool), sizes)
                tokens, starts = _whole(words, at, sizes)
                order = np.argsort(words)
                counts = [np.bincount(x, minlength=len(words))[order] for x in (at, at[marked])]
                pairs, inverse, _ = grouped(bigram_keys(tokens, starts))
                sets = ((WORDS, words[order], *counts), (BIGRAMS, pairs, np.bincount(inverse, minlength=len(pairs)), np.bincount(inverse[marked], minlength=len(pairs))))
                for kind, keys, n, t in sets:
                    bucket = (keys >> np.uint64(64 - bits)).astype(np.int64)
                    cuts = np.flatnonzero(np.diff(bucket, prepend=-1))
                    out = [(row["chunk"], kind << 40 | int(bucket[lo]), packer.pack(keys[lo:hi]), packer.pack(n[lo:hi]), packer.pack(t[lo:hi])) for lo, hi in zip(cuts, [*cuts[1:], len(keys)], strict=True)]
                    if out:
                        cols = list(zip(*out, strict=True))
                        yield pa.RecordBatch.from_arrays([pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.int64()), *(pa.array(c, pa.binary()) for c in cols[2:])], ["chunk", "bucket", "keys", "n", "t"])
        trim()

    return chunks.select("chunk", "sizes", "marks", "at", "words").mapInArrow(run, "chunk long, bucket long, keys binary, n binary, t binary")


def add_up(keys: list[np.ndarray], n: list[np.ndarray], t: list[np.ndarray], least: int):
    """(totals n and t for each part's keys, 0 under the least; kept keys, all n, all t, n and t that are not kept)."""
    sizes = np.cumsum([len(k) for k in keys])[:-1]
    u, inverse, _ = grouped(np.concatenate(keys))
    total = []
    for parts in (n, t):
        x = np.zeros(len(u), np.int64)
        np.add.at(x, inverse, np.concatenate(parts).astype(np.int64))
        total.append(x)
    kept = total[0] >= least
    stats = [int(kept.sum()), *(int(x.sum()) for x in total), *(int(x[~kept].sum()) for x in total)]
    back = [np.split(np.where(kept, x, 0)[inverse], sizes) for x in total]
    return back, stats


def _totals(parts: DataFrame, tasks: int) -> DataFrame:
    """chunk, bucket, and packed totals in the order of the chunk's keys; for chunk -1, stats of the bucket."""

    def run(table: pa.Table) -> pa.Table:
        packer, bucket = Packer(), table.column("bucket")[0].as_py()
        order = np.argsort(table.column("chunk").to_numpy(), kind="stable")
        cols = [[packer.unpack(table.column(c)[i].as_buffer()) for i in order] for c in ("keys", "n", "t")]
        (n, t), stats = add_up(*cols, MIN_WORD if bucket >> 40 == WORDS else MIN_BIGRAM)
        chunks = [*table.column("chunk").to_numpy()[order].tolist(), -1]
        blobs = [[packer.pack(x) for x in col] for col in (n, t)]
        return pa.table({"chunk": pa.array(chunks, pa.int64()), "bucket": pa.array([bucket] * len(chunks), pa.int64()), "n": pa.array([*blobs[0], b""], pa.binary()), "t": pa.array([*blobs[1], b""], pa.binary()), "stats": pa.array([None] * len(blobs[0]) + [stats], pa.list_(pa.int64()))})

    return parts.repartition(tasks, "bucket").groupBy("bucket").applyInArrow(run, "chunk long, bucket long, n binary, t binary, stats array<long>")


def _losses(sizes, at, words, totals, facts) -> tuple[np.ndarray, np.ndarray]:
    """Target loss and background loss of each document of a chunk. totals: (n, t) of the sorted words, then of the sorted bigrams."""
    n_all, n_target, unk_all, unk_target, size = facts
    tokens, starts = _whole(words, at, sizes)
    order, out = np.argsort(words), []
    _, inverse, some = grouped(bigram_keys(tokens, starts))
    doc = np.repeat(np.arange(len(sizes)), sizes)
    for which, (all_of, unk) in ((1, (n_target, unk_target)), (0, (n_all, unk_all))):
        which = which if n_target else 0
        all_of, unk = (all_of, unk) if n_target else (n_all, unk_all)
        known = np.zeros(len(words), bool)
        count = np.zeros(len(words))
        known[order] = totals[WORDS][0] > 0
        count[order] = totals[WORDS][which]
        count = np.where(known, count, unk)
        context = np.log(count + MU)
        own = np.log(totals[BIGRAMS][which] + MU * (count[at[some]] + 1) / (all_of + size))
        before = np.empty(len(at))
        before[1:] = context[at[:-1]]
        before[starts] = np.log(MU)
        out.append(np.bincount(doc, before - own[inverse], len(sizes)))
    return out[0], out[1]


def score(docs: DataFrame, target_ids: DataFrame, id_col: str = "doc_id", text_col: str = "text", chunk_tokens: int = CHUNK_TOKENS, bucket_tokens: int = BUCKET_TOKENS) -> DataFrame:
    """id, n_tokens, target_loss, background_loss, score of every row; losses in nats per token. target_ids: the ids of target documents (column id_col)."""
    marks = target_ids.select(F.col(id_col).alias("__t")).where("__t is not null").distinct()
    marks = materialise(marks.withColumn("mark", F.lit(True)), "lm-marks")
    plain = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))
    few = marks.count() <= BROADCAST_IDS
    rows = plain.join(F.broadcast(marks) if few else marks, F.col("id") == F.col("__t"), "left").select("id", "text", "mark")
    chunks = materialise(_chunks(rows, chunk_tokens), "lm-chunks")
    n_chunks, tokens = chunks.agg(F.count(F.lit(1)), F.coalesce(F.sum("n"), F.lit(0))).first()
    bits = max(5, int(tokens // bucket_tokens).bit_length())
    totals = materialise(_totals(_parts(chunks, bits), min(1 << 16, 2 << bits)), "lm-totals")
    # Five numbers a kind; their sums are all that comes to the driver.
    sums = {r.kind: r for r in totals.where("chunk = -1").groupBy(F.shiftright("bucket", 40).cast("int").alias("kind")).agg(*[F.sum(F.col("stats")[i]).alias(c) for i, c in enumerate(("kept", "n", "t", "unk_n", "unk_t"))]).collect()}
    w = sums.get(WORDS)
    facts = (w.n, w.t, w.unk_n, w.unk_t, w.kept + 1) if w else (0, 0, 0, 0, 1)
    none = F.lit(None).cast("binary")
    both = chunks.select("chunk", F.lit(-1).cast("long").alias("bucket"), "ids", "sizes", "at", "words", none.alias("a"), none.alias("b")).unionByName(
        totals.where("chunk >= 0").select("chunk", "bucket", F.lit(None).cast(chunks.schema["ids"].dataType).alias("ids"), *[none.alias(c) for c in ("sizes", "at", "words")], F.col("n").alias("a"), F.col("t").alias("b"))
    )
    out = T.StructType([T.StructField("id", plain.schema["id"].dataType), T.StructField("n_tokens", T.LongType()), T.StructField("loss_t", T.DoubleType()), T.StructField("loss_b", T.DoubleType())])

    def apply(table: pa.Table) -> pa.Table:
        packer, bucket = Packer(), table.column("bucket").to_numpy()
        order = np.argsort(bucket)
        own = int(order[0])
        sizes, at, words = (packer.unpack(table.column(c)[own].as_buffer()) for c in ("sizes", "at", "words"))
        found = []
        for kind in (WORDS, BIGRAMS):
            use = [i for i in order[1:].tolist() if bucket[i] >> 40 == kind]
            found.append([np.concatenate([packer.unpack(table.column(c)[i].as_buffer()) for i in use] or [np.zeros(0, np.uint64)]).astype(float) for c in ("a", "b")])
        loss = _losses(sizes.astype(np.int64), at.astype(np.int64), words, found, facts)
        ids = table.column("ids")[own].values
        return pa.table({"id": ids, "n_tokens": pa.array(sizes.astype(np.int64)), "loss_t": pa.array(loss[0]), "loss_b": pa.array(loss[1])})

    losses = both.repartition(int(max(1, min(1 << 16, n_chunks))), "chunk").groupBy("chunk").applyInArrow(apply, out)
    n = F.when(F.col("n_tokens") > 0, F.col("n_tokens"))
    return losses.select("id", "n_tokens", (F.col("loss_t") / n).alias("target_loss"), (F.col("loss_b") / n).alias("background_loss"), ((F.col("loss_t") - F.col("loss_b")) / n).alias("score"))
