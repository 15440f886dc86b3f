"""Lexical retrieval packing: sequences filled with a seed document and its best unused neighbours under BM25.

1. Every text is encoded once; ids fit in 16 bits and are kept that way in a table of the shared folder.
2. Document frequencies of all token ids over all documents (as many numbers as the vocabulary has) give BM25's weights.
3. The index is sharded. A document's shard is its weighted min-hash, two tokens drawn with more weight on late ids (which
   the vocabulary gave to rare tokens), so lexically close documents tend to share it. A shard holds about SHARD_TOKENS
   tokens; larger ones are split by a hash of the id, so copies or a large source never fill one task.
4. In a shard, the lowest unused document is the seed. All its distinct tokens query the shard; the unused documents
   with the best scores fill the window, as many as it takes, and unrelated ones only when none with a score is left. The last one is cut at the end of the window, and what is left of it
   seeds the next, so every sequence but a shard's last is full. The rest of a shard is cut into powers of two, which
   need no padding.

Defined cases: a null or empty text is its end-of-document id alone. Equal scores go by the lower position, which is by
id and then hash of the ids. Repeated rows are documents of their own. A null id is packed like others. An empty table
gives an empty table.
"""

from __future__ import annotations

import functools
import os
import unicodedata
import zlib

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import materialise, trim

WINDOW = 2048
END_ID = 1
SHARD_TOKENS = 1_500_000
#: Bytes of texts that are encoded at a time.
BATCH_BYTES = 4_000_000
#: Neighbours that are ranked at first; the next ones follow when these are used up.
RANK_FIRST = 64
K1, B = 1.2, 0.75
PIECES = "long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"


class ChunkIds:
    """Ids of white-space-free chunks, remembered up to a bound. The tokenizer drops white space and no token crosses it,
    so the ids of a text are those of its chunks in order.

    A-Z are lower-cased first, as the tokenizer does anyway. A token ends where letters do, so texts are cut between a letter of
    a-z and a mark too, and a word with other closing marks has the word's ids and the marks'. New words are encoded many
    at a time, as a token that ends a word says so; lower-case Latin ones need no normalising. What is not all letters is
    encoded by itself. Many texts are cut, and their ids put together, as arrays: only their distinct chunks are looked up one by one."""

    #: Chunks of a generation. The one before it is kept too, so that what is used again and again is never learnt anew.
    BOUND = 400_000
    MARKS = ".,!?;:#*$%&|<>()[]{}=+~_/\\\"@^`-"

    def __init__(self, path: str, bound: int = BOUND):
        self.bound = bound
        os.environ["TOKENIZERS_PARALLELISM"] = "false"  # a task has one core
        from tokenizers import Tokenizer, pre_tokenizers

        self.one = Tokenizer.from_file(path)
        self.bare = Tokenizer(self.one.model)  # shares the vocabulary
        self.bare.pre_tokenizer = pre_tokenizers.WhitespaceSplit()
        # The tokenizer's letters for bytes: those that can't be printed have the code points from 256 on, in order.
        unseen = [b for b in range(256) if not (33 <= b <= 126 or 161 <= b <= 172 or b >= 174)]
        self.letters = np.arange(256, dtype=np.uint16)
        self.letters[unseen] = 256 + np.arange(len(unseen))
        self.letters[32] = 32
        self.is_letter, self.is_mark = np.zeros(256, bool), np.zeros(256, bool)
        self.is_letter[np.frombuffer(b"abcdefghijklmnopqrstuvwxyz", np.uint8)] = True
        self.is_mark[np.frombuffer(b".,!?;:", np.uint8)] = True  # none that a special token has
        self.known: dict[bytes, bytes] = {}
        self.older: dict[bytes, bytes] = {}
        self.ends = np.zeros(1 << 16, bool)
        for token, i in self.one.get_vocab(with_added_tokens=False).items():
            self.ends[i] = token.endswith("</w>")

    def split(self, texts: pa.Array) -> pa.ListArray:
        """The chunks of each text; some are empty."""
        lower = pc.ascii_lower(texts)
        # A special token's string is one only in lower case, so such texts keep their case.
        special = pc.match_substring(texts, "<|")
        if pc.any(special).as_py():
            lower = pc.if_else(special, texts, lower)
        lower = pa.concat_arrays([lower])
        ends = np.frombuffer(lower.buffers()[1], np.int32)[lower.offset : lower.offset + len(lower) + 1]
        raw = np.frombuffer(lower.buffers()[2], np.uint8)[ends[0] : ends[-1]] if ends[-1] > ends[0] else np.zeros(0, np.uint8)
        ends = ends - ends[0]
        cut = np.flatnonzero(self.is_letter[raw[:-1]] & self.is_mark[raw[1:]]) + 1
        raw, ends = np.insert(raw, cut, 32), (ends + np.searchsorted(cut, ends)).astype(np.int32)
        return pc.ascii_split_whitespace(pa.StringArray.from_buffers(len(texts), pa.py_buffer(ends), pa.py_buffer(raw)))

    def _many(self, encoder, words: list[str]) -> list[str]:
        """Learns words that are one token run each; returns those that turn out not to be."""
        groups, left = [words[i : i + 1000] for i in range(0, len(words), 1000)], []
        as_text = self._in_letters if encoder is self.bare else str
        for group, got in zip(groups, encoder.encode_batch_fast([as_text(" ".join(g)) for g in groups], add_special_tokens=False), strict=True):
            ids = np.array(got.ids, np.uint16)
            stop = np.flatnonzero(self.ends[ids]) + 1
            if len(stop) != len(group):
                left += group
                continue
            raw, stop = ids.tobytes(), (2 * stop).tolist()
            self.known.update((w.encode(), raw[a:e]) for w, a, e in zip(group, [0, *stop[:-1]], stop, strict=True))
        return left

    def _in_letters(self, text: str) -> str:
        """The text's bytes as the letters that the vocabulary is written in, but for spaces."""
        return text if text.isascii() else self.letters[np.frombuffer(text.encode(), np.uint8)].astype("<u2").tobytes().decode("utf-16-le")

    def learn(self, chunks: set[bytes]) -> None:
        """Makes the ids of all these chunks known."""
        if len(self.known) + len(chunks) > self.bound:
            self.older, self.known = self.known, {}
        known, older, marked, basic, letters, odd = self.known, self.older, [], set(), set(), set()
        new = chunks.difference(known)
        again = new.intersection(older)
        known.update(zip(again, map(older.__getitem__, again), strict=True))
        for raw in new.difference(again):
            if raw.isalpha() and raw.islower():
                basic.add(raw.decode())
                continue
            c = raw.decode()
            # Below U+0250 nothing is composed or taken apart.
            if c.isalpha() and max(c) < "\u0250" and c == c.lower():
                basic.add(c)
                continue
            word = c.rstrip(self.MARKS)
            # Letters that neither normalising nor lower-casing takes apart
            if not (word.isalpha() and (word.isascii() or (unicodedata.is_normalized("NFC", word) and word.lower().isalpha()))):
                odd.add(c)
                continue
            if len(word) < len(c):
                marks = c[len(word) :]
                marked.append((raw, word.encode(), marks.encode()))
                if marks.encode() not in known:
                    odd.add(marks)
                if word.encode() in known:
                    continue
            (basic if word.isascii() and word.islower() else letters).add(word)
        odd.update(self._many(self.bare, list(basic)))
        odd.update(self._many(self.one, list(letters)))
        odd = list(odd)
        for c, got in zip(odd, self.one.encode_batch_fast(odd, add_special_tokens=False), strict=True):
            known[c.encode()] = np.array(got.ids, np.uint16).tobytes()
        known.update((raw, known[word] + known[marks]) for raw, word, marks in marked)

    def encode(self, texts: list[str]) -> list[bytes]:
        return self.encode_array(pa.array(texts, pa.string()), [])[0].to_pylist()

    def encode_array(self, texts: pa.Array, tail: list[int]) -> tuple[pa.Array, np.ndarray, np.ndarray]:
        """The ids of texts without nulls, with those of tail behind each, as 16-bit numbers: one binary value a text, and all ids with
        the places where texts begin and end."""
        chunks = self.split(texts)
        coded = chunks.flatten().dictionary_encode()
        names = _as_bytes(coded.dictionary)
        got = list(map(self.known.get, names))
        missing = [i for i, x in enumerate(got) if x is None]
        if missing:
            self.learn({names[i] for i in missing})
            for i in missing:
                got[i] = self.known[names[i]]
        got.append(np.array(tail, np.uint16).tobytes())
        own = np.frombuffer(b"".join(got), np.uint16)
        size = np.fromiter(map(len, got), np.int64, len(got)) // 2
        first = np.cumsum(size) - size
        ends = chunks.offsets.to_numpy().astype(np.int64)
        at = np.insert(coded.indices.to_numpy().astype(np.int64), ends[1:] - ends[0], len(names))
        n = size[at]
        stop = np.cumsum(n)
        ids = own[np.repeat(first[at] - (stop - n), n) + np.arange(stop[-1] if len(stop) else 0)]
        place = np.append(0, stop)[ends - ends[0] + np.arange(len(ends))]
        return pa.Array.from_buffers(pa.binary(), len(texts), [None, pa.py_buffer((2 * place).astype(np.int32)), pa.py_buffer(ids)]), ids, place


def _as_bytes(strings: pa.Array) -> list[bytes]:
    """As to_pylist() would give, several times as fast."""
    if not len(strings):
        return []
    ends = np.frombuffer(strings.buffers()[1], np.int32)[strings.offset : strings.offset + len(strings) + 1].tolist()
    raw = strings.buffers()[2].to_pybytes() if ends[-1] else b""
    return [raw[a:e] for a, e in zip(ends[:-1], ends[1:], strict=True)]


@functools.lru_cache(1)
def chunk_ids(path: str, bound: int = ChunkIds.BOUND) -> ChunkIds:
    """One for each worker process, kept with its chunks from task to task until forget()."""
    return ChunkIds(path, bound)


def forget() -> None:
    """Frees what a worker has learnt: workers outlive the encoding, and other operators' tasks come to them next."""
    if chunk_ids.cache_info().currsize:
        chunk_ids.cache_clear()
        trim()


def encode(docs: DataFrame, path: str, id_col: str, text_col: str, end_id: int = END_ID, bound: int = ChunkIds.BOUND) -> DataFrame:
    """id, n (ids with the end id), ids (16-bit, little-endian), route (the weighted min-hash). A row with n < 0 for each task has, in ids, how many of
    the task's documents hold each token: pairs of 64-bit numbers, and its documents and tokens under -1 and -2."""

    def run(batches):
        memo = chunk_ids(path, bound)
        rng = np.random.default_rng(7)
        cost = (-np.log(rng.random(1 << 16)) / np.log2(np.arange(1 << 16) + 2.0) ** 4).astype(np.float32)
        name = rng.integers(0, 1 << 62, 1 << 16)
        df, rows, tokens = np.zeros(1 << 16, np.int64), 0, 0
        for b in batches:
            texts = pc.fill_null(b.column(1), "")
            far = np.cumsum(pc.binary_length(texts).to_numpy(zero_copy_only=False).astype(np.int64))
            at = 0
            while at < b.num_rows:
                begin, at = at, max(at + 1, int(np.searchsorted(far, (far[at - 1] if at else 0) + BATCH_BYTES)))
                ids, flat, place = memo.encode_array(texts.slice(begin, at - begin), [end_id])
                route = []
                for k in range(len(ids)):
                    one = flat[place[k] : place[k + 1]]
                    df[one] += 1  # a repeated index counts once
                    own = cost[one]
                    best = one[own.argmin()]
                    own[one == best] = np.inf
                    route.append(int(name[best] ^ (name[one[own.argmin()]] >> 1)))
                rows, tokens = rows + len(ids), tokens + len(flat)
                yield pa.RecordBatch.from_arrays([b.column(0).slice(begin, len(ids)), pa.array(np.diff(place), pa.int64()), ids, pa.array(route, pa.int64())], names)
        held = np.flatnonzero(df)
        pairs = np.column_stack([np.append(held, [-1, -2]), np.append(df[held], [rows, tokens])]).astype(np.int64)
        yield pa.RecordBatch.from_arrays([pa.array([None], pa.int64()), pa.array([-1], pa.int64()), pa.array([pairs.tobytes()], pa.binary()), pa.array([0], pa.int64())], names)
        trim()

    names = ["id", "n", "ids", "route"]
    return docs.select(F.col(id_col).cast("long"), text_col).mapInArrow(run, "id long, n long, ids binary, route long")


def frequencies(encoded: DataFrame) -> tuple[np.ndarray, int, int]:
    """Documents that hold each id, documents, and tokens, over the whole table; at most 65,536 numbers."""

    def spread(batches):
        for b in batches:
            for x in b.column(0):
                pairs = np.frombuffer(x.as_buffer(), np.int64).reshape(-1, 2)
                yield pa.RecordBatch.from_arrays([pa.array(pairs[:, 0].copy()), pa.array(pairs[:, 1].copy())], ["token", "docs"])

    df, rows, tokens = np.zeros(1 << 16, np.int64), 0, 0
    for token, n in encoded.where("n < 0").select("ids").mapInArrow(spread, "token long, docs long").groupBy("token").agg(F.sum("docs")).collect():
        if token == -1:
            rows = n
        elif token == -2:
            tokens = n
        else:
            df[token] = n
    return df, rows, tokens


def pack_shard(ids: list[np.ndarray], idf: np.ndarray, mean_length: float, window: int = WINDOW):
    """(document, start, length, sequence, offset) of every piece, greedily, for the documents of one shard."""
    n = len(ids)
    length = np.array([len(x) for x in ids], np.int64)
    # Term frequencies of the whole shard at once: keys are document and token.
    keys, tf = np.unique(np.repeat(np.arange(n) << 16, length) | np.concatenate(ids), return_counts=True)
    owner, term = keys >> 16, keys & 0xFFFF
    weight = idf[term] * tf * (K1 + 1) / (tf + K1 * (1 - B + B * length[owner] / mean_length))
    begin = np.flatnonzero(np.diff(owner, prepend=-1))
    # Terms by their place among the shard's own, so that what a query looks up stays small.
    own_terms, term = np.unique(term, return_inverse=True)
    place = np.zeros(1 << 16, np.int64)
    place[own_terms] = np.arange(len(own_terms))
    holder, wanted, weight, room_for = owner[begin], np.zeros(len(own_terms), np.float32), weight.astype(np.float32), np.empty(len(term), np.float32)
    unused, score = np.ones(n, bool), np.zeros(n, np.float32)
    pieces, doc, start, sequence, room, low = [], -1, 0, 0, window, 0
    ranked: list[int] = []
    step, more = RANK_FIRST, False

    def best() -> list[int]:
        """The next unused neighbours, the best one last."""
        found = np.flatnonzero((score > 0) & unused)
        if len(found) > step:
            # All that tie with the last one are ranked too, so that equal scores go by position.
            found = found[score[found] >= -np.partition(-score[found], step - 1)[step - 1]]
        return found[np.lexsort((-found, score[found]))].tolist()

    while True:
        if doc < 0:
            while ranked and not unused[ranked[-1]]:
                ranked.pop()
            if not ranked and more:
                step *= 4
                ranked = best()
                more = bool(ranked)
            if ranked:
                doc = ranked.pop()
            else:
                while low < n and not unused[low]:
                    low += 1
                if low == n:
                    break
                doc = low
            start, unused[doc] = 0, False
        if room == window:  # the document that opens a sequence is its seed
            if 4 * unused[holder].sum() < 3 * len(holder):  # used documents leave the index
                keep = unused[owner]
                owner, term, weight = owner[keep], term[keep], weight[keep]
                begin = np.flatnonzero(np.diff(owner, prepend=-1))
                holder, room_for = owner[begin], np.empty(len(term), np.float32)
            score[:] = 0
            wanted[:] = 0
            wanted[place[ids[doc]]] = 1
            if len(begin):
                np.take(wanted, term, out=room_for, mode="clip")
                np.multiply(room_for, weight, out=room_for)
                score[holder] = np.add.reduceat(room_for, begin)
            step, more = RANK_FIRST, True
            ranked = best()
        take = min(room, length[doc] - start)
        pieces.append((doc, start, take, sequence, window - room))
        start, room = start + take, room - take
        if start == length[doc]:
            doc = -1
        if not room:
            sequence, room = sequence + 1, window
    return _cut_rest(pieces, sequence, window)


def _cut_rest(pieces, sequence: int, window: int):
    """Cuts the last, unfilled sequence into powers of two, largest first."""
    full = [p for p in pieces if p[3] < sequence]
    rest = [(d, s, take) for d, s, take, q, _ in pieces if q == sequence]
    total = sum(take for _, _, take in rest)
    sizes = [1 << k for k in range(window.bit_length() - 1, -1, -1) if total >> k & 1]
    at = 0
    for d, s, take in rest:
        while take:
            part = min(take, sizes[0] - at)
            full.append((d, s, part, sequence, at))
            s, take, at = s + part, take - part, at + part
            if at == sizes[0]:
                sizes.pop(0)
                sequence, at = sequence + 1, 0
    return full


def pack(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text", window: int = WINDOW, shard_tokens: int = SHARD_TOKENS, end_id: int = END_ID, with_ids: bool = True, bound: int = ChunkIds.BOUND) -> DataFrame:
    """One row per piece: id, start, length, ids_crc32, doc_tokens, sequence_id, offset and, unless with_ids=False, ids (16-bit).
    bound: chunks that a worker remembers; fewer take less memory and more time."""
    encoded = materialise(encode(docs, path, id_col, text_col, end_id, bound), "ids")
    df, rows, tokens = frequencies(encoded)
    idf = np.log1p((rows - df + 0.5) / (df + 0.5))
    mean_length = tokens / max(1, rows)
    buckets = max(1, tokens // shard_tokens)
    routed = encoded.where("n >= 0").withColumn("bucket", F.pmod("route", F.lit(buckets)))
    sizes = materialise(routed.groupBy("bucket").agg(F.sum("n").alias("tokens")), "buckets")
    base = 1 << 20
    shards = sizes.select("bucket", F.ceil(F.col("tokens") / F.lit(2 * shard_tokens)).cast("long").alias("parts"))
    # A split bucket's rows meet one row of this table, which is as small as the number of shards.
    dealt = routed.join(shards, "bucket").select("id", "n", "ids", (F.col("bucket") * base + F.pmod(F.xxhash64("id", "ids"), "parts")).alias("shard"))
    held = docs.sparkSession.sparkContext.broadcast(idf)
    tasks = int(max(1, min(1 << 16, 2 * tokens // shard_tokens)))

    def run(table: pa.Table) -> pa.Table:
        forget()
        order = sorted(range(table.num_rows), key=lambda i: (k if (k := keys[i]) is not None else -(1 << 63), crcs[i])) if (keys := table.column("id").to_pylist()) and (crcs := [zlib.crc32(x.as_buffer()) for x in table.column("ids")]) else []
        raw = [np.frombuffer(table.column("ids")[i].as_buffer(), np.uint16) for i in order]
        pieces = pack_shard(raw, held.value, mean_length, window)
        shard = table.column("shard")[0].as_py()
        cut = [raw[d][s : s + take] for d, s, take, _, _ in pieces]
        out = pa.table(
            {
                "id": pa.array([keys[order[p[0]]] for p in pieces], pa.int64()),
                "start": pa.array([p[1] for p in pieces], pa.int64()),
                "length": pa.array([p[2] for p in pieces], pa.int64()),
                "ids_crc32": pa.array([zlib.crc32(x.astype("<u4").tobytes()) for x in cut], pa.int64()),
                "doc_tokens": pa.array([len(raw[p[0]]) for p in pieces], pa.int64()),
                "sequence_id": pa.array([(shard << 21) + p[3] for p in pieces], pa.int64()),
                "offset": pa.array([p[4] for p in pieces], pa.int64()),
            }
        )
        return out.append_column("ids", pa.array([x.astype("<u2").tobytes() for x in cut], pa.binary())) if with_ids else out

    schema = T._parse_datatype_string(f"id {PIECES}" + ", ids binary" * with_ids)
    return dealt.repartition(tasks, "shard").groupBy("shard").applyInArrow(run, schema)
