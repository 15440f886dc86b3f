"""The sparse similarity graph: divergences of response distributions, edge probabilities, pruning, draws, components.

With p = (r + eps) / Z, Z = sum(r) + eps * D, the symmetric divergence of two items needs only the words they share and
two numbers for each item:

    cross(s, t) = ln(eps / Z_t) + eps / Z_s * A_t + 1 / Z_s * sum over shared words of r_s * ln(1 + r_t / eps)
    J(s, t) = cross(s, s) + cross(t, t) - cross(s, t) - cross(t, s),   A_t = sum of ln(1 + r_t / eps)

so pairs come from products of blocks of items, kept as one row a block, and no row is made for a pair and word. Each task
meets its blocks in a Cartesian product, which reads both sides from the shared folder and shuffles nothing. nearest_items()
keeps the best edges of each item there, so the pairs themselves are never written. Where even all pairs are too many,
pair_divergences() takes the pairs that candidate_pairs() finds instead.
"""

from __future__ import annotations

import contextlib
import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from ..rng import u01
from ..sources.tables import keep

#: Items and rows of responses in a block, and words that are multiplied at a time: what a task holds of two blocks.
BLOCK_ITEMS, BLOCK_ROWS, BLOCK_WORDS = 2048, 2_000_000, 2048
#: Tasks a core in which blocks meet, at most.
TASKS = 16
#: Edge probabilities have so many places.
PLACES = 9
#: A setting of the session: rows that Python workers get at a time.
_BATCH = "spark.sql.execution.arrow.maxRecordsPerBatch"
#: Bytes of dense blocks that a task keeps between products, and the share of two blocks' pairs beyond which they are all compared in
#: double precision.
DENSE_BYTES, MANY = 150_000_000, 1 / 32


def item_scalars(resp: DataFrame, dims: int, eps: float = 1e-2) -> DataFrame:
    """item_id, z, a, h (= cross of the item with itself)."""
    log = F.log(1 + F.col("r") / eps)
    g = resp.groupBy("item_id").agg((F.sum("r") + eps * dims).alias("z"), F.sum(log).alias("a"), F.sum(F.col("r") * log).alias("own"))
    return g.select("item_id", "z", "a", (F.log(eps / F.col("z")) + eps / F.col("z") * F.col("a") + F.col("own") / F.col("z")).alias("h"))


def item_blocks(resp: DataFrame, dims: int, eps: float = 1e-2) -> DataFrame:
    """block and, as bytes, ids (ascending), z, a, h (as item_scalars), starts, feats and rs of its items: every item is in one block."""
    resp = resp.select("item_id", "feat", "r")
    size = resp.agg(F.count(F.lit(1)).alias("rows"), F.count_distinct("item_id").alias("items")).first()
    blocks = max(1, -(-size["items"] // BLOCK_ITEMS), -(-size["rows"] // BLOCK_ROWS))

    def run(table: pa.Table) -> pa.Table:
        item, feat, r = (table.column(c).to_numpy() for c in ("item_id", "feat", "r"))
        order = np.lexsort((feat, item))
        item, feat, r = item[order], feat[order].astype(np.int64), r[order].astype(float)
        ids, start = np.unique(item, return_index=True)
        log = np.log(1 + r / eps)
        z, a = np.add.reduceat(r, start) + eps * dims, np.add.reduceat(log, start)
        h = np.log(eps / z) + eps / z * a + np.add.reduceat(r * log, start) / z
        cells = [ids, z, a, h, np.append(start, len(item)).astype(np.int64), feat, r]
        return pa.table([table.column("block")[:1].combine_chunks(), *[pa.array([x.tobytes()], pa.binary()) for x in cells]], names=["block", *_CELLS])

    routed = resp.select(F.pmod(F.xxhash64("item_id"), F.lit(blocks)).alias("block"), F.col("item_id").cast("long"), F.col("feat").cast("long"), F.col("r").cast("double"))
    return keep(routed.groupBy("block").applyInArrow(run, "block long, " + ", ".join(f"{c} binary" for c in _CELLS)), "item-blocks")


_CELLS = ("ids", "z", "a", "h", "starts", "feats", "rs")


def _met(blocks: DataFrame) -> DataFrame:
    """Every block with itself and with every other one, once, so that each has about as many on either side.

    Either side has so many partitions that their product makes some tasks a core, however finely the files are split."""
    blocks = blocks.coalesce(math.ceil(math.sqrt(TASKS * blocks.sparkSession.sparkContext.defaultParallelism)))
    x, y = (blocks.select(*[F.col(c).alias(f"{side}_{c}") for c in blocks.columns]) for side in "xy")
    d = F.col("x_block") - F.col("y_block")
    once = (d == 0) | ((d < 0) & (d % 2 != 0)) | ((d > 0) & (d % 2 == 0))
    return x.hint("shuffle_replicate_nl").join(y, once)


def _side(batch, i: int, prefix: str) -> tuple:
    """block, and the arrays of _CELLS."""
    kinds = (np.int64, float, float, float, np.int64, np.int64, float)
    cells = [np.frombuffer(batch.column(prefix + c)[i].as_buffer(), kind) for c, kind in zip(_CELLS, kinds, strict=True)]
    return batch.column(f"{prefix}block")[i].as_py(), *cells


def _read_blocks(batches, eps: float):
    """The blocks that meet, with what _compared() gives of them."""
    for b in batches:
        for i in range(b.num_rows):
            x, y = _side(b, i, "x_"), _side(b, i, "y_")
            yield (x[0], y[0]), (x[1], y[1]), *_compared(x, y, eps), x[0] == y[0]


def _compared(x: tuple, y: tuple, eps: float) -> tuple[np.ndarray, np.ndarray]:
    """j of two blocks' items, and whether they share a word; x's items are the rows."""

    def spread(of, words, at, values):
        """A row for each item, a column for each word."""
        _, ids, _, _, _, starts, feats, _ = of
        row = np.repeat(np.arange(len(ids)), np.diff(starts))
        col = np.searchsorted(words, feats)
        hit = np.flatnonzero(words[np.minimum(col, len(words) - 1)] == feats)
        at[row[hit], col[hit]] = values[hit]

    (_, ids, z, a, h, starts, feats, r), (_, ids_y, z_y, a_y, h_y, starts_y, feats_y, r_y) = x, y
    log, log_y = np.log(1 + r / eps), np.log(1 + r_y / eps)
    part, part_y = r / np.repeat(z, np.diff(starts)), r_y / np.repeat(z_y, np.diff(starts_y))
    plain = len(r) > 0 and len(r_y) > 0 and r.min() > 0 and r_y.min() > 0
    common = np.intersect1d(feats, feats_y)
    total = np.zeros((len(ids), len(ids_y)))
    shared = None if plain else np.zeros(total.shape, bool)
    for k in range(0, len(common), BLOCK_WORDS):
        words = common[k : k + BLOCK_WORDS]
        u, v = np.zeros((len(ids), 2 * len(words))), np.zeros((len(ids_y), 2 * len(words)))
        spread(x, words, u[:, : len(words)], part)
        spread(x, words, u[:, len(words) :], log)
        spread(y, words, v[:, : len(words)], log_y)
        spread(y, words, v[:, len(words) :], part_y)
        total += u @ v.T
        if not plain:  # responses of zero are words too
            u, v = np.zeros((len(ids), len(words)), np.float32), np.zeros((len(ids_y), len(words)), np.float32)
            spread(x, words, u, np.ones(len(feats), np.float32))
            spread(y, words, v, np.ones(len(feats_y), np.float32))
            shared |= u @ v.T > 0
    if plain:
        shared = total > 0
    np.negative(total, out=total)
    total += (h - np.log(eps / z))[:, None]
    total += (h_y - np.log(eps / z_y))[None, :]
    total -= (eps / z)[:, None] * a_y[None, :]
    total -= a[:, None] * (eps / z_y)[None, :]
    np.maximum(total, 0, out=total)
    return total, shared


class _Dense:
    """A block as dense arrays: minus j of two blocks' items is one product of single-precision factors, off by at most
    error(), and exact() gives j of single pairs as _compared() does."""

    @staticmethod
    def fits(side: tuple, dims: int) -> bool:
        _, ids, _, _, _, _, feats, r = side
        return dims <= BLOCK_WORDS and len(ids) > 0 and feats.min() >= 0 and feats.max() < dims and r.min() > 0

    def __init__(self, side: tuple, dims: int, eps: float):
        _, self.ids, z, self.a, h, starts, feats, r = side
        self.e, self.c, self.dims = eps / z, h - np.log(eps / z), dims
        row = np.repeat(np.arange(len(self.ids)), np.diff(starts))
        self.p, self.log = np.zeros((len(self.ids), dims)), np.zeros((len(self.ids), dims))
        self.p[row, feats], self.log[row, feats] = r / z[row], np.log(1 + r / eps)
        one = np.ones(len(z))
        self.u = np.hstack([self.p, self.log, np.stack([self.e, self.a, -self.c, one], 1)]).astype(np.float32)
        self.v = np.hstack([self.log, self.p, np.stack([self.a, self.e, one, -self.c], 1)]).astype(np.float32)
        self.bytes = self.p.nbytes + self.log.nbytes + self.u.nbytes + self.v.nbytes

    def error(self, other: _Dense) -> float:
        """Of a sum of so many rounded products, by the sum of their sizes: shares sum to one at most."""
        most = self.log.max() + other.log.max() + self.e.max() * other.a.max() + self.a.max() * other.e.max() + np.abs(self.c).max() + np.abs(other.c).max()
        return float(most * (2 * self.dims + 16) * 2.0**-24)

    def exact(self, other: _Dense, row: np.ndarray, col: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """j of the pairs, and whether they share a word."""
        j, shared = np.zeros(len(row)), np.zeros(len(row), bool)
        for k in range(0, len(row), 4096):
            s, t = row[k : k + 4096], col[k : k + 4096]
            cross = np.einsum("ij,ij->i", self.p[s], other.log[t]) + np.einsum("ij,ij->i", self.log[s], other.p[t])
            shared[k : k + 4096] = cross > 0
            j[k : k + 4096] = self.c[s] + other.c[t] - self.e[s] * other.a[t] - self.a[s] * other.e[t] - cross
        return np.maximum(j, 0), shared


def symmetric_kl(resp: DataFrame, dims: int, eps: float = 1e-2, mode: str = "full", most_items: int | None = None, blocks: DataFrame | None = None, places: int | None = None) -> DataFrame:
    """s, t (s < t), j for every pair of items that share a word. mode half gives half the sum of both directions; places
    rounds j. blocks: the item_blocks() of resp, if they are at hand.

    most_items: words in more items make no pairs of their own, which bounds the join at scale; their terms are then
    left out of j only for pairs that share nothing else."""
    if most_items is not None:
        return _symmetric_kl_by_join(resp, dims, eps, mode, most_items)
    factor = 0.5 if mode == "half" else 1.0

    def value(j, shared):
        j = j * factor
        return (j if places is None else np.floor(j * 10**places + 0.5) / 10**places), shared

    return _every(item_blocks(resp, dims, eps) if blocks is None else blocks, eps, value, "j")


def all_edges(resp: DataFrame, dims: int, tau: float = 0.2, q_min: float = 1e-3, eps: float = 1e-2, blocks: DataFrame | None = None, places: int = PLACES, cap: float = 1 - 1e-9) -> DataFrame:
    """s, t, q: the edges_of() all pairs that share a word; places of q."""

    def value(j, shared):
        q = np.minimum(cap, np.floor(np.exp(-tau * j) * 10**places + 0.5) / 10**places)
        return q, shared & (q >= q_min)

    return _every(item_blocks(resp, dims, eps) if blocks is None else blocks, eps, value, "q")


def _every(blocks: DataFrame, eps: float, value, name: str) -> DataFrame:
    """s, t and a number of every pair: value takes j and shared, and returns the numbers and which pairs stay."""

    def run(batches):
        for _, (ids, ids_y), j, shared, same in _read_blocks(batches, eps):
            v, kept = value(j, shared)
            if same:
                kept = np.triu(kept, 1)
            step = max(1, 200_000 // max(1, len(ids_y)))
            for k in range(0, len(ids), step):
                row, col = np.nonzero(kept[k : k + step])
                s, t = ids[k + row], ids_y[col]
                yield pa.RecordBatch.from_arrays([pa.array(np.minimum(s, t)), pa.array(np.maximum(s, t)), pa.array(v[k + row, col])], ["s", "t", name])

    return _met(blocks).mapInArrow(run, f"s long, t long, {name} double")


def nearest_items(resp: DataFrame, dims: int, tau: float = 0.2, q_min: float = 1e-3, k: int = 6, mode: str = "union", eps: float = 1e-2, blocks: DataFrame | None = None, cap: float = 1 - 1e-9) -> DataFrame:
    """nearest() of the edges_of() all pairs that share a word, exactly: each task keeps the k best edges of its items by what
    it has met, which are all that can be among their k best.

    Single-precision products find the pairs that may be among the k best of an end, by the k best that it has within its own
    block and in its task so far; their probabilities come from double precision."""
    unit, none = 10**PLACES, max(0, math.floor(q_min * 10**PLACES))
    single = tau > 0

    def best(j, shared):
        """For each row, its k best columns as numbers: probability first, then the lower column; -1 is none."""
        q = np.minimum(cap, np.floor(np.exp(-tau * j) * unit + 0.5) / unit)
        key = (np.rint(q * unit).astype(np.int64) << 20) | (len(j[0]) - 1 - np.arange(len(j[0])))
        key[~shared | (q < q_min)] = -1
        return key

    def farthest(low):
        """The greatest j that gives a probability of low or more in units."""
        with np.errstate(divide="ignore"):
            return -np.log(np.maximum(0, low - 0.5) / unit) / tau + 1e-9

    def floors(batches):
        """The blocks, with the lowest probability in units that an edge among the k best of each item can have, by its own block."""
        for b in batches:
            out = []
            for i in range(b.num_rows):
                side = _side(b, i, "")
                low = np.full(len(side[1]), none, np.int64)
                if single and len(low) > k and _Dense.fits(side, dims):
                    x = _Dense(side, dims, eps)
                    near = x.u[:, : 2 * dims] @ x.v[:, : 2 * dims].T
                    apart = near <= 0
                    near += x.u[:, 2 * dims :] @ x.v[:, 2 * dims :].T
                    near[apart] = -np.inf
                    np.fill_diagonal(near, -np.inf)
                    j = np.maximum(0, x.error(x) - np.partition(near, len(low) - k, axis=1)[:, len(low) - k].astype(float))
                    low = np.maximum(low, np.minimum(np.floor(np.exp(-tau * j) * unit + 0.5), math.floor(cap * unit + 0.5)).astype(np.int64))
                out.append(low.tobytes())
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(out, pa.binary())], [*b.schema.names, "floors"])

    def run(batches):
        held, dense = {}, {}

        def top(block, ids, low):
            if block not in held:
                held[block] = ids, np.full((len(ids), k), -1, np.int64), np.zeros((len(ids), k), np.int64), low.copy()
            return held[block]

        def add(to, others, key):
            """The best of two whole blocks."""
            _, q0, o0, low = to
            n = min(k, key.shape[1])
            best_ = np.partition(key, key.shape[1] - n, axis=1)[:, key.shape[1] - n :]
            q, o = np.where(best_ < 0, -1, best_ >> 20), others[len(others) - 1 - (best_ & 0xFFFFF).clip(max=len(others) - 1)]
            q, o = np.hstack([q0, q]), np.hstack([o0, o])
            order = np.lexsort((o, -q), axis=1)[:, :k]
            q0[:], o0[:] = np.take_along_axis(q, order, 1), np.take_along_axis(o, order, 1)
            np.maximum(low, q0[:, -1], out=low)

        def put(to, row, q, o):
            """Single edges."""
            _, q0, o0, low = to
            rows = np.unique(row)
            at = np.concatenate([np.repeat(rows, k), row])
            q, o = np.concatenate([q0[rows].ravel(), q]), np.concatenate([o0[rows].ravel(), o])
            order = np.lexsort((o, -q, at))
            first = np.searchsorted(at[order], rows)[:, None] + np.arange(k)
            q0[rows], o0[rows] = q[order][first], o[order][first]
            low[rows] = np.maximum(low[rows], q0[rows, -1])

        def as_dense(side):
            if side[0] not in dense:
                while dense and sum(d.bytes for d in dense.values()) > DENSE_BYTES:
                    dense.pop(next(iter(dense)))
                dense[side[0]] = _Dense(side, dims, eps)
            return dense[side[0]]

        def few(x, y, to, to_y, same):
            """Puts the edges that may be among the best; false if they are too many."""
            u, v = as_dense(x), as_dense(y)
            near = u.u @ v.v.T
            off = u.error(v)
            reach, reach_y = (np.nextafter((-farthest(t[3]) - off).astype(np.float32), np.float32(-np.inf)) for t in (to, to_y))
            found = near >= reach[:, None]
            if not same:
                found |= near >= reach_y[None, :]
            at = np.flatnonzero(found)
            if len(at) > MANY * found.size + 64 * k:
                return False
            row, col = np.divmod(at, found.shape[1])
            if same:
                row, col = row[row != col], col[row != col]
            j, shared = u.exact(v, row, col)
            q = np.minimum(cap, np.floor(np.exp(-tau * j) * unit + 0.5) / unit)
            keep_ = shared & (q >= q_min)
            row, col, q = row[keep_], col[keep_], np.rint(q[keep_] * unit).astype(np.int64)
            for t, own, other, ids in ((to, row, col, y[1]), *(() if same else ((to_y, col, row, x[1]),))):
                good = q >= t[3][own]
                if good.any():
                    put(t, own[good], q[good], ids[other[good]])
            return True

        for b in batches:
            for i in range(b.num_rows):
                x, y = _side(b, i, "x_"), _side(b, i, "y_")
                same = x[0] == y[0]
                to, to_y = (top(s[0], s[1], np.frombuffer(b.column(f"{name}_floors")[i].as_buffer(), np.int64)) for s, name in ((x, "x"), (y, "y")))
                if single and _Dense.fits(x, dims) and _Dense.fits(y, dims) and few(x, y, to, to_y, same):
                    continue
                j, shared = _compared(x, y, eps)
                if same:
                    np.fill_diagonal(shared, False)
                add(to, y[1], best(j, shared))
                if not same:
                    add(to_y, x[1], best(np.ascontiguousarray(j.T), shared.T))
        for ids, q, o, _ in held.values():
            row, col = np.nonzero(q >= 0)
            yield pa.RecordBatch.from_arrays([pa.array(ids[row]), pa.array(o[row, col]), pa.array(np.minimum(cap, q[row, col] / unit))], ["v", "o", "q"])

    blocks = item_blocks(resp, dims, eps) if blocks is None else blocks
    started = keep(blocks.mapInArrow(floors, "block long, " + ", ".join(f"{c} binary" for c in (*_CELLS, "floors"))), "block-floors")
    with _few_rows(blocks.sparkSession):
        best = keep(_best(_met(started).mapInArrow(run, "v long, o long, q double"), k), "best-ends")
    return _votes(best, mode)


@contextlib.contextmanager
def _few_rows(spark, rows: int = 2):
    """Python workers get few rows at a time, as a row holds two whole blocks."""
    before = spark.conf.get(_BATCH)
    spark.conf.set(_BATCH, str(rows))
    try:
        yield
    finally:
        spark.conf.set(_BATCH, before)


def _symmetric_kl_by_join(resp: DataFrame, dims: int, eps: float, mode: str, most_items: int | None) -> DataFrame:
    """The same by an equi-join on words, one row for each pair and word."""
    scalars = item_scalars(resp, dims, eps)
    rows = resp.select("item_id", "feat", "r")
    seeds = rows
    if most_items is not None:
        rare = resp.groupBy("feat").agg(F.count(F.lit(1)).alias("d")).where(F.col("d") <= most_items).select("feat")
        seeds = rows.join(F.broadcast(rare), "feat", "left_semi")
    a = rows.select("feat", F.col("item_id").alias("s"), F.col("r").alias("r_s"))
    b = rows.select("feat", F.col("item_id").alias("t"), F.col("r").alias("r_t"))
    both = a.join(b, "feat").where("s < t")
    if most_items is not None:
        x, y = seeds.select("feat", F.col("item_id").alias("s")), seeds.select("feat", F.col("item_id").alias("t"))
        both = both.join(x.join(y, "feat").where("s < t").select("s", "t").distinct(), ["s", "t"], "left_semi")
    shared = both.groupBy("s", "t").agg(F.sum(F.col("r_s") * F.log(1 + F.col("r_t") / eps)).alias("st"), F.sum(F.col("r_t") * F.log(1 + F.col("r_s") / eps)).alias("ts"))
    left = scalars.select(F.col("item_id").alias("s"), F.col("z").alias("z_s"), F.col("a").alias("a_s"), F.col("h").alias("h_s"))
    right = scalars.select(F.col("item_id").alias("t"), F.col("z").alias("z_t"), F.col("a").alias("a_t"), F.col("h").alias("h_t"))
    cross_st = F.log(eps / F.col("z_t")) + eps / F.col("z_s") * F.col("a_t") + F.col("st") / F.col("z_s")
    cross_ts = F.log(eps / F.col("z_s")) + eps / F.col("z_t") * F.col("a_s") + F.col("ts") / F.col("z_t")
    j = F.greatest(F.lit(0.0), F.col("h_s") + F.col("h_t") - cross_st - cross_ts) * (0.5 if mode == "half" else 1.0)
    return shared.join(left, "s").join(right, "t").select("s", "t", j.alias("j"))


def symmetric_kl_dense(resp: DataFrame, dims: int, eps: float = 1e-2) -> DataFrame:
    """The full graph by the definition, for small N: every pair of items, every word. A cross join by its nature."""
    items = resp.select("item_id").distinct()
    feats = resp.sparkSession.range(dims).select(F.col("id").cast("int").alias("feat"))
    full = items.crossJoin(F.broadcast(feats)).join(resp.select("item_id", "feat", "r"), ["item_id", "feat"], "left").select("item_id", "feat", (F.coalesce("r", F.lit(0.0)) + eps).alias("r"))
    p = full.withColumn("p", F.col("r") / F.sum("r").over(Window.partitionBy("item_id"))).select("item_id", "feat", "p")
    a, b = p.select("feat", F.col("item_id").alias("s"), F.col("p").alias("p_s")), p.select("feat", F.col("item_id").alias("t"), F.col("p").alias("p_t"))
    return a.join(b, "feat").where("s < t").groupBy("s", "t").agg(F.sum((F.col("p_s") - F.col("p_t")) * F.log(F.col("p_s") / F.col("p_t"))).alias("j"))


def edge_probability(j: Column, tau: float = 0.2, cap: float = 1 - 1e-9) -> Column:
    """exp(-tau * j), below one, to nine places, so that equal items have equal edges whatever the order of their sums."""
    return F.least(F.lit(cap), F.round(F.exp(-tau * j), PLACES))


def edges_of(pairs: DataFrame, tau: float = 0.2, q_min: float = 1e-3) -> DataFrame:
    """s, t, q without the edges of very low probability."""
    return pairs.select("s", "t", edge_probability(F.col("j"), tau).alias("q")).where(F.col("q") >= q_min)


def nearest(edges: DataFrame, k: int = 6, mode: str = "union") -> DataFrame:
    """At most k best edges of each vertex: kept if either end keeps it (union) or both do (mutual); capped takes edges
    from the best down while both ends have room. Ties go to the lower neighbour."""
    if mode == "capped":
        return _capped(edges, k)
    ends = edges.select(F.col("s").alias("v"), F.col("t").alias("o"), "q").unionByName(edges.select(F.col("t").alias("v"), F.col("s").alias("o"), "q"))
    return _voted(ends, k, mode)


def _voted(ends: DataFrame, k: int, mode: str) -> DataFrame:
    """s, t, q of the edges (v, o, q) that are among the k best of v; one end's choice is enough, or both must choose it (mutual)."""
    return _votes(_best(ends, k), mode)


def _best(ends: DataFrame, k: int) -> DataFrame:
    ranked = ends.withColumn("n", F.row_number().over(Window.partitionBy("v").orderBy(F.desc("q"), "o")))
    return ranked.where(F.col("n") <= k).select("v", "o", "q")


def _votes(best: DataFrame, mode: str) -> DataFrame:
    kept = best.groupBy(F.least("v", "o").alias("s"), F.greatest("v", "o").alias("t")).agg(F.max("q").alias("q"), F.count(F.lit(1)).alias("votes"))
    return kept.where(F.col("votes") >= (2 if mode == "mutual" else 1)).select("s", "t", "q")


def _capped(edges: DataFrame, k: int) -> DataFrame:
    """Greedy from the best edge down while both ends have room, by rounds: an edge that is among the best of what is left
    at both ends, within their room, can't lose its place to a better one, so all such edges are taken at once."""
    left = keep(edges.select("s", "t", "q"), "capped-left")
    taken = None
    while True:
        ends = left.select(F.col("s").alias("v"), "s", "t", "q").unionByName(left.select(F.col("t").alias("v"), "s", "t", "q"))
        if taken is not None:
            degree = taken.select(F.explode(F.array("s", "t")).alias("v")).groupBy("v").agg(F.count(F.lit(1)).alias("d"))
            ends = ends.join(degree, "v", "left").withColumn("room", k - F.coalesce("d", F.lit(0)))
        else:
            ends = ends.withColumn("room", F.lit(k))
        ranked = ends.withColumn("n", F.row_number().over(Window.partitionBy("v").orderBy(F.desc("q"), "s", "t")))
        marked = keep(ranked.groupBy("s", "t", "q").agg(F.max(F.when(F.col("room") <= 0, 1).otherwise(0)).alias("full"), F.min(F.when(F.col("n") <= F.col("room"), 1).otherwise(0)).alias("sure")), "capped-round")
        new = marked.where("sure = 1 and full = 0").select("s", "t", "q")
        taken = keep(new if taken is None else taken.unionByName(new), "capped-taken")
        left = marked.where("sure = 0 and full = 0").select("s", "t", "q")
        if left.limit(1).count() == 0:
            return taken


def draw_edges(edges: DataFrame, labels: DataFrame, seed: int, step: int, tag: str = "e", draw=u01) -> DataFrame:
    """Edges that are turned on: between items of one label, with probability q, by the keyed draw."""
    ls, lt = labels.select(F.col("item_id").alias("s"), F.col("cat").alias("cat_s")), labels.select(F.col("item_id").alias("t"), F.col("cat").alias("cat_t"))
    same = edges.join(ls, "s").join(lt, "t").where("cat_s = cat_t")
    return same.where(draw(seed, step, tag, F.col("s"), F.col("t")) < F.col("q")).select("s", "t", "q", F.col("cat_s").alias("cat"))


def components(edges: DataFrame, vertices: DataFrame) -> DataFrame:
    """item_id, cp (the lowest item of its connected component) for all vertices, isolated ones too.

    In a round each item, and the item that its label names, takes the lowest label among the item's neighbours, and labels
    jump to their own labels, so rounds grow with the logarithm of the longest path. Labels only fall; the loop ends when none does."""
    both = keep(edges.select(F.col("s").alias("u"), F.col("t").alias("v")).unionAll(edges.select(F.col("t").alias("u"), F.col("s").alias("v"))).distinct(), "cc-edges")
    labels = vertices.select("item_id", F.col("item_id").alias("cp"))
    while True:
        low = both.join(labels.select(F.col("item_id").alias("v"), "cp"), "v").groupBy(F.col("u").alias("item_id")).agg(F.min("cp").alias("low"))
        seen = keep(labels.join(low, "item_id", "left").select("item_id", "cp", F.least("cp", F.coalesce("low", "cp")).alias("low")), "cc-seen")
        roots = seen.where("low < cp").groupBy(F.col("cp").alias("item_id")).agg(F.min("low").alias("hook"))
        hooked = keep(seen.join(roots, "item_id", "left").select("item_id", F.least("low", F.coalesce("hook", "low")).alias("new"), "cp"), "cc-hooked")
        if not hooked.where("new < cp").limit(1).count():
            return hooked.select("item_id", "cp")
        up = hooked.select(F.col("item_id").alias("new"), F.col("new").alias("above"))
        labels = keep(hooked.join(up, "new", "left").select("item_id", F.least("new", F.coalesce("above", "new")).alias("cp")), "cc-labels")


def pair_divergences(resp: DataFrame, pairs: DataFrame, dims: int, eps: float = 1e-2) -> DataFrame:
    """s, t, j of the given pairs (s, t): the items' words meet as sorted arrays, one row a pair, so nothing is formed for
    words that many items have."""
    scalars = item_scalars(resp, dims, eps)
    words = resp.groupBy("item_id").agg(F.map_from_entries(F.collect_list(F.struct("feat", "r"))).alias("m"))
    items = keep(words.join(scalars, "item_id"), "pair-items")
    x = items.select(F.col("item_id").alias("s"), F.col("m").alias("m_s"), F.col("z").alias("z_s"), F.col("a").alias("a_s"), F.col("h").alias("h_s"))
    y = items.select(F.col("item_id").alias("t"), F.col("m").alias("m_t"), F.col("z").alias("z_t"), F.col("a").alias("a_t"), F.col("h").alias("h_t"))
    both = pairs.join(x, "s").join(y, "t")
    common = F.array_intersect(F.map_keys("m_s"), F.map_keys("m_t"))
    add = lambda u, v: F.aggregate(common, F.lit(0.0), lambda acc, f: acc + F.col(u)[f] * F.log(1 + F.col(v)[f] / eps))
    cross_st = F.log(eps / F.col("z_t")) + eps / F.col("z_s") * F.col("a_t") + add("m_s", "m_t") / F.col("z_s")
    cross_ts = F.log(eps / F.col("z_s")) + eps / F.col("z_t") * F.col("a_s") + add("m_t", "m_s") / F.col("z_t")
    return both.select("s", "t", F.greatest(F.lit(0.0), F.col("h_s") + F.col("h_t") - cross_st - cross_ts).alias("j"))


def candidate_pairs(resp: DataFrame, method: str = "both", most_items: int = 300, bands: int = 40, seed: int = 42) -> DataFrame:
    """s, t: the pairs of items that meet in a bucket of candidate_buckets()."""
    done = candidate_buckets(resp, method, most_items, bands, seed)
    a, b = done.select("bucket", F.col("item_id").alias("s")), done.select("bucket", F.col("item_id").alias("t"))
    return a.join(b, "bucket").where("s < t").select("s", "t").distinct()


def candidate_buckets(resp: DataFrame, method: str = "both", most_items: int = 300, bands: int = 40, seed: int = 42) -> DataFrame:
    """item_id, kind, bucket: items of a bucket are worth a divergence. rare_words (kind w): a shared word. minhash (kind h): an
    equal weighted minimum of keyed hashes, words with great responses counting more; both: either. bucket is a 64-bit hash.

    A bucket of more than most_items items is split by a further minimum, again and again, so no item is left out and
    no bucket makes more than most_items squared pairs; what a split loses shows in the recall against all pairs."""
    def lowest(i):
        # Exponential races: the word of the lowest -ln(u) / r wins with a probability in proportion to r.
        u = (F.shiftrightunsigned(F.xxhash64(F.lit(seed), F.lit(i), "feat"), 11).cast("double") + 0.5) * F.lit(2.0**-53)
        return F.min_by("feat", -F.log(u) / F.col("r"))

    depth, first = 3, []
    mins = keep(resp.groupBy("item_id").agg(F.collect_list("feat").alias("words"), *[lowest(i).alias(f"m{i}") for i in range(bands + depth)]), "candidate-minima")
    if method in ("rare_words", "both"):
        first.append(F.transform("words", lambda f: F.struct(F.lit("w").alias("kind"), F.xxhash64(F.lit("w"), f).alias("bucket"))))
    if method in ("minhash", "both"):
        first.append(F.array(*[F.struct(F.lit("h").alias("kind"), F.xxhash64(F.lit("h"), F.lit(b), F.col(f"m{b}")).alias("bucket")) for b in range(bands)]))
    more = [F.col(f"m{bands + d}").alias(f"more{d}") for d in range(depth)]
    left = mins.select("item_id", *more, F.explode(F.concat(*first)).alias("key")).select("item_id", "key.kind", "key.bucket", *[f"more{d}" for d in range(depth)])
    done = None
    for d in range(depth + 1):
        large = left.groupBy("bucket").agg(F.count(F.lit(1)).alias("size")).where(F.col("size") > most_items)
        sized = keep(left.join(large, "bucket", "left"), "candidate-keys")
        small = sized.where("size is null").select("item_id", "kind", "bucket")
        done = small if done is None else done.unionByName(small)
        left = sized.where("size is not null")
        if d < depth:
            left = left.withColumn("bucket", F.xxhash64("bucket", f"more{d}")).drop("size")
        else:  # what is still too large: parts of most_items by a hash of the item
            part = F.pmod(F.xxhash64("item_id"), F.ceil(F.col("size") / most_items))
            done = done.unionByName(left.select("item_id", "kind", F.xxhash64("bucket", part).alias("bucket")))
    return done


def candidate_counts(buckets: DataFrame, edges: DataFrame) -> DataFrame:
    """method, candidates, hits, query_hits: the pairs that candidate_pairs() would make of these buckets, by kind of bucket (both:
    either), the edges among them, and the ends of those whose id is divisible by 100.

    Blocks of items meet as in the divergences: a pair is a place in a table of two blocks, so pairs are counted, not written."""
    blocks = max(1, -(-buckets.agg(F.count_distinct("item_id")).first()[0] // BLOCK_ITEMS))
    cells = {"ids": np.int64, "buckets": np.int64, "rows": np.int32, "kinds": np.int8, "from": np.int64, "to": np.int64}

    def pack(table: pa.Table) -> pa.Table:
        item, bucket, kind, other = (table.column(c).to_numpy() for c in ("item_id", "bucket", "kind", "other"))
        ids, edge = np.unique(item), kind == 2
        order = np.lexsort((item[~edge], bucket[~edge]))
        held = [x[~edge][order] for x in (bucket, item, kind)]
        out = [ids, held[0], np.searchsorted(ids, held[1]), held[2], item[edge], other[edge]]
        return pa.table([table.column("block")[:1].combine_chunks(), *[pa.array([x.astype(kind).tobytes()], pa.binary()) for x, kind in zip(out, cells.values(), strict=True)]], names=["block", *cells])

    def run(batches):
        candidates, hits, query_hits = (np.zeros(3, np.int64) for _ in range(3))
        for b in batches:
            for i in range(b.num_rows):
                x, y = ([np.frombuffer(b.column(f"{name}_{c}")[i].as_buffer(), kind) for c, kind in cells.items()] for name in "xy")
                same = b.column("x_block")[i].as_py() == b.column("y_block")[i].as_py()
                met = np.zeros((3, len(x[0]), len(y[0])), bool)
                first, last = (np.searchsorted(y[1], x[1], side) for side in ("left", "right"))
                size = last - first
                ends = np.cumsum(size)
                at = 0
                while at < len(size):  # so many entries that they make about half a million places
                    to = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + 500_000)))
                    n = size[at:to]
                    place = np.repeat(first[at:to] - (np.cumsum(n) - n), n) + np.arange(n.sum())
                    met[np.repeat(x[3][at:to], n), np.repeat(x[2][at:to], n), y[2][place]] = True
                    at = to
                np.logical_or(met[0], met[1], out=met[2])
                if same:
                    for m in met:
                        np.fill_diagonal(m, False)
                candidates += np.count_nonzero(met, axis=(1, 2)) // (2 if same else 1)
                for u, v, turned in ((x, y, False), *(() if same else ((y, x, True),))):
                    col = np.searchsorted(v[0], v_ids := u[5])
                    here = np.flatnonzero(v[0][np.minimum(col, len(v[0]) - 1)] == v_ids)
                    row, col = np.searchsorted(u[0], u[4][here]), col[here]
                    hit = met[:, col, row] if turned else met[:, row, col]
                    hits += hit.sum(1)
                    query_hits += hit @ ((u[4][here] % 100 == 0).astype(np.int64) + (u[5][here] % 100 == 0))
        names = pa.array(["rare_words", "minhash", "both"])
        yield pa.RecordBatch.from_arrays([names, *map(pa.array, (candidates, hits, query_hits))], ["method", "candidates", "hits", "query_hits"])

    block = F.pmod(F.xxhash64("item_id"), F.lit(blocks)).alias("block")
    nothing = F.lit(0).cast("long")
    kind = F.when(F.col("kind") == "w", 0).otherwise(1).cast("long").alias("kind")
    rows = buckets.select(block, F.col("item_id").cast("long"), "bucket", kind, nothing.alias("other"))
    rows = rows.unionByName(edges.withColumnRenamed("s", "item_id").select(block, F.col("item_id").cast("long"), nothing.alias("bucket"), F.lit(2).cast("long").alias("kind"), F.col("t").cast("long").alias("other")))
    packed = keep(rows.groupBy("block").applyInArrow(pack, "block long, " + ", ".join(f"`{c}` binary" for c in cells)), "candidate-blocks")
    sums = _met(packed).mapInArrow(run, "method string, candidates long, hits long, query_hits long")
    with _few_rows(buckets.sparkSession):
        return keep(sums.groupBy("method").agg(*[F.sum(c).alias(c) for c in ("candidates", "hits", "query_hits")]), "candidate-counts")


#: DuckDB CTEs over resp: scal, jp (s, t, j), and edges.
def graph_sql(dims: int, eps: float = 1e-2, tau: float = 0.2, q_min: float = 1e-3, k: int = 6) -> str:
    return f"""
scal AS (SELECT item_id, z, a, ln({eps} / z) + {eps} / z * a + own / z AS h FROM (
  SELECT item_id, sum(r) + {eps} * {dims} AS z, sum(ln(1 + r / {eps})) AS a, sum(r * ln(1 + r / {eps})) AS own FROM resp GROUP BY item_id)),
shared AS (SELECT x.item_id AS s, y.item_id AS t, sum(x.r * ln(1 + y.r / {eps})) AS st, sum(y.r * ln(1 + x.r / {eps})) AS ts
  FROM resp x JOIN resp y ON x.feat = y.feat AND x.item_id < y.item_id GROUP BY 1, 2),
jp AS (SELECT s, t, greatest(0, u.h + v.h - (ln({eps} / v.z) + {eps} / u.z * v.a + st / u.z) - (ln({eps} / u.z) + {eps} / v.z * u.a + ts / v.z)) AS j
  FROM shared JOIN scal u ON u.item_id = s JOIN scal v ON v.item_id = t),
weak AS (SELECT s, t, q FROM (SELECT s, t, least(1 - 1e-9, round(exp(-{tau} * j), 9)) AS q FROM jp) WHERE q >= {q_min}),
ends AS (SELECT s AS v, t AS o, q FROM weak UNION ALL SELECT t, s, q FROM weak),
best AS (SELECT v, o, q FROM (SELECT *, row_number() OVER (PARTITION BY v ORDER BY q DESC, o) AS n FROM ends) WHERE n <= {k}),
votes AS (SELECT least(v, o) AS s, greatest(v, o) AS t, max(q) AS q, count(*) AS votes FROM best GROUP BY 1, 2),
edges AS (SELECT s, t, q FROM votes)"""
