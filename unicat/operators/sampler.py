"""Cluster samplers over partitions: the single-cut and the composite-cut moves.

The kernels below are DataFrame operators for one step on a graph of any size. Two engines run whole chains with the same
keyed draws and the same code for the moves of a step, so they give the same trace. run_chains() holds the graph and the
responses of a checked size in one task a chain (chains of different seeds run side by side). distributed_chain() keeps them
in tables and brings only the step's picked clusters to the driver: their sizes, summed responses and edges to others.
Energies come from the categories' sums alone, and a step touches only what it moves.

For a fixed draw of the switches, moving a cluster from label A to B keeps the target if the acceptance has the factor
W(B) / W(A), W being the product of 1 - q over edges between the cluster and other clusters of its label. With a second
level of clusters over components the same factor comes in once more, as the upper graph's off-probability of a pair is
that product. The choice among the K labels and a new one brings (K_A + 1) / (K_B + 1). fidelity="paper" leaves out the
latter two, as the published ratio does, and accepts all picked composites with one test.
"""

from __future__ import annotations

import math
from bisect import bisect_left
from itertools import islice

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..params import Params
from ..rng import fast01, fast01_np, u01
from ..sources.tables import keep
from . import graph, posterior

#: Bytes of responses and edges that run_chains() broadcasts; larger sets go through distributed_chain().
LOCAL_BYTES = 1_000_000_000
#: Cells whose summed responses a step makes at a time, and proposals that it weighs at a time at most.
MASSES, AHEAD = 512, 64


# Kernels


def pick_component(parts: DataFrame, seed: int, step: int, draw=u01) -> DataFrame:
    """One row: the component with the lowest keyed number."""
    cps = parts.select("cp").distinct().withColumn("u", draw(seed, step, "p", F.col("cp")))
    return cps.agg(F.min_by("cp", F.struct("u", "cp")).alias("cp"))


def propose_label(picked: DataFrame, parts: DataFrame, labels: DataFrame, seed: int, step: int) -> DataFrame:
    """cp, cat_from, cat_to, k: uniform over the labels in use, in order, and a new one (the greatest plus one)."""
    old = parts.join(F.broadcast(picked.select("cp")), "cp", "left_semi").join(labels, "item_id").groupBy("cp").agg(F.min("cat").alias("cat_from"))
    # As many labels as categories, which the models hold anyway.
    cats = labels.agg(F.array_sort(F.collect_set("cat")).alias("cats"))
    at = F.floor(u01(seed, step, "l", F.col("cp")) * (F.size("cats") + 1)).cast("int")
    new = F.when(at < F.size("cats"), F.col("cats")[at]).otherwise(F.array_max("cats") + 1)
    return old.crossJoin(F.broadcast(cats)).select("cp", "cat_from", new.alias("cat_to"), F.size("cats").cast("long").alias("k"))


def log_cut_ratio(edges: DataFrame, parts: DataFrame, labels: DataFrame, moves: DataFrame) -> DataFrame:
    """cp, log_ratio of each move: summed ln(1 - q) of its edges to the rest of the new label, less those of the old one."""
    state = parts.join(labels, "item_id")
    a = state.select(F.col("item_id").alias("s"), F.col("cp").alias("cp_s"), F.col("cat").alias("cat_s"))
    b = state.select(F.col("item_id").alias("t"), F.col("cp").alias("cp_t"), F.col("cat").alias("cat_t"))
    across = edges.join(a, "s").join(b, "t").where("cp_s <> cp_t")
    ends = across.select(F.col("cp_s").alias("cp"), F.col("cat_t").alias("other"), "q").unionByName(across.select(F.col("cp_t").alias("cp"), F.col("cat_s").alias("other"), "q"))
    hit = ends.join(F.broadcast(moves.select("cp", "cat_from", "cat_to")), "cp")
    log = F.log1p(-F.col("q"))
    ratio = F.sum(F.when(F.col("cat_from") == F.col("cat_to"), 0.0).when(F.col("other") == F.col("cat_to"), log).when(F.col("other") == F.col("cat_from"), -log).otherwise(0.0))
    return moves.select("cp").join(hit.groupBy("cp").agg(ratio.alias("log_ratio")), "cp", "left").select("cp", F.coalesce("log_ratio", F.lit(0.0)).alias("log_ratio"))


def component_graph(edges: DataFrame, parts: DataFrame, labels: DataFrame, scope: str = "same_label", scale: float = 1.0) -> DataFrame:
    """a, b (a < b), q: the upper graph; q = scale * (1 - product of 1 - q over the edges between two components)."""
    state = parts.join(labels, "item_id")
    x = state.select(F.col("item_id").alias("s"), F.col("cp").alias("cp_s"), F.col("cat").alias("cat_s"))
    y = state.select(F.col("item_id").alias("t"), F.col("cp").alias("cp_t"), F.col("cat").alias("cat_t"))
    across = edges.join(x, "s").join(y, "t").where("cp_s <> cp_t")
    if scope == "same_label":
        across = across.where("cat_s = cat_t")
    return across.groupBy(F.least("cp_s", "cp_t").alias("a"), F.greatest("cp_s", "cp_t").alias("b")).agg((scale * (1 - F.exp(F.sum(F.log1p(-F.col("q")))))).alias("q"))


def composites(upper: DataFrame, parts: DataFrame, seed: int, step: int, draw=u01) -> DataFrame:
    """cp, comp: components of the upper graph after its edges are switched."""
    on = upper.where(draw(seed, step, "c", F.col("a"), F.col("b")) < F.col("q")).select(F.col("a").alias("s"), F.col("b").alias("t"))
    vertices = parts.select(F.col("cp").alias("item_id")).distinct()
    return graph.components(on, vertices).select(F.col("item_id").alias("cp"), F.col("cp").alias("comp"))


def pick_composites(comps: DataFrame, seed: int, step: int, p_pick: float = 0.3, draw=u01) -> DataFrame:
    """comp of each one that is picked: those under p_pick, and always the one with the lowest number."""
    u = comps.select("comp").distinct().withColumn("u", draw(seed, step, "k", F.col("comp")))
    low = u.agg(F.min(F.struct("u", "comp")).alias("low"))
    return u.crossJoin(F.broadcast(low)).where((F.col("u") < p_pick) | (F.col("comp") == F.col("low.comp"))).select("comp")


def moved_labels(labels: DataFrame, parts: DataFrame, moves: DataFrame) -> DataFrame:
    """The labels after every move in moves (cp, cat_to)."""
    at = parts.join(F.broadcast(moves.select("cp", "cat_to")), "cp").select("item_id", "cat_to")
    return labels.join(at, "item_id", "left").select("item_id", F.coalesce("cat_to", "cat").alias("cat"))


def single_step(resp: DataFrame, edges: DataFrame, labels: DataFrame, reference: DataFrame, params: Params, step: int) -> tuple[DataFrame, DataFrame]:
    """One whole single-cut step by DataFrames: (report, labels if accepted). The report has one row."""
    parts = graph.components(graph.draw_edges(edges, labels, params.seed, step), labels)
    return atom_step(resp, edges, labels, parts, reference, params, step)


def atom_step(resp: DataFrame, edges: DataFrame, labels: DataFrame, parts: DataFrame, reference: DataFrame, params: Params, step: int, factor: float = 1.0) -> tuple[DataFrame, DataFrame]:
    """The rest of a step whose atoms (item_id, cp) are given: one is picked and moved. factor: 2 for composites within a
    label, whose second level of cuts equals the first."""
    move = keep(propose_label(pick_component(parts, params.seed, step), parts, labels, params.seed, step), "move")
    after = moved_labels(labels, parts, move)

    def total(state, name):
        m = posterior.select_words(posterior.category_means(resp, state), reference, params.model_words, params.rule)
        return posterior.energy(m, params.beta).select(F.col("k").alias(f"k_{name}"), F.col("energy").alias(f"energy_{name}"))

    ratio = log_cut_ratio(edges, parts, labels, move).withColumn("log_ratio", factor * F.col("log_ratio"))
    one = move.join(ratio, "cp").crossJoin(total(labels, "before")).crossJoin(total(after, "after"))
    labels_ratio = F.log((F.col("k_before") + 1) / (F.col("k_after") + 1)) if params.fidelity == "reversible" else F.lit(0.0)
    log_alpha = F.least(F.lit(0.0), F.col("log_ratio") + labels_ratio + F.col("energy_before") - F.col("energy_after"))
    report = one.select("cp", "cat_from", "cat_to", "k_before", "k_after", "log_ratio", "energy_before", "energy_after", log_alpha.alias("log_alpha"), (F.log(u01(params.seed, step, "a")) < log_alpha).alias("accepted"))
    return report, after


# Whole chains


class Cells:
    """What a step can move: atoms (clusters) in cells of one label each, with the edges between cells of different atoms.

    Only cells of picked atoms need their masses (summed responses) and edges."""

    def __init__(self, atom, label, size, mass, edges):
        self.atom, self.label, self.size, self.mass = atom, label, size, mass  # arrays over cells; mass: cell -> vector
        self.own, self.other, self.log_off = edges  # sorted by own


class Masses:
    """The summed responses of the wanted cells, which are asked for about in their order: made for some cells at a time, by one
    sum; the last two lots stay."""

    def __init__(self, chain: Chain, order: np.ndarray, ends: np.ndarray, wanted: np.ndarray):
        self.chain, self.order, self.ends, self.wanted, self.listed, self.lots = chain, order, ends, wanted, wanted.tolist(), {}

    def __getitem__(self, cell: int) -> np.ndarray:
        lot, at = divmod(bisect_left(self.listed, cell), MASSES)
        if lot not in self.lots:
            if len(self.lots) > 1:
                self.lots.pop(next(iter(self.lots)))
            cells = self.wanted[lot * MASSES : (lot + 1) * MASSES]
            size = self.ends[cells + 1] - self.ends[cells]
            self.lots[lot] = list(self.chain.mass(self.order[runs(self.ends[cells], size)], np.repeat(np.arange(len(cells)), size), len(cells)))
        return self.lots[lot][at]


def runs(first: np.ndarray, size: np.ndarray) -> np.ndarray:
    """The places first, first + 1, ... of each run, size of them."""
    return np.repeat(first - (np.cumsum(size) - size), size) + np.arange(size.sum())


class Model:
    """The categories of a state: their sizes, summed responses and gains, and the energy."""

    def __init__(self, params: Params, e_0: np.ndarray, beta: float, stats: dict[int, list]):
        self.p, self.e_0, self.beta, self.held, self.cats = params, e_0, beta, stats, sorted(stats)
        self.gains = {}
        for at in range(0, len(stats), MASSES):
            some = list(islice(stats.items(), at, at + MASSES))
            self.gains.update(zip((c for c, _ in some), self.many_gains([v[0] for _, v in some], np.stack([v[1] for _, v in some])), strict=True))
        self.now = beta * len(stats) - sum(self.gains.values())

    def gain(self, n: int, total: np.ndarray) -> float:
        """Log-likelihood of a category of n items with summed responses total."""
        if not n:
            return 0.0
        p, held = self.p, total > 1e-12
        words = int(np.count_nonzero(held))
        if not words:
            return 0.0
        e = total / n
        if words <= p.model_words:
            return n * float(self.kl(e, np.flatnonzero(held)).sum())
        # Only the best words need logarithms if the gap chooses them, and only ties at the last one need a sort.
        if p.rule == "mean_gap":
            by = np.where(held, e - self.e_0, -np.inf)
        else:
            by = np.full(len(e), -np.inf)
            by[held] = self.kl(e, np.flatnonzero(held))
        at = np.flatnonzero(by >= np.partition(by, len(by) - p.model_words)[len(by) - p.model_words])
        if len(at) > p.model_words:
            at = at[np.argsort(-by[at], kind="stable")[: p.model_words]]
        return n * float(self.kl(e, at).sum())

    def many_gains(self, n, total: np.ndarray) -> list[float]:
        """gain() of many categories, the rows of total, in one pass."""
        t, (rows, dims) = self.p.model_words, total.shape
        if t >= dims:
            return [self.gain(k, x) for k, x in zip(n, total, strict=True)]
        n = np.array(n, float)
        e = total / n[:, None]
        by = e - self.e_0 if self.p.rule == "mean_gap" else self.kl_of(e, self.e_0)
        if total.min() <= 1e-12:
            np.putmask(by, total <= 1e-12, -np.inf)
        last, few = np.sort(by, axis=1)[:, dims - t], ()  # many equal values make a partition slower than a sort
        at = (by >= last[:, None]).ravel().nonzero()[0]
        if len(at) > t * rows:  # of equal words the first ones
            row = at // dims
            equal = by.ravel()[at] == last[row]
            first = np.searchsorted(row, np.arange(rows + 1))
            so_far = np.append(0, np.cumsum(equal))
            room = t - np.diff(first) + np.diff(so_far[first])
            at = at[~equal | (so_far[1:] - so_far[first[row]] <= room[row])]
            few = (last == -np.inf).nonzero()[0].tolist()
        out = (n * self.kl_of(e.ravel()[at], self.e_0[at % dims]).reshape(rows, t).sum(axis=1)).tolist()
        for k in few:  # with fewer words than a model has
            out[k] = self.gain(int(n[k]), total[k])
        return out

    def two_gains(self, n: tuple[int, int], total: np.ndarray) -> list[float]:
        return self.many_gains(n, total)

    def kl(self, e: np.ndarray, at: np.ndarray) -> np.ndarray:
        return self.kl_of(e[at], self.e_0[at])

    def kl_of(self, e: np.ndarray, o: np.ndarray) -> np.ndarray:
        f = np.minimum(np.maximum(e, self.p.clip), 1 - self.p.clip)
        return f * np.log(f / o) + (1 - f) * np.log((1 - f) / (1 - o))

    def step(self, cells: Cells, picked: list[int], ids: np.ndarray, step: int) -> tuple[int, bool, float, dict[int, int]]:
        """Moves the picked atoms one after another: (items moved, whether any move was accepted, last log ratio, atom -> new label).

        What the next atoms of one cell leave and make of their categories is weighed at a time, as if none of them moved; a
        category that an accepted move has changed meanwhile is weighed again when the atom's turn comes."""
        p, moved, accepted, last, log_joint, at_now = self.p, 0, False, 0.0, 0.0, {}
        factor = 2.0 if p.move == "composite" and p.fidelity == "reversible" and p.scope == "same_label" else 1.0
        joint = p.fidelity == "paper" and p.move == "composite"
        undo = ({c: [v[0], v[1].copy()] for c, v in self.held.items()}, dict(self.gains), self.now) if joint else None
        u_label, u_accept = fast01_np(p.seed, step, "l", ids[picked]), fast01_np(p.seed, step, "a", ids[picked])
        order = np.argsort(cells.atom, kind="stable")
        by_atom, cats = cells.atom[order], self.cats
        first, last_ = (np.searchsorted(by_atom, picked, side).tolist() for side in ("left", "right"))
        ends = np.searchsorted(cells.own, np.arange(len(cells.label) + 1)).tolist()
        u_label, u_accept, size, label = u_label.tolist(), u_accept.tolist(), cells.size.tolist(), cells.label.tolist()
        order, held, gains = order.tolist(), self.held, self.gains
        # Of atoms of one cell: the cell, and what is weighed: (state of the category it holds for, size after, gain after).
        cell = [order[x] if y - x == 1 else None for x, y in zip(first, last_, strict=True)]
        without: list[tuple | None] = [None] * len(picked)
        within: list[tuple | None] = [None] * len(picked)
        others, offs, masses = cells.other.tolist(), cells.log_off.tolist(), cells.mass
        reach, until = [4, 4], [0, 0]
        total = np.empty((2 * AHEAD, len(self.e_0)))

        def target(k: int) -> int:
            at = int(u_label[k] * (len(cats) + 1))
            return cats[at] if at < len(cats) else cats[-1] + 1

        def window(k: int, side: int, stale: bool) -> range:
            """The proposals that are weighed with this one: twice as many as last time if all of those were of use, else fewer."""
            if stale:
                reach[side] = min(AHEAD, 2 * reach[side] if k >= until[side] else max(3, reach[side] * 3 // 4))
            until[side] = min(len(picked), k + reach[side])
            return range(k, until[side])

        def weigh(k: int, leave: bool, enter: bool) -> None:
            """Weighs what is not or no longer known of the old and of the new category of this proposal and of later ones."""
            n, put = [], []
            for x in window(k, 0, leave):
                if (i := cell[x]) is not None and ((w := without[x]) is None or w[0] is not held[label[i]]):
                    was = held[label[i]]
                    if was[0] == size[i]:
                        without[x] = was, 0, 0.0
                    else:
                        np.subtract(was[1], masses[i], out=total[len(n)])
                        put.append((without, x, was))
                        n.append(was[0] - size[i])
            for x in window(k, 1, enter):
                if (i := cell[x]) is not None:
                    was = held.get(target(x), nothing)
                    if (w := within[x]) is None or w[0] is not was:
                        np.add(was[1], masses[i], out=total[len(n)])
                        put.append((within, x, was))
                        n.append(was[0] + size[i])
            if n:
                for (side, x, was), k_, gain in zip(put, n, self.many_gains(n, total[: len(n)]), strict=True):
                    side[x] = was, k_, gain

        nothing = [0, 0.0]

        def cut(i: int, old: int, new: int) -> float:
            lo, hi = ends[i], ends[i + 1]
            if hi - lo < 32:  # fewer than arrays are worth
                to_new = to_old = 0.0
                for x in range(lo, hi):
                    there = label[others[x]]
                    if there == new:
                        to_new += offs[x]
                    elif there == old:
                        to_old += offs[x]
                return to_new - to_old
            there = cells.label[cells.other[lo:hi]]
            w = cells.log_off[lo:hi]
            return float(w[there == new].sum() - w[there == old].sum())

        for k, c in enumerate(picked):
            new = target(k)
            if (i := cell[k]) is not None:
                old = label[i]
                if old == new:
                    continue
                was, to = held[old], held.get(new, nothing)
                leave, enter = without[k] is None or without[k][0] is not was, within[k] is None or within[k][0] is not to
                if leave or enter:
                    weigh(k, leave, enter)
                (_, left, left_gain), (_, grown, grown_gain) = without[k], within[k]
                moving, ratio = (i,), cut(i, old, new)
                k_new = len(held) + (to is nothing) - (not left)
                gained, lost = grown_gain + left_gain, gains.get(new, 0.0) + gains[old]
            else:
                moving = [x for x in order[first[k] : last_[k]] if label[x] != new]
                if not moving:
                    continue
                ratio, shift = 0.0, {new: [0, 0.0]}
                for x in moving:
                    old, mass, n = label[x], masses[x], size[x]
                    dn, dx = shift.get(old, [0, 0.0])
                    shift[old] = [dn - n, dx - mass]
                    shift[new] = [shift[new][0] + n, shift[new][1] + mass]
                    ratio += cut(x, old, new)
                after = {}
                for cat, (dn, dx) in shift.items():
                    n, x = held.get(cat, [0, 0.0])
                    after[cat] = n + dn, x + dx
                fresh = {cat: self.gain(*v) for cat, v in after.items() if v[0]}
                k_new = len(held) + (new not in held) - sum(1 for v in after.values() if not v[0])
                gained, lost = sum(fresh.values()), sum(gains.get(cat, 0.0) for cat in after)
            then = self.now + self.beta * (k_new - len(held)) - gained + lost
            last = factor * ratio + self.now - then
            if p.fidelity == "reversible":
                last += math.log((len(held) + 1) / (k_new + 1))
            log_joint += last
            if joint or math.log(max(1e-300, u_accept[k])) < last:
                cells.label[order[first[k] : last_[k]]] = new
                for x in moving:
                    label[x] = new
                if i is not None:
                    mass = masses[i]
                    after, fresh = {new: (grown, to[1] + mass), old: (left, was[1] - mass if left else None)}, {new: grown_gain, old: left_gain}
                for cat, v in after.items():
                    if v[0]:
                        if cat not in held:
                            cats.append(cat)  # a new one follows the greatest
                        held[cat], gains[cat] = list(v), fresh[cat]
                    elif held.pop(cat, None) is not None:
                        gains.pop(cat)
                        del cats[bisect_left(cats, cat)]
                self.now, moved, accepted, at_now[c] = then, moved + sum(size[x] for x in moving), True, new
        if joint and accepted and not math.log(max(1e-300, float(fast01_np(p.seed, step, "a")))) < log_joint:
            self.held, self.gains, self.now = undo
            self.cats = sorted(self.held)
            return 0, False, log_joint, {}
        return moved, accepted, log_joint if joint else last, at_now


def joined(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The lowest vertex of each vertex's component: labels are hooked to lower ones and then jump to their own labels."""
    label = np.arange(n)
    while len(a):
        x, y = label[a], label[b]
        apart = x != y
        if not apart.any():
            return label
        a, b, x, y = a[apart], b[apart], x[apart], y[apart]
        np.minimum.at(label, np.maximum(x, y), np.minimum(x, y))
        while not np.array_equal(up := label[label], label):
            label = up
    return label


class Chain:
    """A chain over items 0..n-1. Responses are a dense array, or (first place of each item, features, values) and the number of features."""

    def __init__(self, ids, resp, edges, e_0: np.ndarray, params: Params):
        self.ids, self.p, self.e_0 = np.asarray(ids, np.int64), params, np.clip(e_0, params.clip, 1 - params.clip)
        if isinstance(resp, np.ndarray):
            row, feat = np.nonzero(resp)
            resp = np.searchsorted(row, np.arange(len(resp) + 1)), feat, resp[row, feat]
        self.begin, self.feat, self.r = resp
        self.s, self.t, self.q = edges
        self.log_off = np.log1p(-self.q)
        self.beta = params.beta_for(len(self.ids))

    def start(self) -> np.ndarray:
        n, p = len(self.ids), self.p
        if p.initial == "singletons":
            return np.arange(1, n + 1)
        if p.initial == "random":
            return 1 + (fast01_np(p.seed, 0, "i", self.ids) * 8).astype(np.int64)
        if p.initial == "components":
            return self.parts(np.ones(n, np.int64), -1)[0] + 1
        return np.ones(n, np.int64)

    def mass(self, members: np.ndarray, row: np.ndarray | None = None, rows: int = 1) -> np.ndarray:
        """Summed responses of some items; with the row of each, a row of sums for each of so many rows."""
        size = self.begin[members + 1] - self.begin[members]
        at, dims = runs(self.begin[members], size), len(self.e_0)
        if row is None:
            return np.bincount(self.feat[at], self.r[at], dims)
        return np.bincount(self.feat[at] + np.repeat(row * dims, size), self.r[at], rows * dims).reshape(rows, dims)

    def model(self, labels: np.ndarray) -> Model:
        cats, at, size = np.unique(labels, return_inverse=True, return_counts=True)
        order, ends, stats = np.argsort(at, kind="stable"), np.append(0, np.cumsum(size)), {}
        for lo in range(0, len(cats), MASSES):
            hi = min(len(cats), lo + MASSES)
            rows = self.mass(order[ends[lo] : ends[hi]], np.repeat(np.arange(hi - lo), size[lo:hi]), hi - lo)
            stats.update({c: [n, x.copy()] for c, n, x in zip(cats[lo:hi].tolist(), size[lo:hi].tolist(), rows, strict=True)})
        return Model(self.p, self.e_0, self.beta, stats)

    def energy(self, labels: np.ndarray) -> float:
        return self.model(labels).now

    def parts(self, labels: np.ndarray, step: int) -> tuple[np.ndarray, np.ndarray]:
        """(component of each item, edges within a label)."""
        same = np.flatnonzero(labels[self.s] == labels[self.t])
        on = same[fast01_np(self.p.seed, step, "e", self.ids[self.s[same]], self.ids[self.t[same]]) < self.q[same]]
        return joined(len(labels), self.s[on], self.t[on]), same

    def clusters(self, labels: np.ndarray, step: int) -> np.ndarray:
        """The atoms of a step: components, or composites of them."""
        cp, same = self.parts(labels, step)
        if self.p.move == "single":
            return cp
        use = same if self.p.scope == "same_label" else np.arange(len(self.q))
        a, b = cp[self.s[use]], cp[self.t[use]]
        apart = a != b
        pair, at = np.unique(np.minimum(a, b)[apart] * len(labels) + np.maximum(a, b)[apart], return_inverse=True)
        off = np.bincount(at, self.log_off[use][apart], len(pair))
        a, b = pair // len(labels), pair % len(labels)
        on = fast01_np(self.p.seed, step, "c", self.ids[a], self.ids[b]) < self.p.cp_scale * (1 - np.exp(off))
        return joined(len(labels), a[on], b[on])[cp]

    def picks(self, atoms: np.ndarray, step: int) -> list[int]:
        own = np.unique(atoms)
        u = fast01_np(self.p.seed, step, "p" if self.p.move == "single" else "k", self.ids[own])
        chosen = np.zeros(len(own), bool) if self.p.move == "single" else u < self.p.p_pick
        chosen[np.argmin(u)] = True
        return own[chosen].tolist()

    def cells(self, atoms: np.ndarray, labels: np.ndarray, picked: list[int]) -> tuple[Cells, np.ndarray]:
        """The cells of a state, and the cell of each item."""
        pair, cell, size = np.unique(atoms * (len(labels) + 2) + labels, return_inverse=True, return_counts=True)
        atom, label = pair // (len(labels) + 2), pair % (len(labels) + 2)
        wanted = np.zeros(len(labels), bool)
        wanted[picked] = True
        order = np.argsort(cell, kind="stable")
        mass = Masses(self, order, np.append(0, np.cumsum(size)), np.flatnonzero(wanted[atom]))
        across = atoms[self.s] != atoms[self.t]
        s, t, w = self.s[across], self.t[across], self.log_off[across]
        x, y = wanted[atoms[s]], wanted[atoms[t]]
        own, other, w = np.concatenate([cell[s[x]], cell[t[y]]]), np.concatenate([cell[t[x]], cell[s[y]]]), np.concatenate([w[x], w[y]])
        by = np.argsort(own, kind="stable")
        return Cells(atom, label, size, mass, (own[by], other[by], w[by])), cell

    def run(self):
        """(trace rows, best labels, last labels)."""
        p, labels = self.p, self.start()
        model = self.model(labels)
        best, best_labels, stale = model.now, labels.copy(), 0
        trace = [(0, len(model.held), model.now, True, 0.0, 0, 0)]
        for step in range(1, p.steps + 1):
            # Labels in use are few and new ones follow the greatest, but they may outgrow the items: they are numbered anew.
            used, low = np.unique(labels, return_inverse=True)
            atoms = self.clusters(labels, step)
            picked = self.picks(atoms, step)
            cells, cell = self.cells(atoms, low, picked)
            cells.label = used[cells.label]
            moved, accepted, last, at_now = model.step(cells, picked, self.ids, step)
            if at_now:
                labels = cells.label[cell]
            trace.append((step, len(model.held), model.now, accepted, min(0.0, last), moved, len(np.unique(atoms))))
            if model.now < best - 1e-9:
                best, best_labels, stale = model.now, labels.copy(), 0
            else:
                stale += 1
                if stale >= p.patience:
                    break
        return trace, best_labels, labels


TRACE = "chain long, step int, k int, energy double, accepted boolean, log_alpha double, n_moved long, n_atoms long, model_words int, seconds double, item_ids array<long>, cats array<int>"


def run_chains(spark: SparkSession, resp: DataFrame, edges: DataFrame, dims: int, e_0, params: Params | list[Params], seeds: list[int], items: DataFrame | None = None) -> DataFrame:
    """All chains, one task each, of the same params or each of its own: their traces (TRACE); the row of step -1 of a chain has its best labels.

    items: all items (item_id), those without a word too; without it, those that have responses. The graph and the responses
    are broadcast if they have at most LOCAL_BYTES."""
    vertices = (items if items is not None else resp).select("item_id").distinct()
    size = 12 * resp.count() + 24 * edges.count() + 8 * vertices.count()
    if size > LOCAL_BYTES:
        raise ValueError(f"{size} bytes of responses and edges: use distributed_chain()")
    ids = np.sort(vertices.toArrow().column(0).to_numpy())
    rows = resp.select("item_id", "feat", "r").toArrow()
    feat, item = rows.column(1).to_numpy(), np.searchsorted(ids, rows.column(0).to_numpy())
    order = np.lexsort((feat, item))
    csr = np.searchsorted(item[order], np.arange(len(ids) + 1)), feat[order].astype(np.int32), rows.column(2).to_numpy()[order]
    del rows, feat, item, order  # the driver holds them once
    e = edges.select("s", "t", "q").toArrow()
    s, t, q = (e.column(i).to_numpy() for i in range(3))
    by = np.lexsort((t, s))
    own = params if isinstance(params, list) else [params] * len(seeds)
    held = spark.sparkContext.broadcast((ids, csr, (np.searchsorted(ids, s[by]), np.searchsorted(ids, t[by]), q[by]), np.asarray(e_0)))

    def run(batches):
        import time
        from dataclasses import replace

        import pandas as pd

        for batch in batches:
            for chain in batch["id"].tolist():
                began = time.time()
                ids, csr, graph_, e_0 = held.value
                trace, best, _ = Chain(ids, csr, graph_, e_0, replace(own[chain], seed=seeds[chain])).run()
                took = (time.time() - began) / max(1, len(trace) - 1)
                out = [(chain, *t, own[chain].model_words, took, None, None) for t in trace]
                out.append((chain, -1, len(np.unique(best)), min(t[2] for t in trace), True, 0.0, 0, 0, own[chain].model_words, took, ids.tolist(), best.tolist()))
                yield pd.DataFrame(out, columns=[c.split()[0] for c in TRACE.split(", ")])

    # A range has its rows in as many partitions as it is told, so every chain has a task of its own.
    return keep(spark.range(0, len(seeds), 1, len(seeds)).mapInPandas(run, TRACE), "traces")


def distributed_chain(resp: DataFrame, edges: DataFrame, items: DataFrame, e_0, params: Params, steps: int):
    """One chain of any size, the same one that run_chains() gives: (trace rows, labels of the best state as a table).

    A step's graph work is DataFrame jobs; the driver gets the sums of the picked clusters and their edges to others, added
    up by cluster, and decides the moves."""
    p, e_0 = params, np.clip(np.asarray(e_0), params.clip, 1 - params.clip)
    labels = keep(items.select("item_id", F.lit(1).cast("long").alias("cat")), "chain-labels")
    beta = p.beta_for(labels.count())
    edges = edges.select("s", "t", "q")

    def vectors(rows: DataFrame, keys: list[str]) -> dict:
        out: dict = {}
        for r in rows.groupBy(*keys, "feat").agg(F.sum("r").alias("total")).collect():
            out.setdefault(tuple(r[k] for k in keys), np.zeros(len(e_0)))[r.feat] = r.total
        return out

    sizes = {r.cat: r["count"] for r in labels.groupBy("cat").count().collect()}
    totals = vectors(resp.join(labels, "item_id"), ["cat"])
    model = Model(p, e_0, beta, {c: [n, totals.get((c,), np.zeros(len(e_0)))] for c, n in sizes.items()})
    best, best_labels, trace = model.now, labels, [(0, len(model.held), model.now, True, 0.0, 0, 0)]
    for step in range(1, steps + 1):
        parts = graph.components(graph.draw_edges(edges, labels, p.seed, step, draw=fast01), labels)
        if p.move == "single":
            atoms = parts.select("item_id", F.col("cp").alias("atom"))
            picked = pick_component(parts, p.seed, step, fast01).select(F.col("cp").alias("atom"))
        else:
            comps = keep(composites(component_graph(edges, parts, labels, p.scope, p.cp_scale), parts, p.seed, step, fast01), "chain-comps")
            atoms = parts.join(comps, "cp").select("item_id", F.col("comp").alias("atom"))
            picked = pick_composites(comps, p.seed, step, p.p_pick, fast01).select(F.col("comp").alias("atom"))
        state = keep(atoms.join(labels, "item_id"), "chain-state")
        chosen = sorted(r.atom for r in picked.collect())
        mine = F.broadcast(state.sparkSession.createDataFrame([(c,) for c in chosen], "atom long"))
        own = state.join(mine, "atom", "left_semi")
        cell_rows = own.groupBy("atom", "cat").count().collect()
        masses = vectors(resp.join(own, "item_id"), ["atom", "cat"])
        x = state.select(F.col("item_id").alias("s"), F.col("atom").alias("a_s"), F.col("cat").alias("c_s"))
        y = state.select(F.col("item_id").alias("t"), F.col("atom").alias("a_t"), F.col("cat").alias("c_t"))
        across = edges.join(x, "s").join(y, "t").where("a_s <> a_t").withColumn("w", F.log1p(-F.col("q")))
        ends = across.select(F.col("a_s").alias("atom"), F.col("c_s").alias("cat"), F.col("a_t").alias("o_atom"), F.col("c_t").alias("o_cat"), "w").unionByName(across.select(F.col("a_t").alias("atom"), F.col("c_t").alias("cat"), F.col("a_s").alias("o_atom"), F.col("c_s").alias("o_cat"), "w"))
        met = ends.join(mine, "atom", "left_semi").groupBy("atom", "cat", "o_atom", "o_cat").agg(F.sum("w").alias("w")).collect()
        every = sorted({(r.atom, r.cat) for r in cell_rows} | {(r.o_atom, r.o_cat) for r in met})
        place = {k: i for i, k in enumerate(every)}
        size = np.zeros(len(every), np.int64)
        for r in cell_rows:
            size[place[r.atom, r.cat]] = r["count"]
        met = sorted((place[r.atom, r.cat], place[r.o_atom, r.o_cat], r.w) for r in met)
        ids = np.array(sorted({a for a, _ in every}), np.int64)
        cells = Cells(
            np.searchsorted(ids, [a for a, _ in every]), np.array([c for _, c in every], np.int64), size, {place[k]: masses.get(k, np.zeros(len(e_0))) for k in ((r.atom, r.cat) for r in cell_rows)},
            (np.array([m[0] for m in met], np.int64), np.array([m[1] for m in met], np.int64), np.array([m[2] for m in met])),
        )
        moved, accepted, last, at_now = model.step(cells, np.searchsorted(ids, chosen).tolist(), ids, step)
        if at_now:
            moves = state.sparkSession.createDataFrame([(int(ids[a]), int(c)) for a, c in at_now.items()], "atom long, cat_to long")
            labels = keep(state.join(F.broadcast(moves), "atom", "left").select("item_id", F.coalesce("cat_to", "cat").alias("cat")), "chain-labels")
        trace.append((step, len(model.held), model.now, accepted, min(0.0, last), moved, state.select("atom").distinct().count()))
        if model.now < best - 1e-9:
            best, best_labels = model.now, labels
    return trace, best_labels


def best_labels(traces: DataFrame) -> DataFrame:
    """chain, item_id, cat of every chain's best state."""
    return traces.where("step = -1").select("chain", F.explode(F.arrays_zip("item_ids", "cats")).alias("x")).select("chain", F.col("x.item_ids").alias("item_id"), F.col("x.cats").alias("cat"))
