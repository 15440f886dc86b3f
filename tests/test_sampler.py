"""The samplers against the exact law over all partitions of a few items, and the chain against its own definitions."""

import itertools
import math
from dataclasses import replace

import numpy as np
import pytest

from unicat.operators.sampler import Chain
from unicat.params import Params


def partitions(n):
    def grow(prefix, k):
        if len(prefix) == n:
            yield tuple(prefix)
            return
        for c in range(k + 1):
            yield from grow(prefix + [c], max(k, c + 1))

    return list(grow([], 0))


def canonical(labels):
    seen = {}
    return tuple(seen.setdefault(int(c), len(seen)) for c in labels)


class Walk(Chain):
    """A chain that counts the partitions it visits."""

    def run(self):
        self.visits = {}
        return super().run()

    def clusters(self, labels, step):
        key = canonical(labels)
        self.visits[key] = self.visits.get(key, 0) + 1
        return super().clusters(labels, step)


def toy(data=1, **options):
    r = np.random.default_rng(data)
    resp = r.uniform(0.05, 0.6, (5, 4))
    pairs = list(itertools.combinations(range(5), 2))
    q = r.uniform(0.1, 0.6, len(pairs))
    edges = (np.array([a for a, _ in pairs]), np.array([b for _, b in pairs]), q)
    p = Params(beta=0.4, model_words=4, rule="kl_gain", steps=options.pop("steps", 12_000), patience=10**9, **options)
    return Walk(range(5), resp, edges, np.full(4, 0.2), p)


def exact(chain):
    e = {p: math.exp(-chain.energy(np.array(p) + 1)) for p in partitions(5)}
    z = sum(e.values())
    return {p: v / z for p, v in e.items()}


def distance(chain):
    chain.run()
    n = sum(chain.visits.values())
    law = exact(chain)
    return 0.5 * sum(abs(chain.visits.get(p, 0) / n - v) for p, v in law.items())


@pytest.mark.parametrize("move", ["single", "composite"])
def test_chains_reach_the_exact_law(move):
    assert len(partitions(5)) == 52
    assert distance(toy(move=move)) < 0.09


def test_the_ratio_without_the_second_level_has_another_law():
    assert distance(toy(move="composite", fidelity="paper")) > 0.15


def test_energy_is_kept_incrementally():
    for move in ("single", "composite"):
        chain = toy(move=move, steps=300)
        trace, best, last = chain.run()
        assert abs(trace[-1][2] - chain.energy(last)) < 1e-8
        assert abs(min(t[2] for t in trace) - chain.energy(best)) < 1e-8


def test_the_same_seed_gives_the_same_chain():
    assert toy(steps=200).run()[0] == toy(steps=200).run()[0] != toy(steps=200, seed=1).run()[0]


def test_best_state_is_the_optimum_of_all_partitions():
    chain = toy(steps=3000)
    _, best, _ = chain.run()
    assert abs(chain.energy(best) - min(chain.energy(np.array(p) + 1) for p in partitions(5))) < 1e-9


def test_joint_acceptance_and_any_scope_run():
    for options in ({"fidelity": "paper"}, {"scope": "any", "fidelity": "paper"}, {"initial": "singletons"}, {"initial": "components"}, {"initial": "random"}):
        chain = toy(steps=100, **options)
        trace, best, last = chain.run()
        assert abs(trace[-1][2] - chain.energy(last)) < 1e-8


def test_fast_draws_agree_with_spark(spark):
    from pyspark.sql import functions as F

    from unicat.rng import fast01, fast01_np

    rows = spark.range(5).select(fast01(7, 3, "c", F.col("id"), F.col("id") * 10 - 20).alias("u")).collect()
    assert [r.u for r in rows] == fast01_np(7, 3, "c", np.arange(5), np.arange(5) * 10 - 20).tolist()


def _graph(spark):
    r = np.random.default_rng(5)
    n, k = 24, 6
    resp = np.where(r.random((n, k)) < 0.6, r.uniform(0.1, 0.7, (n, k)), 0)
    resp[:12, 0] = resp[12:, 1] = 0.8
    resp[23] = 0  # an item without any word
    pairs = [(a, b) for a in range(n) for b in range(a + 1, n) if r.random() < (0.4 if (a < 12) == (b < 12) else 0.05)]
    q = np.round(r.uniform(0.2, 0.7, len(pairs)), 6)
    ids = np.arange(n) * 3 + 5
    resp_df = spark.createDataFrame([(int(ids[i]), int(f), "S", float(resp[i, f])) for i, f in zip(*np.nonzero(resp))], "item_id long, feat int, wtype string, r double")  # noqa: B905
    edges = spark.createDataFrame([(int(ids[a]), int(ids[b]), float(x)) for (a, b), x in zip(pairs, q, strict=True)], "s long, t long, q double")
    return resp_df, edges, spark.createDataFrame([(int(i),) for i in ids], "item_id long"), np.full(k, 0.3)


@pytest.mark.parametrize("move", ["single", "composite"])
def test_distributed_chain_has_the_trace_of_the_local_one(spark, move, monkeypatch):
    from unicat.operators import sampler

    resp, edges, items, e_0 = _graph(spark)
    p = Params(beta=0.5, model_words=4, rule="kl_gain", steps=3, patience=99, seed=3, move=move, p_pick=0.5)
    local = sampler.run_chains(spark, resp, edges, 6, e_0, p, [3], items)
    want = [tuple(r)[1:8] for r in local.where("step >= 0").orderBy("step").collect()]
    trace, best = sampler.distributed_chain(resp, edges, items, e_0, p, 3)
    for a, b in zip(trace, want, strict=True):
        assert (a[0], a[1], a[3], a[5], a[6]) == (b[0], b[1], b[3], b[5], b[6]) and abs(a[2] - b[2]) < 1e-6 and abs(a[4] - b[4]) < 1e-6
    assert {r.item_id: r.cat for r in best.collect()} == {r.item_id: r.cat for r in sampler.best_labels(local).collect()} and best.count() == 24
    monkeypatch.setattr(sampler, "LOCAL_BYTES", 100)
    with pytest.raises(ValueError):
        sampler.run_chains(spark, resp, edges, 6, e_0, p, [3], items)


def test_every_chain_has_a_task_of_its_own(spark):
    from unicat.operators import sampler

    resp, edges, items, e_0 = _graph(spark)
    assert spark.range(0, 10, 1, 10).rdd.glom().map(len).collect() == [1] * 10
    got = sampler.run_chains(spark, resp, edges, 6, e_0, Params(steps=5), list(range(10)), items)
    assert got.where("step = -1").count() == 10


def test_params_scale_beta():
    assert replace(Params(), beta_mode="per_item").beta_for(500) == 150


def test_two_gains_in_one_pass_are_the_gains(monkeypatch):
    from unicat.operators.sampler import Model

    r = np.random.default_rng(2)
    model = Model(Params(model_words=6), np.round(r.uniform(0.05, 0.3, 20), 1), 300.0, {})
    for held in (20, 9, 6, 3, 0):
        for total in (r.uniform(0.1, 5, (2, 20)), r.integers(1, 4, (2, 20)).astype(float)):  # the latter has ties
            total[:, held:] = 0
            for got, n, x in zip(model.two_gains((7, 9), total), (7, 9), total, strict=True):
                at = np.flatnonzero(x > 1e-12)
                at = at[np.argsort(-(x / n - model.e_0)[at], kind="stable")[:6]]
                f, o = np.clip(x[at] / n, 1e-6, 1 - 1e-6), model.e_0[at]
                assert got == pytest.approx(n * float((f * np.log(f / o) + (1 - f) * np.log((1 - f) / (1 - o))).sum()), abs=1e-9)


def test_a_step_over_many_categories_sorts_them_once():
    """Twenty thousand categories at the start: a pick must not look at all of them."""
    r = np.random.default_rng(3)
    n = 20_000
    resp = (np.arange(n + 1), r.integers(0, 8, n), r.uniform(0.1, 0.8, n))
    chain = Chain(range(n), resp, (np.zeros(0, int), np.zeros(0, int), np.zeros(0)), np.full(8, 0.2), Params(steps=1, initial="singletons", move="composite"))
    model = chain.model(chain.start())
    assert model.cats == sorted(model.held) == list(range(1, n + 1))
    atoms = chain.clusters(chain.start(), 1)
    picked = chain.picks(atoms, 1)
    cells, _ = chain.cells(atoms, chain.start() - 1, picked)
    cells.label = cells.label + 1
    model.step(cells, picked, chain.ids, 1)
    assert model.cats == sorted(model.held) and len(model.cats) < n and sum(v[0] for v in model.held.values()) == n
    labels, totals = cells.label, np.zeros((n + len(picked) + 2, 8))
    np.add.at(totals, (labels[resp[0][:-1]], resp[1]), resp[2])
    assert all(np.allclose(v[1], totals[c]) for c, v in model.held.items())


def test_chains_of_different_params_run_side_by_side(spark):
    from unicat.operators import sampler

    resp, edges, items, e_0 = _graph(spark)
    kinds = [Params(steps=4, initial=x, beta=0.5, model_words=w) for x, w in (("one", 4), ("singletons", 3))]
    both = sampler.run_chains(spark, resp, edges, 6, e_0, kinds, [1, 2], items)
    for i, p in enumerate(kinds):
        alone = sampler.run_chains(spark, resp, edges, 6, e_0, p, [1 + i], items)
        cut = lambda t, c: [tuple(r)[1:9] for r in t.where(f"chain = {c}").orderBy("step").collect()]
        assert cut(both, i) == cut(alone, 0)


@pytest.mark.parametrize("options", [{"initial": "singletons"}, {"initial": "one", "rule": "kl_gain"}, {"initial": "random", "fidelity": "paper", "scope": "any"}])
def test_proposals_are_weighed_many_at_a_time_with_the_same_trace(options, monkeypatch):
    """Categories are weighed ahead for later proposals, fewer passes than proposals, and an accepted move is never overlooked."""
    from unicat.operators import sampler

    r = np.random.default_rng(5)
    n, passes, proposals = 400, [], []
    resp = np.where(r.uniform(size=(n, 20)) < 0.5, np.round(r.uniform(0.1, 0.9, (n, 20)), 1), 0.0)  # with ties, and categories of few words
    pairs = np.unique(np.sort(r.integers(0, n, (900, 2)), axis=1), axis=0)
    pairs = pairs[pairs[:, 0] != pairs[:, 1]]
    edges = pairs[:, 0], pairs[:, 1], r.uniform(0.05, 0.5, len(pairs))
    p = Params(**{"beta": 2.0, "model_words": 6, "steps": 25, "patience": 99} | options)
    chain = Chain(range(n), resp, edges, np.full(20, 0.2), p)
    kl_of, picks = sampler.Model.kl_of, Chain.picks
    monkeypatch.setattr(sampler.Model, "kl_of", lambda self, e, o: passes.append(1) or kl_of(self, e, o))
    monkeypatch.setattr(Chain, "picks", lambda self, atoms, step: proposals.extend(out := picks(self, atoms, step)) or out)
    trace, best, last = chain.run()
    assert abs(trace[-1][2] - chain.energy(last)) < 1e-8 and abs(min(t[2] for t in trace) - chain.energy(best)) < 1e-8
    if options["initial"] == "singletons":
        assert len(passes) < 0.75 * len(proposals)
    monkeypatch.setattr(sampler, "AHEAD", 1)
    again = Chain(range(n), resp, edges, np.full(20, 0.2), p).run()
    assert again[0] == trace and np.array_equal(again[1], best)
