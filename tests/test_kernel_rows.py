"""The merge kernel keeps its rows as arrays: same merges as by pricing every partition anew, and in time."""

import time

import numpy as np
import pytest

from flowregions.functions.numbers import lfact, lmulti
from flowregions.plans import kernel, mcmc


def drawn(n, near, seed=3):
    rng = np.random.default_rng(seed)
    at = np.concatenate([rng.choice(np.delete(np.arange(n), k), near, replace=False) for k in range(n)])
    src, w = np.repeat(np.arange(n), near), rng.integers(1, 5, n * near)
    return kernel.Network(np.arange(n), src, at, w, src, at)


def length(net, model, label):
    """The total of a partition from scratch."""
    groups = np.unique(label)
    block = lambda x: np.array([[x[(label[net.src] == r) & (label[net.dst] == s)].sum() for s in groups] for r in groups])
    size, e, w = np.array([(label == g).sum() for g in groups]), block(net.e), block(net.w)
    ends = w if model.ends == "w" else e
    start = kernel._State(net, model)
    return model.constant(net.n, len(groups), int(e.sum()), int(w.sum())) + model.group(size, ends.sum(axis=1), ends.sum(axis=0), np.diag(ends)).sum() + model.pair(np.outer(size, size), e, w).sum() + model.fixed(net.e, net.w, start.k_out, start.k_in)


@pytest.mark.parametrize("rep", ["mg", "w"])
@pytest.mark.parametrize("dc", [False, True])
def test_each_merge_is_the_best_of_all_that_touch(rep, dc):
    net, model = drawn(14, 3), kernel.BlockModel(rep, dc)
    path = kernel.greedy(net, model)
    for p, q in zip(path, path[1:]):
        label = mcmc.labels_at(path, net.n, p[0])
        pairs = sorted({(min(label[i], label[j]), max(label[i], label[j])) for i in range(net.n) for j in net.touch[i] if label[i] != label[j]})
        totals = [length(net, model, np.where(label == s, r, label)) for r, s in pairs]
        assert q[5] == pytest.approx(min(totals), abs=1e-6)
        assert q[5] == pytest.approx(totals[pairs.index((q[2], q[3]))], abs=1e-6)


def test_multiset_lengths_by_the_table_and_beyond():
    for n, k in ((1, 0), (7, 3), (10**5, 12), (2 * 10**6, 3)):
        assert float(lmulti(np.array([n]), np.array([k]))[0]) == pytest.approx(float(lfact(n + k - 1) - lfact(k) - lfact(n - 1)), abs=1e-9)


def test_rows_are_not_turned_into_arrays_one_by_one(monkeypatch):
    """Pricing calls of a merge do not grow with the clusters that touch; before, 25 and one array for each."""
    net, calls, model = drawn(300, 8), [0], kernel.BlockModel("mg")
    priced = kernel.BlockModel.pair
    monkeypatch.setattr(kernel.BlockModel, "pair", lambda *a: (calls.__setitem__(0, calls[0] + 1), priced(*a))[1])
    began = time.monotonic()
    path = kernel.greedy(net, model)
    assert len(path) == 300 and calls[0] < 300 * 14
    assert time.monotonic() - began < 30


@pytest.mark.parametrize("rep", ["mg", "w"])
def test_changes_of_gains_are_priced_once_for_the_merged_pair(monkeypatch, rep):
    """A merge prices a candidate beside it once, 6 blocks; before, for each of the two clusters and for both, 36."""
    net, priced, calls = drawn(400, 8), [0], [0]
    pair = kernel.BlockModel.pair

    def counted(model, nn, e, w):
        calls[0], priced[0] = calls[0] + 1, priced[0] + max(np.size(nn), np.size(w))
        return pair(model, nn, e, w)

    monkeypatch.setattr(kernel.BlockModel, "pair", counted)
    path = kernel.greedy(net, kernel.BlockModel(rep))
    assert len(path) == 400 and calls[0] < 400 * 8
    assert priced[0] < 5_000_000  # 7.4 and 8.3 million before


def test_gains_kept_are_those_priced_anew(monkeypatch):
    """Gains that were only changed along the way equal those of the same partition priced from its units."""
    net, model = drawn(120, 5), kernel.BlockModel("mg")
    every, left = [], kernel._Candidates.best
    monkeypatch.setattr(kernel._Candidates, "best", lambda t: (every.append((t.u.copy(), t.v.copy(), t.gains[: len(t.u)].copy())), left(t))[1])
    path = kernel.greedy(net, model)
    for k in (20, 70, 110):
        label, (u, v, gains) = mcmc.labels_at(path, net.n, k), every[k]
        here, some = path[k][5] - model.constant(net.n, net.n - k, int(net.e.sum()), int(net.w.sum())), np.flatnonzero(u < net.n)[:: max(1, 110 - k)]
        for i in some.tolist():
            there = length(net, model, np.where(label == v[i], u[i], label)) - model.constant(net.n, net.n - k - 1, int(net.e.sum()), int(net.w.sum()))
            assert gains[i] == pytest.approx(there - here, abs=1e-7)
