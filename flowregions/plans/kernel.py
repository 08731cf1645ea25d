"""The exact greedy merge of one network, in the memory of one task.

Clusters keep sparse rows of blocks, as arrays. All candidate gains are kept. A merge computes anew the candidates of
the merged cluster, and changes those candidates (u, v) where u or v has flow to or from the merged pair, by
J(u and v together) - J(u) - J(v), J(x) being by how much the blocks of x with the pair become longer; no other gain
depends on it. Each cluster lists the places of its candidates, and the best is found by the least gains of groups of places.
"""

from __future__ import annotations

import heapq
from collections.abc import Callable
from dataclasses import dataclass

import numpy as np

from flowregions.functions.numbers import TABLE, lchoose, lcompositions, lfact, lmulti, table


#: Pairs of units priced together at the start, and places of candidates that share a least gain.
SOME, PLACES = 1 << 14, 128


@dataclass(frozen=True)
class Objective:
    """Any total of the form constant + sum over groups + sum over ordered pairs of groups, to be made small.

    constant(n, b, e, w): of units, groups, edges and weight. group(n, out, into, own): of a group's units, what leaves
    and enters it, and what stays inside. pair(nn, e, w): of the unit pairs, edges and weight of a block; it must be 0
    for a block without edges, which is what lets a merge look at neighbours only. ends: whether out, into and own
    count weight ("w") or edges ("e"). All but ``constant`` take numpy arrays.
    """

    constant: Callable = lambda n, b, e, w: 0.0
    group: Callable = lambda n, out, into, own: np.zeros(np.shape(n))
    pair: Callable = lambda nn, e, w: np.zeros(np.shape(e))
    ends: str = "w"

    def fixed(self, e: np.ndarray, w: np.ndarray, k_out: np.ndarray, k_in: np.ndarray) -> float:  # noqa: ARG002
        return 0.0

    def check(self) -> None:
        """Raises where an empty block costs something."""
        sizes, none = np.array([1, 4, 100]), np.zeros(3, dtype=np.int64)
        if np.abs(self.pair(sizes, none, none)).max() > 1e-12:
            raise ValueError("the pair term must be 0 for a block without edges")


class BlockModel(Objective):
    """Terms of the block model: constant, per group, per ordered pair of groups. A pair without edges costs nothing."""

    def __init__(self, rep: str = "w", degree_corrected: bool = False):
        for name, value in (("rep", rep), ("dc", degree_corrected), ("ends", "w" if rep == "mg" else "e")):
            object.__setattr__(self, name, value)

    def constant(self, n: int, b: int, e: int, w: int) -> float:
        bits = lchoose(n - 1, b - 1) + lfact(n) + lmulti(b * b, w)
        return float(bits if self.rep == "mg" else bits + lmulti(b * b, e))

    def group(self, n, out, into, own=None):  # noqa: ARG002
        """out, into: edges (or their weights) that leave and enter, for the degree-corrected model."""
        bits = -lfact(n)
        return bits + lfact(out) + lfact(into) + lmulti(n, out) + lmulti(n, into) if self.dc else bits

    def pair(self, nn, e, w):
        if self.rep == "mg":
            return -lfact(w) if self.dc else lmulti(nn, w)
        return (-lfact(e) if self.dc else lchoose(nn, e)) + lcompositions(w, e)

    def fixed(self, e: np.ndarray, w: np.ndarray, k_out: np.ndarray, k_in: np.ndarray) -> float:
        """What no partition changes."""
        if not self.dc:
            return 0.0
        return float((lfact(w).sum() if self.rep == "mg" else 0.0) - lfact(k_out).sum() - lfact(k_in).sum())


def modularity_objective(w: float) -> Objective:
    """Negated directed modularity of a network of total weight w, as a sum over groups alone."""
    return Objective(group=lambda n, out, into, own: -(own / w - out * (into / w) / w))  # noqa: ARG005


def poisson_objective() -> Objective:
    """Poisson block model in bits with half the logarithm of the weight for each block's rate: an objective of the user's own kind."""
    return Objective(constant=lambda n, b, e, w: b * b * 0.5 * float(np.log2(max(w, 1))), pair=lambda nn, e, w: np.where(w > 0, -w * np.log2(np.maximum(w, 1) / np.maximum(nn, 1)), 0.0))  # noqa: ARG005


class Network:
    """Units 0..n-1 in order of their ids, flows between them, and which touch."""

    def __init__(self, units: np.ndarray, src: np.ndarray, dst: np.ndarray, w: np.ndarray, a: np.ndarray, b: np.ndarray, e: np.ndarray | None = None):
        self.units = np.unique(units)
        n = self.n = len(self.units)
        self.src, self.dst, self.w = np.searchsorted(self.units, src), np.searchsorted(self.units, dst), np.asarray(w, dtype=np.int64)
        #: edges behind each flow: one, but in the network of groups that a hierarchy describes
        self.e = np.ones(len(self.w), dtype=np.int64) if e is None else np.asarray(e, dtype=np.int64)
        a, b = np.searchsorted(self.units, a), np.searchsorted(self.units, b)
        self.touch: list[set[int]] = [set() for _ in range(n)]
        for i, j in zip(a.tolist(), b.tolist(), strict=True):
            if i != j:
                self.touch[i].add(j)
                self.touch[j].add(i)

    def pairs(self) -> tuple[np.ndarray, np.ndarray]:
        """The pairs of units that touch, the smaller first, in order."""
        long = np.fromiter(map(len, self.touch), dtype=np.int64, count=self.n)
        u, v = np.arange(self.n).repeat(long), np.fromiter((j for t in self.touch for j in t), dtype=np.int64, count=int(long.sum()))
        key = np.sort((u * self.n + v)[u < v])
        return key // self.n, key % self.n


class _State:
    """Rows of clusters as arrays: keys (an end x of what leaves, n + x of what enters), edges and weights. A merge writes the row of the cluster that
    stays; the other rows go on naming the one that is gone, ``now`` says where it went, and entries that have come to name the same cluster are added up as they are read."""

    def __init__(self, net: Network, model: Objective):
        self.model, n = model, net.n
        self.n = n
        #: lengths that look at weights alone take one column of values, others edges and weights
        self.thin = type(model) is BlockModel and model.rep == "mg"
        self.lean = self.thin and not model.dc
        self.size = np.ones(2 * n, dtype=np.int64)
        self.now = np.arange(2 * n)
        self.members = [np.array([x]) for x in range(n)]
        values = net.w[:, None] if self.thin else np.stack([net.e, net.w], axis=1)
        key, values = self.added(np.concatenate([net.src * (2 * n) + net.dst, net.dst * (2 * n) + n + net.src]), np.concatenate([values, values]))
        ends = np.searchsorted(key // (2 * n), np.arange(n + 1)).tolist()
        of, at = key // (2 * n), key % (2 * n)
        self.rows = [(at[i:j].copy(), values[i:j].copy()) for i, j in zip(ends[:-1], ends[1:], strict=True)]
        one = net.w if model.ends == "w" else net.e
        self.k_out = np.bincount(net.src, weights=one, minlength=n).astype(np.int64)
        self.k_in = np.bincount(net.dst, weights=one, minlength=n).astype(np.int64)
        loops = net.src == net.dst
        self.own = np.bincount(net.src[loops], weights=one[loops], minlength=n).astype(np.int64)
        #: edges and weight inside each cluster
        self.inner = np.stack([np.bincount(net.src[loops], weights=x[loops], minlength=n).astype(np.int64) for x in (net.e, net.w)])
        #: length of each cluster's blocks with others
        there = at % n != of
        ones = np.ones(int(there.sum()), dtype=np.int64)
        self.blocks = np.bincount(of[there], weights=self.price(ones, values[there]), minlength=n)
        #: a row under way, zero but where it is laid out; and two at once, out and in
        self.wide = np.zeros((2 * n, values.shape[1]), dtype=np.int64)
        self.two = np.zeros((2, 2 * n, values.shape[1]), dtype=np.int64)
        self.longer = np.zeros(n)

    @staticmethod
    def added(key: np.ndarray, values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Distinct keys in order, with the sums of their values."""
        order = key.argsort(kind="stable")
        key, values = key.take(order), values.take(order, axis=0)
        starts = np.ones(len(key), dtype=bool)
        np.not_equal(key[1:], key[:-1], out=starts[1:])
        first = starts.nonzero()[0]
        return (key.take(first), np.add.reduceat(values, first, axis=0)) if len(first) < len(key) else (key, values)

    def price(self, nn: np.ndarray, values: np.ndarray) -> np.ndarray:
        w = values[..., -1]
        if self.lean and nn.size and int(nn.max()) + int(w.max()) <= TABLE:  # as lmulti, which here has nothing to look after
            known, nn = table(), nn - 1
            found = known.take(nn + w)
            found -= known.take(w)
            found -= known.take(nn)
            return found
        found = self.model.pair(nn, values[..., 0], w)
        return found if np.shape(found) == nn.shape else np.broadcast_to(found, nn.shape)

    @staticmethod
    def kind(nn: np.ndarray, values: np.ndarray) -> np.ndarray | None:
        """One number for each block, the same for equal ones; none where the numbers are too large for that."""
        out, room = nn, 1 << 62
        for k in range(values.shape[1]):
            wide = int(values[:, k].max(initial=0)) + 1
            room //= wide
            if int(nn.max(initial=0)) >= room:
                return None
            out = out * wide + values[:, k]
        return out

    def row(self, x: int) -> tuple[np.ndarray, np.ndarray]:
        at, values = self.rows[x]
        to = self.now.take(at)
        if (to != at).any():
            at, values = self.rows[x] = self.added(to, values)
        return at, values

    def beside(self, r: int, s: int) -> np.ndarray:
        """Other clusters that r or s have flows with."""
        ends = np.concatenate([self.row(r)[0], self.row(s)[0]]) % self.n
        ends = np.unique(ends)
        return ends[(ends != r) & (ends != s)]

    def together(self, t: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(position in t, keys, values) of the rows of all of t."""
        ats, rows = zip(*[self.rows[x] for x in t.tolist()], strict=True)
        long = np.fromiter(map(len, ats), dtype=np.int64, count=len(ats))
        of = np.arange(len(t)).repeat(long)
        at, values = np.concatenate(ats), np.concatenate(rows)
        to = self.now.take(at)
        if (to != at).any():
            key, values = self.added(of * (2 * self.n) + to, values)
            of = key // (2 * self.n)
            to = key - of * (2 * self.n)
            ends = np.searchsorted(of, np.arange(len(t) + 1))
            for k in np.flatnonzero(3 * np.diff(ends) < 2 * long).tolist():  # a copy is worth its time where the row has become much shorter
                self.rows[t[k]] = to[ends[k] : ends[k + 1]].copy(), values[ends[k] : ends[k + 1]].copy()
        return of, to, values

    def alone(self, u: np.ndarray, v: np.ndarray) -> np.ndarray:
        """Change of all group and pair terms when two units merge, for each pair (u, v), before any merge."""
        n, found = self.n, [np.zeros(0)]
        long = np.array([len(x[0]) for x in self.rows])
        begin = np.cumsum(long) - long
        every, values = (np.concatenate([x[k] for x in self.rows]) for k in (0, 1))
        known = np.repeat(np.arange(n), long) * (2 * n) + every
        for k in range(0, len(u), SOME):
            a, b = u[k : k + SOME], v[k : k + SOME]
            m, ends, one = len(a), np.concatenate([a, b]), np.ones(len(a), dtype=np.int64)
            take = np.repeat(begin[ends] - np.cumsum(long[ends]) + long[ends], long[ends]) + np.arange(long[ends].sum())
            of = np.repeat(np.arange(2 * m) % m, long[ends])
            at = every[take] % n
            third = (at != a[of]) & (at != b[of])
            key, sums = self.added((of * (2 * n) + every[take])[third], values[take][third])
            cost = np.bincount(key // (2 * n), weights=self.price(np.full(len(key), 2), sums), minlength=m)
            ways = []
            for x in (a * (2 * n) + b, a * (2 * n) + n + b):
                at = np.minimum(np.searchsorted(known, x), max(len(known) - 1, 0))
                ways.append(np.where((known[at] == x)[:, None], values[at], 0) if len(known) else np.zeros((m, values.shape[1]), dtype=np.int64))
            found.append(cost + self.ends(a, b, one, one, ways[0], ways[1]))
        return np.concatenate(found)

    def ends(self, r: np.ndarray, t: np.ndarray, nr: np.ndarray, nt: np.ndarray, to: np.ndarray, back: np.ndarray) -> np.ndarray:
        """What a merge of r and t changes, but for the new lengths of their blocks with third clusters."""
        g, m, both = self.model.group, len(t), nr + nt
        own_r, own_t = (self.inner[-1:, x].T if self.thin else self.inner[:, x].T for x in (r, t))
        inside = self.own[r] + self.own[t] + (to + back)[:, -1 if self.model.ends == "w" else 0]
        join = lambda f, whole: np.concatenate([whole, f[t], f[r]])
        cost = g(np.concatenate([both, nt, nr]), join(self.k_out, self.k_out[r] + self.k_out[t]), join(self.k_in, self.k_in[r] + self.k_in[t]), join(self.own, inside))
        block = self.price(np.concatenate([both * both, nr * nt, nr * nt, nt * nt, nr * nr]), np.concatenate([own_r + own_t + to + back, to, back, own_t, own_r])).reshape(5, m)
        return cost[:m] - cost[m : 2 * m] - cost[2 * m :] + block[0] + block[1] + block[2] - block[3] - block[4] - self.blocks[r] - self.blocks[t]

    def gains(self, r: int, mine: tuple, t: np.ndarray) -> np.ndarray:
        """Change of all group and pair terms when r, whose row ``mine`` is laid out, and each of t merge."""
        n, size, (at, values), m = self.n, self.size, mine, len(t)
        nt, nr = size[t], np.full(m, size[r])
        both = nr + nt
        to, back = self.wide.take(t, axis=0), self.wide.take(n + t, axis=0)
        total = self.ends(np.full(m, r), t, nr, nt, to, back)
        # r's blocks with third clusters, as if the other had none there
        sizes, size_of = np.unique(both, return_inverse=True)
        there = (at != r) & (at != n + r)
        third, nu = values[there], size[at[there]]
        # many are of one size and have the same values: these are priced once
        kind = self.kind(nu, third)
        first, many = (np.unique(kind, return_index=True, return_counts=True)[1:]) if kind is not None else (slice(None), np.ones(len(nu)))
        nu, third = nu[first], third[first]
        cost = (self.price(sizes[:, None] * nu, np.broadcast_to(third, (len(sizes), *third.shape))) @ many)[size_of]
        # the other's blocks with third clusters, and what the sum of both adds to the above
        of, key, values = self.together(t)
        side = key % n
        there = ((side != r) & (side != t.take(of))).nonzero()[0]
        of, key, values = of.take(there), key.take(there), values.take(there, axis=0)
        nb, here = both.take(of) * size.take(key), self.wide.take(key, axis=0)
        k = len(of)
        change = self.price(np.concatenate([nb, nb, nt * both, nt * both]), np.concatenate([here + values, here, to, back]))
        return total + cost + np.bincount(of, weights=change[:k] - change[k : 2 * k], minlength=m) - change[2 * k : 2 * k + m] - change[2 * k + m :]

    def merge(self, r: int, s: int, u: np.ndarray, v: np.ndarray) -> np.ndarray:
        """Merges s into r; the change of the gains of the pairs (u, v) of other clusters.

        The blocks of a cluster x with r and s become longer by J(x) when these two merge, and the gain of (u, v) by
        J(u and v together) - J(u) - J(v).
        """
        n, size, two, price = self.n, self.size, self.two, self.price
        (at, values), (more, others) = self.row(r), self.row(s)
        two[0][at], two[1][more] = values, others
        key, sums = self.added(self.now[np.concatenate([at, more])], np.concatenate([values, others]))
        ends = key % n
        far = (ends != r) & (ends != s)
        x, nr, ns = key[far], int(size[r]), int(size[s])
        nx, k = size[x], len(x)
        cost = price(np.concatenate([nx * (nr + ns), nx * nr, nx * ns]), np.concatenate([sums[far], two[0][x], two[1][x]]))
        longer = self.longer
        np.add.at(longer, ends[far], cost[:k] - cost[k : 2 * k] - cost[2 * k :])
        nb, m, nu, nv = size.take(u) + size.take(v), len(u), n + u, n + v
        left, right = ([row.take(u, axis=0) + row.take(v, axis=0), row.take(nu, axis=0) + row.take(nv, axis=0)] for row in two)
        nn = [nb * (nr + ns), nb * nr, nb * ns]
        after = price(np.concatenate([nn[0], nn[0], nn[1], nn[1], nn[2], nn[2]]), np.concatenate([left[0] + right[0], left[1] + right[1], *left, *right]))
        after = after.reshape(6, m)
        change = after[0] + after[1] - after[2] - after[3] - after[4] - after[5] - longer.take(u) - longer.take(v)
        touched = np.unique(ends[far])
        self.blocks[touched] += longer[touched]
        longer[touched] = 0.0
        two[0][at], two[1][more] = 0, 0
        # the merged cluster's row names itself by r
        gone = (key == s) | (key == n + s)
        self.now[self.members[s]], self.now[n + self.members[s]] = r, n + r
        self.members[r], self.members[s] = np.concatenate([self.members[r], self.members[s]]), None
        if gone.any():
            key, sums = self.added(self.now[key], sums)
        empty = np.zeros(0, dtype=np.int64), np.zeros((0, sums.shape[1]), dtype=np.int64)
        self.rows[r], self.rows[s] = (key, sums), empty
        inner = sums[key == r].sum(axis=0)
        self.inner[:, r] = inner
        size[r] = size[n + r] = nr + ns
        self.k_out[r] += self.k_out[s]
        self.k_in[r] += self.k_in[s]
        self.own[r] = self.inner[1 if self.model.ends == "w" else 0, r]
        there = (key != r) & (key != n + r)
        self.blocks[r] = float(price(size[key[there]] * (nr + ns), sums[there]).sum())
        return change


class _Candidates:
    """Pairs of clusters that touch, and their gains. A pair has a place, which both of its clusters list; empty places name cluster n, and lists may go on naming them."""

    def __init__(self, u: np.ndarray, v: np.ndarray, gains: np.ndarray, n: int):
        self.n, self.there, self.is_met, self.mark = n, len(u), np.zeros(n + 1, dtype=bool), np.full(n + 1, -1)
        self.fill(u, v, gains)

    def fill(self, u: np.ndarray, v: np.ndarray, gains: np.ndarray) -> None:
        self.u, self.v, m = u.copy(), v.copy(), len(u)
        wide = np.full(-(-max(m, 1) // PLACES) * PLACES, np.inf)
        wide[:m] = gains
        #: gains, and the least of each PLACES of them
        self.gains, self.in_rows = wide, wide.reshape(-1, PLACES)
        self.least = self.in_rows.min(axis=1)
        end = np.concatenate([u, v])
        order = np.argsort(end, kind="stable")
        ends = np.searchsorted(end[order], np.arange(self.n + 1)).tolist()
        order %= max(m, 1)
        self.places = [order[i:j] for i, j in zip(ends[:-1], ends[1:], strict=True)]

    def set(self, places: np.ndarray, gains: np.ndarray) -> None:
        self.gains[places] = gains
        if 4 * len(places) < len(self.least):
            rows = places // PLACES
            self.least[rows] = self.in_rows[rows].min(axis=1)
        else:
            hit = np.zeros(len(self.least), dtype=bool)
            hit[places // PLACES] = True
            self.least[hit] = self.in_rows[hit].min(axis=1)

    def best(self) -> int:
        """The least gain (to 1e-9), of equal ones the smallest pair."""
        least = self.least.min()
        rows = np.flatnonzero(self.least <= least + 1e-8)
        at = (rows[:, None] * PLACES + np.arange(PLACES)).ravel()
        near = at[self.gains[at] <= least + 1e-8]  # those that may round to the least
        rounded = np.round(self.gains[near], 9)
        ties = near[rounded == rounded.min()]
        return int(ties[np.lexsort((self.v[ties], self.u[ties]))[0]] if len(ties) > 1 else ties[0])

    def join(self, best: int, r: int, s: int) -> tuple[np.ndarray, np.ndarray]:
        """(places, other ends) of the pairs that r has once s is part of it; the other places of s are emptied."""
        if 2 * self.there < len(self.u):  # half of the places are empty
            full = np.flatnonzero(self.u < self.n)
            best = int(np.searchsorted(full, best))
            self.fill(self.u[full], self.v[full], self.gains[full])
        u, v = self.u, self.v
        own, others = (k[(u[k] < self.n) & (k != best)] for k in (self.places[r], self.places[s]))
        near, far = u[own] + v[own] - r, u[others] + v[others] - s
        self.mark[near] = own
        twice = self.mark[far] >= 0
        self.mark[near] = -1
        gone = np.append(others[twice], best)
        u[gone], v[gone] = self.n, self.n
        self.set(gone, np.inf)
        self.there -= len(gone)
        self.places[r], self.places[s] = np.concatenate([own, others[~twice]]), gone[:0]
        return self.places[r], np.concatenate([near, far[~twice]])

    def of(self, clusters: np.ndarray) -> np.ndarray:
        """Places of the pairs that have one of ``clusters``."""
        if not len(clusters):
            return clusters
        lists = [self.places[x] for x in clusters.tolist()]
        long = np.fromiter(map(len, lists), dtype=np.int64, count=len(lists))
        met = self.is_met
        met[clusters] = True
        if 4 * long.sum() > len(self.u):
            some = (met.take(self.u) | met.take(self.v)).nonzero()[0]
        else:
            some = np.concatenate(lists)
            first, met[self.n] = self.u.take(some), True
            some = some[(first == clusters.repeat(long)) | ~met.take(first)]
        met[clusters] = met[self.n] = False
        return some


def start_length(net: Network, model: Objective, state: _State | None = None) -> float:
    """The total of all units alone."""
    state = state or _State(net, model)
    e, w = int(net.e.sum()), int(net.w.sum())
    ones = np.ones(len(net.w), dtype=np.int64)
    pairs = model.pair(ones, net.e, net.w).sum() if len(net.w) else 0.0
    return model.constant(net.n, net.n, e, w) + float(model.group(state.size[: net.n], state.k_out, state.k_in, state.own).sum()) + float(pairs) + model.fixed(net.e, net.w, state.k_out, state.k_in)


def greedy(net: Network, model: Objective, stop: str = "full", b: int | None = None) -> list[tuple[int, int, int, int, float, float]]:
    """(step, groups, kept, absorbed, gain without the constant, total) of each merge; step 0 is the start.

    stop: "full" merges as long as clusters touch, "first_increase" until no merge helps, "fixed_b"
    until b groups are left. Equal gains (to 1e-9) go to the smallest pair.
    """
    model.check()
    state = _State(net, model)
    e, w, n = int(net.e.sum()), int(net.w.sum()), net.n
    now = start_length(net, model, state)
    path = [(0, n, -1, -1, 0.0, now)]
    u, v = net.pairs()
    cands = _Candidates(u, v, state.alone(u, v), n)
    left, before = n, model.constant(n, n, e, w)
    while cands.there and left > 1 and (stop != "fixed_b" or left > b):
        best = cands.best()
        r, s, gain = int(cands.u[best]), int(cands.v[best]), float(cands.gains[best])
        after = model.constant(n, left - 1, e, w)
        new = now + gain + after - before
        if stop == "first_increase" and new >= now:
            break
        places, near = cands.join(best, r, s)
        some = cands.of(state.beside(r, s))
        cands.set(some, cands.gains.take(some) + state.merge(r, s, cands.u.take(some), cands.v.take(some)))
        if len(near):
            mine = state.row(r)
            state.wide[mine[0]] = mine[1]
            cands.u[places], cands.v[places] = np.minimum(r, near), np.maximum(r, near)
            cands.set(places, state.gains(r, mine, near))
            state.wide[mine[0]] = 0
        left -= 1
        now, before = new, after
        path.append((len(path), left, r, s, gain, now))
    return path


def greedy_modularity(net: Network) -> list[tuple[int, int, int, int, float, float]]:
    """The same for modularity (negated, so that less is better). A merge changes only its own gains, so a heap with stale entries serves."""
    all_ = float(net.w.sum()) or 1.0
    flow: list[dict[int, float]] = [{} for _ in range(net.n)]
    own = 0.0
    for s, d, w in zip(net.src.tolist(), net.dst.tolist(), net.w.tolist(), strict=True):
        if s == d:
            own += w / all_
        else:
            flow[s][d] = flow[s].get(d, 0.0) + w
            flow[d][s] = flow[d].get(s, 0.0) + w
    out = np.bincount(net.src, weights=net.w, minlength=net.n) / all_
    into = np.bincount(net.dst, weights=net.w, minlength=net.n) / all_
    touch = [set(t) for t in net.touch]
    gain = lambda r, s: -(flow[r].get(s, 0.0) / all_ - out[r] * into[s] - out[s] * into[r])
    heap = [(round(gain(i, j), 12), i, j, 0, 0) for i in range(net.n) for j in touch[i] if i < j]
    heapq.heapify(heap)
    age, alive = [0] * net.n, [True] * net.n
    now, left = -(own - float((out * into).sum())), net.n
    path = [(0, left, -1, -1, 0.0, now)]
    while heap:
        g, r, s, ar, as_ = heapq.heappop(heap)
        if not (alive[r] and alive[s]) or age[r] != ar or age[s] != as_:
            continue
        g = gain(r, s)
        for u, w in flow[s].items():
            flow[u].pop(s, None)
            if u != r:
                flow[r][u] = flow[r].get(u, 0.0) + w
                flow[u][r] = flow[u].get(r, 0.0) + w
        flow[r].pop(s, None)
        out[r], into[r] = out[r] + out[s], into[r] + into[s]
        alive[s] = False
        touch[r] = (touch[r] | touch[s]) - {r, s}
        for t in touch[s]:
            touch[t].discard(s)
            if t != r:
                touch[t].add(r)
        age[r] += 1
        for t in touch[r]:
            i, j = min(r, t), max(r, t)
            heapq.heappush(heap, (round(gain(i, j), 12), i, j, age[i], age[j]))
        left -= 1
        now += g
        path.append((len(path), left, r, s, g, now))
    return path


def page_rank(net: Network, damping: float = 0.85, rounds: int = 200) -> tuple[np.ndarray, np.ndarray]:
    """Visit rates, and the flow along each edge in the stationary state."""
    n = net.n
    out = np.bincount(net.src, weights=net.w, minlength=n)
    step = net.w / out[net.src]
    p = np.full(n, 1.0 / n)
    for _ in range(rounds):
        moved = np.bincount(net.dst, weights=p[net.src] * step, minlength=n)
        p_new = damping * (moved + p[out == 0].sum() / n) + (1 - damping) / n
        if np.abs(p_new - p).sum() < 1e-14:
            break
        p = p_new
    return p, p[net.src] * step


def map_equation(p: np.ndarray, leaves: np.ndarray, visits: np.ndarray) -> float:
    """Two-level code length: p of the units, and for each group what leaves it and its visits."""
    h = lambda x: np.where(x > 0, x * np.log2(np.maximum(x, 1e-300)), 0.0)
    return float(h(leaves.sum()) - 2 * h(leaves).sum() - h(p).sum() + h(leaves + visits).sum())


def greedy_map_equation(net: Network) -> list[tuple[int, int, int, int, float, float]]:
    """The same for the map equation. Its total of leaving rates joins all groups, so all candidates are priced anew at each merge, in one vector step."""
    p, moved = page_rank(net)
    flow: list[dict[int, float]] = [{} for _ in range(net.n)]  # both ways together: all that a merge needs
    leaves = np.zeros(net.n)
    for s, d, x in zip(net.src.tolist(), net.dst.tolist(), moved.tolist(), strict=True):
        if s != d:
            leaves[s] += x
            flow[s][d] = flow[s].get(d, 0.0) + x
            flow[d][s] = flow[d].get(s, 0.0) + x
    visits = p.copy()
    touch = [set(t) for t in net.touch]
    h = lambda x: np.where(x > 0, x * np.log2(np.maximum(x, 1e-300)), 0.0)
    now, left = map_equation(p, leaves, visits), net.n
    path = [(0, left, -1, -1, 0.0, now)]
    total = leaves.sum()
    pairs = sorted({(min(i, j), max(i, j)) for i in range(net.n) for j in touch[i]})
    u, v = (np.array([q[k] for q in pairs], dtype=np.int64) for k in (0, 1))
    between = np.array([flow[i].get(j, 0.0) for i, j in pairs])
    while len(u):
        alone = leaves[u] + leaves[v]
        joint = alone - between
        gain = h(total + joint - alone) - h(total) - 2 * (h(joint) - h(leaves[u]) - h(leaves[v])) + h(joint + visits[u] + visits[v]) - h(leaves[u] + visits[u]) - h(leaves[v] + visits[v])
        rounded = np.round(gain, 12)
        ties = np.flatnonzero(rounded == rounded.min())
        best = ties[np.lexsort((v[ties], u[ties]))[0]]
        r, s, d, q = int(u[best]), int(v[best]), float(gain[best]), float(joint[best])
        total += q - leaves[r] - leaves[s]
        leaves[r], leaves[s], visits[r] = q, 0.0, visits[r] + visits[s]
        for t, x in flow[s].items():
            del flow[t][s]
            if t != r:
                flow[r][t] = flow[t][r] = flow[r].get(t, 0.0) + x
        flow[s] = {}
        touch[r] = (touch[r] | touch[s]) - {r, s}
        for t in touch[s]:
            touch[t].discard(s)
            if t != r:
                touch[t].add(r)
        touch[s] = set()
        other = (u != r) & (u != s) & (v != r) & (v != s)
        near = sorted(touch[r])
        u = np.append(u[other], [min(r, t) for t in near]).astype(np.int64)
        v = np.append(v[other], [max(r, t) for t in near]).astype(np.int64)
        between = np.append(between[other], [flow[r].get(t, 0.0) for t in near])
        now += d
        left -= 1
        path.append((len(path), left, r, s, d, now))
    return path
