"""Unconstrained block models fitted by simulated annealing: eight variants for each form of the flows.

Three switches make the variants, as each touches another term: degree correction the placement of
edges, ranking and nesting the cost of the matrix between groups. A chain moves one unit at a time,
takes what shortens the code and, while it is warm, also some of what does not; cold, it goes on until a
whole sweep takes nothing. Moves of nested variants are priced under the hierarchy as it stands; the
hierarchy is built anew between sweeps. Blocks are sparse: a chain holds the blocks that have edges, a
move looks at those of two groups. Networks, variants and chains are independent tasks; a nested variant
shares its task with the flat one it starts from, so it is never longer.
"""

from __future__ import annotations

import hashlib
import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from flowregions.functions.numbers import lchoose, lfact, lmulti
from flowregions.plans import kernel
from flowregions.plans.greedy import gathered, network_of

VARIANTS = ("bm", "bm_dc", "bm_r", "bm_rdc", "bm_n", "bm_ndc", "bm_rn", "bm_rndc")
#: The flat variant that each nested one starts from.
FLAT = {v: v.replace("n", "").rstrip("_") for v in VARIANTS if "n" in v}
#: The schedule: warm sweeps, and the first and last temperature in bits. Cold sweeps go on until none takes a move.
WARM, HOT, COOL = 10, 6.0, 0.3

FIT = "network_id string, model string, rep string, chain int, b int, dl double, start double, unit_id int, label int, path array<int>"


class Level(kernel.BlockModel):
    """The matrix between groups as a multigraph of its own, for the next level of a hierarchy."""

    def pair(self, nn, e, w):
        return lmulti(nn, w) if self.rep == "mg" else lmulti(nn, e) + lmulti(nn, w)


def matrix_bits(e: np.ndarray, w: np.ndarray, rep: str, ranked: bool) -> float:
    """Bits of the matrices between B groups; ranked: in order of the ranking, edges up, down and along it apart."""
    b = len(e)
    bits = 0.0
    for m in (w,) if rep == "mg" else (e, w):
        if ranked:
            up, down, flat = int(np.triu(m, 1).sum()), int(np.tril(m, -1).sum()), int(np.trace(m))
            bits += float(lmulti(3, up + down + flat)) + (float(lmulti(b * (b - 1) // 2, up) + lmulti(b * (b - 1) // 2, down)) if b > 1 else 0.0) + float(lmulti(b, flat))
        else:
            bits += float(lmulti(b * b, int(m.sum())))
    return bits


def ranking(e: np.ndarray, w: np.ndarray, rep: str) -> np.ndarray:
    """An order of the groups that makes the ranked matrix short: by net flow, then swaps of neighbours as long as one helps."""
    order, b = np.argsort(w.sum(axis=0) - w.sum(axis=1), kind="stable").tolist(), len(e)
    pairs = [x.tolist() for x in ((w,) if rep == "mg" else (e, w))]
    sums = []
    for m in pairs:
        sums.append([sum(m[order[i]][order[j]] for i in range(b) for j in range(i + 1, b)), sum(m[order[j]][order[i]] for i in range(b) for j in range(i + 1, b)), sum(m[i][i] for i in range(b))])
    price = lambda ways: sum(spread_bits(b, *x) for x in ways)
    best, changed = price(sums), True
    while changed:
        changed = False
        for k in range(b - 1):
            p, q = order[k], order[k + 1]
            new = [[x[0] - m[p][q] + m[q][p], x[1] + m[p][q] - m[q][p], x[2]] for x, m in zip(sums, pairs, strict=True)]
            bits = price(new)
            if bits < best - 1e-9:
                order[k], order[k + 1], sums, best, changed = q, p, new, bits, True
    return np.array(order)


def nested_bits(e: np.ndarray, w: np.ndarray, rep: str, ranked: bool) -> tuple[float, list[np.ndarray]]:
    """(bits, labels of each level) of the matrices under the best hierarchy found; a single level is the flat cost."""
    b = len(e)
    best, levels = matrix_bits(e, w, rep, ranked), [np.zeros(b, dtype=np.int64)]
    if b < 3:
        return best, levels
    src, dst = np.nonzero(w)
    i, j = np.triu_indices(b, 1)
    net = kernel.Network(np.arange(b), src, dst, w[src, dst], i, j, e[src, dst])
    path = kernel.greedy(net, Level(rep))
    flat = lambda k: float(lmulti(k * k, int(w.sum())) + (0.0 if rep == "mg" else lmulti(k * k, int(e.sum()))))
    step = min((p for p in path if 1 < p[1] < b), key=lambda p: (p[5], p[1]), default=None)
    if step is None:
        return best, levels
    label = np.unique(labels_at(path, b, step[0]), return_inverse=True)[1].ravel()
    k = int(label.max()) + 1
    up = np.zeros((b, k), dtype=np.int64)
    up[np.arange(b), label] = 1
    if ranked:  # the groups above are numbered by their rank, should theirs be the last matrix
        place = np.argsort(ranking(up.T @ e @ up, up.T @ w @ up, rep))
        label, up = place[label], up[:, np.argsort(place)]
    rest, above = nested_bits(up.T @ e @ up, up.T @ w @ up, rep, ranked)
    whole = step[5] - flat(step[1]) + rest
    return (whole, [label, *above]) if whole < best - 1e-9 else (best, levels)


def spread_bits(b: int, up: int, down: int, flat: int) -> float:
    """Edges up, down and along a ranking of b groups, each over its own pairs."""
    half = b * (b - 1) // 2
    return float(lmulti(3, up + down + flat)) + (float(lmulti(half, up) + lmulti(half, down)) if b > 1 else 0.0) + float(lmulti(b, flat))


class Tree:
    """The groups above a chain's groups, with the sums of the blocks between them."""

    def __init__(self, slots: list[int], e: np.ndarray, w: np.ndarray, levels: list[np.ndarray], rep: str, ranked: bool):
        self.rep, self.ranked, self.levels = rep, ranked, levels
        label = self.levels[0]
        k = int(label.max()) + 1
        self.parent = dict(zip(slots, label.tolist(), strict=True))
        up = np.zeros((len(slots), k), dtype=np.int64)
        up[np.arange(len(slots)), label] = 1
        self.e, self.w = up.T @ e @ up, up.T @ w @ up
        self.inside = np.bincount(label, minlength=k)
        self.now = self.bits(self.e, self.w, self.inside) if len(self.levels) > 1 else None

    def bits(self, e: np.ndarray, w: np.ndarray, inside: np.ndarray) -> float:
        """Bits of all levels above the groups: who is in which, and the matrices."""
        total, b = 0.0, int(inside.sum())
        for level in range(len(self.levels)):
            if level:
                label = self.levels[level]
                k = int(label.max()) + 1
                some = inside > 0  # a group above that has lost all it had is no node any more
                up = np.zeros((len(label), k), dtype=np.int64)
                up[np.arange(len(label)), label] = 1
                b, inside, below = int(some.sum()), up.T @ some.astype(np.int64), (e, w)
                e, w = up.T @ e @ up, up.T @ w @ up
            k = int((inside > 0).sum())
            total += float(lchoose(b - 1, k - 1) + lfact(b) - lfact(inside).sum())
            if self.ranked and level == len(self.levels) - 1:  # the last matrix is the ranked one
                return total + matrix_bits(below[0][np.ix_(some, some)], below[1][np.ix_(some, some)], self.rep, True)
            nn = inside[:, None] * inside[None, :]
            total += float(lmulti(nn, w).sum() + (0.0 if self.rep == "mg" else lmulti(nn, e).sum()))
        return total


class Chain:
    """A partition with its blocks, and its length under one variant."""

    def __init__(self, net: kernel.Network, variant: str, rep: str, label: np.ndarray):
        self.net, self.rep = net, rep
        switches = variant.partition("_")[2]
        self.dc, self.ranked, self.nested = "dc" in switches, "r" in switches, "n" in switches
        self.model = kernel.BlockModel(rep, self.dc)
        n = net.n
        one = net.w if rep == "mg" else net.e
        self.k_out, self.k_in = ([int(k) for k in np.bincount(x, weights=one, minlength=n)] for x in (net.src, net.dst))
        self.fixed = self.model.fixed(net.e, net.w, np.array(self.k_out, dtype=np.int64), np.array(self.k_in, dtype=np.int64))
        self.totals = int(net.e.sum()), int(net.w.sum())
        # flows of each unit: (other, edges, weight) out and in, and with itself
        self.flow: tuple[list, list] = ([[] for _ in range(n)], [[] for _ in range(n)])
        self.self_ = [(0, 0)] * n
        for s, d, e, w in zip(net.src.tolist(), net.dst.tolist(), net.e.tolist(), net.w.tolist(), strict=True):
            if s == d:
                self.self_[s] = (self.self_[s][0] + e, self.self_[s][1] + w)
            else:
                self.flow[0][s].append((d, e, w))
                self.flow[1][d].append((s, e, w))
        self.load(label)

    def load(self, label: np.ndarray) -> None:
        """Groups 0..B-1 in order of their labels; for ranked variants that order is the ranking."""
        self.label = np.unique(label, return_inverse=True)[1].ravel().tolist()
        b = max(self.label) + 1
        self.size, self.out, self.into = [0] * b, [0] * b, [0] * b
        self.cells: tuple[list[dict], list[dict]] = ([{} for _ in range(b)], [{} for _ in range(b)])
        for i, g in enumerate(self.label):
            self.size[g] += 1
            self.out[g] += self.k_out[i]
            self.into[g] += self.k_in[i]
        for s, d, e, w in zip(self.net.src.tolist(), self.net.dst.tolist(), self.net.e.tolist(), self.net.w.tolist(), strict=True):
            self.add(self.label[s], self.label[d], e, w)
        self.place = list(range(b))
        self.free: list[int] = []
        self.active = list(range(b))
        self.at = {g: k for k, g in enumerate(self.active)}
        self.count()
        self.tree = self.known = None
        self.cost: dict[int, float] = {}

    def add(self, r: int, s: int, e: int, w: int) -> None:
        cell = self.cells[0][r].get(s)
        if cell is None:
            self.cells[0][r][s] = self.cells[1][s][r] = [e, w]
            return
        cell[0] += e
        cell[1] += w
        if not cell[0]:
            del self.cells[0][r][s], self.cells[1][s][r]

    def count(self) -> None:
        """Edges and weight up, down and along the ranking."""
        self.ways = [[0, 0], [0, 0], [0, 0]]
        for r in self.active:
            for s, (e, w) in self.cells[0][r].items():
                way = self.ways[self.way(r, s)]
                way[0] += e
                way[1] += w

    def way(self, r: int, s: int) -> int:
        return 0 if self.place[r] < self.place[s] else 1 if self.place[r] > self.place[s] else 2

    def dense(self) -> tuple[np.ndarray, np.ndarray]:
        """Edges and weights between the groups, in order of the ranking."""
        order = sorted(self.active, key=lambda g: self.place[g])
        at = {g: k for k, g in enumerate(order)}
        e, w = (np.zeros((len(order), len(order)), dtype=np.int64) for _ in range(2))
        for r in order:
            for s, cell in self.cells[0][r].items():
                e[at[r], at[s]], w[at[r], at[s]] = cell
        return e, w

    def matrix(self, b: int, ways: list) -> float:
        """Bits of the matrices between b groups, by the ranking's sums where the variant has one."""
        if self.ranked:
            return sum(spread_bits(b, *(x[c] for x in ways)) for c in ((1,) if self.rep == "mg" else (0, 1)))
        if b not in self.cost:
            e, w = self.totals
            self.cost[b] = float(lmulti(b * b, w) + (0.0 if self.rep == "mg" else lmulti(b * b, e)))
        return self.cost[b]

    def change(self, i: int, s: int) -> tuple[float, tuple]:
        """Bits that moving unit i to group s adds, and what ``move`` needs."""
        r, n = self.label[i], self.net.n
        label, size = self.label, self.size
        mine: tuple[dict, dict] = ({}, {})
        for side in (0, 1):
            for j, e, w in self.flow[side][i]:
                cell = mine[side].get(label[j])
                if cell is None:
                    mine[side][label[j]] = [e, w]
                else:
                    cell[0] += e
                    cell[1] += w
        # blocks that change: (row, column) -> edges and weight added
        delta: dict[tuple[int, int], list[int]] = {}

        def put(a: int, c: int, e: int, w: int) -> None:
            cell = delta.setdefault((a, c), [0, 0])
            cell[0] += e
            cell[1] += w

        for t, (e, w) in mine[0].items():
            put(r, t, -e, -w)
            put(s, t, e, w)
        for t, (e, w) in mine[1].items():
            put(t, r, -e, -w)
            put(t, s, e, w)
        e, w = self.self_[i]
        if e:
            put(r, r, -e, -w)
            put(s, s, e, w)
        # every block with an end in r or s, before and after
        nr, ns = size[r], size[s]
        new_size = {r: nr - 1, s: ns + 1}
        keys = set(delta)
        for g in (r, s):
            keys.update((g, t) for t in self.cells[0][g])
            keys.update((t, g) for t in self.cells[1][g])
        rows = []
        for a, c in keys:
            e, w = self.cells[0][a].get(c, (0, 0))
            de, dw = delta.get((a, c), (0, 0))
            rows.append((size[a] * size[c], e, w, new_size.get(a, size[a]) * new_size.get(c, size[c]), e + de, w + dw))
        bits = 0.0
        if rows:
            x = np.array(rows, dtype=np.int64)
            both = self.model.pair(x[:, [0, 3]], x[:, [1, 4]], x[:, [2, 5]])
            bits = float((both[:, 1] - both[:, 0]).sum())
        out, into = self.k_out[i], self.k_in[i]
        some = np.array([[nr, ns, nr - 1, ns + 1], [self.out[r], self.out[s], self.out[r] - out, self.out[s] + out], [self.into[r], self.into[s], self.into[r] - into, self.into[s] + into]], dtype=np.int64)
        g = self.model.group(*some)
        if self.dc:  # a group without units has no degrees to tell
            g = np.where(some[0] > 0, g, 0.0)
        bits += float(g[2] + g[3] - g[0] - g[1])
        b = len(self.active)
        c = b - (nr == 1) + (ns == 0)
        if c != b:
            bits += float(lchoose(n - 1, c - 1) - lchoose(n - 1, b - 1))
        ways = self.ways
        if self.ranked:
            ways = [list(x) for x in ways]
            for (a, t), (e, w) in delta.items():
                way = ways[self.way(a, t)]
                way[0] += e
                way[1] += w
        if self.tree is None:
            return bits + self.matrix(c, ways) - self.matrix(b, self.ways), (delta, ways, None)
        grown = self.under(r, s, delta, nr == 1, ns == 0)
        return bits + grown[3] - self.tree.now, (delta, ways, grown)

    def under(self, r: int, s: int, delta: dict, gone: bool, new: bool) -> tuple:
        """(edges, weights, groups inside, bits) of the level above after a move; a new group stands beside r."""
        tree = self.tree
        of = lambda g: tree.parent.get(g, tree.parent[r])
        if not gone and not new and of(r) == of(s):
            return tree.e, tree.w, tree.inside, tree.now
        e, w, inside = tree.e.copy(), tree.w.copy(), tree.inside.copy()
        for (a, t), (de, dw) in delta.items():
            e[of(a), of(t)] += de
            w[of(a), of(t)] += dw
        inside[of(r)] -= gone
        inside[of(s)] += new
        return e, w, inside, tree.bits(e, w, inside)

    def move(self, i: int, s: int, what: tuple) -> None:
        r = self.label[i]
        delta, ways, grown = what
        for (a, c), (e, w) in delta.items():
            if e:
                self.add(a, c, e, w)
            elif w:
                cell = self.cells[0][a][c]
                cell[1] += w
        self.ways = ways
        self.label[i] = s
        for x, k in ((self.size, 1), (self.out, self.k_out[i]), (self.into, self.k_in[i])):
            x[r] -= k
            x[s] += k
        if grown is not None:
            if s not in self.tree.parent:
                self.tree.parent[s] = self.tree.parent[r]
            self.tree.e, self.tree.w, self.tree.inside, self.tree.now = grown
        if self.size[s] == 1:
            self.at[s] = len(self.active)
            self.active.append(s)
            self.free.remove(s)
        if not self.size[r]:
            last = self.active.pop()
            if last != r:
                self.active[self.at[r]] = last
                self.at[last] = self.at[r]
            del self.at[r]
            self.free.append(r)
            if self.tree is not None:
                self.tree.parent.pop(r, None)

    def empty(self) -> int:
        """A group without units, last in the ranking."""
        if not self.free:
            for x in (self.size, self.out, self.into):
                x.append(0)
            for side in self.cells:
                side.append({})
            self.place.append(0)
            self.free.append(len(self.size) - 1)
        g = self.free[-1]
        self.place[g] = 1 + max(self.place[x] for x in self.active)
        return g

    def hierarchy(self) -> tuple[float, list[np.ndarray]]:
        """Bits and levels of the best hierarchy found above the groups; kept until something moves."""
        key = (tuple(self.label), tuple(self.place))
        if self.known is None or self.known[0] != key:
            self.known = key, nested_bits(*self.dense(), self.rep, self.ranked)
        return self.known[1]

    def length(self) -> float:
        """From scratch, with the best hierarchy found where the variant has one."""
        return self.below() + (self.hierarchy()[0] if self.nested else self.matrix(len(self.active), self.ways))

    def below(self) -> float:
        """All but the cost of the matrices between groups."""
        act, n = self.active, self.net.n
        size, out, into = (np.array([x[g] for g in act], dtype=np.int64) for x in (self.size, self.out, self.into))
        rows = [(self.size[r] * self.size[s], *cell) for r in act for s, cell in self.cells[0][r].items()]
        x = np.array(rows, dtype=np.int64).reshape(-1, 3)
        return float(lchoose(n - 1, len(act) - 1) + lfact(n)) + float(self.model.group(size, out, into).sum()) + float(self.model.pair(*x.T).sum()) + self.fixed

    def grow(self) -> None:
        """Builds the hierarchy anew; a single level is priced as the flat matrix is."""
        levels = self.hierarchy()[1]
        self.tree = Tree(sorted(self.active, key=lambda g: self.place[g]), *self.dense(), levels, self.rep, self.ranked) if len(levels) > 1 else None

    def rank(self) -> None:
        """Orders the groups by net flow, then swaps neighbours as long as that shortens the code."""
        cells, b = self.cells[0], len(self.active)
        net = {g: sum(c[1] for c in self.cells[1][g].values()) - sum(c[1] for c in cells[g].values()) for g in self.active}
        order = sorted(self.active, key=lambda g: (net[g] / self.size[g], g))
        for k, g in enumerate(order):
            self.place[g] = k
        self.count()
        best = self.matrix(b, self.ways)
        changed = True
        while changed:
            changed = False
            for k in range(b - 1):
                p, q = order[k], order[k + 1]
                there, back = cells[p].get(q, (0, 0)), cells[q].get(p, (0, 0))
                ways = [[self.ways[0][c] - there[c] + back[c] for c in (0, 1)], [self.ways[1][c] + there[c] - back[c] for c in (0, 1)], self.ways[2]]
                bits = self.matrix(b, ways)
                if bits < best - 1e-9:
                    order[k], order[k + 1] = q, p
                    self.place[p], self.place[q] = k + 1, k
                    self.ways, best, changed = ways, bits, True

    def labels(self) -> np.ndarray:
        """Each unit's group by its place in the ranking."""
        return np.array([self.place[g] for g in self.label])

    def sweep(self, rng: np.random.Generator, t: float) -> int:
        """Proposes a move for every unit; the number taken at temperature t."""
        taken = 0
        for i in rng.permutation(self.net.n).tolist():
            r = self.label[i]
            near = self.flow[0 if rng.random() < 0.5 else 1][i]
            pick = rng.random()
            if pick < 0.7 and near:
                s = self.label[near[int(rng.integers(len(near)))][0]]
            elif pick < 0.97 or self.size[r] == 1:
                s = self.active[int(rng.integers(len(self.active)))]
            else:
                s = self.empty()
            if s == r:
                continue
            bits, what = self.change(i, s)
            if bits < -1e-9 or t > 0 and rng.random() < math.exp(-bits * math.log(2) / t):
                self.move(i, s, what)
                taken += 1
        return taken

    def anneal(self, rng: np.random.Generator, visited: list | None = None) -> None:
        """Warm sweeps by the schedule, then cold ones until none takes a move; the shortest partition met at the end of a sweep stays. visited: gets (sweep, groups, length)."""
        best, kept = self.length(), self.labels()
        k, last = 0, math.inf
        while True:
            t = HOT * (COOL / HOT) ** (k / max(1, WARM - 1)) if k < WARM else 0.0
            if self.nested:
                self.grow()
            taken = self.sweep(rng, t)
            if self.ranked:
                self.rank()
            new = self.length()
            if visited is not None:
                visited.append((k + 1, len(self.active), new))
            if new < best - 1e-9:
                best, kept = new, self.labels()
            k += 1
            # a cold sweep shortens the code, or the hierarchy or ranking it was priced under has nothing more to give
            if k > WARM:
                if not taken or new >= last - 1e-9:
                    break
                last = new
        self.load(kept)


def labels_at(path: list, n: int, step: int) -> np.ndarray:
    label = np.arange(n)
    for _, _, r, s, _, _ in path[1 : step + 1]:
        label[label == s] = r
    return label


#: Numbers of groups, as multiples of the greedy optimum's, at which chains start, and the finer ones at which a hierarchy is tried.
STARTS, FINER = (1.0, 2.5, 6.0), (1.5, 2.0, 4.0)


def merge_paths(net: kernel.Network, rep: str) -> list[list]:
    """Greedy merges along flows, wherever the units lie, and along borders."""
    along = kernel.Network(net.units, net.units[net.src], net.units[net.dst], net.w, net.units[net.src], net.units[net.dst])
    return [kernel.greedy(x, kernel.BlockModel(rep)) for x in (along, net)]


def steps(path: list, times: tuple[float, ...]) -> list[int]:
    """Steps of a path at which there are so many times as many groups as at its optimum."""
    best = min(path, key=lambda p: (p[5], p[1]))[1]
    return sorted({min(len(path) - 1, max(0, path[0][1] - round(best * t + (t > 1)))) for t in times})


def fit(net: kernel.Network, variant: str, rep: str, rng: np.random.Generator, merges: list[list], flat: Chain | None = None, visited: list | None = None) -> tuple[Chain, float]:
    """(fitted chain, length at its start). A flat variant is annealed from steps of both greedy paths and keeps the shortest result; a nested one
    from the fitted ``flat`` one, or from a finer step of a path where that is shorter under a hierarchy."""
    labels = [flat.labels()] if flat is not None else []
    labels += [labels_at(path, net.n, k) for path in merges for k in steps(path, FINER if flat is not None else STARTS)]
    begun = []
    for label in labels:
        state = Chain(net, variant, rep, label)
        if state.ranked:
            state.rank()
            state.load(state.labels())
        begun.append((state.length(), len(begun), state))
    begun.sort(key=lambda x: (round(x[0], 9), x[1]))
    found = []
    for length, k, state in begun[:1] if flat is not None else begun:
        seen: list = []
        state.anneal(rng, seen)
        found.append((round(state.length(), 9), k, state, length, seen))
    _, _, state, length, seen = min(found, key=lambda x: x[:2])
    if visited is not None:
        visited += seen
    return state, length


def paths(state: Chain) -> tuple[np.ndarray, list[list[int]]]:
    """(labels by smallest unit, but by rank where groups are ranked; each unit's labels at all levels, the last one a single group)."""
    own = state.labels()
    order = np.unique(own)
    at = np.searchsorted(order, own)
    low = np.array([state.net.units[np.flatnonzero(at == g)[0]] for g in range(len(order))])
    label = at if state.ranked else low[at]
    levels = state.hierarchy()[1] if state.nested else []
    out = [[int(x)] for x in label]
    for up in levels:
        at = up[at]
        for k, x in enumerate(at.tolist()):
            out[k].append(x)
    return label, out


def generator(*names) -> np.random.Generator:
    return np.random.default_rng(int.from_bytes(hashlib.blake2b(":".join(map(str, names)).encode(), digest_size=8).digest(), "big"))


def anneal(flows: DataFrame, units: DataFrame, adjacency: DataFrame, variants: tuple[str, ...] = VARIANTS, reps: tuple[str, ...] = ("mg", "w"), chains: int = 1, seed: int = 1) -> DataFrame:
    """FIT rows, one for each unit, network, variant, form and chain: the shortest partition met, its length, the length at the start."""
    flat = sorted({FLAT.get(v, v) for v in variants})
    jobs = F.explode(F.array(*[F.struct(F.lit(v).alias("model"), F.lit(r).alias("rep"), F.lit(c).alias("chain")) for v in flat for r in reps for c in range(chains)]))
    rows = gathered(flows, units, adjacency).withColumn("job", jobs).select("network_id", "job.*", "kind", "a", "b", "w")
    # fits are long and their rows few: a fixed number of tasks keeps the optimizer from putting them together
    rows = rows.repartition(4 * flows.sparkSession.sparkContext.defaultParallelism, "network_id", "model", "rep", "chain")

    def solve(tab: pa.Table) -> pa.Table:
        name, model, rep, chain = (tab.column(c)[0].as_py() for c in ("network_id", "model", "rep", "chain"))
        net = network_of(tab)
        merges = merge_paths(net, rep)
        base, begin = fit(net, model, rep, generator(name, model, rep, chain, seed), merges)
        found = [(model, base, begin)]
        for nested in (v for v in variants if FLAT.get(v) == model):
            found.append((nested, *fit(net, nested, rep, generator(name, nested, rep, chain, seed), merges, base)))
        tables = []
        for variant, state, begin in found:
            if variant in variants:
                label, path = paths(state)
                n, dl, b = net.n, state.length(), len(state.active)
                tables.append(pa.table({"network_id": [name] * n, "model": [variant] * n, "rep": [rep] * n, "chain": pa.array([chain] * n, pa.int32()), "b": pa.array([b] * n, pa.int32()), "dl": [dl] * n, "start": [begin] * n, "unit_id": pa.array(net.units, pa.int32()), "label": pa.array(label, pa.int32()), "path": pa.array(path, pa.list_(pa.int32()))}))
        return pa.concat_tables(tables)

    return rows.groupBy("network_id", "model", "rep", "chain").applyInArrow(solve, FIT)


def settle(net: kernel.Network, rep: str, label: np.ndarray) -> Chain:
    """A partition into contiguous groups, made shorter by moves of single units over borders for as long as one helps.

    Of the groups that a unit touches the one that shortens the code most takes it, unless its own group would fall apart;
    with its last unit a group goes.
    """
    state = Chain(net, "bm", rep, label)

    def holds(i: int) -> bool:
        """Whether the group of i stays in one piece without it."""
        own = [j for j in net.touch[i] if state.label[j] == state.label[i]]
        if len(own) < 2:
            return True
        met, todo, missing = {i, own[0]}, [own[0]], set(own[1:])
        while todo and missing:
            for j in net.touch[todo.pop()]:
                if j not in met and state.label[j] == state.label[i]:
                    met.add(j)
                    missing.discard(j)
                    todo.append(j)
        return not missing

    taken = True
    while taken:
        taken = False
        for i in range(net.n):
            near = sorted({state.label[j] for j in net.touch[i]} - {state.label[i]})
            if not near:
                continue
            bits, s, what = min(((bits, s, what) for s in near for bits, what in [state.change(i, s)]), key=lambda x: (round(x[0], 9), x[1]))
            if bits < -1e-9 and holds(i):
                state.move(i, s, what)
                taken = True
    return state


REGIONS = "network_id string, model string, unit_id int, label int, b int, dl double"


def regions(flows: DataFrame, units: DataFrame, adjacency: DataFrame, rep: str = "w") -> DataFrame:
    """REGIONS rows: of each network the shortest greedy partition, settled by moves over borders, with its groups and length; contiguous where the borders are connected."""

    def solve(tab: pa.Table) -> pa.Table:
        net = network_of(tab)
        path = kernel.greedy(net, kernel.BlockModel(rep))
        best = min(path, key=lambda p: (round(p[5], 9), p[1]))
        state = settle(net, rep, labels_at(path, net.n, best[0]))
        label, n = paths(state)[0], net.n
        return pa.table({"network_id": pa.array([tab.column("network_id")[0].as_py()] * n, pa.string()), "model": ["settled"] * n, "unit_id": pa.array(net.units, pa.int32()), "label": pa.array(label, pa.int32()), "b": pa.array([len(state.active)] * n, pa.int32()), "dl": [state.length()] * n})

    return gathered(flows, units, adjacency).groupBy("network_id").applyInArrow(solve, REGIONS)


def trace(flows: DataFrame, units: DataFrame, adjacency: DataFrame, variant: str = "bm", rep: str = "w", seed: int = 1) -> DataFrame:
    """(network_id, sweep, b, dl): the partitions an annealed chain visits, sweep by sweep, from its start (sweep 0)."""

    def solve(tab: pa.Table) -> pa.Table:
        name, net = tab.column("network_id")[0].as_py(), network_of(tab)
        visited: list = []
        _, begin = fit(net, variant, rep, generator(name, variant, rep, 0, seed), merge_paths(net, rep), visited=visited)
        rows = [(0, None, begin), *visited]
        return pa.table({"network_id": [name] * len(rows), "sweep": pa.array([r[0] for r in rows], pa.int32()), "b": pa.array([r[1] for r in rows], pa.int32()), "dl": [float(r[2]) for r in rows]})

    return gathered(flows, units, adjacency).groupBy("network_id").applyInArrow(solve, "network_id string, sweep int, b int, dl double")


def hierarchy(fits: DataFrame) -> DataFrame:
    """HIERARCHY rows (network_id, model, level, node, label) of fitted rows: level 0 the units', then the groups', up to a single one."""
    levels = F.posexplode(F.transform("path", lambda x, i: F.struct(F.when(i == 0, F.col("unit_id")).otherwise(F.get("path", i - 1)).alias("node"), x.alias("label"))))
    return fits.select("network_id", "model", levels.alias("level", "x")).select("network_id", "model", "level", "x.node", "x.label").distinct()


def best_chain(fits: DataFrame) -> DataFrame:
    """Of each (network, variant, form) the chain with the shortest length."""
    best = fits.groupBy("network_id", "model", "rep").agg(F.min_by("chain", F.struct(F.round("dl", 9), "chain")).alias("chain"))
    return fits.join(best, ["network_id", "model", "rep", "chain"])


def score_rows(fits: DataFrame, n: DataFrame | None = None) -> DataFrame:
    """(network_id, model, rep, n, b, dl) from fitted rows."""
    return fits.groupBy("network_id", "model", "rep").agg(F.count("*").alias("n"), F.first("b").alias("b"), F.first("dl").alias("dl"))
