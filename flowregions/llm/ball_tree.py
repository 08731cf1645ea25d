"""Exact top-k inner products by ball trees, one per shard.

A node bounds its vectors by a centre and a radius: no inner product with q exceeds
q . centre + |q| * radius. Each query goes through the leaves in falling order of their bounds and
stops at the first leaf whose bound is below its kth score so far. A query first searches its home
shard; the kth score found there goes with it to all other shards, which mostly can only prune.
"""

from __future__ import annotations

import heapq
import math
from fractions import Fraction

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from flowregions.llm import shards as S
from flowregions.llm.common import cut

#: Vectors of a leaf.
LEAF = 256
#: The largest sum of products of whole numbers that doubles add exactly.
EXACT = 2.0**53


class Tree:
    """Leaves as ranges of an order of the rows, with the bounds of all nodes above them."""

    def __init__(self, x: np.ndarray, leaf: int = LEAF):
        self.order = np.arange(len(x))
        centres, radii, self.leaves, self.above = [], [], [], []
        todo = [(0, len(x), [])]
        while todo:
            a, b, path = todo.pop()
            part = x[self.order[a:b]]
            centre = part.mean(axis=0)
            path = [*path, len(centres)]
            centres.append(centre)
            radii.append(np.sqrt(np.square(part - centre).sum(axis=1).max()))
            spread = part.max(axis=0) - part.min(axis=0)
            if b - a <= leaf or not spread.any():
                self.leaves.append((a, b))
                self.above.append(path)
                continue
            axis, half = int(spread.argmax()), (b - a) // 2
            self.order[a:b] = self.order[a:b][np.argpartition(part[:, axis], half)]
            todo += [(a, a + half, path), (a + half, b, path)]
        self.centres, self.radii = np.array(centres), np.array(radii)

    def bounds(self, q: np.ndarray) -> np.ndarray:
        """For each query and leaf the least bound of the nodes on the leaf's path, a little above for rounding."""
        size = np.sqrt(np.square(q).sum(axis=1))
        node = q @ self.centres.T + size[:, None] * self.radii
        node += 1e-9 * (np.abs(node) + size[:, None] * (self.radii + np.sqrt(np.square(self.centres).sum(axis=1)))) + 1e-6
        return np.stack([node[:, p].min(axis=1) for p in self.above], axis=1)


def search(q_ids, q, floor, ids, x, k, leaf=LEAF):
    """(query row, vector ids, scores) of one shard; ``floor``: the kth score each query brings. Whole numbers whose sums doubles hold."""
    tree = Tree(x, leaf)
    x, ids = x[tree.order], ids[tree.order]
    bound = tree.bounds(q)
    turn = np.argsort(-bound, axis=1, kind="stable")
    scores, found = np.full((len(q), k), -np.inf), np.full((len(q), k), np.iinfo(np.int64).max)
    kth = floor.copy()
    alive = np.arange(len(q))
    for r in range(len(tree.leaves)):
        at = turn[alive, r]
        alive = alive[bound[alive, at] >= kth[alive]]  # equal scores may have smaller ids
        if not len(alive):
            break
        at = turn[alive, r]
        by = np.argsort(at, kind="stable")
        for some in np.split(alive[by], np.flatnonzero(np.diff(at[by])) + 1):
            a, b = tree.leaves[turn[some[0], r]]
            got = q[some] @ x[a:b].T
            got[q_ids[some][:, None] == ids[a:b][None, :]] = -np.inf
            hit = np.flatnonzero((got >= kth[some][:, None]).any(axis=1))
            for j in hit:
                i = some[j]
                new = np.flatnonzero((got[j] >= kth[i]) & (got[j] > -np.inf))
                s, d = np.concatenate([scores[i], got[j, new]]), np.concatenate([found[i], ids[a:b][new]])
                top = S.top_rows(s, d, k)
                scores[i, : len(top)], found[i, : len(top)] = s[top], d[top]
                kth[i] = max(kth[i], scores[i, k - 1])
    row, col = np.nonzero(scores > -np.inf)
    return row, found[row, col], scores[row, col]


def whole(x: float, scale: float) -> int:
    """floor(scale * x) as Python's whole number, also where the product is past the doubles."""
    return math.floor(Fraction(scale) * Fraction(x)) if abs(x) > 2.0**900 else math.floor(scale * x)


def large(q_ids, q, ids, x, k, scale=1.0):
    """As search, by Python's whole numbers floor(scale * x), for vectors too large for doubles: all products, nothing pruned; scores past a long become the nearest long."""
    wide = [[whole(c, scale) for c in v] for v in x]
    out: tuple[list, list, list] = ([], [], [])
    for j, (i, v) in enumerate(zip(q_ids, q, strict=True)):
        v = [whole(c, scale) for c in v]
        scored = heapq.nsmallest(k, ((-sum(a * b for a, b in zip(v, w, strict=True)), int(d)) for d, w in zip(ids, wide, strict=True) if d != i))
        for s, d in scored:
            out[0].append(j)
            out[1].append(d)
            out[2].append(max(-(2**63), min(2**63 - 1, -s)))
    return out


def top_products(vectors: DataFrame, every: int = 50, k: int = 5, id_col: str = "vec_id", vector_col: str = "embedding", scale: float = 256.0) -> DataFrame:
    """(query_id, rank, vec_id, score): for each row whose id is divisible by ``every`` the k highest inner products of vectors of whole numbers floor(scale * x), exactly.

    Vectors that are null or hold null or non-finite numbers take no part; repeated ids count once
    (see shards); only vectors of one length are compared; zero vectors score 0. Equal scores go to the
    smaller id. An empty table gives no rows; other columns are not read.
    """
    import pyarrow as pa

    rows = cut(S.usable(vectors, id_col, vector_col))
    shards = S.count_shards(rows)

    def visit(asked: pa.Table, shard: pa.Table) -> pa.Table:
        there = {x.shape[1]: (ids, x) for _, ids, x in S.matrices(shard, "row", "w")} if shard.num_rows else {}
        floor = asked.column("kth").to_numpy() if asked.num_rows else np.zeros(0)
        cols: tuple[list, list, list] = ([], [], [])
        for at, q_ids, q in S.matrices(asked) if asked.num_rows else ():
            if q.shape[1] not in there:
                continue
            ids, x = there[q.shape[1]]
            # sizes first: products past the doubles are never formed
            most = (abs(scale) * float(np.abs(q).max()) + 1) * (abs(scale) * float(np.abs(x).max()) + 1)
            if most * q.shape[1] < EXACT:
                row, got, s = search(q_ids, np.floor(scale * q), floor[at], ids, np.floor(scale * x), k)
                s = s.astype(np.int64)
            else:
                row, got, s = large(q_ids, q, ids, x, k, scale)
            for c, v in zip(cols, (q_ids[row], got, s), strict=True):
                c.append(pa.array(v, pa.int64()))
        names = ("query_id", "vec_id", "score")
        return pa.table({n: pa.chunked_array(c, pa.int64()) for n, c in zip(names, cols, strict=True)})

    schema = "query_id long, vec_id long, score long"
    queries = rows.filter(F.col("id") % every == 0)
    home = F.col("shard") == S.shard_of(shards)
    first = cut(S.visits(queries.withColumn("kth", F.lit(float("-inf"))), rows, visit, schema, home=home, shards=shards))
    if shards == 1:
        return S.best(first, k)
    reached = first.groupBy("query_id").agg(F.when(F.count("*") >= k, F.min("score").cast("double")).alias("kth"))
    asked = queries.join(reached.withColumnRenamed("query_id", "id"), "id", "left").withColumn("kth", F.coalesce("kth", F.lit(float("-inf"))))
    rest = S.visits(asked, rows, visit, schema, home=~home, shards=shards)
    return S.best(first.unionByName(rest), k)
