"""Approximate nearest neighbours by a permutation index.

Pivots are a bounded sample of the vectors. Every vector is represented by its nearest pivots in
order, and posted under each of them with the pivot's place (an inverted file per pivot). A query
adds up, over the postings of its own few nearest pivots, how much better each vector's places fit than a
missing pivot would: the footrule distance of the two orders. The closest part of the shard by that
distance, ties at its edge included, is reranked by the exact inner product.

For inner products the vectors get one more component that brings all of them to the norm of the
longest, so that the nearest in angle is the largest inner product; the query gets a zero there.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from flowregions.llm import shards as S
from flowregions.llm.common import cut

#: Pivots, how many of them represent a vector and how many a query, and the part of a shard that is reranked exactly. A query's far
#: pivots tell little, so it asks for its nearest only. Near-uniform 64-d vectors are the hardest case for any index; the README has
#: the recall measured on these and on clustered ones. The index takes all rows; only the pivots are a sample.
PIVOTS, PLACES, ASKED, PART = 1024, 256, 64, 0.08
#: Candidates reranked for each neighbour wanted, at least: among fewer the order of pivots cannot be told from chance.
LEAST = 5


def orders(x: np.ndarray, pivots: np.ndarray, places: int) -> np.ndarray:
    """The nearest pivots of each row, nearest first."""
    out = np.empty((len(x), places), dtype=np.int32)
    for k in range(0, len(x), 4096):
        near = x[k : k + 4096] @ pivots.T
        some = np.argpartition(-near, places - 1, axis=1)[:, :places]
        out[k : k + 4096] = np.take_along_axis(some, np.argsort(-np.take_along_axis(near, some, 1), axis=1, kind="stable"), 1)
    return out


def search(q_ids: np.ndarray, q: np.ndarray, ids: np.ndarray, x: np.ndarray, pivots: np.ndarray, norm: float, k: int, places: int, asked_places: int, part: float):
    """(query ids, vector ids, scores) of one shard."""
    lift = np.sqrt(np.maximum(norm**2 - np.einsum("ij,ij->i", x, x), 0.0))
    places = min(places, len(pivots))
    own = orders(np.hstack([x, lift[:, None]]), pivots, places)
    asked = orders(np.hstack([q, np.zeros((len(q), 1))]), pivots, min(asked_places, places))
    order = np.argsort(own.ravel(), kind="stable")
    posted, place = (order // places).astype(np.int32), (order % places).astype(np.int16)
    begin = np.searchsorted(own.ravel()[order], np.arange(len(pivots) + 1))
    least = max(int(np.ceil(part * len(x))), LEAST * k)
    out: tuple[list, list, list] = ([], [], [])
    for j in range(len(q)):
        gain = np.zeros(len(x), dtype=np.int16 if places * asked.shape[1] < 2**15 else np.int32)
        for at, p in enumerate(asked[j]):
            a, b = begin[p], begin[p + 1]
            # a pivot missing from the vector's places counts as standing just behind the last one
            gain[posted[a:b]] += (places - at) - np.abs(place[a:b] - np.int16(at))
        if least < len(x):
            edge = np.partition(gain, len(x) - least)[len(x) - least]
            near = np.flatnonzero(gain >= edge)
        else:
            near = np.arange(len(x))
        near = near[ids[near] != q_ids[j]]
        scores = np.einsum("ij,j->i", x[near], q[j])
        top = S.top_rows(scores, ids[near], k)
        out[0].append(np.full(len(top), q_ids[j]))
        out[1].append(ids[near][top])
        out[2].append(scores[top])
    return [np.concatenate(o) for o in out]


def pivots_of(rows: DataFrame, pivots: int) -> np.ndarray | None:
    """Distinct vectors with the smallest hashes of their ids, of the commonest length among them; at most 8 times as many rows come to the driver."""
    sample = rows.orderBy(F.xxhash64("id", F.lit(7)), "id").limit(8 * pivots).collect()
    if not sample:
        return None
    lengths = [len(r["v"]) for r in sample]
    d = max(sorted(set(lengths)), key=lengths.count)
    distinct = dict.fromkeys(tuple(r["v"]) for r in sample if len(r["v"]) == d)
    return np.array(list(distinct)[:pivots])


def nearest(vectors: DataFrame, every: int = 20, k: int = 20, id_col: str = "vec_id", vector_col: str = "embedding", pivots: int = PIVOTS, places: int = PLACES, asked: int = ASKED, part: float = PART) -> DataFrame:
    """(query_id, rank, vec_id, score): the k vectors found with the largest inner product for each row whose id is divisible by ``every``.

    Vectors that are null, zero or hold null or non-finite numbers take no part; repeated ids count
    once (see shards). Vectors of another length than the pivots' are compared exactly among their
    own length. An empty table gives no rows. Fewer candidates than k: all of them.
    """
    import pyarrow as pa

    rows = cut(S.usable(vectors, id_col, vector_col, zero=False))
    chosen = pivots_of(rows, pivots)
    norm = rows.agg(F.max(F.sqrt(F.aggregate("v", F.lit(0.0), lambda s, x: s + x * x)))).first()[0] or 0.0
    schema = "query_id long, vec_id long, score double"
    if chosen is None:
        return S.best(vectors.sparkSession.createDataFrame([], schema), k)
    lift = np.sqrt(np.maximum(norm**2 - np.einsum("ij,ij->i", chosen, chosen), 0.0))
    lifted = np.hstack([chosen, lift[:, None]])

    def visit(queries: pa.Table, shard: pa.Table) -> pa.Table:
        there = {x.shape[1]: (ids, x) for _, ids, x in S.matrices(shard, "row", "w")} if shard.num_rows else {}
        found = []
        for _, q_ids, q in S.matrices(queries) if queries.num_rows else ():
            if q.shape[1] in there:
                ids, x = there[q.shape[1]]
                fits = x.shape[1] == lifted.shape[1] - 1
                found.append(search(q_ids, q, ids, x, lifted if fits else np.zeros((1, x.shape[1] + 1)), norm, k, places, asked, part if fits else 1.0))
        cols = [np.concatenate([f[c] for f in found]) if found else [] for c in range(3)]
        return pa.table({"query_id": pa.array(cols[0], pa.int64()), "vec_id": pa.array(cols[1], pa.int64()), "score": pa.array(cols[2], pa.float64())})

    return S.best(S.visits(rows.filter(F.col("id") % every == 0), rows, visit, schema), k)
