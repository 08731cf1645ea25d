"""Vectors dealt into shards of bounded size, and blocks of queries that visit every shard.

A vector takes part when it is not null, not empty and holds only finite numbers; rows without an id
take no part, and of rows with one id the smallest vector (in array order) stands for it.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Rows of a shard and queries of a block: both bound a task's memory.
SHARD_ROWS, BLOCK_QUERIES = 32_768, 2_048


def usable(frame: DataFrame, id_col: str, vector_col: str, zero: bool = True) -> DataFrame:
    """(id long, v array<double>) of the vectors that take part; ``zero``: whether zero vectors do."""
    v = F.col("v")
    rows = frame.select(frame[id_col].cast("long").alias("id"), frame[vector_col].cast("array<double>").alias("v"))
    finite = F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) != float("inf")))
    rows = rows.filter(F.col("id").isNotNull() & v.isNotNull() & (F.size(v) > 0) & finite)
    if not zero:
        rows = rows.filter(F.exists(v, lambda x: x != 0))
    return rows.groupBy("id").agg(F.min("v").alias("v"))


def matrices(table, id_col: str = "id", vector_col: str = "v") -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(row numbers, ids, matrix) of an Arrow table, for each length of vector."""
    v = table.column(vector_col).combine_chunks()
    flat = v.flatten().to_numpy(zero_copy_only=False)
    ends = np.cumsum(v.value_lengths().to_numpy(zero_copy_only=False))
    ids = table.column(id_col).to_numpy()
    size = np.diff(ends, prepend=0)
    for d in np.unique(size):
        rows = np.flatnonzero(size == d)
        yield rows, ids[rows], flat[(ends[rows] - d)[:, None] + np.arange(d)]


def visits(queries: DataFrame, rows: DataFrame, search: Callable, schema: str, shard_rows: int = SHARD_ROWS, block: int = BLOCK_QUERIES, home: Column | None = None, shards: int = 0) -> DataFrame:
    """``search(query table, shard table)`` for each block of queries and each shard, as a co-group on (shard, block). The shard's
    columns are ``row`` (its id) and ``w``.

    Shards are dealt by a hash of the id, so one very common vector spreads evenly. home: only the
    visits it allows take place; it may use ``shard`` and the queries' columns.
    """
    shards = shards or count_shards(rows, shard_rows)
    blocks = max(1, -(-queries.count() // block))
    left = queries.withColumn("block", F.pmod(F.xxhash64("id", F.lit(1)), F.lit(blocks)).cast("int")).withColumn("shard", F.explode(F.sequence(F.lit(0), F.lit(shards - 1))))
    if home is not None:
        left = left.filter(home)
    right = rows.select(F.col("id").alias("row"), F.col("v").alias("w"), shard_of(shards).alias("of_shard"), F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("of_block"))
    return left.groupBy("shard", "block").cogroup(right.groupBy("of_shard", "of_block")).applyInArrow(search, schema)


def count_shards(rows: DataFrame, shard_rows: int = SHARD_ROWS) -> int:
    return max(1, -(-rows.count() // shard_rows))


def shard_of(shards: int) -> Column:
    return F.pmod(F.xxhash64("id"), F.lit(shards)).cast("int")


def best(found: DataFrame, k: int) -> DataFrame:
    """The k best of each query: score first, then the smaller id. Shards send k rows a query at most."""
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def top_rows(scores: np.ndarray, ids: np.ndarray, k: int) -> np.ndarray:
    """Positions of the k highest scores, ties to the smaller id, best first."""
    if len(scores) > k:
        edge = np.partition(scores, len(scores) - k)[len(scores) - k]
        keep = np.flatnonzero(scores >= edge)
    else:
        keep = np.arange(len(scores))
    return keep[np.lexsort((ids[keep], -scores[keep]))][:k]
