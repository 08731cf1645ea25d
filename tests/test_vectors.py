"""The exact neighbour graph of vectors against brute force."""

import time

import numpy as np
import pytest

from flowregions.operators import adjacency as adj


def brute(rows, k):
    v = {i: np.array(x) / np.linalg.norm(x) for i, x in rows}
    return {(i, j) for i in v for j in sorted((j for j in v if j != i), key=lambda j: (-round(float(v[i] @ v[j]), 9), j))[:k]}


@pytest.mark.parametrize("block", [7, 1000])
def test_knn_is_exact_with_copies_and_vectors_without_direction(spark, block):
    draw = np.random.default_rng(5)
    rows = [(k, draw.normal(size=6).tolist()) for k in range(40)] + [(k, [1.0, 2.0, 0.0, 0.0, 0.0, 1.0]) for k in range(40, 60)]
    odd = [(90, None), (91, [0.0] * 6), (92, [float("nan")] * 6), (93, [1.0, None, 0.0, 0.0, 0.0, 0.0]), (None, [1.0] * 6)]
    got = adj.knn(spark.createDataFrame(rows + odd, "vec_id long, embedding array<double>"), 8, block=block).collect()
    assert {(r.src, r.dst) for r in got} == brute(rows, 8) and len(got) == 60 * 8


def test_knn_of_few_and_of_none(spark):
    few = spark.createDataFrame([(1, [1.0, 0.0]), (2, [1.0, 1.0]), (3, [0.0, 1.0])], "vec_id long, embedding array<double>")
    assert {(r.src, r.dst) for r in adj.knn(few, 8).collect()} == {(a, b) for a in (1, 2, 3) for b in (1, 2, 3) if a != b}
    assert adj.knn(few.filter("vec_id > 3"), 8).count() == 0


def test_knn_of_ten_thousand_in_time(spark):
    draw = np.random.default_rng(6).normal(size=(10_000, 16))
    rows = spark.createDataFrame([(k, x) for k, x in enumerate(draw.tolist())], "vec_id long, embedding array<double>")
    began = time.monotonic()
    assert adj.knn(rows, 8).count() == 80_000
    assert time.monotonic() - began < 60
