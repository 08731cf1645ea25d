import math

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from flowregions.functions import bits, numbers


@pytest.fixture(scope="module")
def grid(spark):
    rows = [(n, k) for n in range(0, 51) for k in range(0, n + 1)]
    return spark.createDataFrame(rows, "n int, k int")


def test_binomials_equal_whole_numbers(grid):
    rows = grid.select("n", "k", bits.lchoose(F.col("n"), F.col("k")).alias("c"), bits.lmulti(F.col("n") + 1, F.col("k")).alias("m"), bits.lfact(F.col("n")).alias("f")).collect()
    for r in rows:
        assert r.c == pytest.approx(math.log2(math.comb(r.n, r.k)), abs=1e-9)
        assert r.m == pytest.approx(math.log2(math.comb(r.n + r.k, r.k)), abs=1e-9)
        assert r.f == pytest.approx(math.log2(math.factorial(r.n)), abs=1e-9)


def test_large_binomials_keep_their_digits(spark):
    cases = [(10**12, 3), (10**15, 7), (10**9, 10**6), (625, 60000)]
    rows = spark.createDataFrame(cases, "n long, k long").select("n", "k", bits.lmulti(F.col("n"), F.col("k")).alias("m")).collect()
    for r in rows:
        exact = math.log2(math.comb(r.n + r.k - 1, r.k)) if r.k <= 10**5 else sum(math.log2((r.n + j) / (j + 1)) for j in range(r.k))
        assert r.m == pytest.approx(exact, rel=1e-11, abs=1e-8)


def test_edges(spark):
    one = spark.range(1)
    row = one.select(bits.lchoose(F.lit(3), F.lit(5)).alias("outside"), bits.lcompositions(F.lit(0), F.lit(0)).alias("nothing"), bits.lmulti(F.lit(1), F.lit(9)).alias("one_kind"), bits.plogp(F.lit(0.0)).alias("zero"), bits.lgamma(F.lit(0.5)).alias("half")).first()
    assert row.outside is None and row.nothing == 0 and row.one_kind == pytest.approx(0, abs=1e-12) and row.zero == 0
    assert row.half == pytest.approx(math.lgamma(0.5), abs=1e-9)


def test_sql_functions(spark):
    bits.register_sql(spark)
    got = spark.sql("select lchoose_bits(10, 3) c, lmulti_bits(4, 5) m, lfact_bits(200) f").first()
    assert got.c == pytest.approx(math.log2(120)) and got.m == pytest.approx(math.log2(56)) and got.f == pytest.approx(math.lgamma(201) / math.log(2), rel=1e-10)


@settings(max_examples=50, deadline=None)
@given(st.integers(0, 3000), st.integers(0, 3000))
def test_numpy_forms(a, b):
    n, k = max(a, b), min(a, b)
    assert float(numbers.lchoose(n, k)) == pytest.approx(math.log2(math.comb(n, k)), abs=1e-6)


def test_text_and_columns_give_the_same_lengths(spark):
    grid = spark.range(0, 40).select(F.col("id").alias("n"), (F.col("id") * 7 % 23).alias("k"))
    text = (bits.lfact("n"), bits.lchoose("n + k", "k"), bits.lmulti("n", "k"), bits.lcompositions("n + k", "n"), bits.plogp("n / 40"), bits.lgamma("n + 0.5D"), bits.lchoose(50, "k"))
    n, k = F.col("n"), F.col("k")
    columns = (bits.lfact(n), bits.lchoose(n + k, k), bits.lmulti(n, k), bits.lcompositions(n + k, n), bits.plogp(n / 40), bits.lgamma(n + 0.5), bits.lchoose(50, k))
    for row in grid.select(*[F.struct(a.alias("text"), b.alias("column")) for a, b in zip(text, columns, strict=True)]).collect():
        for pair in row:
            assert pair.text == pair.column
