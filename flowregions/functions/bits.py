"""Code lengths in bits as Catalyst expressions.

Spark has no log-gamma. Binomials are built from entropy terms and the remainders of Stirling's
formula, so that no two huge numbers are subtracted: they stay exact to about 1e-12 of a bit relative
to their own size even for n = 10^15. Everything stays in generated code.

Operands are numbers, SQL text over the columns at hand ("n - 1"), or Columns. A formula of text is
parsed once, where each operator of a Column is several calls from Python to the JVM (seconds for a plan
of some hundred of them), so the engine's own plans use text.
"""

from __future__ import annotations

import functools
import math
from collections.abc import Callable

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

LN2 = math.log(2.0)
#: Below this, remainders come from a table; from here on the series is exact to 1e-14.
TABLE = 16
HALF_LN_2PI = 0.5 * math.log(2 * math.pi)


def _operators(sign: str) -> tuple[Callable, Callable]:
    def left(self: Text, x: Text | float) -> Text:
        return Text(f"({self.sql} {sign} {_text(x).sql})")

    def right(self: Text, x: Text | float) -> Text:
        return Text(f"({_text(x).sql} {sign} {self.sql})")

    return left, right


class Text:
    """A formula as SQL text, with the operators of a Column."""

    __add__, __radd__ = _operators("+")
    __sub__, __rsub__ = _operators("-")
    __mul__, __rmul__ = _operators("*")
    __truediv__, __rtruediv__ = _operators("/")
    __lt__, __gt__ = _operators("<")[0], _operators(">")[0]
    __eq__ = _operators("=")[0]
    __or__ = _operators("OR")[0]
    __hash__ = None

    def __init__(self, sql: str) -> None:
        self.sql = sql

    def __neg__(self) -> Text:
        return Text(f"(-{self.sql})")

    def cast(self, kind: str) -> Text:
        return Text(f"CAST({self.sql} AS {kind})")


def _text(x: Text | float) -> Text:
    return x if isinstance(x, Text) else Text(f"({float(x)!r}D)")


def _formula(of: Callable) -> Callable:
    """``of`` with operands as doubles in one form: text, parsed at the end, unless one of them is a Column."""

    @functools.wraps(of)
    def made(*args: Column | Text | str | float) -> Column | Text:
        if any(isinstance(x, Column) for x in args):
            return of(*[(x if isinstance(x, Column) else F.expr(x) if isinstance(x, str) else F.lit(x)).cast("double") for x in args])
        if any(isinstance(x, Text) for x in args):  # inside another formula
            return of(*[_text(x) for x in args])
        return F.expr(of(*[Text(f"({x})").cast("double") if isinstance(x, str) else _text(x) for x in args]).sql)

    return made


def _call(name: str, x: Column | Text) -> Column | Text:
    return Text(f"{name}({x.sql})") if isinstance(x, Text) else F.call_function(name, x)


def _choose(*cases: tuple, otherwise: Column | Text | float) -> Column | Text:
    """The value of the first condition that holds."""
    if isinstance(cases[0][0], Text):
        whens = " ".join(f"WHEN {cond.sql} THEN {'CAST(NULL AS DOUBLE)' if value is None else _text(value).sql}" for cond, value in cases)
        return Text(f"(CASE {whens} ELSE {_text(otherwise).sql} END)")
    chain = F
    for cond, value in cases:
        chain = chain.when(cond, F.lit(value).cast("double"))
    return chain.otherwise(otherwise)


def _remainder_value(m: int) -> float:
    return math.lgamma(m + 1) - ((m + 0.5) * math.log(m) - m + HALF_LN_2PI)


REMAINDERS = f"array({', '.join(f'{_remainder_value(k)!r}D' for k in range(1, TABLE))})"


@_formula
def remainder(m):
    """ln m! - Stirling's formula at m, m >= 1."""
    place = m.cast("int") - 1
    known = Text(f"get({REMAINDERS}, CAST({place.sql} AS INT))") if isinstance(m, Text) else F.get(F.expr(REMAINDERS), place)
    q = 1.0 / (m * m)
    series = (1.0 / 12 - q * (1.0 / 360 - q * (1.0 / 1260 - q / 1680))) / m
    return _choose((m < TABLE, known), otherwise=series)


@_formula
def lfact(n):
    """log2 n!"""
    return _choose((n < 2, 0.0), otherwise=((n + 0.5) * _call("ln", n) - n + HALF_LN_2PI + remainder(n)) / LN2)


@_formula
def lgamma(x):
    """ln Gamma(x) for whole or real x > 0: the series, shifted up for small x."""
    z = x + 8
    shift = x
    for k in range(1, 8):
        shift = shift * (x + k)
    q = 1.0 / (z * z)
    series = (1.0 / 12 - q * (1.0 / 360 - q * (1.0 / 1260 - q * (1.0 / 1680 - q / 1188)))) / z
    return (z - 0.5) * _call("ln", z) - z + HALF_LN_2PI + series - _call("ln", shift)


@_formula
def lchoose(n, k):
    """log2 of the binomial; 0 at both ends, null where k is outside 0..n."""
    rest = n - k
    entropy = -k * _call("ln", k / n) - rest * _call("log1p", -k / n)
    edge = 0.5 * (_call("ln", n) - _call("ln", k) - _call("ln", rest)) - HALF_LN_2PI
    inside = (entropy + edge + remainder(n) - remainder(k) - remainder(rest)) / LN2
    return _choose(((k < 0) | (k > n), None), ((k == 0) | (rest == 0), 0.0), otherwise=inside)


@_formula
def lmulti(n, k):
    """log2 of the number of multisets of k out of n kinds; 0 for k = 0."""
    return _choose((k == 0, 0.0), otherwise=lchoose(n + k - 1, k))


@_formula
def lcompositions(w, e):
    """log2 of the ways to split w into e positive parts in order; 0 for nothing."""
    return _choose((e == 0, 0.0), otherwise=lchoose(w - 1, e - 1))


@_formula
def plogp(p):
    """p log2 p, 0 at 0."""
    return _choose((p > 0, p * _call("log2", p)), otherwise=0.0)


def entropy(count, total) -> Column:
    """Entropy in bits of a distribution given by counts, as an aggregate: log2 total - sum c log2 c / total."""
    share = f"({count}) / ({total})" if isinstance(count, str) and isinstance(total, str) else (F.expr(count) if isinstance(count, str) else count) / (F.expr(total) if isinstance(total, str) else total)
    return -F.sum(plogp(share))


#: SQL functions of one expression each.
SQL_FUNCTIONS = {
    "lfact_bits": ("n DOUBLE", "CASE WHEN n < 2 THEN 0D WHEN n < 150 THEN log2(aggregate(sequence(1, CAST(n AS INT)), 1D, (a, x) -> a * x)) ELSE ((n + 0.5) * ln(n) - n + 0.5 * ln(2 * pi()) + 1 / (12 * n) - 1 / (360 * n * n * n)) / ln(2) END"),
    "lchoose_bits": ("n DOUBLE, k DOUBLE", "CASE WHEN k < 0 OR k > n THEN CAST(NULL AS DOUBLE) WHEN k = 0 OR k = n THEN 0D ELSE lfact_bits(n) - lfact_bits(k) - lfact_bits(n - k) END"),
    "lmulti_bits": ("n DOUBLE, k DOUBLE", "CASE WHEN k = 0 THEN 0D ELSE lchoose_bits(n + k - 1, k) END"),
}


def register_sql(spark: SparkSession) -> None:
    """Makes lfact_bits, lchoose_bits and lmulti_bits callable from SQL."""
    for name, (args, body) in SQL_FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({args}) RETURNS DOUBLE RETURN {body}")
