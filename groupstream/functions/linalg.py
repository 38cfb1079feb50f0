"""Vector algebra as column expressions. With a known dimension sums are unrolled, so they run in generated code."""

from __future__ import annotations

from collections.abc import Sequence
from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F


def dot(a: Column, b: Column, d: int | None = None) -> Column:
    if d is None:
        return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)
    return reduce(lambda s, x: s + x, [F.get(a, F.lit(i)) * F.get(b, F.lit(i)) for i in range(d)])


def norm(a: Column, d: int | None = None) -> Column:
    return F.sqrt(dot(a, a, d))


def cosine(a: Column, b: Column, d: int | None = None) -> Column:
    """Zero where either vector is zero."""
    size = norm(a, d) * norm(b, d)
    return F.when(size > 0, dot(a, b, d) / size).otherwise(F.lit(0.0))


def add(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x + y)


def axpy(s: Column | float, a: Column, b: Column) -> Column:
    """s * a + b."""
    s = F.lit(s) if not isinstance(s, Column) else s
    return F.zip_with(a, b, lambda x, y: s * x + y)


def scale(s: Column | float, a: Column) -> Column:
    s = F.lit(s) if not isinstance(s, Column) else s
    return F.transform(a, lambda x: s * x)


def blend(share: float, a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: F.lit(share) * x + F.lit(1 - share) * y)


def zeros(d: int) -> Column:
    return F.array(*[F.lit(0.0)] * d)


def sigmoid(x: Column) -> Column:
    return 1.0 / (1.0 + F.exp(-x))


ACTIVATIONS = {"sigmoid": sigmoid, "tanh": F.tanh, "identity": lambda x: x}


def matvec(matrix: Sequence[Sequence[float]], x: Column, bias: Sequence[float] | None = None) -> Column:
    """A matrix that every task holds, times a vector column."""
    bias = bias or [0.0] * len(matrix)
    rows = [reduce(lambda s, t: s + t, [F.lit(float(w)) * F.get(x, F.lit(j)) for j, w in enumerate(row)]) + F.lit(float(b)) for row, b in zip(matrix, bias)]
    return F.array(*rows)


def dense(matrix, x: Column, bias=None, act: str = "sigmoid") -> Column:
    return F.transform(matvec(matrix, x, bias), ACTIVATIONS[act])


def vec_sum(a: Column, d: int) -> Column:
    """Element-wise sum of a group's vectors: d partial sums, combined before the shuffle."""
    return F.array(*[F.sum(F.get(a, F.lit(i))) for i in range(d)])


def vec_mean(a: Column, d: int) -> Column:
    return F.array(*[F.avg(F.get(a, F.lit(i))) for i in range(d)])


def rounded(a: Column, digits: int = 6) -> Column:
    """Rounded components; adding zero turns -0 into 0."""
    return F.transform(a, lambda x: F.round(x, digits) + F.lit(0.0))


def unit(a: Column, d: int | None = None) -> Column:
    n = norm(a, d)
    return F.when(n > 0, F.transform(a, lambda x: x / n)).otherwise(a)
