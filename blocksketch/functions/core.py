"""Column expressions that the operators share; all of them stay in generated code."""

from __future__ import annotations

from collections.abc import Sequence
from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F

TWO32 = 4294967296.0


def hash_int(*parts: Column | str) -> Column:
    """The first 32 bits of md5 over the parts joined with ``|``, as BIGINT.

    Unlike ``rand`` it depends on the row's own values, never on partitioning,
    and any other engine can compute it.
    """
    cols = [F.lit(p) if isinstance(p, str) else p for p in parts]
    return F.conv(F.substring(F.md5(F.concat_ws("|", *[c.cast("string") for c in cols])), 1, 8), 16, 10).cast("long")


def hash_uniform(*parts: Column | str) -> Column:
    """Uniform in [0, 1)."""
    return hash_int(*parts) / F.lit(TWO32)


def hash_normal(*parts: Column | str) -> Column:
    """Standard normal by the Box-Muller transform of two hashed uniforms."""
    first = (hash_int("r", *parts) + 1) / F.lit(TWO32 + 1)
    return F.sqrt(-2.0 * F.log(first)) * F.cos(2.0 * F.pi() * hash_uniform("t", *parts))


def add(terms: Sequence[Column]) -> Column:
    """Left-to-right sum."""
    return reduce(lambda a, b: a + b, terms)


def dot(features: Column, x: Sequence[float]) -> Column:
    """Inner product with a vector held in the plan (the 'broadcast' of the parameters)."""
    if len(x) <= 16:
        return add([F.get(features, F.lit(i)) * F.lit(float(v)) for i, v in enumerate(x)])
    held = F.array(*[F.lit(float(v)) for v in x])
    return F.aggregate(F.zip_with(features, held, lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v)


def quadratic(features: Column, m: Sequence[Sequence[float]]) -> Column:
    """a' M a for a symmetric M of few columns."""
    d = len(m)
    at = [F.get(features, F.lit(i)) for i in range(d)]
    return add([(1.0 if i == j else 2.0) * F.lit(float(m[i][j])) * at[i] * at[j] for i in range(d) for j in range(i, d)])


def half_up(value: Column) -> Column:
    """Nearest integer, halves up, the same for negatives."""
    return F.floor(value + 0.5)


def rounded(value: Column, digits: int) -> Column:
    """Rounded, with one zero."""
    return F.round(value, digits) + F.lit(0.0)
