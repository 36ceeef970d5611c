"""Threshold partitions and class indices of biases and degrees."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F


def uniform_thresholds(ell: int) -> tuple[float, ...]:
    return tuple(-1 + 2 * k / ell for k in range(ell)) + (1.0,)


def is_lambda_wide(t: tuple[float, ...], lam: float) -> bool:
    return all(lam / 2 - 1e-12 <= b - a <= lam + 1e-12 for a, b in zip(t, t[1:]))


def refine_partition(t: tuple[float, ...], lam: float, strict: bool = False) -> tuple[tuple[float, ...], list[int]]:
    """Splits every interval into equal parts of width at most lam; also the base class of each part."""
    out, base = [t[0]], []
    for k, (a, b) in enumerate(zip(t, t[1:])):
        if strict and b - a < lam / 2:
            raise ValueError(f"interval {k + 1} is narrower than lam/2")
        parts = max(1, math.ceil((b - a) / lam - 1e-9))
        out += [a + (b - a) * p / parts for p in range(1, parts)] + [b]
        base += [k + 1] * parts
    return tuple(out), base


def class_index(x: Column, t: tuple[float, ...]) -> Column:
    """1-based class of x: half-open intervals, the last closed; null outside.  A balanced tree of
    comparisons, so depth grows with the logarithm of the number of classes and stays in codegen."""

    def tree(lo: int, hi: int) -> Column:
        if hi - lo == 1:
            return F.lit(hi)
        mid = (lo + hi) // 2
        return F.when(x < F.lit(float(t[mid])), tree(lo, mid)).otherwise(tree(mid, hi))

    return F.when((x >= F.lit(float(t[0]))) & (x <= F.lit(float(t[-1]))), tree(0, len(t) - 1))


def whole_div(a: Column, b: Column) -> Column:
    """Integer quotient of non-negative longs, without a detour through doubles."""
    return F.call_function("div", a.cast("long"), b.cast("long"))


def bias_class(d_out: Column, deg: Column, ell: int) -> Column:
    """Class of the bias among ell equal ones, in integers: (bias + 1)/2 = d_out/deg."""
    return F.least(F.lit(ell).cast("long"), whole_div(d_out * ell, deg) + 1).cast("int")


def degree_class(deg: Column, k: int) -> Column:
    """Dyadic class: a holds 2^(a-1) <= deg < 2^a, the last one everything above."""
    return F.least(F.length(F.bin(deg.cast("long"))), F.lit(k)).cast("int")


def degree_class_general(deg: Column, d: tuple[float, ...]) -> Column:
    """Classes of arbitrary degree thresholds."""
    return class_index(F.least(deg.cast("double"), F.lit(float(d[-1]))), d)
