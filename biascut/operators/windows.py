"""Windows, smoothing of matrices and arrays, bounds, norms, and estimate notions.

Cells are rows: matrices (i, j, x), arrays (a, b, i, j, x), absent cells zero.  A normalisation is a
product of one factor an axis, and containment is symmetric, so smoothing is a *scatter* axis by
axis: every cell spreads over its window carrying its factor.  An array takes four passes of 2w+1
instead of one of (2w+1)^4.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

C_WIN = 17 * 624  # the constant of the array-to-matrix bound, fixed value


def window(i: Column, w: int, size: int) -> Column:
    """The 1-D window as an array."""
    return F.sequence(F.greatest(i - w, F.lit(1)), F.least(i + w, F.lit(size)))


def window_size(i: Column, w: int, size: int) -> Column:
    return F.least(i + w, F.lit(size)) - F.greatest(i - w, F.lit(1)) + 1


def size_of(i: int, w: int, size: int) -> int:
    return min(i + w, size) - max(i - w, 1) + 1


def _extreme(i: Column, w: int, size: int, pick) -> Column:
    """Extreme 1-D window size over the radius-1 window around i."""
    near = [F.greatest(i - 1, F.lit(1)), i, F.least(i + 1, F.lit(size))]
    return pick(*(window_size(n, w, size) for n in near))


def nu(i: Column, w: int, size: int) -> Column:
    return F.lit(1.0) / window_size(i, w, size)


def nu_lo(i: Column, w: int, size: int) -> Column:
    return F.lit(1.0) / _extreme(i, w, size, F.greatest)


def nu_hi(i: Column, w: int, size: int) -> Column:
    return F.lit(1.0) / _extreme(i, w, size, F.least)


def _spread(cells: DataFrame, axis: str, factor: Column, radius: int, size: int) -> DataFrame:
    others = [c for c in cells.columns if c not in (axis, "x")]
    out = cells.select(*others, (F.col("x") * factor).alias("x"), F.explode(window(F.col(axis), radius, size)).alias(axis))
    return out.groupBy(*others, axis).agg(F.sum("x").alias("x")).select(*(c for c in cells.columns))


def _axes(cells: DataFrame, ell: int, k: int | None) -> list[tuple[str, int]]:
    return ([("a", k), ("b", k)] if k else []) + [("i", ell), ("j", ell)]


def smooth_matrix(m: DataFrame, w: int, ell: int) -> DataFrame:
    return reduce(lambda c, ax: _spread(c, ax[0], nu(F.col(ax[0]), w, ax[1]), w, ax[1]), _axes(m, ell, None), m)


def smooth_array(a: DataFrame, w: int, k: int, ell: int) -> DataFrame:
    return reduce(lambda c, ax: _spread(c, ax[0], nu(F.col(ax[0]), w, ax[1]), w, ax[1]), _axes(a, ell, k), a)


def lower_array(a: DataFrame, w: int, k: int, ell: int) -> DataFrame:
    return reduce(lambda c, ax: _spread(c, ax[0], nu_lo(F.col(ax[0]), w, ax[1]), w - 1, ax[1]), _axes(a, ell, k), a)


def upper_array(a: DataFrame, w: int, k: int, ell: int) -> DataFrame:
    return reduce(lambda c, ax: _spread(c, ax[0], nu_hi(F.col(ax[0]), w, ax[1]), w + 1, ax[1]), _axes(a, ell, k), a)


def _keys(cells: DataFrame) -> list[str]:
    return [c for c in ("a", "b", "i", "j") if c in cells.columns]


def _aligned(p: DataFrame, q: DataFrame) -> DataFrame:
    keys = _keys(p)
    both = p.select(*keys, F.col("x").alias("p")).join(q.select(*keys, F.col("x").alias("q")), keys, "full")
    return both.select(*keys, F.coalesce("p", F.lit(0.0)).alias("p"), F.coalesce("q", F.lit(0.0)).alias("q"))


def l1(p: DataFrame, q: DataFrame) -> DataFrame:
    return _aligned(p, q).agg(F.coalesce(F.sum(F.abs(F.col("p") - F.col("q"))), F.lit(0.0)).alias("l1"))


def linf(p: DataFrame, q: DataFrame) -> DataFrame:
    return _aligned(p, q).agg(F.coalesce(F.max(F.abs(F.col("p") - F.col("q"))), F.lit(0.0)).alias("linf"))


def norms(p: DataFrame, q: DataFrame) -> DataFrame:
    d = F.abs(F.col("p") - F.col("q"))
    return _aligned(p, q).agg(F.sum(d).alias("l1"), F.max(d).alias("linf"))


def mass(m: DataFrame) -> DataFrame:
    return m.agg(F.coalesce(F.sum("x"), F.lit(0.0)).alias("mass"))


def smoothed_error(estimate: DataFrame, m: DataFrame, w: int, ell: int) -> DataFrame:
    """One row l1: the estimate is a (w, eps)-smoothed one iff it is at most eps."""
    return l1(estimate, smooth_matrix(m, w, ell))


def pointwise_violation(estimate: DataFrame, a: DataFrame, w: int, k: int, ell: int) -> DataFrame:
    """One row worst: the least delta for which the estimate is (w, delta)-pointwise."""
    keys = _keys(a)
    band = _aligned(lower_array(a, w, k, ell), upper_array(a, w, k, ell)).select(*keys, F.col("p").alias("lo"), F.col("q").alias("hi"))
    x, lo, hi = F.coalesce("x", F.lit(0.0)), F.coalesce("lo", F.lit(0.0)), F.coalesce("hi", F.lit(0.0))
    joined = estimate.select(*keys, "x").join(band, keys, "full")
    return joined.agg(F.coalesce(F.max(F.greatest(lo - x, x - hi, F.lit(0.0))), F.lit(0.0)).alias("worst"))


def array_to_matrix_bound(delta: float, k: int, ell: int, w: int) -> float:
    return delta * (k * ell) ** 2 + C_WIN / w


def classify_against_window(cell: list[Column], centre: list[Column], w: int, reach: int = 0) -> Column:
    """inner (must count), borderline (may count) or outer (must not) for the window around a centre.
    With ``reach`` 0 only distance w is borderline; with 1 also w+1, as in the upper envelope, since a
    label that is off by one can move such a cell into the window."""
    far = F.greatest(*(F.abs(c - z) for c, z in zip(cell, centre)))
    return F.when(far <= w - 1, "inner").when(far <= w + reach, "borderline").otherwise("outer")


def border_fraction(w: int, k: int, ell: int) -> float:
    """Share of cells of a middle window of radius w+1 that lie outside the one of radius w-1."""
    mid = [(k + 1) // 2, (k + 1) // 2, (ell + 1) // 2, (ell + 1) // 2]
    wide = reduce(lambda p, x: p * size_of(x[0], w + 1, x[1]), zip(mid, (k, k, ell, ell)), 1)
    core = reduce(lambda p, x: p * size_of(x[0], w - 1, x[1]), zip(mid, (k, k, ell, ell)), 1) if w >= 1 else 0
    return (wide - core) / wide


def adversarial_relabel(a: DataFrame, shift: dict[str, Column], w: int, k: int, ell: int) -> DataFrame:
    """Estimates an array after moving every cell's label by at most one an axis: each cell spreads
    over the window of its *moved* label with its moved factor."""
    sizes = dict(_axes(a, ell, k))
    moved = a.select(*(F.greatest(F.lit(1), F.least(F.lit(sizes[c]), F.col(c) + shift.get(c, F.lit(0)))).alias(c) for c in _keys(a)), "x")
    return smooth_array(moved.groupBy(*_keys(a)).agg(F.sum("x").alias("x")), w, k, ell)
