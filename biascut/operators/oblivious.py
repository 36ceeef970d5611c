"""Snapshot rules: per-class selection probabilities, their values, cuts and ratio certificates.

A rule labels a vertex of bias class i one with probability r_i, independently; its expected value
is the sum over cells of r_i (1 - r_j) x(i, j), a lower bound on the optimum that changes by no more
than the L1 distance of the matrices.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .classes import refine_partition, uniform_thresholds
from .windows import size_of


@dataclass(frozen=True)
class Selection:
    """Thresholds and probabilities; with ``num`` and ``den`` the probabilities are exact fractions."""

    t: tuple[float, ...]
    r: tuple[float, ...]
    num: tuple[int, ...] | None = None
    den: int | None = None

    @property
    def ell(self) -> int:
        return len(self.r)

    def column(self, i: Column) -> Column:
        """r_i as an expression: an array literal indexed by class."""
        return F.element_at(F.array(*(F.lit(float(x)) for x in self.r)), i.cast("int"))

    def mapping(self) -> Column:
        return F.create_map(*(v for k, x in enumerate(self.r) for v in (F.lit(k + 1), F.lit(float(x)))))

    def table(self, spark) -> DataFrame:
        return spark.createDataFrame([(k + 1, self.t[k], self.t[k + 1], self.r[k]) for k in range(self.ell)], "i int, lo double, hi double, r double")


def uniform_clamped(ell: int = 21) -> Selection:
    """Equal classes, r = 1/2 + midpoint clipped to [0, 1], as fractions over 2 ell."""
    num = tuple(min(2 * ell, max(0, 2 * (2 * i - 1) - ell)) for i in range(1, ell + 1))
    return Selection(uniform_thresholds(ell), tuple(n / (2 * ell) for n in num), num, 2 * ell)


def clamped_linear(a: float = 0.49, f: int = 99) -> Selection:
    """One class below -a and one from a on; f equal ones between; r = 1/2 + x/(2a) at midpoints."""
    inner = [-a + 2 * a * k / f for k in range(f)] + [a]
    mids = [(x + y) / 2 for x, y in zip(inner, inner[1:])]
    return Selection((-1.0, *inner, 1.0), (0.0, *(0.5 + x / (2 * a) for x in mids), 1.0))


def greedy_selection() -> Selection:
    """One for positive bias, zero for negative; an even vertex counts as positive."""
    return Selection((-1.0, 0.0, 1.0), (0.0, 1.0), (0, 1), 1)


def coin_selection() -> Selection:
    return Selection((-1.0, 1.0), (0.5,), (1,), 2)


def refine_selection(sel: Selection, lam: float) -> Selection:
    """The same rule on a refined partition."""
    t, base = refine_partition(sel.t, lam)
    return Selection(t, tuple(sel.r[b - 1] for b in base), tuple(sel.num[b - 1] for b in base) if sel.num else None, sel.den)


def oblivious_value(m: DataFrame, sel: Selection) -> DataFrame:
    """One row value, from normalised cells (i, j, x)."""
    return m.agg(F.coalesce(F.sum(F.col("x") * sel.column(F.col("i")) * (1 - sel.column(F.col("j")))), F.lit(0.0)).alias("value"))


def oblivious_value_exact(counts: DataFrame, sel: Selection) -> DataFrame:
    """One row (num, m, value) from cell counts: integers up to one last division."""
    c = F.array(*(F.lit(n).cast("long") for n in sel.num))
    part = F.col("weight") * F.element_at(c, F.col("i").cast("int")) * (F.lit(sel.den) - F.element_at(c, F.col("j").cast("int")))
    s = counts.agg(F.sum(part).cast("long").alias("num"), F.sum("weight").cast("long").alias("m"))
    return s.select("num", "m", (F.col("num") / (F.col("m") * F.lit(sel.den**2))).alias("value"))


def vertex_chances(edges: DataFrame, sel: Selection) -> DataFrame:
    """(vid, p): the rule's probability of each vertex.  Equal classes of whole degrees are told in integers, as in
    snapshots: a bias on a threshold (4/7 among 21 classes) may lie below it in floating point."""
    from .classes import bias_class, class_index
    from .vertex_stats import degrees

    d = degrees(edges)
    whole = sel.t == uniform_thresholds(sel.ell) and dict(d.dtypes)["deg"] == "bigint"
    i = bias_class(F.col("d_out"), F.col("deg"), sel.ell) if whole else class_index((F.col("d_out") - F.col("d_in")) / F.col("deg"), sel.t)
    return d.select("vid", sel.column(i).alias("p"))


def oblivious_cut(edges: DataFrame, sel: Selection, seed: int = 0) -> DataFrame:
    """(vid, side): the cut itself, with one md5 coin a vertex."""
    coin = F.conv(F.substring(F.md5(F.concat(F.col("vid").cast("string"), F.lit(f":{seed}"))), 1, 8), 16, 10).cast("long")
    return vertex_chances(edges, sel).select("vid", (coin < F.col("p") * float(1 << 32)).cast("int").alias("side"))


def oblivious_cut_mean(edges: DataFrame, sel: Selection, seeds: int) -> DataFrame:
    """One row: the mean value of the cuts of ``seeds`` seeds, all in one pass over the edges."""
    from .edges import as_weighted

    chance = vertex_chances(edges, sel)
    w = as_weighted(edges)
    x = w.join(chance.select(F.col("vid").alias("u"), F.col("p").alias("pu")), "u").join(chance.select(F.col("vid").alias("v"), F.col("p").alias("pv")), "v")

    def side(vid, p, s):
        return F.conv(F.substring(F.md5(F.concat(vid.cast("string"), F.lit(":"), s.cast("string"))), 1, 8), 16, 10).cast("long") < p * float(1 << 32)

    hit = F.size(F.filter(F.sequence(F.lit(0), F.lit(seeds - 1)), lambda s: side(F.col("u"), F.col("pu"), s) & ~side(F.col("v"), F.col("pv"), s)))
    return x.agg((F.sum(F.col("weight") * hit) / (F.sum("weight") * seeds)).alias("value"))


def smoothed_selection(sel: Selection, w: int) -> tuple[list[float], list[float]]:
    """Means of r, and of 1 - r, over each class's window: smoothing and the rule in one product."""
    ell, r = sel.ell, np.array(sel.r)
    mean = [float(r[max(0, i - w) : i + w + 1].sum()) / size_of(i + 1, w, ell) for i in range(ell)]
    return mean, [1 - x for x in mean]


def smoothed_value(m: DataFrame, sel: Selection, w: int) -> DataFrame:
    """The rule's value of the smoothed matrix without making that matrix."""
    up, down = smoothed_selection(sel, w)
    pick = lambda v, c: F.element_at(F.array(*(F.lit(x) for x in v)), F.col(c).cast("int"))
    return m.agg(F.coalesce(F.sum(F.col("x") * pick(up, "i") * pick(down, "j")), F.lit(0.0)).alias("value"))


def certify_ratio(sel: Selection, iterations: int = 60, present: list[int] | None = None) -> dict[str, float]:
    """The least ratio of the rule's value to the optimum over all weighted graphs, or over those whose
    vertices lie in the classes ``present`` (which must allow a graph).

    Vertices matter only by (class, side of the best cut).  The least value over edge weights
    between such types, with the cut edges weighing one in all and every type's bias within its
    class, is a linear programme.  Solved by a primal-dual interior-point method; ``lower`` is a
    bound from the dual alone: multipliers of the bias constraints are kept non-negative and the
    value follows from the reduced costs, with cycles of negative reduced cost off the cut paid for.
    """
    t, r = np.array(sel.t), np.array(sel.r)
    some = np.arange(sel.ell) if present is None else np.array(sorted(set(present))) - 1
    n = 2 * len(some)
    cls, side = np.tile(some, 2), np.arange(n) // len(some)  # types: side 0 first, then side 1
    lo, hi = t[cls], t[cls + 1]
    cost = np.outer(r[cls], 1 - r[cls])  # by tail type and head type
    cut = np.outer(side == 1, side == 0).astype(float)
    # rows: out - in - lo (out + in) >= 0 and hi (out + in) - out + in >= 0 of each type, with slacks; cut weight 1.
    # An edge meets the two rows of its tail (factors of ``tails``), the two of its head, and the cut's.
    tails, heads = (1 - lo, hi - 1), (-1 - lo, hi + 1)

    def times(x: np.ndarray, slack: np.ndarray) -> np.ndarray:
        out, into = x.sum(axis=1), x.sum(axis=0)
        return np.concatenate([f * out + g * into - s for f, g, s in zip(tails, heads, np.split(slack, 2))] + [[(x * cut).sum()]])

    def back(y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        low, high = y[:n], y[n : 2 * n]
        return (tails[0] * low + tails[1] * high)[:, None] + (heads[0] * low + heads[1] * high)[None, :] + cut * y[-1], -y[: 2 * n]

    def normal(d: np.ndarray, slack: np.ndarray) -> np.ndarray:
        """The constraint matrix times the weights times its transpose, from sums of ``d``."""
        N = np.zeros((2 * n + 1, 2 * n + 1))
        for i in range(2):
            for j in range(2):
                block = N[i * n : (i + 1) * n, j * n : (j + 1) * n]
                block += np.diag(tails[i] * tails[j] * d.sum(axis=1) + heads[i] * heads[j] * d.sum(axis=0))
                block += np.outer(tails[i], heads[j]) * d + np.outer(heads[i], tails[j]) * d.T
            N[i * n : (i + 1) * n, -1] = N[-1, i * n : (i + 1) * n] = tails[i] * (d * cut).sum(axis=1) + heads[i] * (d * cut).sum(axis=0)
        N[-1, -1] = (d * cut).sum()
        N[np.arange(2 * n), np.arange(2 * n)] += slack
        return N

    size = n * n + 2 * n
    pack = lambda x, slack: np.concatenate([x.ravel(), slack])
    split = lambda v: (v[: n * n].reshape(n, n), v[n * n :])
    b = np.zeros(2 * n + 1)
    b[-1] = 1
    c = pack(cost, np.zeros(2 * n))
    x, y, s = np.ones(size), np.zeros(2 * n + 1), np.ones(size)
    for _ in range(iterations):
        rp, rd, gap = b - times(*split(x)), c - pack(*back(y)) - s, x @ s / size
        if max(np.abs(rp).max(), np.abs(rd).max(), gap) < 1e-10:
            break
        d = x / s
        N = normal(*split(d))
        N[np.diag_indices_from(N)] += 1e-13 * np.trace(N) / len(N)
        solve = np.linalg.inv(N)

        def direction(mu, extra):
            rc = mu - x * s - extra
            dy = solve @ (rp + times(*split(d * rd - rc / s)))
            ds = rd - pack(*back(dy))
            return (rc - x * ds) / s, dy, ds

        dx, dy, ds = direction(0.0, 0.0)
        step = lambda v, dv: min(1.0, float((-v[dv < 0] / dv[dv < 0]).min(initial=np.inf)))
        aim = (x + step(x, dx) * dx) @ (s + step(s, ds) * ds) / size
        dx, dy, ds = direction((aim / gap) ** 3 * gap, dx * ds)
        ap, ad = 0.995 * step(x, dx), 0.995 * step(s, ds)
        x, y, s = x + min(ap, 1) * dx, y + min(ad, 1) * dy, s + min(ad, 1) * ds
    mult = np.maximum(y[: 2 * n], 0)  # of the slack rows: non-negative
    reduced = cost - back(np.append(mult, 0.0))[0]
    off = float(min(0.0, reduced[cut == 0].min(initial=0.0)))
    # an uncut edge of negative reduced cost can weigh at most 3 times the cut: every value is >= cut/4
    lower = float(reduced[cut == 1].min()) + 3 * off
    return {"primal": float(c @ x), "dual": float(b @ y), "lower": lower}
