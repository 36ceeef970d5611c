"""Unknown stream length: sparsification, a geometric grid of guesses, a small exact buffer."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from .edges import edge_count
from .exact import exact_val
from .estimator import estimate_of, estimate_value
from .hashing import below, edge_word, hex_threshold
from .layered import Sketch, _finish, build_sketch, edge_layers, sparse_word
from .oblivious import Selection, uniform_clamped
from .params import C_SPARSE, Params, practical_params, theory_params

GROWTH = 1.9  # ratio of neighbouring guesses, fixed value


def sparsify(edges: DataFrame, p: float, seed: int = 0, coin: str = "md5") -> DataFrame:
    """Keeps every edge with probability p, by a coin of its id: one more filter in the scan."""
    if p >= 1:
        return edges
    return edges.where(below(edge_word(F.col("eid"), F.concat_ws(":", F.lit("s"), F.lit(seed)), coin), F.lit(float(p))))


def sparsify_rate(n: int, m: float, eps: float, c: float = C_SPARSE) -> float:
    return min(1.0, c * n / (eps**2 * m))


def guess_grid(n: int, power: float = 2.0) -> list[tuple[int, float]]:
    """(t, 1.9^t) from sqrt(n) to n^power."""
    lo = math.floor(math.log(max(math.sqrt(n), 1)) / math.log(GROWTH))
    hi = math.ceil(power * math.log(max(n, 2)) / math.log(GROWTH))
    return [(t, GROWTH**t) for t in range(lo, hi + 1)]


def select_guess(m: int, grid: list[tuple[int, float]]) -> int:
    """The t with 1.9^t <= m < 1.9^(t+1); the nearest end outside the grid."""
    for t, g in grid:
        if g <= m < GROWTH * g:
            return t
    return grid[0][0] if m < grid[0][1] else grid[-1][0]


def select_guess_column(m, grid: list[tuple[int, float]]):
    out = F.lit(grid[0][0])
    for t, g in grid:
        out = F.when(m >= F.lit(float(g)), F.lit(t)).otherwise(out)
    return out


def sketch_all_guesses(edges: DataFrame, n: int, make=practical_params, power: float = 2.0, **kw) -> Sketch:
    """One scan for all guesses: the guess is one more key of the parameter table."""
    return build_sketch(edges, {t: make(max(1, round(g)), **kw) for t, g in guess_grid(n, power)})


def guess_of(s: Sketch, m: int) -> Sketch:
    """The part of a many-guess sketch that fits the observed length."""
    t = select_guess(m, [(g, GROWTH**g) for g in sorted(s.params)])
    pick = lambda df: df.where(F.col("guess") == t)
    return Sketch(s.meta, pick(s.vertices), pick(s.edges), pick(s.overflow), {t: s.params[t]})


def small_graph_exact(edges: DataFrame, m_min: int, max_n: int = 20) -> DataFrame | None:
    """The exact row for streams of at most m_min edges, else None; reads m_min + 1 edges at most."""
    head = edges.limit(m_min + 1)
    return exact_val(head, max_n) if head.count() <= m_min else None


@dataclass
class Pass:
    """What one scan of a stream of unknown length leaves: its length, the edges that each guess's
    sparsifier let through, all guesses' sampled rows, and the first edges of every task."""

    m: int
    kept: dict[int, int]
    rows: DataFrame
    grid: list[tuple[int, float]]
    params: dict[int, Params]
    buffer_limit: int

    @property
    def guess(self) -> int:
        return select_guess(self.m, self.grid)

    @property
    def buffer(self) -> DataFrame | None:
        """The whole stream, if it is no longer than the buffer."""
        return self.rows.where("guess = -1").select("eid", "u", "v") if self.m <= self.buffer_limit else None

    def sketch(self) -> Sketch:
        """The sketch of the guess that the length picks."""
        t = self.guess
        meta = self.rows.sparkSession.createDataFrame([(self.kept[t],)], "m long")
        s = _finish(self.rows.where(F.col("guess") == t), meta, {t: self.params[t]})
        s.held = (self.rows, s.held[1])
        return s


def one_pass(edges: DataFrame, n: int, eps: float, make=practical_params, power: float = 2.0, seed: int = 0) -> Pass:
    """Counter, exact buffer, and a sparsified sketch for every guess of the length, side by side in one
    scan.  n: the number of vertices, or a bound on it.  A guess g sees each edge with probability
    min(C n / eps^2, g) / g, and ``make`` gives its parameters from the edges it then expects."""
    grid, limit = guess_grid(n, power), math.isqrt(n)
    rates = {t: sparsify_rate(n, g, eps) for t, g in grid}
    params = {t: make(max(1, round(rates[t] * g))).replace(seed=seed) for t, g in grid}
    let = [F.sum((F.col("_w") < F.lit("g" if r >= 1 else hex_threshold(r))).cast("long")).alias(f"kept_{t}") for t, r in rates.items()]
    seen = Observation()
    counted = edges.select("eid", "u", "v", sparse_word(F.col("eid"), seed).alias("_w")).observe(seen, F.count(F.lit(1)).alias("m"), *let)
    rows = edge_layers(counted, params, rates, head=limit).persist()
    rows.count()
    got = seen.get
    return Pass(got["m"], {t: got[f"kept_{t}"] or 0 for t in rates}, rows, grid, params, limit)


def estimate_unknown(edges: DataFrame, n: int, eps: float, sel: Selection | None = None, make=practical_params, power: float = 2.0, self_normalize: bool = False, seed: int = 0) -> DataFrame:
    """One row (t, m, kept, exact, value, mass, overflow) for a stream of unknown length: the optimum where
    the buffer holds the stream, else the estimate from the guess that the length picks."""
    p = one_pass(edges, n, eps, make, power, seed)
    spark, whole = edges.sparkSession, p.buffer
    if whole is not None and whole.select(F.explode(F.array("u", "v")).alias("vid")).distinct().count() <= 20:
        value = exact_val(whole).first()["value"] if p.m else 0.0
        row = (p.guess, p.m, p.m, True, value, 1.0, False)
    else:
        s = p.sketch()
        r = estimate_value(s, sel or uniform_clamped(21), self_normalize).first()
        row = (p.guess, p.m, p.kept[p.guess], False, r["value"], r["mass"], r["overflow"])
        s.close()
    p.rows.unpersist()
    return spark.createDataFrame([row], "t int, m long, kept long, exact boolean, value double, mass double, overflow boolean")


def estimate_maxdicut(edges: DataFrame, eps: float | None = None, params: Params | None = None, sel: Selection | None = None, n: int | None = None, m_hat: int | None = None, mode: str = "independent", self_normalize: bool = False, seed: int = 0) -> DataFrame:
    """One row (value, clipped, mass, m, overflow).  With ``m_hat`` or ``params`` the length is taken as
    known and one sketch is made; else ``estimate_unknown`` scans once for all guesses of the length
    (``n`` bounds the vertices; without it they are counted first) and answers short streams exactly."""
    sel = sel or uniform_clamped(21)
    if params is None and m_hat is None:
        n = n or max(4, edges.select(F.explode(F.array("u", "v")).alias("vid")).distinct().count())
        if eps is None:
            make = lambda m: practical_params(m, ell=sel.ell, t=sel.t)
            row = estimate_unknown(edges, n, 0.1, sel, make, 4.0, self_normalize, seed)
        else:
            from .oblivious import refine_selection

            one = theory_params(n, 1, eps, sel.t, seed)[0]
            make = lambda m: theory_params(n, m, eps, sel.t, seed)[0]
            row = estimate_unknown(edges, n, eps, refine_selection(sel, eps / one.w), make, 2.0, self_normalize, seed)
        return row.select("value", F.least(F.greatest("value", F.lit(0.0)), F.lit(1.0)).alias("clipped"), "mass", "m", "overflow")
    if params is None:
        if eps is None:
            params = practical_params(m_hat, ell=sel.ell, mode=mode, seed=seed, t=sel.t)
        else:
            from .oblivious import refine_selection

            n = n or max(4, m_hat)
            if m_hat > C_SPARSE * n / eps**2:
                edges = sparsify(edges, sparsify_rate(n, m_hat, eps), seed)
                m_hat = edge_count(edges).first()["m"]
            params, t = theory_params(n, m_hat, eps, sel.t, seed)
            sel = refine_selection(sel, eps / params.w)
            params = params.replace(mode=mode)
            assert len(t) == sel.ell + 1
    return estimate_of(edges, params, sel, self_normalize)
