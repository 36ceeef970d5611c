"""Parameters of the layered sketch: the theorem's formulas, and free constants with its structure."""

from __future__ import annotations

import dataclasses
import math
from dataclasses import dataclass

from .classes import refine_partition
from .hashing import PRIME, coefficients

C_SPARSE = 1.0


@dataclass(frozen=True)
class Params:
    k: int
    ell: int
    w: int
    k_star: int
    p0: float
    e_cap: int
    v_cap: int
    eps: float = 0.0
    seed: int = 0
    mode: str = "independent"  # or "nested": one coin an edge, one hash a vertex, shared by layers
    store: str = "incident"  # or "induced": only edges with both ends tracked
    coin: str = "md5"
    force_p1: bool = False
    force_q1: bool = False
    single_layer: int | None = None
    t: tuple[float, ...] | None = None  # bias thresholds; None: ell equal classes, in integers
    d: tuple[float, ...] | None = None  # degree thresholds; None: dyadic
    rising: bool = True  # False: every layer tracks with p0, however sparse its edges

    def q(self, a: int) -> float:
        return 1.0 if self.force_q1 else 2.0 ** min(self.k_star - a, 0)

    def shift(self, a: int) -> int:
        """log2 of 1/q."""
        return 0 if self.force_q1 else max(a - self.k_star, 0)

    def threshold(self, a: int) -> int:
        """Vertices with a hash below it are tracked in layer a."""
        p = 1.0 if self.force_p1 else min(self.p0 / self.q(a) if self.rising else self.p0, 1.0)
        return PRIME if p >= 1 else int(p * PRIME)

    def p(self, a: int) -> float:
        return self.threshold(a) / PRIME

    @property
    def layers(self) -> list[int]:
        return [self.single_layer] if self.single_layer else list(range(1, self.k + 1))

    def rows(self, guess: int = 0) -> list[tuple]:
        """(guess, layer, q, threshold, c0..c3) for the parameter table."""
        nested = self.mode == "nested"
        return [(guess, a, self.q(a), self.threshold(a), *coefficients(self.seed, a, nested)) for a in self.layers]

    def replace(self, **changes) -> Params:
        return dataclasses.replace(self, **changes)

    def check(self) -> Params:
        if not (self.w < self.k and self.w < self.ell):
            raise ValueError("the window must be narrower than both partitions")
        if self.e_cap <= 2 ** (self.k_star + self.w + 2):
            raise ValueError("e_cap must exceed 2^(k_star + w + 2)")
        return self


def degree_layers(m: float) -> int:
    return max(1, math.ceil(math.log2(2 * max(m, 1))))


def theory_params(n: int, m_hat: int, eps: float, base: tuple[float, ...] = (-1.0, 1.0), seed: int = 0) -> tuple[Params, tuple[float, ...]]:
    """The theorem's parameters and its refined partition.  k_star is rounded up, so that sampling
    rates are powers of two.  They are all one where k_star, of the order of log log n, reaches k: at any
    size that can be run, but for graphs with few vertices for their edges."""
    w = math.ceil(1 / eps)
    lam = eps / w
    t, _ = refine_partition(base, lam)
    ell, k = len(t) - 1, degree_layers(m_hat)
    logn = math.log2(max(n, 4))
    k_star = math.ceil(6 * math.log2(logn))
    D = 2.0 ** (k_star + w + 2)
    rho = 1000 * math.sqrt(D) * (k * ell) ** 3 / eps
    return Params(k, ell, w, k_star, rho / math.sqrt(m_hat), max(math.ceil(logn**7), int(D) + 1), math.ceil(10 * rho * math.sqrt(2 * m_hat)), eps, seed, t=None if len(base) == 2 else t), t


def practical_params(m_hat: int, k_star: int = 8, p0: float = 0.25, w: int = 2, ell: int = 21, e_cap: int | None = None, v_cap: int = 10**6, seed: int = 0, **more) -> Params:
    """Free constants with the structural constraints; no guarantee at small sizes."""
    p = Params(degree_layers(m_hat), ell, w, k_star, p0, e_cap or 2 ** (k_star + w + 2) + 1, v_cap, 0.0, seed, **more)
    return p


def theory_range(n: int, eps: float) -> tuple[float, float]:
    """Handled edge counts: below the first the graph is kept whole, above the second sparsified."""
    return math.sqrt(n), C_SPARSE * n / eps**2


def error_budget(eps: float, c_smooth: float = 7.0, c_win: float = 17 * 624) -> dict[str, float]:
    w = math.ceil(1 / eps)
    return {"smoothing": c_smooth * eps, "window": c_win / w, "estimate": eps, "total": c_smooth * eps + c_win / w + eps}
