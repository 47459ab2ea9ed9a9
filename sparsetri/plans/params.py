"""How many edges, picks and neighbours to sample, and what error to expect of them."""

from __future__ import annotations

import math
from dataclasses import dataclass, replace


@dataclass(frozen=True)
class SamplePlan:
    m: int
    n: int
    kappa: int  # any upper bound of the degeneracy
    t_guess: float  # any lower bound of the number of triangles
    eps: float
    r: int
    ell: int | None  # None until the degrees of the sample are known
    s: int
    seed: int = 1
    reps: int = 1
    coin: str = "md5"
    mode: str = "budget"
    exhaustive: bool = False  # neighbourhoods of at most s are then counted instead of sampled

    @property
    def degree_cut(self) -> float:
        """Edges of larger degree are never owners."""
        return self.m * self.kappa**2 / (self.eps**2 * self.t_guess) if self.t_guess else math.inf

    @property
    def owner_threshold(self) -> float:
        """A triangle whose least count is larger stays without owner."""
        return self.kappa / (2 * self.eps)

    @property
    def exact_is_cheaper(self) -> bool:
        return self.r >= self.m

    def with_degrees(self, d_r: int, c: float = 21) -> SamplePlan:
        """Fixes ell by the sample's degree sum."""
        if self.ell is not None:
            return self
        t_asg = (1 - 12 * self.eps) * self.t_guess if self.eps < 1 / 12 else self.t_guess
        return replace(self, ell=math.ceil(c * math.log(self.n) / self.eps**2 * self.m * d_r / (self.r * t_asg)))


def plan_theory(m: int, n: int, kappa: int, t_guess: float, eps: float, c_r: float = 7, c_s: float = 61, **other) -> SamplePlan:
    """Sizes with proven constants: c_r > 6, c_s > 60, eps < 1/6."""
    if not 0 < eps < 1 / 6:
        raise ValueError("eps must be in (0, 1/6)")
    t_asg = (1 - 12 * eps) * t_guess if eps < 1 / 12 else t_guess
    scale = math.log(n) / eps**2
    return SamplePlan(m, n, kappa, t_guess, eps, math.ceil(c_r * scale * m * (kappa / eps) / t_asg), None, math.ceil(c_s * scale * m * kappa / t_guess), mode="theory", **other)


def plan_budget(m: int, n: int, kappa: int, t_guess: float, eps: float, r: int, ell: int, s: int, **other) -> SamplePlan:
    return SamplePlan(m, n, kappa, t_guess, eps, r, ell, s, **other)


def predicted_rse(m: int, d_e: int, t: float, sum_t2: float, r: int, ell: int, assigned: bool = True) -> float:
    """Relative standard error of the six-pass estimate; sum_t2 is over assigned (or incident) counts of edges."""
    total = t if assigned else 3 * t
    return math.sqrt(max(0.0, m * sum_t2 / (r * total**2) - 1 / r) + max(0.0, d_e / total - 1) / ell)


def plan_from_rse(m: int, n: int, kappa: int, t_guess: float, d_e: int, sum_t2: float, target: float, eps: float = 0.1, **other) -> SamplePlan:
    """r and ell for a wanted relative error, with half of its square for each; ell is at least 4r."""
    half = target**2 / 2
    r = max(1, math.ceil((m * sum_t2 / t_guess**2 - 1) / half))
    ell = max(4 * r, math.ceil(max(0.0, d_e / t_guess - 1) / half))
    return SamplePlan(m, n, kappa, t_guess, eps, r, ell, math.ceil(61 * math.log(n) / eps**2 * m * kappa / t_guess), mode="rse", **other)
