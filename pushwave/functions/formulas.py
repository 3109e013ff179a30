"""Scalars of the estimators: walk constant, thresholds, capacities, bounds, ladder, cost model.

Notation: n nodes, m arcs, eps relative error, delta score threshold, pf failure probability,
L = ln(2/pf), C = (2 + 2*eps/3) * L / (eps^2 * delta).
"""

from __future__ import annotations

from dataclasses import dataclass, replace
from math import ceil, log, log2, sqrt


@dataclass(frozen=True)
class PprParams:
    """alpha: stop probability; delta and p_fail default to 1/n; dangling: what a node without
    out-arcs does; rng: xxhash64 (fast) or md5 (the same numbers in any SQL engine); shared_walks:
    all queries draw the same walks from a start node, as a stored index does."""

    alpha: float = 0.2
    eps: float = 0.5
    delta: float | None = None
    p_fail: float | None = None
    seed: int = 42
    dangling: str = "absorb"
    rng: str = "xxhash64"
    shared_walks: bool = True

    def __post_init__(self):
        if not 0 < self.alpha < 1:
            raise ValueError("alpha must lie between 0 and 1")
        if not 0 < self.eps <= 1:
            raise ValueError("eps must lie in (0, 1]")
        if self.dangling not in ("absorb", "self_loop", "reject"):
            raise ValueError(f"unknown dangling policy {self.dangling}")
        if self.rng not in ("xxhash64", "md5"):
            raise ValueError(f"unknown rng {self.rng}")

    def resolve(self, n: int) -> PprParams:
        return replace(self, delta=self.delta or 1 / n, p_fail=self.p_fail or 1 / n)

    @property
    def walks(self) -> float:
        """C, of resolved parameters."""
        return walk_constant(self.eps, self.delta, self.p_fail)


def walk_constant(eps: float, delta: float, p_fail: float) -> float:
    return (2 + 2 * eps / 3) * log(2 / p_fail) / (eps * eps * delta)


def push_threshold(m: int, c: float) -> tuple[float, int]:
    """(rho*, case): 1/sqrt(mC) while m <= C, else 1/C because residues never sum to more than 1."""
    m = max(m, 1)
    return (1 / sqrt(m * c), 1) if m <= c else (1 / c, 2)


def total_walks(residue: float, c: float) -> int:
    return ceil(residue * c)


def index_capacity(degree: int, rho: float, c: float, alpha: float = 0.0) -> int:
    """Walks stored for a node: enough for any residue at most degree*rho; alpha > 0 leaves out zero-hop walks."""
    return ceil((1 - alpha) * max(degree, 1) * rho * c)


def tail_bound_relative(eps: float, walks: float, residue: float, score: float) -> float:
    return min(1.0, 2 * _exp(-eps * eps * walks * score / (residue * (2 + 2 * eps / 3))))


def tail_bound_absolute(lam: float, walks: float, residue: float, score: float) -> float:
    return min(1.0, 2 * _exp(-lam * lam * walks / (residue * (2 * score + 2 * lam / 3))))


def _exp(x: float) -> float:
    from math import exp

    return exp(max(-745.0, x))


@dataclass(frozen=True)
class Rung:
    delta: float
    eps: float
    p_fail: float
    c: float
    rho: float


def ladder(n: int, m: int, k: int, p: PprParams, halve_eps: bool = True) -> list[Rung]:
    """Falling thresholds 1/k, 1/2k, ... 1/n with their walk constants; the last is clamped to 1/n."""
    k = max(1, min(k, n))
    p = p.resolve(n)
    steps = max(1.0, log2(n / k)) if halve_eps else max(1.0, log(n))
    p_fail, eps = p.p_fail / (n * steps), p.eps / 2 if halve_eps else p.eps
    deltas, d = [], 1 / k
    while d > 1 / n * (1 + 1e-12):
        deltas.append(d)
        d /= 2
    deltas.append(1 / n)
    out = []
    for d in deltas:
        c = walk_constant(eps, d, p_fail)
        out.append(Rung(d, eps, p_fail, c, push_threshold(m, c)[0]))
    return out


def cap_aware_rho(per_degree: float, c: float, m: int) -> float:
    """The threshold at which an index with per_degree walks an out-arc can't run short."""
    return min(push_threshold(m, c)[0], per_degree / c)


def reverse_threshold(n: int, m: int, p: PprParams, shared: bool) -> float:
    """Threshold of reverse pushes: for one target, or for all targets with one batch of walks."""
    p = p.resolve(n)
    one = p.eps * sqrt(m * p.delta / (n * log(1 / p.p_fail)))
    return p.eps * sqrt(m * p.delta / log(1 / p.p_fail)) if shared else one


def expected_costs(n: int, m: int, p: PprParams, kth: float | None = None) -> dict[str, float]:
    """Expected work of each method up to constants (top-k methods need the k-th score)."""
    p = p.resolve(n)
    big, c = log(2 / p.p_fail), p.walks
    out = {
        "monte_carlo": c,
        "push_walk": min(sqrt(m * c), c),
        "bidirectional": sqrt(m * n * big / p.delta) / p.eps,
        "bidirectional_shared": sqrt(m * big / p.delta) / p.eps,
        "push_only": 1 / push_threshold(m, c)[0],
        "power": m * log(1 / (p.delta * p.eps)) / -log(1 - p.alpha),
    }
    if kth:
        out |= {"mc_top_k": big / (kth * p.eps**2), "top_k_halving": min(sqrt(m * big / kth) / p.eps, big / (kth * p.eps**2)), "filter_refine_top_k": (m + n * log(n)) / sqrt(kth)}
    return out
