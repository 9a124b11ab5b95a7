"""Closed-form plans and costs: repetitions, rounds, work and depth."""

from __future__ import annotations

import math
from dataclasses import dataclass


@dataclass(frozen=True)
class Plan:
    q: int
    threshold: int
    p: float
    assumed: bool


def floor_survival(eps: float, k: int = 2) -> float:
    """Least survival probability of a fixed non-trivial (2-eps)-small cut
    under k-out contraction."""
    return math.exp(-4 * (2 - eps) / eps) ** k


def plan_repetitions(n: int, eps: float = 1.0, gamma: float = 1.0, p: float | None = None, structure: str = "contract", cap: int | None = None) -> Plan:
    """q and the vote threshold. p: survival probability to assume (0.25 when
    None and the proven floor is out of reach); ``structure`` probe doubles q
    as a probed edge is kept at half the rate."""
    assumed = p is not None
    p = p if p is not None else floor_survival(eps)
    log = math.log(max(n, 2))
    q = math.ceil((8 if structure == "contract" else 16) * gamma * log / p)
    if cap is not None:
        q = min(q, cap)
    rate = p if structure == "contract" else p / 2
    return Plan(q, max(1, math.floor(rate * q / 2)), p, assumed)


def component_tail_bound(n: int, delta: int) -> dict[str, float]:
    """Sizes up to delta/(8 e^3) have components of a 2-out sample with
    probability at most 8/delta^3 per vertex; vacuous while that size is < 1."""
    size = delta / (8 * math.e**3)
    return {"max_size": size, "probability": 8 / delta**3 if delta else math.inf, "expected_vertices": n * 8 / delta**3 if delta else math.inf, "vacuous": size < 1}


def ball_failure_bound(delta: int) -> dict[str, float]:
    return {"radius": 2 * math.log2(delta / 200) if delta > 200 else 0.0, "probability": min(1.0, (200 / delta) ** 2) if delta else 1.0}


CONGEST = {
    "two_out_partition": lambda n, d, lam, delta: n / max(1, delta),
    "combined": lambda n, d, lam, delta: n**0.8 * d**0.2 + n**0.9,
    "small_cut": lambda n, d, lam, delta: (d + math.sqrt(n)) * lam**4,
    "large_cut": lambda n, d, lam, delta: n / max(1, lam),
    "expander": lambda n, d, lam, delta: n ** (1 - 1 / 353) * d ** (1 / 353) + n ** (1 - 1 / 706),
    "expander_part": lambda n, d, lam, delta: n / max(1, delta) ** (1 / 88),
    "approximate": lambda n, d, lam, delta: d + math.sqrt(n),
    "conjectured": lambda n, d, lam, delta: (d + math.sqrt(n / max(1, lam))) * lam**4,
    "conjectured_combined": lambda n, d, lam, delta: n**0.8 * d**0.2 + n ** (8 / 9),
}


def congest_cost(model: str, n: int, diameter: int, lam: float, delta: int) -> float:
    """Rounds of a message-passing method, logarithms left out."""
    return CONGEST[model](n, diameter, lam, delta)


def congest_crossover(n: int, diameter: int) -> float:
    """The cut size from which the large-cut path has fewer rounds."""
    return n**0.1 if diameter <= math.sqrt(n) else (n / diameter) ** 0.2


def congest_plan(n: int, diameter: int, lam: float) -> tuple[str, float]:
    path = "large_cut" if lam >= congest_crossover(n, diameter) else "small_cut"
    return path, congest_cost(path, n, diameter, lam, 1)


def mpc_costs(n: int, m: int, delta: int, q: int, survivors: int, eps: float = 0.5) -> list[tuple[str, float, float, float]]:
    """(method, rounds, local memory, global memory), constants left out."""
    lg = math.log2(max(2, n))
    return [
        ("this_method", 1.0, float(n), m + n * lg**3),
        ("one_contraction", 1.0, float(n), m / max(1, delta) + n * lg**2),
        ("survivors_by_fingerprint", 1.0, float(n), float(m + n * q + survivors * q)),
        ("survivors_naive", 1.0, float(n), float(m * q)),
        ("earlier_near_linear", lg**2, float(n), float(m * n)),
        ("earlier_super_linear", 1.0, n ** (1 + eps), float(n * m)),
    ]


def work_depth(n: int, m: int) -> list[tuple[str, float, float]]:
    lg = math.log2(max(2, n))
    return [
        ("this_method", m * lg + n * lg**4, lg**3),
        ("contraction", m * lg, lg),
        ("vote_merge", m + n * lg, lg),
        ("earlier", m * lg**4, lg**3),
        ("sequential_certificate", m * lg, m * lg),
        ("sequential_probe", m + n * lg**3, m + n * lg**3),
        ("sequential_tree_packing", m * lg**3, m * lg**3),
        ("sequential_recursive", n**2 * lg**3, n**2 * lg**3),
        ("sequential_flow", m * lg**2 * math.log2(max(2, lg)) ** 2, m * lg**2 * math.log2(max(2, lg)) ** 2),
        ("sequential_diffusion", m * lg**12, m * lg**12),
    ]


def choose_profile(n: int, m: int, task_rows: int = 20_000_000) -> dict[str, object]:
    """Solver by density, components strategy by size."""
    lg = math.log(max(2, n))
    return {"solver": "tree_packing" if m >= n * lg**3 else "max_adjacency", "strategy": "local" if 4 * n <= task_rows else "star"}
