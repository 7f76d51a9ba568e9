"""Sizes that the theory asks for, by method. They are upper bounds; small multiples of k already do well, so callers set them."""

from __future__ import annotations

import math
from dataclasses import asdict, dataclass

#: Objective: whether distinct proxies are needed, solver, factor of the solver.
REGISTRY = {
    "edge": ("loose", "traversal", 2), "cycle": ("loose", "traversal", 3), "clique": ("strict", "matching", 2),
    "star": ("strict", "matching", 2), "bipartition": ("strict", "matching", 3), "tree": ("strict", "traversal", 4),
}
#: Method: base of the kernel size for each family, whether the factor alpha multiplies it, how the parts are counted.
METHODS = {"stream1": (32, 64, False), "stream2": (None, 64, True), "mr2": (8, 16, False), "mr2r": (8, 16, False), "mr3": (None, 16, True), "multi": (8, 16, False)}


def strict(objective: str) -> bool:
    return REGISTRY[objective][0] == "strict"


@dataclass(frozen=True)
class PlanSpec:
    method: str
    objective: str
    alpha: int
    eps_inner: float
    k_prime: float
    parts: int
    cap: int
    local_rows: float


def plan(method: str, objective: str, n: int, k: int, eps: float = 1.0, dim: float = 3.0, gamma: float = 1 / 3) -> PlanSpec | None:
    """The advised sizes, or None where the method does not serve the objective."""
    loose_base, strict_base, with_alpha = METHODS[method]
    alpha = REGISTRY[objective][2]
    base = strict_base if strict(objective) else loose_base
    if base is None:
        return None
    if method == "stream1":
        inner = 1 - 1 / (1 + eps)
    elif method in ("mr2", "mr2r"):
        inner = 1 - 1 / (1 + eps / alpha)
    elif method == "multi":
        inner = 1 - 1 / (1 + eps / (alpha * (2 ** ((1 - gamma) / gamma) - 1)))
    else:
        inner = eps / (alpha + eps)
    k_prime = (base * (alpha if with_alpha else 1) / inner) ** dim * k
    cap = k if strict(objective) and method in ("mr2", "multi", "stream1") else 1
    if method.startswith("stream"):
        parts = 1
    elif method == "mr2r":
        parts = max(1, int(min(math.sqrt(n / (k_prime * max(math.log(n), 1))), n / (k * k_prime))))
        cap = max(1, math.ceil(max(math.log(n), k / parts))) if strict(objective) else 1
    elif method == "multi":
        parts = max(1, math.ceil(n / max(n**gamma * k_prime, 1)))
    else:
        parts = max(1, int(math.sqrt(n / (k_prime * (k if method == "mr2" and strict(objective) else 1)))))
    local = k_prime * cap if method.startswith("stream") else max(n / parts, parts * min(k_prime, n / parts) * cap)
    return PlanSpec(method, objective, alpha, inner, k_prime, parts, cap, local)


def part_count(n: int, size: int, task_rows: int) -> int:
    """Parts of n rows with core-sets of ``size`` rows: as many as balance the largest part with the union of the core-sets, but none of more than ``task_rows``."""
    return max(8, math.ceil(n / task_rows), min(math.ceil(math.sqrt(n / max(size, 1))), task_rows // max(size, 1)))


def table(n: int, k: int, eps: float = 1.0, dim: float = 3.0) -> list[dict]:
    return [asdict(p) for m in METHODS for o in REGISTRY if (p := plan(m, o, n, k, eps, dim))]
