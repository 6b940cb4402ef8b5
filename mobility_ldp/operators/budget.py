"""Shares of the privacy budget, and a ledger of what is spent."""

from __future__ import annotations

import math
from dataclasses import dataclass, field


@dataclass
class BudgetPlan:
    """eps = e1 (length) + e2 (moves inside a trip) + e3 (first and last cell); each of l_k moves gets e2 / l_k, each end e3 / 2."""

    eps: float
    e1: float
    e2: float
    e3: float
    l_k: int
    scheme: str = "default"
    ledger: list[tuple[str, float]] = field(default_factory=list)

    @property
    def per_move(self) -> float:
        return self.e2 / self.l_k if self.l_k else 0.0

    @property
    def per_end(self) -> float:
        return self.e3 / 2

    def spend(self, what: str, eps: float) -> float:
        if self.spent() + eps > self.eps * (1 + 1e-9) and not math.isinf(self.eps):
            raise ValueError(f"{what} would spend more than the budget")
        self.ledger.append((what, eps))
        return eps

    def spent(self) -> float:
        """Sequential composition: the shares add up."""
        return sum(x for _, x in self.ledger)


def plan_budget(eps: float, l_k: int, scheme: str = "default", shares: tuple[float, float, float] | None = None, max_len: int | None = None) -> BudgetPlan:
    """"default": a tenth for the length, the rest equally over l_k moves and two ends. "custom": shares (e1, e2, e3).
    "naive": as default, with max_len moves in place of l_k. "pooled": as default, for one pooled domain."""
    if scheme == "custom":
        if shares is None or not math.isclose(sum(shares), eps, rel_tol=1e-9):
            raise ValueError("shares must add up to eps")
        return BudgetPlan(eps, *shares, l_k, scheme)
    if scheme == "naive":
        l_k = max_len or l_k
    elif scheme not in ("default", "pooled"):
        raise ValueError(f"no scheme {scheme}")
    each = 0.9 * eps / (l_k + 2) if not math.isinf(eps) else math.inf
    return BudgetPlan(eps, eps / 10, each * l_k if l_k else 0.0, 2 * each, l_k, scheme)


def report_bits(cells: int, states: int, l_k: int, max_len: int | None = None) -> dict[str, int]:
    """Bits that a user sends: one report of the length, l_k of moves, two of ends."""
    parts = {"length": max_len or cells, "moves": l_k * states, "ends": 2 * cells}
    return parts | {"total": sum(parts.values())}
