"""Constants of the cell sampler (M7a, M8, M9, M17): pivots, acceptance ranges, XOR counts, error factors, run counts."""

from __future__ import annotations

import math
from dataclasses import dataclass


def epsilon(kappa: float) -> float:
    """The sampling error: probabilities stay within a factor 1 + epsilon of the target, on both sides."""
    check_kappa(kappa)
    return (1 + kappa) * (2.36 + 0.51 / (1 - kappa) ** 2) - 1


def check_kappa(kappa: float) -> None:
    if not 0 < kappa < 1:
        raise ValueError("kappa must lie between 0 and 1")


def sampling_pivot(kappa: float) -> int:
    check_kappa(kappa)
    return math.ceil(4.03 * (1 + 1 / kappa) ** 2)


def cell_range(kappa: float) -> tuple[float, float]:
    """Least and largest scaled weight of a cell that may be sampled from."""
    pivot, root = sampling_pivot(kappa), math.sqrt(2) * (1 + kappa)
    return pivot / root, 1 + root * pivot


def estimation_pivot(tolerance: float = 0.8) -> int:
    return 2 * math.ceil(math.exp(1.5) * (1 + 1 / tolerance) ** 2)


def initial_xors(total: float, kappa: float, w_max: float = 1.0) -> int:
    """XORs with which sampling starts; total and w_max are scaled weights.  None are needed where everything fits into one cell."""
    if total <= cell_range(kappa)[1] * w_max:  # also where there is nothing at all
        return 0
    return max(0, math.ceil(math.log2(total / w_max) + math.log2(1.8) - math.log2(sampling_pivot(kappa))) - 3)


@dataclass(frozen=True)
class EstimateParams:
    """17 runs give the tolerance 0.8 with confidence 0.8; schedule is "leapfrog" or "theory", stop "converged" or "all"."""

    runs: int = 17
    tolerance: float = 0.8
    schedule: str = "leapfrog"
    stop: str = "all"
    attempts: int = 3

    @property
    def pivot(self) -> int:
        return estimation_pivot(self.tolerance)
