"""Privacy accounting, on the driver: the release test, the model, amplification, composition, calibration."""

from __future__ import annotations

import math
from dataclasses import dataclass


@dataclass(frozen=True)
class Budget:
    eps: float
    delta: float


def release_epsilon(k: int, gamma: float, eps0: float, t: int) -> Budget:
    """Of one released record under the randomized test, for a trade-off 1 <= t < k."""
    if not 1 <= t < k:
        raise ValueError("t must lie in 1..k-1")
    return Budget(eps0 + math.log(1 + gamma / t), math.exp(-eps0 * (k - t)))


def best_t(k: int, gamma: float, eps0: float, delta_max: float) -> int | None:
    """The largest t whose delta stays within delta_max: it has the least epsilon."""
    fits = [t for t in range(1, k) if math.exp(-eps0 * (k - t)) <= delta_max]
    return max(fits, default=None)


def min_k(t: int, c: float, eps0: float, n: int) -> int:
    """The least k with delta <= n**-c."""
    return math.ceil(t + c / eps0 * math.log(n))


def entropy_sensitivity(n: int) -> float:
    """Bound on the change of an entropy (bits) when one of n records is added."""
    if n < 2:
        raise ValueError("n must be 2 or more")
    return (2 + 1 / math.log(2) + 2 * math.log2(n)) / n


def advanced(eps: float, count: int, slack: float) -> float:
    """Epsilon of count uses of an eps-private mechanism at an additional delta of slack."""
    return eps * math.sqrt(2 * count * math.log(1 / slack)) + count * eps * (math.exp(eps) - 1)


def compose(eps: float, delta: float, count: int, slack: float | None = None) -> Budget:
    """Of count releases: basic composition, or advanced with slack where that is less."""
    basic = Budget(count * eps, count * delta)
    if slack is None:
        return basic
    better = advanced(eps, count, slack)
    return Budget(better, count * delta + slack) if better < basic.eps else basic


def structure_budget(m: int, eps_entropy: float, eps_size: float, delta: float, values: int | None = None) -> Budget:
    """Of the noisy entropies (m(m+1) of them unless told) and the noisy record count."""
    return Budget(eps_size + advanced(eps_entropy, values or m * (m + 1), delta), delta)


def parameter_budget(m: int, eps_count: float, delta: float) -> Budget:
    """Of the noisy counts of m attributes."""
    return Budget(advanced(eps_count, m, delta), delta)


def model_budget(structure: Budget, parameters: Budget) -> Budget:
    """Structure and parameters come from disjoint records, so the larger counts."""
    return Budget(max(structure.eps, parameters.eps), max(structure.delta, parameters.delta))


def amplify(b: Budget, share: float) -> Budget:
    """Of a mechanism that runs on a secret random share of the records."""
    return Budget(math.log(1 + share * (math.exp(b.eps) - 1)), share * b.delta)


def calibrate(target: float, m: int, delta: float, eps_size: float = 0.01, share: float | None = None) -> tuple[float, float]:
    """(eps of an entropy, eps of a count) with which structure and parameters meet the target each."""
    goal = target if share is None else math.log(1 + (math.exp(target) - 1) / share)

    def solve(cost):
        low, high = 0.0, goal
        for _ in range(200):
            mid = (low + high) / 2
            low, high = (mid, high) if cost(mid) <= goal else (low, mid)
        return low

    return solve(lambda e: structure_budget(m, e, eps_size, delta).eps), solve(lambda e: parameter_budget(m, e, delta).eps)
