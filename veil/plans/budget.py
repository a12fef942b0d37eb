"""Privacy budgets and their arithmetic."""

from __future__ import annotations

import warnings
from dataclasses import dataclass
from math import exp, expm1, log


@dataclass(frozen=True)
class Budget:
    """(eps, delta) of one party. Sequential runs add up; processing what was released costs nothing."""

    eps: float
    delta: float = 0.0
    note: str = ""

    def __post_init__(self) -> None:
        if self.eps < 0 or not 0 <= self.delta < 1:
            raise ValueError("eps must not be negative and delta must lie in [0, 1)")

    def then(self, other: Budget) -> Budget:
        return Budget(self.eps + other.eps, self.delta + other.delta, "composed")

    def post(self) -> Budget:
        return Budget(self.eps, self.delta, "post-processed")

    def within(self, cap: Budget) -> bool:
        return self.eps <= cap.eps + 1e-12 and self.delta <= cap.delta + 1e-18

    @staticmethod
    def cryptographic() -> Budget:
        """The budget of a secure computation: eps 0 and a negligible delta, kept as 0."""
        return Budget(0.0, 0.0, "negligible delta")

    @staticmethod
    def from_symmetric(eps_half: float) -> Budget:
        """A symmetric computational guarantee at eps/2 gives this one at eps."""
        return Budget(2 * eps_half, 0.0, "from symmetric computational privacy")

    def check(self, n: int) -> Budget:
        """Warn where delta is not below one over the number of records."""
        if n > 0 and self.delta >= 1 / n:
            warnings.warn(f"delta {self.delta} is not below 1/{n}", stacklevel=2)
        return self


@dataclass
class Ledger:
    """Spent budget of one party against a cap."""

    cap: Budget
    spent: Budget = Budget(0.0, 0.0)

    def spend(self, b: Budget) -> Budget:
        total = self.spent.then(b)
        if not total.within(self.cap):
            raise ValueError("the budget is exceeded")
        self.spent = total
        return total


def raw_center(eps: float, delta: float, sensitivity: int) -> float:
    """Centre of the noise law before rounding: P(noise < 0) equals 1 - (1-delta)^(1/sensitivity) there."""
    tail = -expm1(log(1 - delta) / sensitivity) if delta > 1e-12 else delta / sensitivity
    return -sensitivity * log((exp(eps / sensitivity) + 1) * tail) / eps


def center(eps: float, delta: float, sensitivity: int) -> int:
    """Integer centre: rounded up, so the law over the integers sums to one and the tail only shrinks."""
    from math import ceil

    return ceil(raw_center(eps, delta, sensitivity) - 1e-12)


def center_negligible(n: int, eps: float, sensitivity: int) -> int:
    """Centre that makes delta vanish faster than any power of 1/n."""
    from math import ceil

    return ceil(log(n) ** 2 * sensitivity / eps)


def delta_negligible(n: int, eps: float, sensitivity: int) -> float:
    """Failure probability at that centre."""
    tail = 1 / (n ** log(n) * (exp(eps / sensitivity) + 1))
    return -expm1(sensitivity * log(1 - tail)) if tail > 1e-16 else sensitivity * tail


def pmf(x: int, mu: int, eps: float, sensitivity: int) -> float:
    """Probability of one noise value around the integer centre."""
    a = eps / sensitivity
    return (exp(a) - 1) / (exp(a) + 1) * exp(-a * abs(x - mu))


def p_negative(mu: int, eps: float, sensitivity: int) -> float:
    """Probability of a negative draw."""
    a = eps / sensitivity
    return exp(-a * mu) / (exp(a) + 1)


def failure(mu: int, eps: float, sensitivity: int) -> float:
    """Probability that one of the changed bins draws a negative value."""
    return 1 - (1 - p_negative(mu, eps, sensitivity)) ** sensitivity


def expected_pad(mu: int, eps: float, sensitivity: int) -> float:
    """Expected number of dummies of a bin."""
    from math import sinh

    a = eps / sensitivity
    return mu + exp(-a * mu) / (2 * sinh(a))
