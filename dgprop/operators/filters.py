"""Polynomial graph filters whose coefficients are a geometric series."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class FilterSpec:
    """Coefficients ``g0 * ratio ** k`` of the powers of D^-beta A D^(beta - 1)."""

    g0: float
    ratio: float
    beta: float = 0.5

    def __post_init__(self) -> None:
        if not 0 < abs(self.ratio) < 1:
            raise ValueError("the ratio has to be between 0 and 1 in size: else the series has no limit")
        if not 0 <= self.beta <= 1:
            raise ValueError("beta has to be between 0 and 1")
        if self.g0 == 0:
            raise ValueError("the first coefficient can't be 0")

    @classmethod
    def restart(cls, alpha: float, beta: float = 0.5) -> FilterSpec:
        """Low pass: alpha * (1 - alpha) ** k."""
        return cls(alpha, 1 - alpha, beta)

    @classmethod
    def alternating(cls, alpha: float, beta: float = 0.5) -> FilterSpec:
        """High pass: alpha * (alpha - 1) ** k."""
        return cls(alpha, alpha - 1, beta)

    @classmethod
    def neg_power(cls, alpha: float, beta: float = 0.5) -> FilterSpec:
        """High pass: (-alpha) ** k."""
        return cls(1.0, -alpha, beta)

    @classmethod
    def power(cls, alpha: float, beta: float = 0.5) -> FilterSpec:
        """Low pass: alpha ** k."""
        return cls(1.0, alpha, beta)

    @property
    def mass(self) -> float:
        """The sum of the coefficients' sizes: the error bound is this times the tolerance."""
        return abs(self.g0) / (1 - abs(self.ratio))

    @property
    def is_low_pass(self) -> bool:
        return self.ratio > 0

    def gamma(self, k: int) -> float:
        return self.g0 * self.ratio**k

    def gammas(self, n: int) -> list[float]:
        return [self.gamma(k) for k in range(n)]

    def response(self, eigenvalue: float) -> float:
        """What an eigenvector of the normalised adjacency is multiplied by."""
        return self.g0 / (1 - self.ratio * eigenvalue)


def k_hop_only(k: int) -> list[float]:
    """The k-th power alone."""
    return [0.0] * k + [1.0]


def restart_truncated(k: int, alpha: float) -> list[float]:
    """k steps of a walk with restart; what is left goes to the last power."""
    return [alpha * (1 - alpha) ** i for i in range(k)] + [(1 - alpha) ** k]


def weighted_hops(weights: list[float]) -> list[float]:
    """Any weights, scaled to sum 1 in size."""
    total = sum(map(abs, weights))
    return [w / total for w in weights]
