"""Privacy parameters, how a query divides them, and the closed formulas around them. All of it runs on the driver."""

from __future__ import annotations

import math
import warnings
from dataclasses import dataclass, replace


def default_delta(n_owners: float, eps: float) -> float:
    """n^(-eps ln n). The number of owners comes from configuration or a private count, never from counting the data here."""
    if n_owners < 1:
        raise ValueError("the number of owners must be at least 1")
    delta = math.exp(-eps * math.log(n_owners) ** 2)
    if delta > 1 / n_owners:
        warnings.warn(f"delta {delta:.3g} for {n_owners:g} owners is above 1/n: no real guarantee", stacklevel=2)
    return delta


@dataclass(frozen=True)
class Shares:
    """What one aggregate and the owner count may spend in each partition, and the count's share over the whole query."""

    per_aggregate: float
    per_count: float
    count_of_query: float


@dataclass(frozen=True)
class PrivacyParams:
    """eps and delta of one query; c_u: the partitions an owner may reach; tau: given instead of derived, or None; suppress: whether keys can vanish."""

    eps: float
    delta: float = 0.0
    c_u: int = 1
    tau: float | None = None
    suppress: bool = True

    def __post_init__(self):
        if not self.eps > 0 or not math.isfinite(self.eps):
            raise ValueError("eps must be positive and finite")
        if not 0 <= self.delta < 1:
            raise ValueError("delta must be in [0, 1)")
        if self.c_u < 1:
            raise ValueError("c_u must be at least 1")

    def split(self, n_aggregates: int, needs_count: bool = True, has_keys: bool = True) -> Shares:
        """Equal parts for the aggregates and, where keys can vanish, one more for the owner count; divided by the partitions of an owner."""
        c_u = self.c_u if has_keys else 1
        parts = n_aggregates + (1 if needs_count else 0)
        if parts == 0:
            raise ValueError("nothing to release")
        each = self.eps / (c_u * parts)
        return Shares(each, each if needs_count else 0.0, each * c_u if needs_count else 0.0)

    def with_(self, **changes) -> PrivacyParams:
        return replace(self, **changes)


def laplace_median_error(sensitivity: float, eps: float) -> float:
    """The median of the absolute Laplace noise of scale sensitivity / eps."""
    return math.log(2) * sensitivity / eps


def epsilon_for_error(sensitivity: float, error: float) -> float:
    """The eps at which the median absolute noise is ``error``."""
    return math.log(2) * sensitivity / error


def error_vs_aggs(sensitivity: float, eps: float, n_aggregates: int) -> float:
    """The median noise of each of n aggregates that divide eps equally: n times that of one."""
    return laplace_median_error(sensitivity, eps / n_aggregates)
