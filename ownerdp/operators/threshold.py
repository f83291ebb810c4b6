"""The least noisy owner count at which a key may be released."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def owner_threshold(eps_t: float, delta: float, c_u: int) -> float:
    """1 - c_u/eps_t ln(2 - 2 (1 - delta)^(1/c_u)). eps_t: the owner count's share over the query; infinite for delta 0."""
    if delta <= 0:
        return math.inf
    alone = -math.expm1(math.log1p(-delta) / c_u)  # 1 - (1 - delta)^(1/c_u), also right for tiny deltas
    return 1 - c_u / eps_t * math.log(2 * alone)


def delta_for_threshold(eps_t: float, tau: float, c_u: int) -> float:
    """The delta that a threshold provides: the inverse of ``owner_threshold``."""
    alone = math.exp((1 - tau) * eps_t / c_u) / 2
    return 1.0 if alone >= 1 else -math.expm1(c_u * math.log1p(-alone))


def single_owner_suppression(delta: float, c_u: int) -> float:
    """How likely a key with one owner stays hidden."""
    return math.exp(math.log1p(-delta) / c_u)


def suppress_rare_keys(df: DataFrame, noisy_owners: str | Column, tau: float) -> DataFrame:
    """The rows whose noisy owner count is at least tau. The count must not be rounded: rounding up would let rarer keys pass."""
    count = noisy_owners if isinstance(noisy_owners, Column) else F.col(noisy_owners)
    return df.filter(count >= F.lit(float(tau)))
