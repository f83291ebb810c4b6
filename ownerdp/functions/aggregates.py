"""Private aggregates: what each takes from an owner, how partials add up across owners, and what is released."""

from __future__ import annotations

import math
from dataclasses import dataclass, field
from typing import Any

from pyspark.sql import Column
from pyspark.sql import functions as F

from ownerdp.functions.clamp import clamp
from ownerdp.functions.noise import Noise, draw_tag, round_to_step, rounding_step

PER_OWNER = ("mean", "median", "one")


def _column(x) -> Column | None:
    return x if x is None or isinstance(x, Column) else F.col(x)


@dataclass
class Context:
    """Where a release stands: the noise, the keys, what one aggregate may spend in a partition, and the limits if they were found in the data."""

    noise: Noise
    keys: list[Column]
    eps: float
    rounded: bool = False

    def laplace(self, scale, tag: str) -> Column:
        return self.noise.laplace(scale, tag, self.keys)

    def noisy(self, value: Column, scale: float, tag: str) -> Column:
        out = value + self.laplace(scale, tag)
        return round_to_step(out, scale) if self.rounded and not self.noise.exact else out

    def rounding(self, scale: float) -> float:
        """How far rounding moves a noisy value at most."""
        return rounding_step(scale) / 2 if self.rounded and not self.noise.exact and scale else 0.0


@dataclass
class Agg:
    """An aggregate of the name ``name`` over the column ``col`` with limits [lo, hi]; without limits they are found privately."""

    name: str
    col: Any = None
    lo: float | None = None
    hi: float | None = None
    per_owner: str = "mean"
    extra: dict = field(default_factory=dict)

    needs_limits = True
    #: kinds of automatic limits, see operators/bounds.py
    bounds_kind = "float"

    def __post_init__(self):
        if not self.name:
            raise ValueError("an aggregate needs a name")
        if (self.lo is None) != (self.hi is None):
            raise ValueError("give both limits or none")
        if self.lo is not None and not self.lo <= self.hi:
            raise ValueError("the lower limit is above the upper one")
        if self.per_owner not in PER_OWNER:
            raise ValueError(f"per_owner is one of {PER_OWNER}")

    @property
    def automatic(self) -> bool:
        return self.needs_limits and self.lo is None

    @property
    def p(self) -> str:
        return f"__p_{self.name}"

    def partial(self) -> Column:
        """One value for each owner and partition; NULL if the owner has none."""
        raise NotImplementedError

    def combine(self, lo, hi) -> dict[str, Column]:
        """Sums over owners, by the names of columns that ``release`` reads."""
        raise NotImplementedError

    def release(self, c: Context, lo: float, hi: float) -> Column:
        raise NotImplementedError

    def half_width(self, level: float, eps: float, lo: float, hi: float) -> tuple[float, float] | float:
        """How far the noise alone moves a result at most, with the given probability."""
        return self.scale(eps, lo, hi) * math.log(1 / (1 - level))

    def scale(self, eps: float, lo: float, hi: float) -> float:
        raise NotImplementedError

    def interval(self, c: Context, level: float, lo: float, hi: float) -> tuple[Column, Column]:
        """Ends between which the result without noise lies with the given probability."""
        width = self.half_width(level, c.eps, lo, hi) + c.rounding(self.scale(c.eps, lo, hi))
        value = self.release(c, lo, hi)
        return value - width, value + width

    def _one_value(self) -> Column:
        x = _column(self.col).cast("double")
        if self.per_owner == "median":
            return F.percentile(x, F.lit(0.5))
        if self.per_owner == "one":  # the record whose hash is least
            return F.min_by(x, F.md5(F.concat(F.lit("one|"), F.coalesce(x.cast("string"), F.lit(""))))).alias(self.p)
        return F.avg(x)


class CountOwners(Agg):
    """Owners in the partition."""

    needs_limits = False

    def partial(self):
        return F.count(F.lit(1)).cast("double")

    def combine(self, lo, hi):
        return {self.p: F.count(F.lit(1)).cast("double")}

    def scale(self, eps, lo, hi):
        return 1 / eps

    def release(self, c, lo, hi):
        return c.noisy(F.col(self.p), self.scale(c.eps, lo, hi), draw_tag(self.name))


class CountContributors(CountOwners):
    """Owners that have at least one row with a value."""

    def partial(self):
        return F.count(_column(self.col) if self.col is not None else F.lit(1)).cast("double")

    def combine(self, lo, hi):
        return {self.p: F.sum((F.col(self.p) > 0).cast("double"))}


class Sum(Agg):
    """The sum of each owner's sum, moved into the limits."""

    def partial(self):
        return F.try_sum(_column(self.col)).cast("double")

    def combine(self, lo, hi):
        return {self.p: F.coalesce(F.sum(clamp(F.col(self.p), lo, hi)), F.lit(0.0))}

    def scale(self, eps, lo, hi):
        return max(abs(lo), abs(hi)) / eps

    def release(self, c, lo, hi):
        return c.noisy(F.col(self.p), self.scale(c.eps, lo, hi), draw_tag(self.name))


class CountRows(Sum):
    """The rows of each owner (those with a value, if a column is given), moved into the limits."""

    bounds_kind = "unsigned"

    def partial(self):
        return F.count(_column(self.col) if self.col is not None else F.lit(1)).cast("double")


class Avg(Agg):
    """The mean over owners of one value each: a noisy sum of distances from the middle of the limits over a noisy count."""

    @property
    def count_share(self) -> float:
        return self.extra.get("count_share", 0.5)

    def partial(self):
        return self._one_value()

    def combine(self, lo, hi):
        p, middle = F.col(self.p), (lo + hi) / 2
        return {f"{self.p}_s": F.coalesce(F.sum(clamp(p, lo, hi) - middle), F.lit(0.0)), f"{self.p}_n": F.count(p).cast("double")}

    def _scales(self, eps, lo, hi):
        return (hi - lo) / 2 / (eps * (1 - self.count_share)), 1 / (eps * self.count_share)

    def scale(self, eps, lo, hi):
        return self._scales(eps, lo, hi)[0]

    def _noisy_parts(self, c: Context, s: str, n: str, lo: float, hi: float, eps: float, part: str = "") -> tuple[Column, Column]:
        """The noisy sum and the noisy count, which every later step reads and nothing else."""
        by_sum, by_count = self._scales(eps, lo, hi)
        total = c.noisy(F.col(s), by_sum, draw_tag(self.name, f"{part}sum")) if by_sum else F.col(s)
        return total, c.noisy(F.col(n), by_count, draw_tag(self.name, f"{part}count"))

    def _mean(self, c: Context, s: str, n: str, lo: float, hi: float, eps: float, part: str = "") -> Column:
        total, count = self._noisy_parts(c, s, n, lo, hi, eps, part)
        return clamp(F.lit((lo + hi) / 2) + total / F.greatest(count, F.lit(1.0)), lo, hi)

    def release(self, c, lo, hi):
        return self._mean(c, f"{self.p}_s", f"{self.p}_n", lo, hi, c.eps)

    def half_width(self, level, eps, lo, hi):
        """Both noises stay inside these with the given probability: each misses with half the rest."""
        return tuple(s * math.log(2 / (1 - level)) for s in self._scales(eps, lo, hi))

    def interval(self, c: Context, level: float, lo: float, hi: float) -> tuple[Column, Column]:
        """The widest that both noises and their rounding allow together, around the sum and the count that the result is made of."""
        total, count = self._noisy_parts(c, f"{self.p}_s", f"{self.p}_n", lo, hi, c.eps)
        by_sum, by_count = (w + c.rounding(s) for w, s in zip(self.half_width(level, c.eps, lo, hi), self._scales(c.eps, lo, hi), strict=True))
        counts = F.greatest(count - by_count, F.lit(1.0)), F.greatest(count + by_count, F.lit(1.0))
        ends = [F.lit((lo + hi) / 2) + (total + sign * by_sum) / n for sign in (-1, 1) for n in counts]
        return F.greatest(F.lit(float(lo)), F.least(*ends)), F.least(F.lit(float(hi)), F.greatest(*ends))


class Var(Avg):
    """The variance over owners of one value each: the mean of squares less the square of the mean, each with half the share."""

    @staticmethod
    def squared_limits(lo: float, hi: float) -> tuple[float, float]:
        return (0.0 if lo <= 0 <= hi else min(lo * lo, hi * hi)), max(lo * lo, hi * hi)

    def combine(self, lo, hi):
        p, (lo2, hi2) = clamp(F.col(self.p), lo, hi), self.squared_limits(lo, hi)
        squares = {f"{self.p}_q": F.coalesce(F.sum(clamp(p * p, lo2, hi2) - (lo2 + hi2) / 2), F.lit(0.0))}
        return super().combine(lo, hi) | squares

    def _variance(self, c, lo, hi):
        lo2, hi2 = self.squared_limits(lo, hi)
        first = self._mean(c, f"{self.p}_s", f"{self.p}_n", lo, hi, c.eps / 2)
        second = self._mean(c, f"{self.p}_q", f"{self.p}_n", lo2, hi2, c.eps / 2, "squares_")
        return F.greatest(F.lit(0.0), second - first * first)

    def release(self, c, lo, hi):
        return self._variance(c, lo, hi)

    def half_width(self, level, eps, lo, hi):
        raise NotImplementedError("no interval for variances")

    def interval(self, c, level, lo, hi):
        raise NotImplementedError("no interval for variances")


class StdDev(Var):
    """The square root of the variance."""

    def release(self, c, lo, hi):
        return F.sqrt(self._variance(c, lo, hi))


class Quantile(Agg):
    """A quantile over owners of one value each, by a noisy search between the limits (operators/quantile.py)."""

    search = True

    def __post_init__(self):
        super().__post_init__()
        if not all(0 <= q <= 1 for q in self.q):
            raise ValueError("quantiles lie in [0, 1]")

    @property
    def q(self) -> list[float]:
        return self.extra["q"]

    @property
    def depth(self) -> int:
        return self.extra.get("depth", 20)

    def partial(self):
        return F.percentile(_column(self.col).cast("double"), F.lit(0.5)) if self.per_owner != "one" else self._one_value()

    def scale(self, eps, lo, hi):
        return self.depth * len(self.q) / eps

    def half_width(self, level, eps, lo, hi):
        raise NotImplementedError("no interval for quantiles")

    def interval(self, c, level, lo, hi):
        raise NotImplementedError("no interval for quantiles")


def priv_count_owners(name: str = "owners") -> Agg:
    return CountOwners(name)


def priv_count(name: str, col=None, lo: float | None = None, hi: float | None = None, automatic: bool = False) -> Agg:
    """Without limits: how many owners contribute. With them, or ``automatic``: how many rows."""
    if lo is None and not automatic:
        return CountContributors(name, col)
    return CountRows(name, col, lo, hi)


def priv_sum(name: str, col, lo: float | None = None, hi: float | None = None) -> Agg:
    return Sum(name, col, lo, hi)


def priv_avg(name: str, col, lo=None, hi=None, per_owner: str = "mean", count_share: float = 0.5) -> Agg:
    return Avg(name, col, lo, hi, per_owner, {"count_share": count_share})


def priv_var(name: str, col, lo=None, hi=None, per_owner: str = "mean") -> Agg:
    return Var(name, col, lo, hi, per_owner)


def priv_stddev(name: str, col, lo=None, hi=None, per_owner: str = "mean") -> Agg:
    return StdDev(name, col, lo, hi, per_owner)


def priv_quantile(name: str, col, q: float, lo=None, hi=None, per_owner: str = "median", depth: int = 20) -> Agg:
    return Quantile(name, col, lo, hi, per_owner, {"q": [q], "depth": depth})


def priv_median(name: str, col, lo=None, hi=None, per_owner: str = "median", depth: int = 20) -> Agg:
    return priv_quantile(name, col, 0.5, lo, hi, per_owner, depth)


def priv_min(name: str, col, lo=None, hi=None, per_owner: str = "median", depth: int = 20) -> Agg:
    return priv_quantile(name, col, 0.0, lo, hi, per_owner, depth)


def priv_max(name: str, col, lo=None, hi=None, per_owner: str = "median", depth: int = 20) -> Agg:
    return priv_quantile(name, col, 1.0, lo, hi, per_owner, depth)


def priv_ntile(name: str, col, n: int, lo=None, hi=None, per_owner: str = "median", depth: int = 20) -> Agg:
    """The n - 1 cut points as an array; they divide the share."""
    return Quantile(name, col, lo, hi, per_owner, {"q": [i / n for i in range(1, n)], "depth": depth, "array": True})
