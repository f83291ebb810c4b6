"""Moving values into limits, whatever they are, and arithmetic that never fails a job."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def clamp(value: Column, lower, upper) -> Column:
    """The value moved into [lower, upper]; infinities go to the limits, NaN to the point of [lower, upper] nearest to zero, NULL stays NULL."""
    lo, hi = (x if isinstance(x, Column) else F.lit(float(x)) for x in (lower, upper))
    x = value.cast("double")
    nothing = F.when(x.isNull(), F.lit(None).cast("double"))  # greatest and least pass over NULL
    return nothing.when(F.isnan(x), F.greatest(lo, F.least(hi, F.lit(0.0)))).otherwise(F.greatest(lo, F.least(hi, x)))


def safe_divide(a: Column, b: Column) -> Column:
    """a / b, NULL where b is zero: a failing branch must not tell anything about an owner."""
    return F.try_divide(a, b)


def safe_cast(value: Column, kind: str) -> Column:
    return value.try_cast(kind)


def safe_sum(value: Column) -> Column:
    """A sum that cannot overflow into an error: doubles for fractions, 38 digits for whole numbers."""
    return F.try_sum(value)
