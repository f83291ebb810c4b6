"""Limits found privately: a noisy histogram of magnitudes in powers of two, and its outermost bins above a threshold."""

from __future__ import annotations

import math
from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ownerdp.functions.noise import Noise

KINDS = ("unsigned", "signed", "float")
BINS = 64
#: Exponents below zero that kind "float" tells apart.
NEGATIVE_EXPONENTS = 64


def magnitude(x: Column) -> Column:
    """The least k with x <= 2^k, for x > 0. log2 alone errs at powers of two, so its floor is corrected by exact powers."""
    guess = F.floor(F.log2(x))
    low = F.when(F.pow(F.lit(2.0), guess) > x, guess - 1).when(F.pow(F.lit(2.0), guess + 1) <= x, guess + 1).otherwise(guess)
    return F.when(F.pow(F.lit(2.0), low) == x, low).otherwise(low + 1).cast("int")


def exponent_range(kind: str, bins: int = BINS) -> tuple[int, int]:
    return (-NEGATIVE_EXPONENTS, bins - 1) if kind == "float" else (0, bins - 1)


def codes(kind: str, bins: int = BINS) -> list[int]:
    """All bins, in the order of the values: 0 is zero, s * (k - lowest + 1) is magnitude k with sign s."""
    lowest, highest = exponent_range(kind, bins)
    top = highest - lowest + 1
    return list(range(0 if kind == "unsigned" else -top, top + 1))


def bin_of(value: Column, kind: str, bins: int = BINS) -> Column:
    """The code of a value's bin; values beyond the range go to the last bin, NaN to zero's, negative ones of "unsigned" too."""
    lowest, highest = exponent_range(kind, bins)
    x = value.cast("double")
    k = F.greatest(F.lit(lowest), F.least(F.lit(highest), F.when(F.abs(x) > 2.0**highest, F.lit(highest)).otherwise(magnitude(F.abs(x)))))
    code = F.when(F.isnan(x) | (x == 0), F.lit(0)).otherwise(F.signum(x).cast("int") * (k - lowest + 1))
    return F.greatest(code, F.lit(0)) if kind == "unsigned" else code


def upper_edge(code: Column, kind: str, bins: int = BINS) -> Column:
    lowest, _ = exponent_range(kind, bins)
    power = lambda k: F.pow(F.lit(2.0), k)
    inner = lambda c: F.when(c == 1, F.lit(0.0) if kind != "float" else power(F.lit(lowest - 1))).otherwise(power(c + (lowest - 2)))
    return F.when(code == 0, F.lit(0.0)).when(code > 0, power(code + (lowest - 1))).otherwise(-inner(-code))


def lower_edge(code: Column, kind: str, bins: int = BINS) -> Column:
    return F.when(code == 0, F.lit(0.0)).otherwise(-upper_edge(-code, kind, bins))


def bounds_threshold(scale: float, p: float, bins: int = BINS) -> float:
    """What none of bins - 1 empty bins exceeds with probability p, under noise of the given scale."""
    log_each = math.log(p) / (bins - 1)
    return -scale * math.log(-2 * math.expm1(log_each))


def bin_counts(partials: DataFrame, keys: Sequence[str], col: str, kind: str, bins: int = BINS) -> DataFrame:
    """(keys, bin, n) of the bins that hold a partial value."""
    return partials.filter(F.col(col).isNotNull()).groupBy(*keys, bin_of(F.col(col), kind, bins).alias("bin")).agg(F.count(F.lit(1)).alias("n"))


def noisy_bins(counts: DataFrame, keys: Sequence[str], kind: str, scale: float, noise: Noise, tag: str = "bounds", bins: int = BINS) -> DataFrame:
    """(keys, bins: array of (bin, n)): every bin gets noise, the empty ones as well."""
    held = F.map_from_entries(F.collect_list(F.struct("bin", "n")))
    by_key = counts.groupBy(*keys).agg(held.alias("held"))
    by_key = noise.prepare(by_key)
    lead = F.concat(F.lit(f"{tag}|"), noise.message("", [F.col(k) for k in keys]))

    def noisy(code: Column) -> Column:
        n = F.coalesce(F.try_element_at("held", code), F.lit(0)).cast("double")
        return F.struct(code.alias("bin"), (n + noise.laplace(scale, F.concat(lead, F.lit("|"), code.cast("string")), [])).alias("n"))

    grid = codes(kind, bins)
    return noise.finish(by_key.select(*keys, F.transform(F.sequence(F.lit(grid[0]), F.lit(grid[-1])), noisy).alias("bins"), *([noise.NONCE] if hasattr(noise, "NONCE") else [])))


def choose_limits(noisy: DataFrame, keys: Sequence[str], kind: str, threshold: float, bins: int = BINS) -> DataFrame:
    """(keys, lower, upper, outside): the edges of the outermost bins above the threshold, NULL if there is none, and the noisy share of values outside."""
    over = F.filter("bins", lambda b: b["n"] > F.lit(threshold))
    chosen = noisy.withColumn("over", F.transform(over, lambda b: b["bin"])).withColumn("lo", F.array_min("over")).withColumn("hi", F.array_max("over"))
    total = F.aggregate("bins", F.lit(0.0), lambda a, b: a + F.greatest(b["n"], F.lit(0.0)))
    inside = F.aggregate(F.filter("bins", lambda b: (b["bin"] >= F.col("lo")) & (b["bin"] <= F.col("hi"))), F.lit(0.0), lambda a, b: a + F.greatest(b["n"], F.lit(0.0)))
    return chosen.select(
        *keys, lower_edge(F.col("lo"), kind, bins).alias("lower"), upper_edge(F.col("hi"), kind, bins).alias("upper"),
        F.when(F.col("lo").isNotNull(), F.greatest(F.lit(0.0), F.lit(1.0) - inside / F.greatest(total, F.lit(1.0)))).alias("outside"),
    )


def approx_bounds(partials: DataFrame, keys: Sequence[str], col: str, eps: float, noise: Noise, p: float = 1 - 1e-9, kind: str = "float", c_u: int = 1, bins: int = BINS, tag: str = "bounds") -> DataFrame:
    """Limits for the values in ``col``, one row for each combination of ``keys`` (one row without keys).

    An owner is in at most c_u partitions and in one bin of each, so the noise has the scale c_u / eps.
    """
    scale = c_u / eps
    noisy = noisy_bins(bin_counts(partials, keys, col, kind, bins), keys, kind, scale, noise, tag, bins)
    return choose_limits(noisy, keys, kind, bounds_threshold(scale, p, bins), bins)
