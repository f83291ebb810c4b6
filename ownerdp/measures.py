"""How far off a release is, how much it hides, and how it would change without one owner."""

from __future__ import annotations

import math
from collections.abc import Callable, Sequence

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ownerdp.functions.noise import Noise


def noise_runs(spark: SparkSession, exact: DataFrame, keys: Sequence[str], value: str, scale: float, n_runs: int, noise: Noise, tag: str = "run") -> DataFrame:
    """(run, keys, exact, noisy): the release's noise drawn again for each run over the exact rows; the data is not read again."""
    both = repeated(exact.select(*keys, F.col(value).cast("double").alias("exact")), n_runs)
    drawn = noise.laplace(scale, F.concat(F.lit(f"{tag}|"), F.col("run").cast("string")), [F.col(k) for k in keys])
    return both.withColumn("noisy", F.col("exact") + drawn)


#: Exact rows that the driver holds, at most, and those that are literals of a plan: with more, compiling takes longer than running.
MOST_EXACT_ROWS, MOST_LITERAL_ROWS = 5000, 100


def _few(rows: DataFrame) -> list:
    held = rows.limit(MOST_EXACT_ROWS + 1).collect()
    if len(held) > MOST_EXACT_ROWS:
        raise ValueError(f"this measure is for at most {MOST_EXACT_ROWS} groups")
    return held


def repeated(rows: DataFrame, n_runs: int) -> DataFrame:
    """Each row once for each number in ``run``. Few rows are literals of the plan and the numbers are spread over the tasks; more than
    MOST_LITERAL_ROWS are spread over the tasks themselves."""
    spark = rows.sparkSession
    held, tasks = rows.limit(MOST_LITERAL_ROWS + 1).collect(), max(8, spark.sparkContext.defaultParallelism)
    if len(held) > MOST_LITERAL_ROWS:
        numbers = F.filter(F.sequence(F.lit(0).cast("long"), F.lit(n_runs).cast("long")), lambda run: run < n_runs)  # none for no runs
        return rows.repartition(tasks).select(F.explode(numbers).alias("run"), *rows.columns)
    runs = spark.range(0, n_runs if held else 0, 1, tasks).select(F.col("id").alias("run"))
    blank = [dict.fromkeys(rows.columns)]
    each = [F.struct(*(F.lit(r[f.name]).cast(f.dataType).alias(f.name) for f in rows.schema)) for r in held or blank]
    return runs.select("run", F.inline(F.array(*each)))


def median_relative_error(runs: DataFrame, by: Sequence[str] = ()) -> DataFrame:
    """The median over runs and returned rows of |noisy - exact| / exact; suppressed rows are not in ``runs``."""
    error = F.abs(F.col("noisy") - F.col("exact")) / F.abs(F.col("exact"))
    return runs.groupBy(*by).agg(F.percentile_approx(error, 0.5, 20_000).alias("median_relative_error"))  # of ranks that are off by one in 20,000 at most


def expected_suppression(owners: Column, tau: Column, scale: Column) -> Column:
    """How likely a key with so many owners stays below the threshold, from the noise's distribution function."""
    x = (tau - owners) / scale
    return F.when(x >= 0, 1 - 0.5 * F.exp(-x)).otherwise(0.5 * F.exp(x))


def suppression_rate(runs: DataFrame, hidden: Column, by: Sequence[str] = ()) -> DataFrame:
    return runs.groupBy(*by).agg(F.avg(hidden.cast("double")).alias("suppression_rate"))


def partition_limit_error(counts: DataFrame, n: str, c_u: Sequence[int]) -> DataFrame:
    """(c_u, lost_share): what limits on partitions lose of all (owner, partition) pairs; ``n`` holds the partitions of each owner."""
    total = F.sum(F.col(n)).cast("double")
    lost = [F.struct(F.lit(c).alias("c_u"), (F.sum(F.greatest(F.col(n) - c, F.lit(0))) / total).alias("lost_share")) for c in c_u]
    return counts.agg(F.array(*lost).alias("all")).select(F.inline("all"))


def clamp_bias(a: float, b: float, u: float) -> float:
    """What an upper limit u takes from the mean of values uniform on [a, b]."""
    return (b - u) ** 2 / (2 * (b - a)) if u < b else 0.0


def clamp_error(a: float, b: float, lower: float, upper: float, n: int, eps: float, form: str = "sum") -> float:
    """The error of a clamped noisy mean of n values uniform on [a, b], for lower <= a.

    ``sum``: bias plus noise scale; ``expected``: the expected absolute error.
    """
    bias, scale = clamp_bias(a, b, upper), (upper - lower) / (eps * n)
    return bias + scale if form == "sum" else bias + scale * math.exp(-bias / scale)


def best_clamp(a: float, b: float, n: int, eps: float) -> float:
    """The upper limit that is best in the form ``sum``."""
    return b - (b - a) / (eps * n)


def poisson_steps(mean: float, most: int) -> list[float]:
    """How likely at most 0, 1, ... ``most`` events are: a uniform number lies above as many of them as a Poisson number is."""
    out, p, total = [], math.exp(-mean), 0.0
    for k in range(most + 1):
        total += p
        out.append(total)
        p *= mean / (k + 1)
    return out


def normal_steps(mean: float, deviation: float, most: int) -> list[float]:
    """The same for a normal number that is rounded and not negative."""
    return [0.5 * math.erfc((mean - k - 0.5) / deviation / math.sqrt(2)) for k in range(most + 1)]


def interval_coverage(runs: DataFrame, lo: str, hi: str, exact: str = "exact") -> DataFrame:
    inside = (F.col(exact) >= F.col(lo)) & (F.col(exact) <= F.col(hi))
    return runs.agg(F.avg(inside.cast("double")).alias("coverage"))


def outside_fraction(values: DataFrame, col: str, lo: float, hi: float) -> DataFrame:
    """The exact share of values outside the limits, beside which the noisy one can be put."""
    out = (F.col(col) < lo) | (F.col(col) > hi)
    return values.agg(F.avg(out.cast("double")).alias("outside"))


def observed_sensitivity(df: DataFrame, owner: str, release: Callable[[DataFrame], DataFrame], keys: Sequence[str], values: Sequence[str], owners: Sequence) -> float:
    """The largest L1 change of a noise-free release when one of the named owners is removed; a run for each. For small tests."""
    whole = {tuple(r[k] for k in keys): [r[v] for v in values] for r in _few(release(df))}
    worst = 0.0
    for o in owners:
        part = {tuple(r[k] for k in keys): [r[v] for v in values] for r in _few(release(df.filter(F.col(owner) != o)))}
        zero = [0.0] * len(values)
        worst = max(worst, sum(abs((x or 0) - (y or 0)) for k in whole.keys() | part.keys() for x, y in zip(whole.get(k, zero), part.get(k, zero), strict=True)))
    return worst


def observed_stability(df: DataFrame, owner: str, limited: Callable[[DataFrame], DataFrame], owners: Sequence) -> int:
    """The most rows that appear or vanish after the limit on partitions when one of the named owners is removed."""
    whole, worst = limited(df), 0
    for o in owners:
        part = limited(df.filter(F.col(owner) != o))
        worst = max(worst, whole.exceptAll(part).count() + part.exceptAll(whole).count())
    return worst


def neighbours(df: DataFrame, owner: str, value, row: Column | None = None) -> DataFrame:
    """The data without one owner, or without the one row of it that the condition names."""
    gone = F.col(owner).eqNullSafe(F.lit(value))
    return df.filter(~(gone & row) if row is not None else ~gone)
