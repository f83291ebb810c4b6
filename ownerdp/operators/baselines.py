"""What private aggregation is compared with: exact answers, simpler histograms with their defects, and releases whose unit is the row."""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ownerdp.functions.noise import Noise, encode_keys
from ownerdp.operators.sampling import limit_partitions
from ownerdp.operators.threshold import owner_threshold, suppress_rare_keys

# Exact answers ---------------------------------------------------------------------------------------------------------


def exact_aggregate(df: DataFrame, keys: Sequence[str], **aggregates: Column) -> DataFrame:
    """No privacy at all: the truth that errors are measured against."""
    return df.groupBy(*keys).agg(*(a.alias(n) for n, a in aggregates.items()))


def exact_histogram(df: DataFrame, key: str) -> DataFrame:
    return exact_aggregate(df, [key], n=F.count(F.lit(1)))


def exact_owner_count(df: DataFrame, owner: str, keys: Sequence[str], approximate: bool = False) -> DataFrame:
    return exact_aggregate(df, keys, owners=F.approx_count_distinct(owner) if approximate else F.countDistinct(owner))


# The ladder of histograms ----------------------------------------------------------------------------------------------


def _noisy(counts: DataFrame, key: str, scale: float, noise: Noise, tag: str) -> DataFrame:
    return counts.withColumn("n", F.col("n") + noise.laplace(scale, tag, [F.col(key)]))


def naive_row_histogram(df: DataFrame, key: str, eps: float, noise: Noise) -> DataFrame:
    """Noise for one row; an owner with many rows shows through."""
    return _noisy(exact_histogram(df, key).withColumn("n", F.col("n").cast("double")), key, 1 / eps, noise, "naive")


def owner_histogram(df: DataFrame, owner: str, key: str, eps: float, noise: Noise, max_rows: int = 1) -> DataFrame:
    """Each owner counts once for a key, or up to ``max_rows`` times; that a key is there at all still tells something."""
    per_owner = df.groupBy(owner, key).agg(F.least(F.count(F.lit(1)), F.lit(max_rows)).alias("rows"))
    return _noisy(per_owner.groupBy(key).agg(F.sum("rows").cast("double").alias("n")), key, max_rows / eps, noise, "owner")


def thresholded_histogram(df: DataFrame, owner: str, key: str, eps: float, tau: float, noise: Noise) -> DataFrame:
    """Rare keys are hidden; an owner with many keys still shows through."""
    return suppress_rare_keys(owner_histogram(df, owner, key, eps, noise), "n", tau)


def private_histogram(df: DataFrame, owner: str, key: str, eps: float, delta: float, c_u: int, noise: Noise) -> DataFrame:
    """The last rung: each owner counts once for at most c_u keys, the noise covers them all, rare keys are hidden."""
    distinct = df.groupBy(owner, key).agg(F.lit(1).alias("one"))
    kept = limit_partitions(distinct, owner, c_u, noise, [key], tag="histogram")
    counts = kept.groupBy(key).agg(F.count(F.lit(1)).cast("double").alias("n"))
    return suppress_rare_keys(_noisy(counts, key, c_u / eps, noise, "private"), "n", owner_threshold(eps, delta, c_u))


# Releases whose unit is the row ----------------------------------------------------------------------------------------


def row_unit_release(df: DataFrame, domain: DataFrame, keys: Sequence[str], kind: str, col: str | None, sensitivity: float, eps: float, noise: Noise, lower: float = 0.0, name: str = "value") -> DataFrame:
    """Counts, averages or medians with noise for one row, over keys that the analyst lists.

    The sensitivity is what the analyst says and nothing enforces it: one owner's rows may move a result by far more.
    """
    if kind == "median":
        return _row_unit_median(df, domain, keys, col, sensitivity, eps, noise, lower, name)
    found = row_unit_totals(df, keys, kind, col, sensitivity, lower)
    listed = domain.join(found, list(keys), "left").fillna(0.0, subset=[c for c in found.columns if c not in keys])
    return listed.select(*keys, row_unit_value(kind, [F.col(c) for c in keys], sensitivity, eps, noise, lower).alias(name))


def row_unit_totals(df: DataFrame, keys: Sequence[str], kind: str, col: str | None, sensitivity: float, lower: float = 0.0) -> DataFrame:
    x = F.col(col).cast("double") if col else None
    if kind == "count":
        sums = [F.count(F.lit(1)).cast("double").alias("s")]
    elif kind == "average":
        inside = F.greatest(F.lit(lower), F.least(F.lit(lower + sensitivity), x))
        sums = [F.sum(inside - lower - sensitivity / 2).alias("s"), F.count(x).cast("double").alias("c")]
    else:
        raise ValueError(f"{kind} is not supported")
    return df.groupBy(*keys).agg(*sums)


def row_unit_value(kind: str, keys: Sequence[Column], sensitivity: float, eps: float, noise: Noise, lower: float = 0.0) -> Column:
    """The noisy value of a row of totals."""
    if kind == "count":
        return F.col("s") + noise.laplace(sensitivity / eps, "row_count", keys)
    count = F.greatest(F.col("c") + noise.laplace(2 / eps, "row_avg_count", keys), F.lit(1.0))
    return lower + sensitivity / 2 + (F.col("s") + noise.laplace(sensitivity / eps, "row_avg_sum", keys)) / count


def _row_unit_median(df, domain, keys, col, sensitivity, eps, noise, lower, name) -> DataFrame:
    """A value drawn with a probability that falls by half the budget for each rank away from the middle.

    The draw needs gaps between sorted values. They are counted in cells of the range, so a key ships at most as many rows as
    there are cells.
    """
    cell = median_cells(F.col(col), sensitivity, lower)
    counts = df.filter(F.col(col).isNotNull()).groupBy(*keys, cell.alias("cell")).agg(F.count(F.lit(1)).alias("n"))
    keyed = counts.withColumn("__key", encode_keys([F.col(k) for k in keys]))
    kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in df.select(*keys).schema)

    def run(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        u = None if noise.exact else _uniform(noise, f"row_median|{rows['__key'].iloc[0]}")
        value = drawn_median(rows["cell"].to_numpy(), rows["n"].to_numpy(), u, sensitivity, eps, lower)
        return pd.DataFrame({k: [key[i]] for i, k in enumerate(keys)} | {name: [value]})

    found = keyed.groupBy(*keys).applyInPandas(run, f"{kinds}, `{name}` double")
    return domain.join(found, list(keys), "left").fillna({name: lower + sensitivity / 2})


MEDIAN_CELLS = 1 << 14


def median_cells(x: Column, sensitivity: float, lower: float = 0.0) -> Column:
    inside = F.greatest(F.lit(lower), F.least(F.lit(lower + sensitivity), x.cast("double")))
    return F.least(F.floor((inside - lower) / sensitivity * MEDIAN_CELLS), F.lit(MEDIAN_CELLS - 1)).cast("long")


def drawn_median(cells: np.ndarray, counts: np.ndarray, u: float | np.ndarray | None, sensitivity: float, eps: float, lower: float = 0.0):
    """The draw for each uniform number, or the likeliest value where there is none."""
    n = np.zeros(MEDIAN_CELLS)
    n[cells] = counts
    utility = -np.abs(np.cumsum(n) - n / 2 - n.sum() / 2)
    weights = np.exp((utility - utility.max()) * eps / 2)
    at = int(utility.argmax()) if u is None else np.searchsorted(np.cumsum(weights) / weights.sum(), u)
    return lower + (np.minimum(at, MEDIAN_CELLS - 1) + 0.5) / MEDIAN_CELLS * sensitivity


def _uniform(noise: Noise, message: str) -> float:
    x = noise.draw(1.0, message)  # a Laplace draw of scale one, turned back into its place in (0, 1)
    return 0.5 * np.exp(x) if x < 0 else 1 - 0.5 * np.exp(-x)


def max_frequency(df: DataFrame, key: str) -> float:
    """The most rows that share a join key: one more aggregate over each joined side."""
    return float(df.groupBy(key).count().agg(F.max("count")).first()[0] or 0)


def smooth_sensitivity(frequencies: Sequence[float], eps: float, delta: float) -> float:
    """The product of the frequencies after k changes, damped by exp(-b k), at its largest; b = eps / (2 ln(2 / delta))."""
    b = eps / (2 * np.log(2 / delta))
    k = np.arange(0, int(np.ceil(len(frequencies) / b)) + 1)
    return float((np.exp(-b * k) * np.prod([f + k for f in frequencies], axis=0)).max())


def join_scale(sensitivity: float, eps: float, frequencies: Sequence[float] = (), delta: float = 1e-9) -> float:
    """The scale of the noise: twice the smooth sensitivity, which makes up for noise that depends on the data, or the analyst's figure."""
    return (2 * smooth_sensitivity(frequencies, eps, delta) if frequencies else sensitivity) / eps


def row_unit_join_count(joined: DataFrame, domain: DataFrame, keys: Sequence[str], sensitivity: float, eps: float, noise: Noise, frequencies: Sequence[float] = (), delta: float = 1e-9, name: str = "value") -> DataFrame:
    """Counts over joins, the only aggregate of this baseline. Without frequencies the analyst's sensitivity is used as given."""
    by = join_scale(sensitivity, eps, frequencies, delta)
    found = joined.groupBy(*keys).agg(F.count(F.lit(1)).cast("double").alias("s"))
    listed = domain.join(found, list(keys), "left").fillna(0.0, subset=["s"])
    return listed.select(*keys, (F.col("s") + noise.laplace(by, "row_join", [F.col(k) for k in keys])).alias(name))
