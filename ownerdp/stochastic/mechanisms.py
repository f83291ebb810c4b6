"""Mechanisms over small databases: what the library ships, run by the library's own code, and versions with known defects that a search must find.

Each gives ``outputs`` for the parts of databases (db_id, mask, rows: array of numbers): (db_id, mask, value), m rows for each part.
Every number of a database is the one row of an owner.
"""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ownerdp.functions.aggregates import Agg, Context, CountOwners, Quantile
from ownerdp.functions.clamp import clamp
from ownerdp.functions.noise import Noise, draw_tag, rounding_step
from ownerdp.operators import bounds, quantile
from ownerdp.operators.threshold import owner_threshold
from ownerdp.plans.ownership import OwnedFrame
from ownerdp.plans.rewrite import cross_owner, partials

PART = ["db_id", "mask"]
Laplace = Callable[[float, str], Column]


def _runs(parts: DataFrame, m: int) -> DataFrame:
    tasks = max(8, parts.sparkSession.sparkContext.defaultParallelism)
    return parts.repartition(tasks, *PART).withColumn("run", F.explode(F.sequence(F.lit(0), F.lit(m - 1))))


def _rows(parts: DataFrame) -> OwnedFrame:
    return OwnedFrame.of(parts.select(*PART, F.posexplode("rows").alias("row", "x")), "row")


class Mechanism:
    def outputs(self, parts: DataFrame, m: int, noise: Noise) -> DataFrame:
        raise NotImplementedError


@dataclass
class Shipped(Mechanism):
    """An aggregate of the column ``x``: its partials, its sums over owners and its release, with the given budget."""

    agg: Agg
    eps: float

    def outputs(self, parts, m, noise):
        totals = cross_owner(partials(_rows(parts), PART, [self.agg]), PART, [self.agg])
        whole = parts.select(*PART).join(totals, PART, "left").fillna(0.0)
        value = self.agg.release(Context(noise, [*map(F.col, PART), F.col("run")], self.eps), self.agg.lo, self.agg.hi)
        return _runs(whole, m).select(*PART, value.alias("value"))


@dataclass
class ShippedQuantile(Mechanism):
    """The noisy search for a quantile."""

    agg: Quantile
    eps: float

    def outputs(self, parts, m, noise):
        a, eps = self.agg, self.eps
        cells = quantile.leaf_counts(partials(_rows(parts), PART, [a]), PART, a.p, a.lo, a.hi, a.depth)
        held = cells.groupBy(*PART).agg(F.collect_list("cell").alias("cells"), F.collect_list("n").alias("n"))
        slots = _runs(parts.select(*PART).join(held, PART, "left"), m // self.CHUNK)

        def search(batches):
            for batch in batches:
                for db_id, mask, its, n, run in zip(*(batch[c] for c in (*PART, "cells", "n", "run")), strict=True):
                    at, counts = (np.array(x if x is not None else [], np.int64) for x in (its, n))
                    found = [quantile.search(at, counts, a.q[0], a.depth, eps, lambda scale, what, i=i: noise.draw(scale, f"{db_id}|{mask}|{run}|{i}|{what}")) for i in range(ShippedQuantile.CHUNK)]
                    yield pd.DataFrame({"db_id": db_id, "mask": mask, "value": a.lo + (a.hi - a.lo) * np.array(found) / (1 << a.depth)})

        return slots.mapInPandas(search, "db_id long, mask int, value double")

    CHUNK = 100


@dataclass
class ShippedLimits(Mechanism):
    """Limits that are found privately: both, as one number; NULL if no bin stands out. The numbers are stretched, so that they fall into several bins."""

    eps: float
    p: float = 0.9
    bins: int = 4
    stretch: float = 16.0

    def outputs(self, parts, m, noise):
        scaled = parts.withColumn("rows", F.transform("rows", lambda x: x * self.stretch))
        counts = bounds.bin_counts(_rows(scaled).unowned(), PART, "x", "signed", self.bins)
        counts = counts.unionByName(parts.select(*PART, F.lit(0).alias("bin"), F.lit(0).cast("long").alias("n"))).groupBy(*PART, "bin").agg(F.sum("n").alias("n"))
        keys = [*PART, "run"]
        noisy = bounds.noisy_bins(_runs(counts, m), keys, "signed", 1 / self.eps, noise, "bounds", self.bins)
        chosen = bounds.choose_limits(noisy, keys, "signed", bounds.bounds_threshold(1 / self.eps, self.p, self.bins), self.bins)
        return chosen.select(*PART, (F.col("lower") * 2 * self.stretch + F.col("upper")).alias("value"))


@dataclass
class ShippedThreshold(Mechanism):
    """The owner count where the hidden one reaches the threshold for delta, else NULL; each has half of the budget."""

    eps: float
    delta: float

    def outputs(self, parts, m, noise):
        agg, tau = CountOwners("n"), owner_threshold(self.eps / 2, self.delta, 1)
        totals = cross_owner(partials(_rows(parts), PART, [agg]), PART, [agg])
        keys = [*map(F.col, PART), F.col("run")]
        hidden = F.col("__owners") + noise.laplace(2 / self.eps, draw_tag("", "owners"), keys)
        value = F.when(hidden >= tau, agg.release(Context(noise, keys, self.eps / 2), 0, 0))
        return _runs(parts.select(*PART).join(totals, PART, "left"), m).select(*PART, value.alias("value"))


@dataclass
class Formula(Mechanism):
    """A mechanism written as a column over the array of numbers and a function ``laplace(scale, tag)``."""

    column: Callable[[Column, Laplace], Column]

    def outputs(self, parts, m, noise):
        laplace = lambda scale, tag: noise.laplace(scale, f"tester_{tag}", [*map(F.col, PART), F.col("run")])
        return _runs(parts, m).select(*PART, self.column(F.col("rows"), laplace).cast("double").alias("value"))


def _sum(rows: Column, lo: float, hi: float) -> Column:
    return F.aggregate(rows, F.lit(0.0), lambda a, x: a + clamp(x, lo, hi))


def accurate_count_avg(eps: float, lo: float, hi: float, scale: str = "range") -> Mechanism:
    """Noise on the sum over the exact count. ``range``: scale hi - lo; ``magnitude``: max(|lo|, |hi|), too little."""
    by = {"range": hi - lo, "magnitude": max(abs(lo), abs(hi))}[scale]
    return Formula(lambda rows, laplace: clamp((_sum(rows, lo, hi) + laplace(by / eps, "sum")) / F.greatest(F.size(rows), F.lit(1)), lo, hi))


def clamp_unsafe(eps: float, lo: float, hi: float) -> Mechanism:
    """A sum that compares as IEEE does, so that NaN passes both limits and marks its owner."""
    naive = lambda x: F.when(x < lo, F.lit(lo)).when((x > hi) & ~F.isnan(x), F.lit(hi)).otherwise(x)
    return Formula(lambda rows, laplace: F.aggregate(rows, F.lit(0.0), lambda a, x: a + naive(x)) + laplace(max(abs(lo), abs(hi)) / eps, "sum"))


def narrow_sum(eps: float, lo: float, hi: float) -> Mechanism:
    """Noise for half of what one number can add."""
    return Formula(lambda rows, laplace: _sum(rows, lo, hi) + laplace(max(abs(lo), abs(hi)) / (2 * eps), "sum"))


def threshold_count(eps: float, tau: float, rounded: bool) -> Mechanism:
    """The noisy count where it reaches tau, else -1. Rounded before the comparison, counts below tau can pass."""

    def run(rows, laplace):
        noisy = F.size(rows) + laplace(1 / eps, "count")
        step = rounding_step(1 / eps)
        seen = F.round(noisy / step) * step if rounded else noisy
        return F.when(seen >= tau, F.round(noisy / step) * step).otherwise(F.lit(-1.0))

    return Formula(run)


def passes_rounded(noisy_count: float, tau: float, step: float) -> bool:
    return round(noisy_count / step) * step >= tau


def expected_pass(owners: int, tau: float, eps: float) -> float:
    """How likely a count of so many owners passes the threshold without rounding."""
    d = (tau - owners) * eps
    return 0.5 * math.exp(-d) if d >= 0 else 1 - 0.5 * math.exp(d)
