"""Quantiles by a noisy search: each step asks how many owners lie on either side of a probe."""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ownerdp.functions.clamp import clamp
from ownerdp.functions.noise import Noise, encode_keys


def leaf_counts(bounded: DataFrame, keys: Sequence[str], col: str, lo: float, hi: float, depth: int) -> DataFrame:
    """(keys, cell, n): owners in each of 2^depth equal cells of [lo, hi]; only cells that hold some."""
    cells = float(1 << depth)
    place = F.floor((clamp(F.col(col), lo, hi) - lo) / (hi - lo) * cells) if hi > lo else F.lit(0)
    cell = F.least(place, F.lit(cells - 1)).cast("long")
    return bounded.filter(F.col(col).isNotNull()).groupBy(*keys, cell.alias("cell")).agg(F.count(F.lit(1)).alias("n"))


def search(cells: np.ndarray, counts: np.ndarray, q: float, depth: int, eps: float, draw) -> float:
    """The place of the quantile as a fraction of 2^depth cells.

    The belief about the place is a density over [0, 2^depth), flat between earlier probes. Each step probes its median, takes
    noisy counts of both sides, and weighs the sides by how likely the quantile lies there. Without noise this is bisection.
    """
    order = np.argsort(cells)
    cells, cum = cells[order], np.concatenate([[0], np.cumsum(counts[order])])
    total = cum[-1]
    edges, mass = np.array([0.0, float(1 << depth)]), np.array([1.0])
    steps = depth
    scale = steps / eps if eps else 0.0
    for step in range(steps):
        reached = np.cumsum(mass)
        i = int(np.searchsorted(reached, 0.5))
        i = min(i, len(mass) - 1)
        before = reached[i] - mass[i]
        probe = edges[i] + (edges[i + 1] - edges[i]) * ((0.5 - before) / mass[i] if mass[i] else 0.5)
        probe = round(probe)
        if probe <= edges[i] or probe >= edges[i + 1]:
            break  # the median lies in one cell
        left = cum[np.searchsorted(cells, probe, side="left")]
        noisy_left, noisy_right = left + draw(scale, f"{step}|left"), (total - left) + draw(scale, f"{step}|right")
        lead = (1 - q) * noisy_left - q * noisy_right  # above zero: more than the share q lies left
        if scale:
            spread = max(q, 1 - q) * scale
            is_left = 1 - 0.5 * np.exp(-lead / spread) if lead >= 0 else 0.5 * np.exp(lead / spread)
        else:
            is_left = 1.0 if (left >= q * total and left > 0) else 0.0
        edges = np.insert(edges, i + 1, probe)
        share = (probe - edges[i]) / (edges[i + 2] - edges[i])
        mass = np.concatenate([mass[:i], [mass[i] * share, mass[i] * (1 - share)], mass[i + 1 :]])
        mass[: i + 1] *= is_left
        mass[i + 1 :] *= 1 - is_left
        if mass.sum() <= 0:
            break
        mass /= mass.sum()
    reached = np.cumsum(mass)
    i = min(int(np.searchsorted(reached, 0.5)), len(mass) - 1)
    before = reached[i] - mass[i]
    return float(edges[i] + (edges[i + 1] - edges[i]) * ((0.5 - before) / mass[i] if mass[i] else 0.5))


def bisect(bounded: DataFrame, keys: Sequence[str], col: str, name: str, tag: str, qs: Sequence[float], lo: float, hi: float, depth: int, eps: float, noise: Noise, as_array: bool = False) -> DataFrame:
    """(keys, name): one search for each quantile, in the task that has the key's cells; eps is divided among them.

    A key needs at most min(its owners, 2^depth) cells in one task.
    """
    counts = leaf_counts(bounded, keys, col, lo, hi, depth).withColumn("__key", encode_keys([F.col(k) for k in keys]))
    kinds = [f"`{f.name}` {f.dataType.simpleString()}" for f in bounded.select(*keys).schema] if keys else []
    schema = ", ".join([*kinds, f"`{name}` " + ("array<double>" if as_array else "double")])
    share = 0.0 if noise.exact else eps / len(qs)

    def run(key: tuple, cells: pd.DataFrame) -> pd.DataFrame:
        lead = cells["__key"].iloc[0]
        draw = lambda q: lambda scale, what: noise.draw(scale, f"{tag}|{q}|{what}|{lead}") if scale else 0.0
        found = [lo + (hi - lo) * search(cells["cell"].to_numpy(), cells["n"].to_numpy(), q, depth, share, draw(q)) / (1 << depth) for q in qs]
        row = {k: [key[i]] for i, k in enumerate(keys)} | {name: [found if as_array else found[0]]}
        return pd.DataFrame(row)

    groups = counts.groupBy(*keys) if keys else counts.groupBy(F.lit(0).alias("__all"))
    return groups.applyInPandas(run, schema)


