"""Samples of mechanisms on neighbouring databases, their histograms compared, and the walk over the graph."""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ownerdp.functions.noise import Noise, RunNoise, TestNoise
from ownerdp.sources.tables import materialise
from ownerdp.stochastic.databases import adjacent_pairs, part_of, sub_databases
from ownerdp.stochastic.mechanisms import PART, Mechanism


def sample_outputs(pairs: DataFrame, mechanism: Mechanism, m: int, noise: Noise | None = None) -> DataFrame:
    """(pair, side, value): m outputs on either side of each pair (pair, larger, smaller), with fresh noise for each."""
    sides = pairs.select(F.col("pair").cast("long").alias("db_id"), F.inline(F.array(*(F.struct(F.lit(side).alias("mask"), F.col(rows).alias("rows")) for side, rows in enumerate(("larger", "smaller"))))))
    return mechanism.outputs(sides, m, noise or TestNoise(1)).select(F.col("db_id").cast("int").alias("pair"), F.col("mask").alias("side"), "value")


def _bucket(value: Column, low: float, high: float, buckets: int) -> Column:
    """Places of a grid: 0 for NaN and NULL, 1 and buckets + 2 for what lies outside."""
    inside = F.floor((value - low) / (high - low) * buckets).cast("int") + 2
    return F.when(F.isnan(value) | value.isNull(), F.lit(0)).when(value < low, F.lit(1)).when(value >= high, F.lit(buckets + 2)).otherwise(inside)


def _grid(samples: DataFrame, low: float | None, high: float | None) -> tuple[float, float]:
    if low is None or high is None:
        ends = samples.filter(~F.isnan("value")).agg(F.percentile_approx("value", [0.001, 0.999], 10_000)).first()[0]
        low, high = ends if ends else (0.0, 1.0)
    return low, high if high > low else low + 1.0


def histograms(samples: DataFrame, by: list[str], low: float, high: float, buckets: int) -> DataFrame:
    """(by, counts): how many outputs lie in each bucket of one grid."""
    placed = samples.select(*by, _bucket(F.col("value"), low, high, buckets).alias("bucket"))
    return placed.groupBy(*by).agg(F.array(*(F.sum((F.col("bucket") == i).cast("long")) for i in range(buckets + 3))).alias("counts"))


def failing_in(mine: Column, other: Column, m: int, eps: float, delta: float, confidence: float) -> Column:
    """In how many buckets the one side is too likely given the other: its share exceeds e^eps times the share there plus delta.

    With ``confidence`` z, both shares are first moved towards each other by z standard deviations."""
    spread = lambda x: F.sqrt(F.greatest(x * (1 - x), F.lit(1.0 / m)) / F.lit(float(m))) * F.lit(float(confidence))

    def fails(a: Column, b: Column) -> Column:
        p, q = a / F.lit(float(m)), b / F.lit(float(m))
        return (F.greatest(p - spread(p), F.lit(0.0)) > F.lit(math.exp(eps)) * (q + spread(q)) + F.lit(float(delta))).cast("int")

    return F.aggregate(F.zip_with(mine, other, fails), F.lit(0), lambda a, x: a + x)


def compare_histograms(samples: DataFrame, m: int, eps: float, delta: float = 0.0, buckets: int = 40, low: float | None = None, high: float | None = None, confidence: float = 0.0) -> DataFrame:
    """(pair, side, buckets, failing) of samples (pair, side, value): for each direction, the buckets in use and those that fail."""
    low, high = _grid(samples, low, high)
    of = histograms(samples, ["pair", "side"], low, high, buckets)
    other = of.select("pair", (1 - F.col("side")).alias("side"), F.col("counts").alias("other"))
    used = F.size(F.filter(F.zip_with("counts", "other", lambda a, b: a + b), lambda x: x > 0))
    return of.join(other, ["pair", "side"]).select("pair", "side", used.alias("buckets"), failing_in(F.col("counts"), F.col("other"), m, eps, delta, confidence).alias("failing"))


@dataclass
class Verdict:
    violated: bool
    pair: tuple | None = None
    side: int | None = None
    failing: int = 0
    pairs_tried: int = 0


def failing_buckets(samples: DataFrame, m: int, eps: float, **options) -> list[tuple[int, int, int]]:
    """(pair, side, failing buckets) in order."""
    return sorted((r["pair"], r["side"], r["failing"]) for r in compare_histograms(samples, m, eps, **options).collect())


def find_violation(
    spark: SparkSession, mechanism: Mechanism, dbs: DataFrame, eps: float, delta: float = 0.0, m: int = 20_000, buckets: int = 40, alpha: float = 0.0, confidence: float = 4.0, order: str = "dfs",
    batch: int = 64, low: float | None = None, high: float | None = None, noise: Noise | None = None,
) -> Verdict:
    """Walks over all neighbouring parts of the databases and stops at the first step with a pair that violates the definition.

    Each part of a database is sampled once, whatever the number of its neighbours; parts, samples and edges stay distributed, and
    only the first violating pair comes to the driver. A step of ``dfs`` takes ``batch`` databases down to the empty one; a step of ``bfs`` takes one
    level of all databases, the largest parts first. A pair fails if more than the share ``alpha`` of its buckets does.
    """
    noise = noise or RunNoise(1)
    ids = dbs.agg(F.min("db_id").alias("first"), F.max("db_id").alias("last"), F.max(F.size("rows")).alias("size")).first()
    if ids["first"] is None:
        return Verdict(False)
    size = F.bit_count("mask")
    if order == "dfs":
        steps = [(F.col("db_id").between(a, a + batch - 1), F.lit(True)) for a in range(ids["first"], ids["last"] + 1, batch)]
    else:
        steps = [(F.lit(True), size == level) for level in range(ids["size"], 0, -1)]
    tried, known, known_level = 0, None, None
    if low is None or high is None:
        low, high = _grid(mechanism.outputs(sub_databases(dbs.orderBy("db_id").limit(8)), min(m, 2000), noise), low, high)
    for number, (of_database, of_edge) in enumerate(steps):
        part = dbs.filter(of_database)
        edges = adjacent_pairs(part).filter(of_edge)
        wanted = sub_databases(part)
        if order != "dfs":
            level = ids["size"] - number
            wanted = wanted.filter(size.isin(level - 1) if known is not None else size.isin(level, level - 1))
        fresh = materialise(histograms(mechanism.outputs(wanted, m, noise), PART, low, high, buckets), "tester-histograms")
        counts = fresh if known is None or order == "dfs" else known.unionByName(fresh)
        if order != "dfs":
            known = fresh.filter(size == level - 1) if known is None else fresh
        larger = counts.select("db_id", "mask", F.col("counts").alias("more"))
        smaller = counts.select("db_id", F.col("mask").alias("less_mask"), F.col("counts").alias("less"))
        pairs = edges.withColumn("less_mask", (F.col("mask") - F.pow(F.lit(2), F.col("removed"))).cast("int")).join(larger, PART).join(smaller, ["db_id", "less_mask"])
        used = F.size(F.filter(F.zip_with("more", "less", lambda a, b: a + b), lambda x: x > 0))
        sides = F.inline(F.array(*(F.struct(F.lit(side).alias("side"), failing_in(F.col(a), F.col(b), m, eps, delta, confidence).alias("failing")) for side, (a, b) in enumerate((("more", "less"), ("less", "more"))))))
        judged = pairs.select("db_id", "mask", "removed", "less_mask", used.alias("used"), sides)
        bad = judged.filter(F.col("failing") > alpha * F.col("used"))
        sorting = ["db_id", F.desc(size), "mask", "removed", "side"]
        found = bad.join(dbs, "db_id").select("*", part_of(F.col("rows"), F.col("mask")).alias("larger"), part_of(F.col("rows"), F.col("less_mask")).alias("smaller")).orderBy(*sorting).first()
        tried += edges.count()
        if found is not None:
            return Verdict(True, (found["larger"], found["smaller"]), found["side"], found["failing"], tried)
    return Verdict(False, pairs_tried=tried)


def find_violation_owner(df: DataFrame, owner: str, release: Callable[[DataFrame, Noise], DataFrame], value: str, owners: list, eps: float, m: int = 200, buckets: int = 20, delta: float = 0.0, confidence: float = 3.0) -> Verdict:
    """The same question end to end: a whole release with and without each named owner, m times with fresh seeds. For small tests."""
    spark = df.sparkSession
    for tried, o in enumerate(owners, 1):
        rows = []
        for side, data in ((0, df), (1, df.filter(F.col(owner) != o))):
            for run in range(m):
                got = release(data, TestNoise(1000 * run + side)).first()
                rows.append((0, side, float(got[value]) if got is not None and got[value] is not None else float("nan")))
        samples = spark.createDataFrame(rows, "pair int, side int, value double")
        found = compare_histograms(samples, m, eps, delta, buckets, confidence=confidence).filter("failing > 0").first()
        if found is not None:
            return Verdict(True, (o,), found["side"], found["failing"], tried)
    return Verdict(False, pairs_tried=len(owners))
