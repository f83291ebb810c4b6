"""Limits on how many partitions an owner reaches."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ownerdp.functions.noise import Noise

SAMPLERS = ("window", "agg")
#: Kept for comparison only: each is biased, or does not bound what an owner contributes.
REJECTED_SAMPLERS = ("first", "systematic", "bernoulli", "replacement")


def limit_partitions(partials: DataFrame, owner: str, c_u: int, noise: Noise, keys: Sequence[str], strategy: str = "window", tag: str = "limit") -> DataFrame:
    """At most c_u rows of each owner, chosen uniformly without replacement.

    ``window`` ranks an owner's rows by a keyed hash; Spark applies the limit before the shuffle as well, so a map task ships
    at most c_u rows of an owner. ``agg`` keeps them in one aggregate; only for owners with few rows.
    """
    order = noise.order(tag, [F.col(owner), *map(F.col, keys)])
    if strategy == "window":
        ranked = partials.withColumn("__order", order)
        rank = F.row_number().over(Window.partitionBy(owner).orderBy("__order"))
        return ranked.withColumn("__rank", rank).filter(F.col("__rank") <= c_u).drop("__rank", "__order")
    if strategy == "agg":
        row = F.struct(order.alias("__order"), *map(F.col, partials.columns))
        return partials.groupBy(F.col(owner).alias("__owner")).agg(F.slice(F.array_sort(F.collect_list(row)), 1, c_u).alias("__rows")).select(F.inline("__rows")).drop("__order")
    if strategy in REJECTED_SAMPLERS:
        return _rejected(partials, owner, c_u, noise, keys, strategy, tag)
    raise ValueError(f"unknown strategy {strategy}")


def _rejected(partials: DataFrame, owner: str, c_u: int, noise: Noise, keys: Sequence[str], strategy: str, tag: str) -> DataFrame:
    by_key = Window.partitionBy(owner).orderBy(*keys)
    if strategy == "first":
        return partials.withColumn("__rank", F.row_number().over(by_key)).filter(F.col("__rank") <= c_u).drop("__rank")
    if strategy == "systematic":
        every = F.greatest(F.lit(1), F.floor(F.count(F.lit(1)).over(Window.partitionBy(owner)) / c_u))
        return partials.withColumn("__keep", (F.row_number().over(by_key) - 1) % every == 0).filter("__keep").drop("__keep")
    uniform = noise.uniform(tag, [F.col(owner), *map(F.col, keys)])
    size = F.count(F.lit(1)).over(Window.partitionBy(owner))
    if strategy == "bernoulli":
        return partials.withColumn("__keep", uniform * size < c_u).filter("__keep").drop("__keep")
    numbered = partials.withColumn("__rank", F.row_number().over(by_key)).withColumn("__size", size)
    draws = numbered.withColumn("__draw", F.explode(F.sequence(F.lit(1), F.lit(c_u)))).filter(
        F.floor(noise.uniform(F.concat(F.lit(tag), F.col("__draw").cast("string")), [F.col(owner)]) * F.col("__size")) + 1 == F.col("__rank")
    )
    return draws.drop("__rank", "__size", "__draw")


def limit_rows(df: DataFrame, owner: str, keys: Sequence[str], most: int, noise: Noise, identity: Sequence[str]) -> DataFrame:
    """At most ``most`` rows of an owner in each partition, at random; ``identity`` names what tells its rows apart."""
    order = noise.order("rows", [F.col(c) for c in (owner, *keys, *identity)])
    rank = F.row_number().over(Window.partitionBy(owner, *keys).orderBy(order, *identity))
    return df.withColumn("__rank", rank).filter(F.col("__rank") <= most).drop("__rank")
