"""Small databases that fill a cube evenly, and the graph of their parts."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def primes(n: int) -> list[int]:
    found: list[int] = []
    k = 2
    while len(found) < n:
        if all(k % p for p in found):
            found.append(k)
        k += 1
    return found


def radical_inverse(index: Column, base: int, digits: int = 40) -> Column:
    """The digits of the index in the base, mirrored behind the point."""
    most = 1
    while base**most < 1 << 40 and most < digits:
        most += 1
    terms = [F.pmod(F.floor(index / F.lit(base**d)), F.lit(base)) / F.lit(float(base) ** (d + 1)) for d in range(most)]
    total = terms[0]
    for t in terms[1:]:
        total = total + t
    return total


def halton_databases(spark: SparkSession, n: int, size: int, r: float) -> DataFrame:
    """(db_id, rows): n databases of ``size`` numbers in [-r, r], the points of a Halton sequence from index 1 on."""
    ids = spark.range(1, n + 1).withColumnRenamed("id", "db_id")
    return ids.select("db_id", F.array(*((radical_inverse(F.col("db_id"), p) * 2 - 1) * r for p in primes(size))).alias("rows"))


def sub_databases(dbs: DataFrame) -> DataFrame:
    """(db_id, mask, rows): every part of each database; bit i of the mask keeps row i."""
    masks = dbs.select("db_id", "rows", F.explode(F.sequence(F.lit(0), F.pow(F.lit(2), F.size("rows")).cast("int") - 1)).alias("mask"))
    return masks.select("db_id", "mask", part_of(F.col("rows"), F.col("mask")).alias("rows"))


def adjacent_pairs(dbs: DataFrame) -> DataFrame:
    """(db_id, mask, removed): the edges of the graph; ``removed`` is the row that the smaller part lacks."""
    masks = dbs.select("db_id", F.size("rows").alias("size"), F.explode(F.sequence(F.lit(0), F.pow(F.lit(2), F.size("rows")).cast("int") - 1)).alias("mask"))
    bits = masks.select("db_id", "mask", F.explode(F.sequence(F.lit(0), F.col("size") - 1)).alias("removed"))
    return bits.filter(F.col("mask").bitwiseAND(F.pow(F.lit(2), F.col("removed")).cast("int")) != 0)


def part_of(rows: Column, mask: Column) -> Column:
    """The rows of a database that a mask keeps."""
    placed = F.transform(rows, lambda x, i: F.struct(x.alias("x"), i.alias("i")))
    return F.transform(F.filter(placed, lambda s: mask.bitwiseAND(F.pow(F.lit(2), s["i"]).cast("int")) != 0), lambda s: s["x"])
