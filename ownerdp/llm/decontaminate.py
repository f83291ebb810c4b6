"""Benchmark decontamination in DataFrame functions only: spaced-seed hashes, then overlaps that tolerate substitutions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ownerdp.llm.common import free_names, small_side

WINDOW = 13
SUBSTITUTIONS = 2
#: Token positions that a seed reads; the others are ignored. Any window of 13 tokens with at most two substitutions
#: contains an intact seed of one of the two masks at some offset (tested over all patterns).
MASKS = ((0, 1, 3, 4, 5, 6), (0, 1, 2, 6, 7, 9))
SHORTEST = 1 + MASKS[0][-1]
#: Seeds of the benchmark that are broadcast at most (about 0.5 kB each); with more of them both sides are shuffled by hash.
MOST_BROADCAST = 200_000


def tokens_of(text: Column) -> Column:
    """Lower-case runs of letters and digits; the array may begin or end with an empty string."""
    return F.split(F.lower(F.coalesce(text, F.lit(""))), r"[^\p{L}\p{N}]+")


def _seeds(words: str, at: str) -> Column:
    """The hash of each mask laid at position ``at``."""
    place = lambda p: F.get(F.col(words), F.col(at) + p)
    return F.array(*(F.xxhash64(F.lit(n), *(place(p) for p in mask)) for n, mask in enumerate(MASKS)))


def benchmark_seeds(benchmark: DataFrame, text: str = "text", item_id: str = "item_id") -> DataFrame:
    """seed, item_id, region (the item's tokens around the seed), before (those ahead of it), need and allowed of its window."""
    items = benchmark.select(F.col(item_id).alias("item_id"), F.filter(tokens_of(F.col(text)), lambda t: t != "").alias("item"))
    size = F.size("item")
    at = items.filter(size >= SHORTEST).select("item_id", "item", F.explode(F.sequence(F.lit(0), size - SHORTEST)).alias("j"))
    seeds = at.select("item_id", "item", "j", F.posexplode(_seeds("item", "j")).alias("mask", "seed"))
    span = F.get(F.array(*(F.lit(m[-1] + 1) for m in MASKS)), F.col("mask"))
    before = F.least(F.col("j"), F.lit(WINDOW) - span)
    return (
        seeds.filter(F.col("j") + span <= size)
        .select(
            "seed", "item_id", before.alias("before"),
            F.slice("item", F.col("j") - before + 1, F.least(size - F.col("j"), F.lit(WINDOW)) + before).alias("region"),
            F.least(size, F.lit(WINDOW)).alias("need"), F.when(size >= WINDOW, SUBSTITUTIONS).otherwise(0).alias("allowed"),
        )
        .distinct()
    )


def _verified() -> Column:
    """Whether some window of the item around the seed equals the document's tokens but for the allowed substitutions."""
    same = F.transform("region", lambda x, t: F.coalesce(F.get(F.col("words"), F.col("i") - F.col("before") + t) == x, F.lit(False)).cast("int"))
    enough = lambda m, k: F.aggregate(F.slice(m, k + 1, F.col("need")), F.lit(0), lambda a, x: a + x) >= F.col("need") - F.col("allowed")
    # the array around ``same`` makes it a bound variable, computed once
    return F.exists(F.array(same), lambda m: F.exists(F.sequence(F.lit(0), F.size("region") - F.col("need")), lambda k: enough(m, k)))


def contaminations(docs: DataFrame, benchmark: DataFrame, text: str = "text", doc_id: str = "doc_id", item_text: str = "text", item_id: str = "item_id") -> DataFrame:
    """(doc_id, item_id, n_seeds): documents that hold a passage of an item, with the number of verified seeds.

    A passage is a window of 13 consecutive tokens of an item of which at least 11 stand at their places in the document;
    items of 7 to 12 tokens must stand in it whole and unchanged; shorter ones, null and empty texts match nothing. Case and
    all characters but letters and digits are ignored. Rows that share a doc_id count as one document.
    """
    seeds = benchmark_seeds(benchmark, item_text, item_id)
    few = seeds.limit(MOST_BROADCAST + 1).count() <= MOST_BROADCAST
    rows = docs.select(F.col(doc_id).alias("doc_id"), tokens_of(F.col(text)).alias("words")).filter(F.size("words") >= SHORTEST)
    at = rows.select("doc_id", "words", F.explode(F.sequence(F.lit(0), F.size("words") - SHORTEST)).alias("i"))
    hashed = at.select("doc_id", "words", "i", F.explode(_seeds("words", "i")).alias("seed"))
    if not few:  # only the tokens around a seed travel
        start = F.greatest(F.col("i") - WINDOW, F.lit(0))
        hashed = hashed.select("doc_id", F.slice("words", start + 1, F.lit(3 * WINDOW)).alias("words"), (F.col("i") - start).alias("i"), "seed")
    hits = hashed.join(F.broadcast(seeds) if few else seeds, "seed")
    # a generator, not a filter: a filter would move into the join and take it out of the generated code
    confirmed = hits.select("doc_id", F.explode(F.when(_verified(), F.array("item_id")).otherwise(F.slice(F.array("item_id"), 1, 0))).alias("item_id"))
    return confirmed.groupBy("doc_id", "item_id").agg(F.count(F.lit(1)).alias("n_seeds"))


def contamination_report(docs: DataFrame, benchmark: DataFrame, **names: str) -> DataFrame:
    """One row for each row of ``docs``: doc_id, contaminated, item_ids (ascending, without nulls), n_seeds."""
    doc_id = names.get("doc_id", "doc_id")
    found = contaminations(docs, benchmark, **names).groupBy(F.col("doc_id").alias("found_id")).agg(F.sort_array(F.collect_set("item_id")).alias("item_ids"), F.sum("n_seeds").alias("n_seeds"))
    ids = docs.select(F.col(doc_id).alias("doc_id"))
    kind = found.schema["item_ids"].dataType
    return ids.join(found, F.col("doc_id").eqNullSafe(F.col("found_id")), "left").select(
        "doc_id", F.col("n_seeds").isNotNull().alias("contaminated"), F.coalesce("item_ids", F.array().cast(kind)).alias("item_ids"), F.coalesce("n_seeds", F.lit(0)).alias("n_seeds")
    )


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, doc_id: str = "doc_id", **names: str) -> DataFrame:
    """``docs`` without the documents that hold a passage of an item, all columns kept, of any names.

    Documents are told by their id: rows that share one, null included, go or stay together, and repeated rows stay repeated. Null, empty
    and short texts hold no passage. Without documents or without items nothing goes.
    """
    (bad_id,) = free_names(docs, "bad_id")
    bad = small_side(contaminations(docs, benchmark, doc_id=doc_id, **names).select(F.col("doc_id").alias(bad_id)).distinct(), "contaminated")
    return docs.join(bad, F.col(doc_id).eqNullSafe(F.col(bad_id)), "left_anti")
