"""Exact deduplication: only rows whose text hash may repeat are shuffled, the rest pass straight through."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ownerdp.llm.bloom import broadcast_bits, contains, possibly_repeated
from ownerdp.llm.common import free_names, map_batches, materialise, small_side

#: Groups of more than this share of the suspected rows are joined by broadcast: at most HOT_GROUPS rows.
HOT_GROUPS = 1000


def exact_duplicates(docs: DataFrame, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """One row for each row of ``docs``: doc_id, keep_id, group_size, kept, text_sha256, suspected.

    Texts are equal when their UTF-8 bytes are; null counts as empty. Of equal texts the row with the largest doc_id stays;
    of rows that also share the doc_id, exactly one. A null doc_id ranks below all others. ``suspected`` tells whether the
    row took part in the shuffle. An empty table gives an empty result.
    """
    spark = docs.sparkSession
    body = F.coalesce(F.col(text), F.lit(""))
    rows = materialise(
        docs.select(
            F.col(doc_id).alias("doc_id"), F.xxhash64(body).alias("h"), F.sha2(body, 256).alias("text_sha256"),
            F.monotonically_increasing_id().alias("row"),
        ),
        "exact-rows",
    )
    repeated = materialise(possibly_repeated(rows.select("h")).distinct(), "exact-hashes")
    n = repeated.count()
    bits = broadcast_bits(repeated, n)
    if bits is None:  # more suspected hashes than a broadcast may hold: ask by a join on the hash
        marked = rows.join(repeated.withColumn("suspected", F.lit(True)), "h", "left").withColumn("suspected", F.coalesce("suspected", F.lit(False)))
    else:
        sent = spark.sparkContext.broadcast(bits)

        def mark(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            words, log2_bits = sent.value
            for batch in batches:
                hit = contains(words, log2_bits, batch.column(1).to_numpy(zero_copy_only=False))
                yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(hit)], names=[*batch.schema.names, "suspected"])

        kind = rows.schema["doc_id"].dataType.simpleString()
        marked = map_batches(rows, mark, f"doc_id {kind}, h long, text_sha256 string, row long, suspected boolean")

    alone = marked.filter(~F.col("suspected")).select(
        "doc_id", F.col("doc_id").alias("keep_id"), F.lit(1).cast("long").alias("group_size"), F.lit(True).alias("kept"), "text_sha256", "suspected"
    )
    suspects = marked.filter("suspected").drop("h")
    groups = materialise(
        suspects.groupBy("text_sha256").agg(F.max(F.struct("doc_id", "row")).alias("keep"), F.count(F.lit(1)).alias("group_size")), "exact-groups"
    )
    total = groups.agg(F.sum("group_size")).first()[0] or 0
    hot = F.col("group_size") > max(1000, total // HOT_GROUPS)
    by_broadcast = suspects.join(F.broadcast(groups.filter(hot)), "text_sha256", "left")
    found = by_broadcast.filter(F.col("group_size").isNotNull())
    others = by_broadcast.filter(F.col("group_size").isNull()).drop("keep", "group_size").join(groups.filter(~hot), "text_sha256")
    members = found.unionByName(others).select(
        "doc_id", F.col("keep.doc_id").alias("keep_id"), "group_size", (F.col("row") == F.col("keep.row")).alias("kept"), "text_sha256", "suspected"
    )
    return alone.unionByName(members)


def drop_exact_duplicates(docs: DataFrame, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """``docs`` without the dropped rows, all columns kept. Rows that repeat a doc_id and a text stay once.

    Null texts count as empty, a null doc_id ranks below all others; columns may have any names. An empty table stays empty.
    """
    sha, own, same = free_names(docs, "sha", "id", "same")
    repeated = exact_duplicates(docs, text, doc_id).filter("group_size > 1").groupBy(F.col("doc_id").alias(own), F.col("text_sha256").alias(same))
    pairs = materialise(repeated.agg(F.max("kept").alias("stays"), F.count(F.lit(1)).alias("n")), "exact-pairs")
    gone = small_side(pairs.filter("not stays").select(own, same), "exact-gone")
    keyed = docs.withColumn(sha, F.sha2(F.coalesce(F.col(text), F.lit("")), 256))
    out = keyed.join(gone, F.col(doc_id).eqNullSafe(F.col(own)) & (F.col(sha) == F.col(same)), "left_anti")
    twins = pairs.filter("stays and n > 1").select(own, same)
    if twins.isEmpty():
        return out.drop(sha)
    # rows that repeat both the doc_id and the text of one that stays: a single one of them is left
    twins = small_side(twins, "exact-twins")
    on = F.col(doc_id).eqNullSafe(F.col(own)) & (F.col(sha) == F.col(same))
    return out.join(twins, on, "left_anti").unionByName(out.join(twins, on, "left_semi").dropDuplicates([doc_id, sha])).drop(sha)
