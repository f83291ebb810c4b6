"""Bloom filters over 64-bit hashes: streamed inside tasks, and one of checked size for broadcasting."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ownerdp.llm.common import map_batches

PROBES = 3
#: Bits of a filter that one task streams its hashes through (4 MB). A fuller task only reports more false hits.
TASK_BITS = 25
#: The largest filter that is ever broadcast: 2^26 bits, 8 MB. Beyond it callers join on the hash instead.
BROADCAST_BITS = 26
BITS_A_HASH = 12


def positions(hashes: np.ndarray, log2_bits: int) -> np.ndarray:
    """PROBES bit positions for each signed 64-bit hash, taken by double hashing."""
    h = hashes.astype(np.uint64)
    first = (h * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - log2_bits)
    step = ((h ^ (h >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)) >> np.uint64(64 - log2_bits) | np.uint64(1)
    mask = np.uint64((1 << log2_bits) - 1)
    return np.stack([(first + np.uint64(k) * step) & mask for k in range(PROBES)])


class StreamingBloom:
    """Tells which hashes of each batch may have been seen in an earlier one, and adds the batch."""

    def __init__(self, log2_bits: int = TASK_BITS):
        self.log2_bits, self.bits = log2_bits, np.zeros(1 << (log2_bits - 3), np.uint8)

    def seen_then_add(self, hashes: np.ndarray) -> np.ndarray:
        at = positions(hashes, self.log2_bits)
        byte, bit = (at >> np.uint64(3)).astype(np.int64), (np.uint8(1) << (at & np.uint64(7)).astype(np.uint8))
        seen = ((self.bits[byte] & bit) != 0).all(axis=0)
        np.bitwise_or.at(self.bits, byte.ravel(), bit.ravel())
        return seen


def _stream_hashes(repeated_before: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bloom = StreamingBloom()
        for batch in batches:
            h = batch.column(0).to_numpy(zero_copy_only=False)
            if not len(h):
                continue
            values, first, counts = np.unique(h, return_index=True, return_counts=True)
            twice = counts > 1
            if repeated_before:  # the second pass: a hash that one task saw twice stays marked
                marked = batch.column(1).to_numpy(zero_copy_only=False).astype(bool)
                twice = twice | np.isin(values, h[marked])
            twice = twice | bloom.seen_then_add(values)
            if repeated_before:
                yield pa.RecordBatch.from_arrays([pa.array(values[twice])], names=["h"])
            else:
                yield pa.RecordBatch.from_arrays([pa.array(values), pa.array(twice)], names=["h", "twice"])

    return run


def possibly_repeated(hashes: DataFrame) -> DataFrame:
    """From one long column: every hash that occurs at least twice, and a few that do not.

    Each task first streams its own hashes through a filter, so a hash that a third of all rows share leaves a task once
    a batch. The hashes alone, 8 bytes each, are then dealt by value, and the receiving tasks stream them again.
    """
    h = hashes.select(F.col(hashes.columns[0]).cast("long").alias("h"))
    local = map_batches(h, _stream_hashes(False), "h long, twice boolean")
    return map_batches(local.repartition("h"), _stream_hashes(True), "h long")


def broadcast_bits(hashes: DataFrame, rows: int) -> tuple[np.ndarray, int] | None:
    """A filter of all ``rows`` hashes as 64-bit words, built by executors; None if it would exceed BROADCAST_BITS."""
    log2_bits = max(10, int(np.ceil(np.log2(max(rows, 1) * BITS_A_HASH))))
    if log2_bits > BROADCAST_BITS:
        return None

    def words(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            h = batch.column(0).to_numpy(zero_copy_only=False)
            at = np.unique(positions(h, log2_bits).ravel())
            word = (at >> np.uint64(6)).astype(np.int64)
            bit = (np.uint64(1) << (at & np.uint64(63))).astype(np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(word), pa.array(bit)], names=["word", "bits"])

    cells = map_batches(hashes.select("h"), words, "word long, bits long").groupBy("word").agg(F.bit_or("bits").alias("bits"))
    found = cells.toArrow()  # at most 2^BROADCAST_BITS / 64 rows
    out = np.zeros(max(1, (1 << log2_bits) >> 6), np.uint64)
    if found.num_rows:
        out[found["word"].to_numpy()] = found["bits"].to_numpy().astype(np.uint64)
    return out, log2_bits


def contains(words: np.ndarray, log2_bits: int, hashes: np.ndarray) -> np.ndarray:
    at = positions(hashes, log2_bits)
    return ((words[(at >> np.uint64(6)).astype(np.int64)] >> (at & np.uint64(63))) & np.uint64(1)).astype(bool).all(axis=0)
