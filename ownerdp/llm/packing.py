"""Packs token ids into rows of one length: best fit, longest pieces first, and writes the matrices with their segments."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from ownerdp.llm.common import map_batches, materialise, per_worker, texts_of

LENGTH = 2048
#: Tokens that a task holds before it packs them: 4M, 16 MB. Rows never mix tokens of two such groups.
GROUP_TOKENS = 1 << 22


class CapacityTree:
    """Open rows by free space: a segment tree of counts over the capacities finds the smallest that still fits a piece."""

    def __init__(self, most: int):
        self.leaves = 1 << most.bit_length()
        self.count = [0] * (2 * self.leaves)
        self.rows: list[list[int]] = [[] for _ in range(most + 1)]

    def add(self, row: int, free: int) -> None:
        self.rows[free].append(row)
        self._shift(free, 1)

    def take(self, need: int) -> tuple[int, int] | None:
        """(row, its free space) of the fullest row with room for ``need``, removed; None if there is none."""
        i, count = need + self.leaves, self.count
        if not count[i]:
            while i > 1 and (i & 1 or not count[i + 1]):  # up to the first right neighbour that holds rows
                i >>= 1
            if i <= 1:
                return None
            i += 1
            while i < self.leaves:
                i = 2 * i if count[2 * i] else 2 * i + 1
        free = i - self.leaves
        self._shift(free, -1)
        return self.rows[free].pop(), free

    def _shift(self, free: int, by: int) -> None:
        i = free + self.leaves
        while i:
            self.count[i] += by
            i >>= 1


def best_fit_decreasing(lengths: list[int], most: int) -> list[list[int]]:
    """The pieces of each row, in the order in which they were placed. Pieces are 1 to ``most`` long; equal ones keep their order."""
    tree, rows = CapacityTree(most), []
    for piece in sorted(range(len(lengths)), key=lambda i: -lengths[i]):
        need = lengths[piece]
        found = tree.take(need)
        if found is None:
            rows.append([piece])
            row, free = len(rows) - 1, most
        else:
            row, free = found
            rows[row].append(piece)
        if free > need:
            tree.add(row, free - need)
    return rows


def split_lengths(length: int, most: int) -> list[tuple[int, int]]:
    """(start, end) of the pieces of one document: whole rows, then the rest. Nothing is lost and nothing repeated."""
    return [(a, min(a + most, length)) for a in range(0, length, most)]


def _fast_encoder(vocabulary: list[bytes], pattern: str):
    def make():
        import tiktoken

        return tiktoken.Encoding("ranks", pat_str=pattern, mergeable_ranks={k: i for i, k in enumerate(vocabulary)}, special_tokens={})

    return per_worker("tiktoken", f"{len(vocabulary)}:{hashlib.sha256(b' '.join(vocabulary)).hexdigest()}:{pattern}", make)


def pack_documents(docs: DataFrame, vocabulary: list[bytes], pattern: str, length: int = LENGTH, end_id: int | None = None, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """Rows of at most ``length`` ids: part, row, doc_ids, starts, cu_seqlens, ids, positions.

    Every document is encoded whole and closed by ``end_id`` (default: the first id after the vocabulary), so null and
    empty texts become that one id. Documents of more than ``length`` ids are cut into whole rows and a rest. doc_ids and
    starts tell for each segment the document and the offset in it; cu_seqlens begins with 0 and ends with the number of
    ids; ids holds them as little-endian integers, padded with ``end_id`` to ``length``; positions restarts at 0 with each
    segment. A task packs groups of GROUP_TOKENS tokens in memory; (part, row) is unique. Nothing is shuffled.
    """
    kind = docs.schema[doc_id].dataType.simpleString()
    stop = len(vocabulary) if end_id is None else end_id
    width = "<u2" if max(len(vocabulary) - 1, stop) < 1 << 16 else "<u4"
    sent = docs.sparkSession.sparkContext.broadcast((vocabulary, pattern))

    def packed(group: list[tuple], id_type, part: int, first_row: int) -> pa.RecordBatch:
        pieces = [(d, a, ids[a:b]) for d, ids in group for a, b in split_lengths(len(ids), length)]
        rows = best_fit_decreasing([len(p[2]) for p in pieces], length)
        cu, ids, positions, of, starts = [], [], [], [], []
        for row in rows:
            parts = [pieces[i] for i in row]
            ends = np.cumsum([0, *(len(p[2]) for p in parts)])
            matrix_row = np.full(length, stop, width)
            matrix_row[: ends[-1]] = np.concatenate([p[2] for p in parts])
            cu.append(ends.astype(np.int32))
            ids.append(matrix_row.tobytes())
            positions.append((np.arange(ends[-1]) - np.repeat(ends[:-1], np.diff(ends))).astype("<u2" if length <= 1 << 16 else "<u4").tobytes())
            of.append([p[0] for p in parts])
            starts.append([p[1] for p in parts])
        n = len(rows)
        columns = [
            pa.array(np.full(n, part, np.int32)), pa.array(np.arange(first_row, first_row + n, dtype=np.int64)), pa.array(of, pa.list_(id_type)), pa.array(starts, pa.list_(pa.int64())),
            pa.array(cu, pa.list_(pa.int32())), pa.array(ids, pa.binary()), pa.array(positions, pa.binary()),
        ]
        return pa.RecordBatch.from_arrays(columns, names=["part", "row", "doc_ids", "starts", "cu_seqlens", "ids", "positions"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        encode = _fast_encoder(*sent.value).encode_ordinary
        context = TaskContext.get()
        part = context.partitionId() if context else 0
        group, held, row, id_type = [], 0, 0, pa.int64()
        for batch in batches:
            id_type = batch.column(0).type
            for d, t in zip(batch.column(0).to_pylist(), texts_of(batch), strict=True):
                ids = np.array([*encode(t), stop], width)
                group.append((d, ids))
                held += len(ids)
                if held >= GROUP_TOKENS:
                    yield (out := packed(group, id_type, part, row))
                    row, group, held = row + out.num_rows, [], 0
        if group:
            yield packed(group, id_type, part, row)

    schema = f"part int, row long, doc_ids array<{kind}>, starts array<long>, cu_seqlens array<int>, ids binary, positions binary"
    return map_batches(docs.selectExpr(f"`{doc_id}` AS doc_id", f"`{text}` AS text"), run, schema)


def write_packed(packed: DataFrame, path: str) -> None:
    """Writes the matrices as Parquet: one fixed-width binary per row, with its segments, by Spark's commit protocol."""
    packed.write.option("compression", "zstd").parquet(path)


def stored(packed: DataFrame) -> DataFrame:
    """The same rows, written in the shared folder and read again."""
    return materialise(packed, "packed-rows")
