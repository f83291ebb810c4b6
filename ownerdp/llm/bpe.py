"""Byte-level BPE: a minimal perfect hash for pre-tokens that are vocabulary entries, a heap over linked bytes for the others."""

from __future__ import annotations

import base64
import hashlib
import heapq
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
import xxhash
from pyspark.sql import DataFrame

from ownerdp.llm.common import BoundedCache, column_values, map_batches, per_worker, texts_of

#: Distinct pre-tokens that a worker keeps with their ids, in each of two generations.
CACHE = 500_000


def read_ranks(path: str) -> list[bytes]:
    """The vocabulary of a rank file by rank; the driver reads it and sends it to the executors."""
    with open(path, "rb") as lines:
        pairs = [line.split() for line in lines if line.strip()]
    out: list[bytes] = [b""] * len(pairs)
    for token, rank in pairs:
        out[int(rank)] = base64.b64decode(token)
    return out


def displaced(h: int, d: int) -> int:
    """A new hash for each displacement, from other bits of the digest than those that chose the bucket."""
    return ((h >> 32 & 0xFFFFFFFF) ^ (d * 0x9E3779B1 & 0xFFFFFFFF)) * (h >> 64 & 0xFFFFFFFF | 1) >> 20


class PerfectHash:
    """A minimal perfect hash of n byte strings by hash and displace: a key's bucket names the displacement that puts it in a slot of its own.

    ``rank(key)`` is the number of the key, or -1 after comparing the bytes in the slot.
    """

    def __init__(self, keys: list[bytes]):
        n = len(keys)
        self.keys, self.n, self.n_buckets = keys, max(n, 1), max(1, n // 2)
        self.shift = np.zeros(self.n_buckets, np.int64)
        self.slot = np.full(self.n, -1, np.int64)
        digests = [xxhash.xxh3_128_intdigest(k) for k in keys]
        buckets: dict[int, list[int]] = {}
        for i, h in enumerate(digests):
            buckets.setdefault((h & 0xFFFFFFFF) % self.n_buckets, []).append(i)
        taken = bytearray(self.n)
        free = 0
        for b, members in sorted(buckets.items(), key=lambda x: (-len(x[1]), x[0])):
            if len(members) == 1:  # what is left over goes to the next free slot, named directly
                while taken[free]:
                    free += 1
                at, self.shift[b] = [free], -free - 1
            else:
                d = 0
                while True:
                    at = [displaced(digests[i], d) % self.n for i in members]
                    if len(set(at)) == len(at) and not any(taken[a] for a in at):
                        break
                    d += 1
                self.shift[b] = d
            for a, i in zip(at, members, strict=True):
                taken[a], self.slot[a] = 1, i
        self._shift, self._slot = self.shift.tolist(), self.slot.tolist()

    def rank(self, key: bytes) -> int:
        h = xxhash.xxh3_128_intdigest(key)
        d = self._shift[(h & 0xFFFFFFFF) % self.n_buckets]
        at = -d - 1 if d < 0 else displaced(h, d) % self.n
        i = self._slot[at]
        return i if i >= 0 and self.keys[i] == key else -1


def merge_bytes(piece: bytes, ranks: dict[bytes, int]) -> list[int]:
    """The ids of a piece: the pair of neighbours with the lowest rank, leftmost first, is joined until no pair is in the vocabulary.

    ``end[i]`` is where the part that starts at i ends, ``before[i]`` where its left neighbour starts; the heap holds
    (rank, start of the left part, end of the right part), and an entry whose parts have changed is skipped.
    """
    n = len(piece)
    end, before = list(range(1, n + 1)), list(range(-1, n - 1))
    heap = [(r, i, i + 2) for i in range(n - 1) if (r := ranks.get(piece[i : i + 2])) is not None]
    heapq.heapify(heap)
    get, push, pop = ranks.get, heapq.heappush, heapq.heappop
    while heap:
        _, i, stop = pop(heap)
        middle = end[i]
        if middle <= i or middle >= stop or end[middle] != stop:
            continue
        end[i], end[middle] = stop, -1
        if stop < n:
            before[stop] = i
            if (r := get(piece[i : end[stop]])) is not None:
                push(heap, (r, i, end[stop]))
        if (left := before[i]) >= 0 and (r := get(piece[left:stop])) is not None:
            push(heap, (r, left, stop))
    out, i = [], 0
    while i < n:
        out.append(ranks[piece[i : end[i]]])
        i = end[i]
    return out


class Codec:
    """Encodes and decodes by the ranks of a vocabulary file, each match of ``pattern`` by itself, without special tokens."""

    def __init__(self, vocabulary: list[bytes], pattern: str):
        self.vocabulary, self.hash = vocabulary, PerfectHash(vocabulary)
        self.ranks = {k: i for i, k in enumerate(vocabulary)}
        self.split = regex.compile(pattern).findall
        self.cache = BoundedCache(CACHE)

    def encode_piece(self, piece: bytes) -> list[int]:
        i = self.hash.rank(piece)
        return [i] if i >= 0 else merge_bytes(piece, self.ranks)

    def packed(self, text: str) -> bytes:
        """The ids of a text as little-endian unsigned 32-bit integers."""
        pieces = self.split(text)
        cache = self.cache
        try:
            return b"".join(map(cache.young.__getitem__, pieces))
        except KeyError:
            pass
        young, old = cache.young, cache.old
        missing = set(pieces).difference(young)
        for piece in missing:
            if (ids := old.get(piece)) is None:
                ids = np.array(self.encode_piece(piece.encode()), "<u4").tobytes()
            young[piece] = ids
        out = b"".join(map(young.__getitem__, pieces))
        cache.make_room(missing)
        return out

    def decode(self, packed: bytes) -> bytes:
        return b"".join(map(self.vocabulary.__getitem__, np.frombuffer(packed, "<u4").tolist()))


def codec(vocabulary: list[bytes], pattern: str) -> Codec:
    key = f"{hashlib.sha256(b' '.join(vocabulary) + pattern.encode()).hexdigest()}"
    return per_worker("bpe", key, lambda: Codec(vocabulary, pattern))


def encode_documents(docs: DataFrame, vocabulary: list[bytes], pattern: str, text: str = "text", doc_id: str = "doc_id", keep_ids: bool = False) -> DataFrame:
    """One row for each row of ``docs``: doc_id, n_tokens, ids_sha256, decoded_sha256, on request ids (array<int>).

    The ids are decoded again, and decoded_sha256 is the hash of what comes out. Null and empty texts have no ids. A
    text of any length is encoded whole. Nothing is shuffled; the vocabulary is sent once, its size that of the file.
    """
    kind = docs.schema[doc_id].dataType.simpleString()
    sent = docs.sparkSession.sparkContext.broadcast((vocabulary, pattern))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        its = codec(*sent.value)
        for batch in batches:
            n, ids, decoded, kept = [], [], [], []
            for text in texts_of(batch):
                packed = its.packed(text)
                n.append(len(packed) >> 2)
                ids.append(hashlib.sha256(packed).hexdigest())
                decoded.append(hashlib.sha256(its.decode(packed)).hexdigest())
                if keep_ids:
                    kept.append(np.frombuffer(packed, "<i4"))
            columns = [batch.column(0), pa.array(n, pa.int64()), pa.array(ids, pa.string()), pa.array(decoded, pa.string())]
            names = ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]
            if keep_ids:
                columns.append(pa.array(kept, pa.list_(pa.int32())))
                names.append("ids")
            yield pa.RecordBatch.from_arrays(columns, names=names)

    return map_batches(docs.selectExpr(f"`{doc_id}` AS doc_id", f"`{text}` AS text"), run, f"doc_id {kind}, n_tokens long, ids_sha256 string, decoded_sha256 string" + ", ids array<int>" * keep_ids)


def decode_documents(encoded: DataFrame, vocabulary: list[bytes], ids: str = "ids", doc_id: str = "doc_id") -> DataFrame:
    """doc_id and text for rows of ids (array<int>); bytes that are no UTF-8 become U+FFFD. Null ids give null."""
    kind = encoded.schema[doc_id].dataType.simpleString()
    sent = encoded.sparkSession.sparkContext.broadcast(vocabulary)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words = sent.value
        for batch in batches:
            texts = [None if x is None else b"".join(words[i] for i in x).decode(errors="replace") for x in column_values(batch, "ids")]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(texts, pa.string())], names=["doc_id", "text"])

    return map_batches(encoded.selectExpr(f"`{doc_id}` AS doc_id", f"`{ids}` AS ids"), run, f"doc_id {kind}, text string")
