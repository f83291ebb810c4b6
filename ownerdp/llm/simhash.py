"""SimHash fingerprints, and their links within a Hamming distance by chains of segments on a ring."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ownerdp.llm.common import column_values, free_names, map_batches, materialise, small_side, texts_of
from ownerdp.llm.components import connected_components

SEED = 42
BITS = 64
#: Segments of the ring. With distance 2 a viable chain begins with four equal segments, 28 bits.
SEGMENTS = 9
_CHUNK = 1 << 16


def words_of(text: str) -> list[bytes]:
    return text.encode().lower().split()


def shingle_hashes(words: list[bytes], size: int) -> np.ndarray:
    """XXH64 of every run of ``size`` words joined by spaces, repeats included; the whole sequence if it is shorter; none for none."""
    if not words:
        return np.zeros(0, np.uint64)
    joined, size = b" ".join(words), min(size, len(words))
    length = np.fromiter(map(len, words), np.int64, len(words))
    end = np.cumsum(length + 1) - 1
    start = (end - length)[: len(words) - size + 1].tolist()
    h = xxhash.xxh64_intdigest
    return np.array([h(joined[a:b], SEED) for a, b in zip(start, end[size - 1 :].tolist(), strict=True)], np.uint64)


def fingerprint(hashes: np.ndarray) -> int:
    """A bit is 1 if it is set in over half of the hashes; zero for none."""
    ones = np.zeros(BITS, np.int64)
    for i in range(0, len(hashes), _CHUNK):
        part = hashes[i : i + _CHUNK].astype("<u8").view(np.uint8).reshape(-1, 8)
        ones += np.add.reduce(np.unpackbits(part, axis=1, bitorder="little"), axis=0, dtype=np.int64)
    return int(np.packbits(2 * ones > len(hashes), bitorder="little").view("<i8")[0])


def fingerprints(docs: DataFrame, shingle: int = 3, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """doc_id and fp (the 64 bits as a signed long) for each row; null and empty texts have fingerprint zero."""
    kind = docs.schema[doc_id].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            fps = [fingerprint(shingle_hashes(words_of(t), shingle)) for t in texts_of(batch)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(fps, pa.int64())], names=["doc_id", "fp"])

    return map_batches(docs.selectExpr(f"`{doc_id}` AS doc_id", f"`{text}` AS text"), run, f"doc_id {kind}, fp long")


def _segment_masks(segments: int) -> list[int]:
    edge = [BITS * i // segments for i in range(segments + 1)]
    return [(1 << edge[i + 1]) - (1 << edge[i]) for i in range(segments)]


def _signed(mask: int) -> int:
    return mask - (1 << BITS) if mask >> (BITS - 1) else mask


def chain_masks(segments: int, distance: int) -> tuple[int, list[tuple[list[int], int]]]:
    """The chain length that must be equal, and for each longer chain its masks by start and its budget.

    If two values differ in at most ``distance`` bits, some segment on the ring starts chains whose lengths 1, 2, ... all
    have at most length * distance / segments differences. Budgets below one mean equality.
    """
    parts = _segment_masks(segments)
    chain = lambda i, n: sum(parts[(i + j) % segments] for j in range(n))
    equal = max(n for n in range(segments + 1) if n * distance < segments)
    return equal, [([_signed(chain(i, n)) for i in range(segments)], n * distance // segments) for n in range(equal, segments + 1)]


def fingerprint_links(fps: DataFrame, distance: int = 2, segments: int = SEGMENTS) -> DataFrame:
    """All pairs a < b of the distinct values in ``fp`` that differ in 1 to ``distance`` bits: columns a, b, bits.

    Candidates share the equal start of a viable chain, which is the join key; the longer chains are tested next, one
    after the other, and the full distance last. A value has few neighbours within so few bits, whatever the number of
    rows that carry it, since only distinct values are joined. ``segments`` must exceed ``distance``.
    """
    if not 0 < distance < segments <= BITS:
        raise ValueError("segments must be more than distance and at most 64")
    _, chains = chain_masks(segments, distance)
    starts = F.explode(F.transform(F.array(*map(F.lit, chains[0][0])), lambda m, i: F.struct(i.alias("start"), m.alias("mask"))))
    keyed = fps.select("fp", starts.alias("s")).select("fp", F.col("s.start").alias("start"), F.col("fp").bitwiseAND(F.col("s.mask")).alias("key"))
    left, right = keyed.withColumnRenamed("fp", "a"), keyed.withColumnRenamed("fp", "b")
    pairs = left.join(right, ["start", "key"]).filter("a < b")
    differing = F.col("a").bitwiseXOR(F.col("b"))
    viable: Column = F.lit(True)
    for masks, budget in chains[1:-1]:
        viable = viable & (F.bit_count(differing.bitwiseAND(F.get(F.array(*map(F.lit, masks)), F.col("start")))) <= budget)
    return pairs.filter(viable).filter(F.bit_count(differing) <= distance).select("a", "b", F.bit_count(differing).alias("bits")).distinct()


def near_duplicates(docs: DataFrame, shingle: int = 3, distance: int = 2, segments: int = SEGMENTS, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """One row for each row of ``docs``: doc_id, fp, component_id (the smallest doc_id reachable over links, itself included).

    Null and empty texts have fingerprint zero and link like any other. Rows with one fingerprint are one node, so copies
    never make pairs. Null doc_ids are ignored in the minimum. An empty table gives an empty result.
    """
    rows = materialise(fingerprints(docs, shingle, text, doc_id), "simhash-rows")
    nodes = materialise(rows.groupBy("fp").agg(F.min("doc_id").alias("low")), "simhash-nodes")
    of = components_of(nodes, fingerprint_links(nodes, distance, segments))
    return rows.join(of, "fp").select("doc_id", "fp", "component_id")


def components_of(nodes: DataFrame, links: DataFrame) -> DataFrame:
    """(fp, component_id) for every node (fp, low)."""
    linked = connected_components(links).select(F.col("node").alias("fp"), "component")
    named = materialise(nodes.join(linked, "fp", "left").withColumn("component", F.coalesce("component", "fp")), "simhash-named")
    lowest = materialise(named.groupBy("component").agg(F.min("low").alias("component_id")), "simhash-lowest")
    return named.join(lowest, "component").select("fp", "component_id")


# Near copies by content: five-word shingles, Jaccard similarity of 0.8 or more ------------------------------------------

#: Bands of BAND_ROWS minima each; two texts of similarity 0.8 share none of them once in 3,000 pairs.
BANDS, BAND_ROWS = 15, 4
#: Pairs of similarity 0.8 differ in 10 of 64 bits on average; more than this many, once in 5,000 pairs.
SIMILAR_BITS, SIMILAR_SEGMENTS = 20, 8
#: Buckets of more texts are compared with a few heads first, and then between the components that are left, block by block.
PAIRWISE = 16


def _permutations() -> np.ndarray:
    return np.random.default_rng(42).integers(1, 1 << 63, BANDS * BAND_ROWS, dtype=np.uint64) | np.uint64(1)


def _band_keys(distinct: np.ndarray, permutations: np.ndarray) -> list[int]:
    with np.errstate(over="ignore"):
        low = [int((distinct * p >> np.uint64(1)).min()) for p in permutations]
    return [xxhash.xxh64_intdigest(repr((b, low[b * BAND_ROWS : (b + 1) * BAND_ROWS])).encode()) - (1 << 63) for b in range(BANDS)]


def _sketches(shingle: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        permutations = _permutations()
        for batch in batches:
            fps, sizes, bands = [], [], []
            for t in texts_of(batch):
                h = np.unique(shingle_hashes(words_of(t), shingle))
                fps.append(fingerprint(h))  # of the set that decides, so that repeats cannot part similar sets
                sizes.append(len(h))
                bands.append(_band_keys(h, permutations) if len(h) else [])
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(fps, pa.int64()), pa.array(sizes, pa.int64()), pa.array(bands, pa.list_(pa.int64()))], names=["row", "fp", "size", "bands"])

    return run


def _sets(shingle: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sets = [np.unique(shingle_hashes(words_of(t), shingle)).tobytes() for t in texts_of(batch)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(sets, pa.binary())], names=["row", "shingles"])

    return run


def viable(a: Column, b: Column, distance: int, segments: int) -> Column:
    """Whether some start on the ring has chains of 1, 2, ... segments whose differences all stay within their share of the distance."""
    parts = [_signed(m) for m in _segment_masks(segments)]
    each = F.array(*(F.bit_count(a.bitwiseXOR(b).bitwiseAND(F.lit(m))) for m in parts))

    def starts_here(x: Column, i: int) -> Column:
        ok, total = F.lit(True), F.lit(0)
        for n in range(segments):
            total = total + F.get(x, F.lit((i + n) % segments))
            ok = ok & (total <= (n + 1) * distance // segments)
        return ok

    return F.exists(F.array(each), lambda x: F.array_contains(F.array(*(starts_here(x, i) for i in range(segments))), True))


def _similar(at_least: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = []
            for x, y in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist(), strict=True):
                one, two = np.frombuffer(x, np.uint64), np.frombuffer(y, np.uint64)
                shared = len(np.intersect1d(one, two, assume_unique=True))
                keep.append(shared >= at_least * (len(one) + len(two) - shared))
            yield batch.select(["a", "b"]).filter(pa.array(keep, pa.bool_()))

    return run


#: Texts of a large bucket that all others in it are compared with first: the most central one, and the first in a random order.
HEADS = 2
#: Rows of a large bucket that are compared with as many others at once, about.
BLOCK = 256
#: Rows that are dealt to pairs of blocks at once.
SLICE = 1024
#: Shingles that two blocks share are compared so many at once.
_SHARED = 4096
#: Ids of candidates that are broadcast at most, 8 bytes each, to find their texts.
MOST_CANDIDATES = 2_000_000


def similar_links(texts: DataFrame, shingle: int = 5, similarity: float = 0.8) -> DataFrame:
    """Links (a, b) between rows of (row, text) whose sets of shingles have the given Jaccard similarity; what they connect is whole.

    Rows that share a band are candidates. Buckets of up to PAIRWISE rows give all their pairs. Of a larger bucket all rows are
    first paired with a few heads, first of all the row whose bands have the largest buckets, the centre of a group of mutated
    copies; so a group of thousands is mostly one component after a few pairs for each of its rows. Chains of fingerprint
    segments and the full distance prune these pairs; only for what is left are the sets built and compared. Pairs of a
    larger bucket that no links connect by then are all compared, block by block.
    """
    sketches = materialise(map_batches(texts, _sketches(shingle), "row long, fp long, size long, bands array<bigint>"), "near-sketches")
    bits = sketches.select("row", "fp")
    each = sketches.select("row", "size", F.explode("bands").alias("key")).distinct()
    sizes = materialise(each.groupBy("key").agg(F.count(F.lit(1)).alias("n")).filter("n > 1"), "near-sizes")
    left = materialise(each.join(sizes, "key").select("row", "size", "key", "n"), "near-shared")  # a band that no other row has leads nowhere
    central = materialise(left.groupBy("row").agg(F.sum("n").alias("central")), "near-central")
    large = materialise(left.filter(F.col("n") > PAIRWISE).drop("n"), "near-large")
    random = [F.min_by("row", F.xxhash64("row", F.lit(i))) for i in range(1, HEADS)]
    heads = large.join(central, "row").groupBy("key").agg(F.array_distinct(F.array(F.max_by("row", F.struct("central", "row")), *random)).alias("heads"))
    star = large.join(heads, "key").select("row", F.explode("heads").alias("head")).filter("row <> head")
    few = left.filter(F.col("n") <= PAIRWISE).groupBy("key").agg(F.sort_array(F.collect_set("row")).alias("rows"))
    pairs = few.select(F.explode("rows").alias("a"), "rows").select("a", F.explode("rows").alias("b")).filter("a < b")
    candidates = pairs.unionByName(star.select(F.least("head", "row").alias("a"), F.greatest("head", "row").alias("b"))).distinct()
    near = F.bit_count(F.col("x").bitwiseXOR(F.col("y"))) <= SIMILAR_BITS
    with_bits = candidates.join(bits.select(F.col("row").alias("a"), F.col("fp").alias("x")), "a").join(bits.select(F.col("row").alias("b"), F.col("fp").alias("y")), "b")
    pruned = materialise(with_bits.filter(viable(F.col("x"), F.col("y"), SIMILAR_BITS, SIMILAR_SEGMENTS)).filter(near).select("a", "b"), "near-pruned")
    links = materialise(_verified(texts, pruned, shingle, similarity), "near-links")
    if large.isEmpty():
        return links
    return links.unionByName(_between_components(texts, large, links, shingle, similarity)).distinct()


def _between_components(texts: DataFrame, large: DataFrame, links: DataFrame, shingle: int, similarity: float) -> DataFrame:
    """Links between rows (row, size, key) of one bucket that ``links`` do not connect, enough of them to connect all that are similar.

    A bucket falls into blocks by size class, apart for its most frequent component, which needs no comparison with itself.
    Sizes of similar sets are in one class or in two that follow each other. Every pair of blocks is a group of its own, so
    that a large bucket spreads over many tasks.
    """
    of = connected_components(links).withColumnRenamed("node", "row")
    size_class = F.floor(F.log("size") / F.lit(-math.log(similarity)) + 1e-9).cast("int")
    named = large.join(of, "row", "left").select("row", "key", F.coalesce("component", "row").alias("component"), size_class.alias("kind"))
    named = materialise(named, "near-components")
    per = materialise(named.groupBy("key", "component").agg(F.count(F.lit(1)).alias("n")), "near-parts")
    mixed = materialise(per.groupBy("key").agg(F.max_by("component", F.struct("n", "component")).alias("main"), F.count(F.lit(1)).alias("parts")).filter("parts > 1").select("key", "main"), "near-mixed")
    open_rows = materialise(named.join(mixed, "key").select("row", "key", "component", "kind", (F.col("component") == F.col("main")).alias("inner")), "near-open")
    blocks = open_rows.groupBy("key", "kind", "inner").agg(F.ceil(F.count(F.lit(1)) / BLOCK).cast("int").alias("blocks"))
    plan = materialise(blocks.groupBy("key").agg(F.collect_list(F.struct("kind", "inner", "blocks")).alias("plan")), "near-plan")
    its_own = F.expr("element_at(filter(plan, p -> p.kind = kind AND p.inner = inner).blocks, 1)").alias("own")
    partners = F.expr("filter(plan, p -> abs(p.kind - kind) <= 1 AND NOT (p.inner AND inner))").alias("plan")
    dealt = map_batches(open_rows.join(plan, "key").select("key", "row", "component", "kind", "inner", its_own, partners), _deal, "pair long, side int, row long, component long")
    ids = materialise(open_rows.select("row").distinct(), "near-open-ids")
    wanted = texts.join(F.broadcast(ids) if ids.count() <= MOST_CANDIDATES else ids, "row", "left_semi")
    sets = materialise(map_batches(wanted.select("row", "text").dropDuplicates(["row"]), _sets(shingle), "row long, shingles binary"), "near-open-sets")
    grouped = materialise(dealt, "near-dealt").join(sets, "row").select("pair", "side", "row", "component", "shingles").groupBy("pair")
    return materialise(grouped.applyInArrow(_compare_blocks(similarity), "a long, b long"), "near-completed")


def _deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """A row goes to every pair that its block makes with a block of its bucket whose sizes may fit: side 0, 1, or 2 for a block with itself."""
    kinds = {"pair": pa.int64(), "side": pa.int32(), "row": pa.int64(), "component": pa.int64()}
    for whole in batches:
        for begin in range(0, whole.num_rows, SLICE):
            batch, out = whole.slice(begin, SLICE), []
            columns = (column_values(batch, n) for n in ("key", "row", "component", "kind", "inner", "own", "plan"))
            for key, row, component, kind, inner, number, plan in zip(*columns, strict=True):
                own = (kind, inner, xxhash.xxh64_intdigest(b"%d" % row, SEED) % number)
                for other in ((p["kind"], p["inner"], i) for p in plan for i in range(p["blocks"])):
                    pair = xxhash.xxh64_intdigest(repr((key, min(own, other), max(own, other))).encode()) - (1 << 63)
                    out.append((pair, 2 if own == other else int(own > other), row, component))
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(x, kind) for x, kind in zip(zip(*out, strict=True), kinds.values(), strict=True)], names=list(kinds))


def _shared_counts(one: list[np.ndarray], two: list[np.ndarray]) -> np.ndarray:
    """The number of shingles that each set of the one list shares with each of the other."""
    flat = [np.concatenate(x) for x in (one, two)]
    rows = [np.repeat(np.arange(len(x)), [len(s) for s in x]) for x in (one, two)]
    common = np.intersect1d(*flat)
    total = np.zeros((len(one), len(two)), np.float32)
    if not len(common):
        return total
    at = [np.minimum(np.searchsorted(common, f), len(common) - 1) for f in flat]
    held = [common[p] == f for p, f in zip(at, flat, strict=True)]
    at, rows = [p[h] for p, h in zip(at, held, strict=True)], [r[h] for r, h in zip(rows, held, strict=True)]
    for begin in range(0, len(common), _SHARED):
        width = min(_SHARED, len(common) - begin)
        parts = []
        for x, p, r in zip((one, two), at, rows, strict=True):
            here = (p >= begin) & (p < begin + width)
            dense = np.zeros((len(x), width), np.float32)
            dense[r[here], p[here] - begin] = 1
            parts.append(dense)
        total += parts[0] @ parts[1].T
    return total


def _compare_blocks(at_least: float):
    def run(table: pa.Table) -> pa.Table:
        side, row, component = (table.column(n).to_numpy() for n in ("side", "row", "component"))
        sets = [np.frombuffer(s, np.uint64) for s in table.column("shingles").to_pylist()]
        ones, twos = np.flatnonzero(side != 1), np.flatnonzero(side != 0)
        if not len(ones) or not len(twos):
            return pa.table({"a": pa.array([], pa.int64()), "b": pa.array([], pa.int64())})
        shared = _shared_counts([sets[i] for i in ones], [sets[i] for i in twos])
        size = np.array([len(s) for s in sets], np.float64)
        similar = shared >= at_least * (size[ones][:, None] + size[twos][None, :] - shared)
        x, y = np.nonzero(similar & (component[ones][:, None] != component[twos][None, :]))
        a, b = [], []
        parent: dict[int, int] = {}

        def root(c: int) -> int:
            while (up := parent.get(c, c)) != c:
                parent[c] = parent.get(up, up)
                c = up
            return c

        for i, j in zip(ones[x].tolist(), twos[y].tolist(), strict=True):  # a link for each pair of components that it joins, not for each pair of rows
            c, d = root(int(component[i])), root(int(component[j]))
            if c != d:
                parent[c] = d
                a.append(min(int(row[i]), int(row[j])))
                b.append(max(int(row[i]), int(row[j])))
        return pa.table({"a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64())})

    return run


def _verified(texts: DataFrame, pairs: DataFrame, shingle: int, similarity: float) -> DataFrame:
    """The pairs whose sets are similar enough. Only texts of the pairs are read into sets and shuffled."""
    ids = materialise(pairs.select(F.col("a").alias("row")).unionByName(pairs.select(F.col("b").alias("row"))).distinct(), "near-ids")
    wanted = texts.join(F.broadcast(ids) if ids.count() <= MOST_CANDIDATES else ids, "row", "left_semi")
    sets = materialise(map_batches(wanted.select("row", "text"), _sets(shingle), "row long, shingles binary"), "near-sets")
    one, two = (sets.select(F.col("row").alias(n), F.col("shingles").alias(s)) for n, s in (("a", "one"), ("b", "two")))
    return map_batches(pairs.join(one, "a").join(two, "b").select("a", "b", "one", "two"), _similar(similarity), "a long, b long")


def similar_groups(docs: DataFrame, shingle: int = 5, similarity: float = 0.8, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """(doc_id, row, keep): the rows of ``docs`` that have near copies, and whether the row is the one of its group that stays.

    ``row`` is xxhash64(doc_id, text). Groups are the components of the links; the smallest doc_id stays. Texts of fewer words
    than a shingle are one shingle; null and empty texts have no near copies.
    """
    rows = docs.select(F.xxhash64(F.col(doc_id), F.col(text)).alias("row"), F.col(doc_id).alias("doc_id"), F.col(text).alias("text"))
    of = connected_components(similar_links(rows.select("row", "text"), shingle, similarity))
    named = materialise(rows.select("row", "doc_id").join(of.withColumnRenamed("node", "row"), "row"), "near-named")
    stays = named.groupBy("component").agg(F.min(F.struct("doc_id", "row")).alias("stays"))
    return named.join(stays, "component").select("doc_id", "row", (F.col("row") == F.col("stays.row")).alias("keep"))


def drop_near_duplicates(docs: DataFrame, shingle: int = 5, similarity: float = 0.8, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """``docs`` with one document of each group of near copies, the one of the smallest doc_id, all columns kept, of any names.

    Rows are told by their id and text: those that repeat both are one row here and stay or go together. Null and empty texts have no near copies
    and stay; a null id is smaller than any other. An empty table stays empty.
    """
    own, row = free_names(docs, "own", "row")
    gone = small_side(similar_groups(docs, shingle, similarity, text, doc_id).filter(~F.col("keep")).select(F.col("row").alias(row)).distinct(), "near-gone")
    return docs.withColumn(own, F.xxhash64(F.col(doc_id), F.col(text))).join(gone, F.col(own) == F.col(row), "left_anti").drop(own)
