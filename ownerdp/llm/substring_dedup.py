"""Substring deduplication: repeated passages are found by window hashes, gathered as reference shards, and removed by suffix automata."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ownerdp.llm.automaton import SuffixAutomaton
from ownerdp.llm.common import BoundedCache, map_batches, materialise, per_worker, texts_of

WINDOW = 35
#: Words of the documents that one map task hashes together; a chunk names the reference shard of the passages that it holds first.
CHUNK_WORDS = 1 << 19
#: Windows of a range of hashes, about the most that a task holds at once, 40 bytes each.
SHARD_WINDOWS = 1 << 21
#: Words of documents that are streamed through one copy of a shard's automaton; with more, further tasks build it again.
STREAM_WORDS = 1 << 22
#: Spans of documents up to this many bytes are broadcast to the documents; beyond it both are shuffled by document.
BROADCAST_BYTES = 32 << 20
#: The most reference text that ``remove_reference_spans`` broadcasts as automata.
REFERENCE_WORDS = 2_000_000
#: Documents whose words a task holds at once.
SLICE = 512
_BASE = 0x9E3779B97F4A7C15


def words_of(text: str) -> list[bytes]:
    return text.encode().split()


def _codes(words: list[bytes]) -> np.ndarray:
    cache: BoundedCache = per_worker("word-codes", "", lambda: BoundedCache(150_000))
    young, old = cache.young, cache.old
    try:
        return np.array(list(map(young.__getitem__, words)), np.uint64)
    except KeyError:
        missing = set(words).difference(young)
        for w in missing:
            young[w] = old.get(w) or xxhash.xxh64_intdigest(w)
        out = np.array(list(map(young.__getitem__, words)), np.uint64)
        cache.make_room(missing)
        return out


def window_hashes(codes: np.ndarray, window: int) -> np.ndarray:
    """A 64-bit hash of every run of ``window`` codes, joined from runs of powers of two."""
    n = len(codes) - window + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    out, done, run, size = np.zeros(n, np.uint64), 0, codes, 1
    with np.errstate(over="ignore"):
        while True:
            if window & size:
                out += run[done : done + n] * np.uint64(pow(_BASE, done, 1 << 64))
                done += size
            if done == window:
                break
            run = run[:-size] + run[size:] * np.uint64(pow(_BASE, size, 1 << 64))
            size *= 2
        out ^= out >> np.uint64(32)
        out *= np.uint64(0xD6E8FEB86659FD93)
        out ^= out >> np.uint64(32)
    return out


_HASHED = "shard long, chunk long, kind int, a binary, b binary, c binary"
_NAMES = ["shard", "chunk", "kind", "a", "b", "c"]


def _row(shard: int, chunk: int, kind: int, a: np.ndarray, b: np.ndarray, c: np.ndarray | None = None) -> pa.RecordBatch:
    values = [pa.array([x.tobytes() if x is not None else b""], pa.binary()) for x in (a, b, c)]
    return pa.RecordBatch.from_arrays([pa.array([shard]), pa.array([chunk]), pa.array([kind], pa.int32()), *values], names=_NAMES)


def _planes(places: np.ndarray) -> np.ndarray:
    """Ascending places as byte planes of their differences; the high planes are zeros, which Spark compresses away."""
    return np.diff(places, prepend=0).astype("<u4").view(np.uint8).reshape(-1, 4).T.copy()


def _from_planes(raw: bytes) -> np.ndarray:
    return np.cumsum(np.frombuffer(raw, np.uint8).reshape(4, -1).T.copy().view("<u4").ravel()).astype(np.int32)


def _slices(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for i in range(0, batch.num_rows, SLICE):
            yield batch.slice(i, SLICE)


def _hash_chunks(window: int, shards: int):
    """For each chunk and shard the hashes of its windows, each once, where they start, and whether they do so again (kind 0);
    for each chunk its documents (kind 1)."""

    def chunk_rows(chunk: int, keys: list[tuple[int, int]], each: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
        size = np.array([len(c) for c in each], np.int64)
        begin = np.cumsum(size) - size
        hashes = [window_hashes(c, window) for c in each]
        at = np.concatenate([np.arange(b, b + len(h), dtype=np.int64) for b, h in zip(begin.tolist(), hashes, strict=True)])
        h = np.concatenate(hashes)
        del hashes
        order = np.argsort(h, kind="stable")
        h, at = h[order], at[order]
        first = np.r_[True, h[1:] != h[:-1]]
        starts = np.flatnonzero(first)
        again = np.diff(np.r_[starts, len(h)]) > 1
        later = np.flatnonzero(~first)
        twins = np.stack([at[later], at[starts[np.cumsum(first)[later] - 1]]]).astype(np.int32)
        yield _row(chunk % shards, chunk, 1, np.array(keys, np.int64).reshape(-1, 2), np.stack([begin, size]), twins)
        h, place = h[starts], at[starts]
        of = (h >> np.uint64(32)) * np.uint64(shards) >> np.uint64(32)  # ascending, as the hashes are
        cuts = np.flatnonzero(np.r_[True, of[1:] != of[:-1]])
        for s, a, b in zip(of[cuts].tolist(), cuts.tolist(), [*cuts[1:].tolist(), len(h)], strict=True):
            by_place = np.argsort(place[a:b]) + a
            yield _row(s, chunk, 0, h[by_place], _planes(place[by_place]), np.packbits(again[by_place]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        part, number, held = TaskContext.get().partitionId(), 0, 0
        keys, each = [], []
        for batch in _slices(batches):
            for key, t in zip(zip(batch.column(1).to_pylist(), batch.column(2).to_pylist(), strict=True), texts_of(batch), strict=True):
                its = words_of(t)
                if len(its) < window:
                    continue
                keys.append(key)
                each.append(_codes(its))
                held += len(its)
                if held >= CHUNK_WORDS:
                    yield from chunk_rows((part << 32) + number, keys, each)
                    number, held, keys, each = number + 1, 0, [], []
        if keys:
            yield from chunk_rows((part << 32) + number, keys, each)

    return run


def _meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows sorted by shard, of which one is held at a time: finds the hashes that two chunks have, or one has twice.
    Each chunk hears where it has them (a) and which chunk has them first (b)."""
    now, held = None, []
    for batch in batches:
        for i, (shard, kind) in enumerate(zip(batch.column(0).to_pylist(), batch.column(2).to_pylist(), strict=True)):
            if kind == 1:
                yield batch.slice(i, 1)
                continue
            if shard != now:
                yield from _meet_in_shard(held)
                now, held = shard, []
            h = np.frombuffer(batch.column(3)[i].as_py(), np.uint64)
            again = np.unpackbits(np.frombuffer(batch.column(5)[i].as_py(), np.uint8), count=len(h)).astype(bool)
            held.append((batch.column(1)[i].as_py(), h, _from_planes(batch.column(4)[i].as_py()), again))
    yield from _meet_in_shard(held)


def _meet_in_shard(held: list[tuple[int, np.ndarray, np.ndarray, np.ndarray]]) -> Iterator[pa.RecordBatch]:
    """held: of each chunk its id, its hashes of one shard, where they start, whether they do so again."""
    if not held:
        return
    held.sort(key=lambda x: x[0])
    chunk_ids = np.array([x[0] for x in held], np.int64)
    source = np.repeat(np.arange(len(held), dtype=np.int32), [len(x[1]) for x in held])
    h, place, twice = (np.concatenate([x[j] for x in held]) for j in (1, 2, 3))
    held.clear()
    by_hash = np.argsort(h, kind="stable")  # stable: of equal hashes the first chunk comes first
    h = h[by_hash]
    first = np.r_[True, h[1:] != h[:-1]]
    del h
    starts = np.flatnonzero(first)
    size = np.diff(np.r_[starts, len(by_hash)])
    repeated = (size > 1) | twice[by_hash[starts]]
    keep = np.repeat(repeated, size)
    mine, owner = by_hash[keep], np.repeat(source[by_hash[starts[repeated]]], size[repeated])
    of = source[mine]
    order = np.lexsort((mine, of))
    mine, owner, of = mine[order], owner[order], of[order]
    cuts = np.searchsorted(of, np.arange(len(chunk_ids) + 1))
    for i, chunk in enumerate(chunk_ids.tolist()):
        a, b = cuts[i], cuts[i + 1]
        if a < b:
            yield _row(0, chunk, 0, _planes(place[mine[a:b]]), chunk_ids[owner[a:b]])


def _runs(window: int):
    """From what a chunk hears, the runs of repeated windows of its documents: words start to end, whose passages chunk ``shard`` has first."""

    def finish(chunk: int, heard: list[tuple[bytes, bytes]], about: tuple[bytes, bytes, bytes]) -> pa.RecordBatch | None:
        keys = np.frombuffer(about[0], np.int64).reshape(-1, 2)
        begin, size = np.frombuffer(about[1], np.int64).reshape(2, -1)
        twins = np.frombuffer(about[2], np.int32).reshape(2, -1)
        owner = np.full(int(begin[-1] + size[-1]) + 1, -1, np.int64)
        for a, b in heard:
            owner[_from_planes(a)] = np.frombuffer(b, np.int64)
        owner[twins[0]] = owner[twins[1]]
        doc = np.repeat(np.arange(len(size)), size)
        at = np.flatnonzero(owner[:-1] >= 0)
        if not len(at):
            return None
        new = np.r_[True, (np.diff(at) > 1) | (owner[at[1:]] != owner[at[:-1]]) | (doc[at[1:]] != doc[at[:-1]])]
        head = np.flatnonzero(new)
        tail = np.r_[head[1:], len(at)] - 1
        of = doc[at[head]]
        columns = [keys[of, 0], keys[of, 1], owner[at[head]], at[head] - begin[of], at[tail] - begin[of] + window, np.full(len(head), chunk)]
        return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], names=["key", "text_hash", "shard", "start", "end", "chunk"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        heard, about, now = [], None, None
        for batch in batches:  # sorted by chunk
            for i in range(batch.num_rows):
                chunk, kind = batch.column(1)[i].as_py(), batch.column(2)[i].as_py()
                if chunk != now:
                    if about is not None and (out := finish(now, heard, about)) is not None:
                        yield out
                    heard, about, now = [], None, chunk
                row = [batch.column(c)[i].as_py() for c in (3, 4, 5)]
                if kind == 1:
                    about = tuple(row)
                else:
                    heard.append((row[0], row[1]))
        if about is not None and (out := finish(now, heard, about)) is not None:
            yield out

    return run


def repeated_runs(keyed: DataFrame, window: int, shards: int) -> DataFrame:
    """(key, text_hash, shard, start, end, chunk) for all windows of the documents that occur elsewhere too.

    ``shards`` ranges of hashes; a task takes several, one after the other.
    """
    tasks = _tasks(keyed)
    hashed = map_batches(keyed, _hash_chunks(window, shards), _HASHED)
    met = map_batches(hashed.repartition(tasks, "shard").sortWithinPartitions("shard"), _meet, _HASHED)
    by_chunk = met.repartition(tasks, "chunk").sortWithinPartitions("chunk")
    return map_batches(by_chunk, _runs(window), "key long, text_hash long, shard long, start long, end long, chunk long")


def _tasks(df: DataFrame) -> int:
    return 2 * max(1, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")))


def _shards(keyed: DataFrame) -> int:
    """As many ranges of hashes as leave SHARD_WINDOWS windows to each, however short the words are: one starts at every second character at most."""
    characters = keyed.agg(F.coalesce(F.sum(F.length("text")), F.lit(0))).first()[0]
    return max(_tasks(keyed), -(-characters // (2 * SHARD_WINDOWS)))


def _cut_passages(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Each run's words, joined by blanks, for its shard."""
    for batch in _slices(batches):
        rows = {n: [] for n in ("key", "text_hash", "shard", "start", "own", "words")}
        for key, h, runs, t in zip(*(batch.column(i).to_pylist() for i in (1, 2, 3)), texts_of(batch), strict=True):
            words = words_of(t)
            for r in runs:
                for name, value in zip(rows, (key, h, r["shard"], r["start"], r["shard"] == r["chunk"], b" ".join(words[r["start"] : r["end"]])), strict=True):
                    rows[name].append(value)
        kinds = (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.bool_(), pa.binary())
        yield pa.RecordBatch.from_arrays([pa.array(v, k) for v, k in zip(rows.values(), kinds, strict=True)], names=list(rows))


def _stream_through(window: int):
    """Rows sorted by shard copy, its reference passages first: builds the automaton, then streams the passages through it."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, automaton = None, None
        for batch in batches:
            out = {n: [] for n in ("key", "text_hash", "start", "end")}
            for copy, reference, key, h, start, joined in zip(*(batch.column(i).to_pylist() for i in range(6)), strict=True):
                if copy != now:
                    now, automaton = copy, SuffixAutomaton()
                words = joined.split(b" ")
                if reference:
                    automaton.add(words)
                else:
                    for a, b in automaton.covered(words, window):
                        for name, value in zip(out, (key, h, start + a, start + b), strict=True):
                            out[name].append(value)
            yield pa.RecordBatch.from_arrays([pa.array(v, pa.int64()) for v in out.values()], names=list(out))

    return run


def confirmed_spans(keyed: DataFrame, runs: DataFrame, window: int) -> DataFrame:
    """(key, text_hash, spans): what the automata of the reference shards cover of each document."""
    of_doc = runs.groupBy("key", "text_hash").agg(F.collect_list(F.struct("shard", "chunk", "start", "end")).alias("runs"))
    with_runs = _join_documents(keyed, of_doc, runs.count() * 48, "inner").select("text", "key", "text_hash", "runs")
    passages = map_batches(with_runs, _cut_passages, "key long, text_hash long, shard long, start long, own boolean, words binary")
    load = runs.groupBy("shard").agg(F.sum(F.col("end") - F.col("start")).alias("load")).select("shard", F.ceil(F.col("load") / STREAM_WORDS).cast("int").alias("copies"))
    sized = passages.join(load, "shard")
    copy_of = lambda n: F.concat_ws(":", F.col("shard"), n)
    references = sized.filter("own").withColumn("n", F.explode(F.sequence(F.lit(0), F.col("copies") - 1)))
    streamed = sized.withColumn("n", F.pmod(F.xxhash64("key", "text_hash", "start"), F.col("copies")).cast("int"))
    columns = lambda df, is_reference: df.select(copy_of(F.col("n")).alias("copy"), F.lit(is_reference).alias("reference"), "key", "text_hash", "start", "words")
    dealt = columns(references, True).unionByName(columns(streamed, False)).repartition(_tasks(keyed), "copy").sortWithinPartitions("copy", F.desc("reference"))
    spans = map_batches(dealt, _stream_through(window), "key long, text_hash long, start long, end long")
    return spans.groupBy("key", "text_hash").agg(F.collect_list(F.struct("start", "end")).alias("spans"))


def _join_documents(keyed: DataFrame, of_doc: DataFrame, size: int, how: str) -> DataFrame:
    """Joins by document; what belongs to the documents is broadcast only up to BROADCAST_BYTES, else both sides are shuffled."""
    return keyed.join(F.broadcast(of_doc) if size <= BROADCAST_BYTES else of_doc, ["key", "text_hash"], how)


def _cut(spans: list[tuple[int, int]], words: list[bytes]) -> tuple[list[bytes], int]:
    """The words outside the spans, and how many lie inside; spans may overlap."""
    kept, at, removed = [], 0, 0
    for start, end in sorted(spans):
        if end > at:
            start = max(start, at)
            kept += words[at:start]
            removed += end - start
            at = end
    return kept + words[at:], removed


def _shorten(id_kind: str, with_text: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in _slices(batches):
            n, gone, digest, texts = [], [], [], []
            for t, spans in zip(texts_of(batch), batch.column(1).to_pylist(), strict=True):
                words = words_of(t)
                kept, removed = _cut([(s["start"], s["end"]) for s in spans or ()], words)
                joined = b" ".join(kept)
                n.append(len(words))
                gone.append(removed)
                digest.append(hashlib.sha256(joined).hexdigest())
                texts.append(joined.decode())
            columns = [batch.column(2), pa.array(n, pa.int64()), pa.array(gone, pa.int64()), pa.array(digest, pa.string())]
            yield pa.RecordBatch.from_arrays([*columns, *([pa.array(texts, pa.string())] if with_text else [])], names=["doc_id", "n_words", "n_removed", "kept_sha256", *["kept"] * with_text])

    return run, f"doc_id {id_kind}, n_words long, n_removed long, kept_sha256 string" + ", kept string" * with_text


def remove_repeated_passages(docs: DataFrame, window: int = WINDOW, text: str = "text", doc_id: str = "doc_id", with_text: bool = False) -> DataFrame:
    """One row for each row of ``docs``: doc_id, n_words, n_removed, kept_sha256, on request the kept words joined by blanks.

    Every word is removed that lies in a run of ``window`` words whose sequence also starts elsewhere, in the same or
    another document; runs are judged on the input. Null, empty and shorter texts keep all their words. Rows that repeat
    both id and text repeat each other's passages.
    """
    rows = docs.select(F.col(doc_id).alias("doc_id"), F.col(text).alias("text"))
    id_kind = rows.schema["doc_id"].dataType.simpleString()
    # a document's key is its id and the hash of its text; rows equal in both get the same spans
    keyed = rows.select("text", F.xxhash64("doc_id").alias("key"), F.xxhash64("text").alias("text_hash"))
    runs = materialise(repeated_runs(keyed, window, _shards(keyed)).distinct(), "substring-runs")
    spans = materialise(confirmed_spans(keyed, runs, window), "substring-spans")
    size = spans.agg(F.sum(F.size("spans") * 16 + 48)).first()[0] or 0
    function, schema = _shorten(id_kind, with_text)
    by_key = rows.withColumns({"key": F.xxhash64("doc_id"), "text_hash": F.xxhash64("text")})
    return map_batches(_join_documents(by_key, spans, size, "left").select("text", "spans", "doc_id"), function, schema)


def remove_reference_spans(docs: DataFrame, references: list[str], window: int = WINDOW, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256, kept of every row after removing what lies in runs of ``window`` words of the references.

    The automata of the references are broadcast, which REFERENCE_WORDS bounds; more text is refused.
    """
    passages = [w for r in references if len(w := words_of(r or "")) >= window]
    if sum(map(len, passages)) > REFERENCE_WORDS:
        raise ValueError(f"the references hold more than {REFERENCE_WORDS} words; use remove_repeated_passages")
    sent = docs.sparkSession.sparkContext.broadcast(passages)
    id_kind = docs.schema[doc_id].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        automaton = SuffixAutomaton()
        for p in sent.value:
            automaton.add(p)
        for batch in batches:
            rows = []
            for d, t in zip(batch.column(1).to_pylist(), texts_of(batch), strict=True):
                words = words_of(t)
                kept, removed = _cut(automaton.covered(words, window), words)
                joined = b" ".join(kept)
                rows.append((d, len(words), removed, hashlib.sha256(joined).hexdigest(), joined.decode()))
            kinds = (batch.column(1).type, pa.int64(), pa.int64(), pa.string(), pa.string())
            columns = [pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds)]
            yield pa.RecordBatch.from_arrays(columns, names=["doc_id", "n_words", "n_removed", "kept_sha256", "kept"])

    schema = f"doc_id {id_kind}, n_words long, n_removed long, kept_sha256 string, kept string"
    return map_batches(docs.select(F.col(text).alias("text"), F.col(doc_id).alias("doc_id")), run, schema)
