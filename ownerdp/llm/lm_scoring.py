"""Language-model scores: counts over the whole corpus, a causal attention model trained on all of it, overlapping windows."""

from __future__ import annotations

import re
import uuid
import zlib
from array import array
from collections import defaultdict
from collections.abc import Iterable, Iterator
from itertools import chain, count, islice, repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ownerdp.llm import attention, spelling
from ownerdp.llm.common import keep_freed_memory, map_batches, materialise, per_worker, texts_of
from ownerdp.llm.packing import _fast_encoder

#: Hash buckets of the neighbouring subword or symbol, for what one tends to follow and to precede.
BUCKETS = 8
#: Distinct words, and their bytes, that a worker keeps, encoded and counted, before it hands their counts on and forgets them.
WORDS_KEPT, BYTES_KEPT = 400_000, 32 << 20
#: Words that are encoded in one text.
WORDS_A_TEXT = 10_000
#: Blanks that a word may hold, as it ends at the space and TAB, LF, VT, FF, CR alone.
_OTHER_BLANK = re.compile(r"[^\S ]")
#: Counts of the most frequent words, at most so many, are sent to the executors; those of the others are looked up by a join.
MOST_HEAD_WORDS = 1 << 19
#: Learning rates of the two rounds: the first is over the documents of one hash in WARM_UP, the second over all others.
RATES, WARM_UP = (0.012, 0.004), 8
#: Windows that a task trains on in a round, at least, if there are so many; fewer make a poor average.
WINDOWS_A_TASK = 16_000
#: A task with fewer windows goes through them several times, up to about so many.
LEAST_WINDOWS = 16_000
#: Documents that a task encodes or scores, and trains on, together.
SLICE, TRAIN_SLICE = 256, 1024
_SYMBOL, _ID = 1, 0


def held_out(doc_id) -> bool:
    """Whether crc32 of the id as text leaves 1 modulo 5; a null id does not."""
    return doc_id is not None and zlib.crc32(str(doc_id).encode()) % 5 == 1


class SubwordCodec:
    """The subwords of words by their bytes, each word encoded behind a blank: by the public library, what was encoded is kept up to a bound.

    ``places`` numbers the words that are kept in the order in which they came. Words that come together are encoded in one text, where each
    begins with its blank; those that hold blanks of other kinds, by which the pattern also splits, are encoded alone.
    """

    def __init__(self, vocabulary: list[bytes], pattern: str):
        self.encode = _fast_encoder(vocabulary, pattern).encode_ordinary
        self.starts = np.array([t.startswith(b" ") for t in vocabulary], bool)
        self.forget()

    def forget(self) -> None:
        self.places, self.held = defaultdict(count().__next__), 0
        self.begin, self.ids = array("q", [0]), array("H")

    def _add(self, words: list[bytes]) -> None:
        for i in range(0, len(words), WORDS_A_TEXT):
            some = words[i : i + WORDS_A_TEXT]
            self.held += sum(map(len, some))
            text = " " + b" ".join(some).decode()
            if all(some) and not _OTHER_BLANK.search(text):
                ids = np.array(self.encode(text), np.uint16)
                ends = np.append(np.flatnonzero(self.starts[ids])[1:], len(ids))
            else:
                each = [self.encode(" " + word.decode()) for word in some]
                ids, ends = np.fromiter(chain.from_iterable(each), np.uint16), np.cumsum([len(x) for x in each])
            self.begin.frombytes((ends.astype(np.int64) + len(self.ids)).tobytes())
            self.ids.frombytes(ids.tobytes())

    @property
    def full(self) -> bool:
        return len(self.places) > WORDS_KEPT or self.held > BYTES_KEPT

    def find(self, words: Iterable[bytes], n: int) -> np.ndarray:
        """The places of n words."""
        out = np.fromiter(map(self.places.__getitem__, words), np.int64, n)
        fresh = list(islice(reversed(self.places), len(self.places) - len(self.begin) + 1))
        self._add(fresh[::-1])
        return out

    def subwords(self, places: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The ids of the words laid end to end, and how many each has."""
        edge, ids = np.array(self.begin, np.int64), np.array(self.ids, np.uint16)
        length = np.diff(edge)[places]
        ahead = np.cumsum(length) - length
        return ids[np.repeat(edge[places] - ahead, length) + np.arange(int(length.sum()))], length


def _codec(sent) -> SubwordCodec:
    vocabulary, pattern = sent.value
    return per_worker("subwords", f"{len(vocabulary)}:{hash(vocabulary[-1])}", lambda: SubwordCodec(vocabulary, pattern))


def _slices(batches: Iterator[pa.RecordBatch], size: int = SLICE) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for i in range(0, batch.num_rows, size):
            yield batch.slice(i, size)


def words_of(text: str) -> list[bytes]:
    return text.encode().lower().split()


def _ids(batch: pa.RecordBatch, column: int) -> list[np.ndarray]:
    return [np.frombuffer(x, "<u2") for x in batch.column(column).to_pylist()]


def encode_documents(rows: DataFrame, sent) -> tuple[DataFrame, DataFrame]:
    """(doc_id, text, held_out, ids) of rows (doc_id, text), written once for the passes that follow, and (key, n): each task's counts of the words,
    and of the end (an empty key), in the training documents. Both are columns of one table, of which a reader takes its own."""
    kind = rows.schema["doc_id"].dataType.simpleString()
    names = ["doc_id", "text", "held_out", "ids", "key", "n"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        per_worker("lm-memory", "", keep_freed_memory)
        codec, counts, ends, id_type = _codec(sent), np.zeros(0, np.int64), 0, None

        def counted() -> Iterator[pa.RecordBatch]:
            seen = np.flatnonzero(counts)
            keys, n = list(codec.places), counts[seen].tolist()
            yield from rows_of([keys[i] for i in seen.tolist()], n)

        def rows_of(keys: list[bytes], n: list[int]) -> Iterator[pa.RecordBatch]:
            for i in range(0, len(keys), 100_000):
                k = keys[i : i + 100_000]
                absent = [pa.nulls(len(k), t) for t in (id_type, pa.string(), pa.bool_(), pa.binary())]
                yield pa.RecordBatch.from_arrays([*absent, pa.array(k, pa.binary()), pa.array(n[i : i + 100_000], pa.int64())], names=names)

        for batch in _slices(batches):
            id_type = batch.column(0).type
            if codec.full:
                yield from counted()
                counts = np.zeros(0, np.int64)
                codec.forget()
            held = np.array([held_out(d) for d in batch.column(0).to_pylist()], bool)
            documents = [words_of(t) for t in texts_of(batch)]
            sizes = np.fromiter(map(len, documents), np.int64, len(documents))
            places = codec.find(chain.from_iterable(documents), int(sizes.sum()))
            ids, length = codec.subwords(places)
            more = np.bincount(places[np.repeat(~held, sizes)], minlength=len(codec.places))
            more[: len(counts)] += counts
            counts, ends = more, ends + int((~held).sum())
            edges = np.append(0, np.cumsum(length))[np.append(0, np.cumsum(sizes))].tolist()
            packed = ids.astype("<u2")
            each = [packed[a:b].tobytes() for a, b in zip(edges[:-1], edges[1:], strict=True)]
            n = batch.num_rows
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(held, pa.bool_()), pa.array(each, pa.binary()), pa.nulls(n, pa.binary()), pa.nulls(n, pa.int64())], names=names)
        if id_type is not None:
            yield from counted()
            yield from rows_of([b""], [ends])

    both = materialise(map_batches(rows, run, f"doc_id {kind}, text string, held_out boolean, ids binary, key binary, n long"), "lm-encoded")
    return both.filter(F.col("held_out").isNotNull()).select(*names[:4]), both.filter("n > 0").select("key", "n")


def _bucket(ids: np.ndarray) -> np.ndarray:
    return (ids.astype(np.uint32) * np.uint32(2654435761)) >> np.uint32(29)


def _around(flat: np.ndarray, n: int) -> np.ndarray:
    """Counts of each value by the bucket of the value ahead of it and, in the second half of a row, behind it."""
    out = np.zeros((n, 2 * BUCKETS), np.int64)
    if len(flat) > 1:
        bucket = _bucket(flat)
        out[:, :BUCKETS] = np.bincount(flat[1:] * BUCKETS + bucket[:-1], minlength=n * BUCKETS).reshape(n, BUCKETS)
        out[:, BUCKETS:] = np.bincount(flat[:-1] * BUCKETS + bucket[1:], minlength=n * BUCKETS).reshape(n, BUCKETS)
    return out


def neighbours(encoded: DataFrame, starts: np.ndarray) -> DataFrame:
    """(at, n) over all training documents: for each id and each symbol the buckets of its neighbours, numbered by ``2 * cell + kind``."""
    n_ids = len(starts)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cells = [np.zeros((n_ids, 2 * BUCKETS), np.int64), np.zeros((2 * n_ids, 2 * BUCKETS), np.int64)]
        end = np.array([n_ids - 1], np.int64)
        for batch in _slices(batches, TRAIN_SLICE):
            flat = np.concatenate([end, *(x for ids in _ids(batch, 0) for x in (ids, end))]).astype(np.int64)
            its = attention.symbols(flat, starts)
            cells[_ID] += _around(flat, n_ids)
            cells[_SYMBOL] += _around(its[its >= 0], 2 * n_ids)
        for kind in (_ID, _SYMBOL):
            found = cells[kind].ravel()
            at = np.flatnonzero(found)
            yield pa.RecordBatch.from_arrays([pa.array(2 * at + kind, pa.int64()), pa.array(found[at], pa.int64())], names=["at", "n"])

    learnt = encoded.filter(~F.col("held_out")).select("ids")
    return map_batches(learnt, run, "at long, n long").groupBy("at").agg(F.sum("n").alias("n"))


def describe_tokens(cells: DataFrame, starts: np.ndarray) -> tuple[attention.Vocabulary, np.ndarray, np.ndarray]:
    """The fixed parts of the model, and the counts of ids and of symbols. At most 6 * n_ids * BUCKETS counts reach the driver, whatever the corpus holds."""
    n_ids = len(starts)
    found = cells.toArrow()
    at, n = found["at"].to_numpy(), found["n"].to_numpy()
    tables = [np.zeros((n_ids, 2 * BUCKETS)), np.zeros((2 * n_ids, 2 * BUCKETS))]
    for kind, table in enumerate(tables):
        mine = at % 2 == kind
        table.ravel()[at[mine] // 2] = n[mine]
    of = [t[:, :BUCKETS].sum(axis=1) for t in tables]  # every occurrence but the first end has something ahead of it
    return attention.describe(of[_ID], tables[_ID], starts, of[_SYMBOL], tables[_SYMBOL]), of[_ID], of[_SYMBOL]


def spelling_tables(words: DataFrame, sent, of_id: np.ndarray, of_symbol: np.ndarray, starts: np.ndarray) -> tuple:
    """What ``Spelling`` is made of, counted over all distinct words; at most ``table_size`` counts reach the driver."""
    n_ids = len(starts)
    group = spelling.groups(np.where(starts, 0, of_id))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec, total = _codec(sent), np.zeros(spelling.table_size(n_ids), np.int32)
        for batch in _slices(batches, 50_000):
            if codec.full:
                codec.forget()
            ids, lengths = codec.subwords(codec.find(batch.column(0).to_pylist(), batch.num_rows))
            if len(lengths):
                np.add.at(total, spelling.cells(ids.astype(np.int64), lengths, group), np.int32(1))  # touches no more of the table than there are words
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(at, pa.int64()), pa.array(total[at].astype(np.int64))], names=["at", "n"])

    found = map_batches(words.filter(F.length("key") > 0).select("key"), run, "at long, n long").groupBy("at").agg(F.sum("n").alias("n")).toArrow()
    return found["at"].to_numpy(), found["n"].to_numpy(), of_symbol[n_ids:], group, ~starts


def train(encoded: DataFrame, vocabulary: attention.Vocabulary, windows: int) -> dict[str, np.ndarray]:
    """Every training document is trained on: in each round, each task goes through all windows of its documents from the same weights, and
    the results are averaged by windows.

    The averages are summed in two levels, so the driver gets one set of weights from each of about the root of the tasks.
    """
    spark = encoded.sparkSession
    w = attention.initial(vocabulary)
    names, shapes = list(w), [v.shape for v in w.values()]
    sizes = np.cumsum([0, *(v.size for v in w.values())])
    learnt = encoded.filter(~F.col("held_out")).withColumn("warm", F.pmod(F.xxhash64("doc_id"), F.lit(WARM_UP)) == 0)

    def unpack(flat: np.ndarray) -> dict[str, np.ndarray]:
        return {k: flat[a:b].reshape(s).astype(np.float32) for k, s, a, b in zip(names, shapes, sizes[:-1], sizes[1:], strict=True)}

    for r, rate in enumerate(RATES):
        sent = spark.sparkContext.broadcast((w, vocabulary))
        mine = windows // WARM_UP if r == 0 else windows - windows // WARM_UP
        tasks = max(1, -(-mine // WINDOWS_A_TASK))  # grows with the corpus
        levels = max(1, int(tasks**0.5))

        def learn(batches: Iterator[pa.RecordBatch], sent=sent, r=r, rate=rate, levels=levels) -> Iterator[pa.RecordBatch]:
            from pyspark import TaskContext

            per_worker("lm-memory", "", keep_freed_memory)
            start, words = sent.value
            trainer, seen = attention.Trainer(start, words, rate), 0
            for batch in _slices(batches, TRAIN_SLICE):
                inputs, goals = attention.training_windows(_ids(batch, 0), words)
                for again in range(max(1, LEAST_WINDOWS // len(inputs)) if not seen and batch.num_rows < TRAIN_SLICE else 1):
                    trainer.run(inputs, goals, seed=1000 * r + again)
                seen += len(inputs)
            part = TaskContext.get().partitionId()
            flat = np.concatenate([trainer.w[k].ravel() for k in names]).astype(np.float64) * seen
            yield pa.RecordBatch.from_arrays([pa.array([part % levels]), pa.array([seen]), pa.array([flat.tobytes()], pa.binary())], names=["level", "seen", "sums"])

        def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            seen, total = 0, np.zeros(int(sizes[-1]))
            for batch in batches:
                for n, flat in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist(), strict=True):
                    seen, total = seen + n, total + np.frombuffer(flat, np.float64)
            yield pa.RecordBatch.from_arrays([pa.array([0]), pa.array([seen]), pa.array([total.tobytes()], pa.binary())], names=["level", "seen", "sums"])

        schema = "level long, seen long, sums binary"
        documents = learnt.filter("warm" if r == 0 else "not warm").select("ids").coalesce(tasks)  # no shuffle
        sums = map_batches(map_batches(documents, learn, schema).repartition(levels, "level"), add, schema).collect()
        if seen := sum(x["seen"] for x in sums):
            w = unpack(sum(np.frombuffer(x["sums"], np.float64) for x in sums) / seen)
    return w


def _head(words: DataFrame) -> tuple[DataFrame, float]:
    """The most frequent words, as many as MOST_HEAD_WORDS at most, by the least count that admits no more."""
    of_size = {r["size"]: r["words"] for r in words.groupBy(F.floor(F.log2("n") * 8).alias("size")).agg(F.count(F.lit(1)).alias("words")).collect()}
    least, held = max(of_size, default=0) + 1, 0
    for size in sorted(of_size, reverse=True):
        if (held := held + of_size[size]) > MOST_HEAD_WORDS:
            break
        least = size
    return words.filter(F.floor(F.log2("n") * 8) >= least), least


def score_documents(docs: DataFrame, vocabulary: list[bytes], pattern: str, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """One row for each row of ``docs``: doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score, n_subwords.

    ``score`` adds up, for each token, log10 of the probability that the attention model gives to its symbol in its window, and of how the
    word goes on by the counts of all training words. Which words' counts are broadcast and which are joined changes no result.
    Null and empty texts hold the end alone. Held-out documents are scored but neither counted nor trained on. A null id is
    not held out. Rows that repeat are counted as often as they are there. The vocabulary may have at most 65,535 ids; the id after its last is
    the end. Without training documents all counts are zero and the model keeps its first weights. An empty table gives an empty result.
    """
    spark = docs.sparkSession
    n_ids = len(vocabulary) + 1
    starts = np.array([t.startswith(b" ") for t in vocabulary] + [True])
    sent = spark.sparkContext.broadcast((vocabulary, pattern))
    rows = docs.select(F.col(doc_id).alias("doc_id"), F.col(text).alias("text"))
    kind = rows.schema["doc_id"].dataType.simpleString()
    encoded, counted_by_task = encode_documents(rows, sent)
    words = materialise(counted_by_task.groupBy("key").agg(F.sum("n").alias("n")), "lm-counts")
    total, distinct = words.agg(F.coalesce(F.sum("n"), F.lit(0)), F.count(F.lit(1))).first()
    described, of_id, of_symbol = describe_tokens(neighbours(encoded, starts), starts)
    tables = spelling_tables(words, sent, of_id, of_symbol, starts)
    head_words, least = _head(words)
    head = head_words.select("key", "n").toArrow()
    weights = train(encoded, described, int(of_id.sum()) // attention.WINDOW)
    model = spark.sparkContext.broadcast((uuid.uuid4().hex, weights, described, tables, head))

    def prepared():
        _, w, description, its, table = model.value
        return attention.Scorer(w, description), spelling.Spelling(*its), dict(zip(table["key"].to_pylist(), table["n"].to_pylist(), strict=True))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        per_worker("lm-memory", "", keep_freed_memory)
        scorer, speller, held = per_worker("lm-model", model.value[0], prepared)
        known_count = held.get
        for batch in _slices(batches):
            ids = _ids(batch, 3)
            documents = [words_of(t) for t in texts_of(batch)]
            for words_in_a_row in documents:
                words_in_a_row.append(b"")
            sizes = np.fromiter(map(len, documents), np.int64, len(documents))
            of = np.repeat(np.arange(len(documents)), sizes)
            tokens_in_a_row = list(chain.from_iterable(documents))
            n = np.fromiter(map(known_count, tokens_in_a_row, repeat(-1)), np.int64, len(tokens_in_a_row))
            flat = np.concatenate([x for i in ids for x in (i, [n_ids - 1])]).astype(np.int64)
            begin = np.flatnonzero(starts[flat])
            share, tokens = speller.parts(flat, np.diff(np.append(begin, len(flat))))
            known = n >= 0
            base = np.bincount(of[known], np.log10((n[known] + 0.5) / (total + 0.5 * (distinct + 1))), len(documents))
            form = np.bincount(of[known], spelling.log10_form(n[known], share[known], tokens[known]), len(documents))
            rest = np.flatnonzero(~known)
            entries = [pa.array([tokens_in_a_row[i] for i in rest.tolist()], pa.binary()), pa.array(share[rest]), pa.array(tokens[rest])]
            tails = pa.ListArray.from_arrays(np.append(0, np.cumsum(np.bincount(of[rest], minlength=len(documents)))).astype(np.int32), pa.StructArray.from_arrays(entries, names=["key", "share", "tokens"]))
            yield pa.RecordBatch.from_arrays(
                [
                    batch.column(0), batch.column(2), pa.array(sizes, pa.int64()), pa.array(np.bincount(of[known], minlength=len(documents)), pa.int64()), pa.array(base, pa.float64()),
                    pa.array(scorer.log10(ids) + form, pa.float64()),
                    pa.array([len(i) for i in ids], pa.int64()), tails,
                ],
                names=["doc_id", "held_out", "n_tokens", "n_known", "base_score", "score", "n_subwords", "tail"],
            )

    schema = f"doc_id {kind}, held_out boolean, n_tokens long, n_known long, base_score double, score double, n_subwords long, tail array<struct<key:binary,share:double,tokens:double>>"
    scored = materialise(map_batches(encoded, run, schema).withColumn("row", F.monotonically_increasing_id()), "lm-scored")
    rare = scored.select("row", F.inline("tail"))
    counted = words.filter(F.floor(F.log2("n") * 8) < least).select("key", "n")
    n = F.coalesce("n", F.lit(0))
    base = F.log10((n + 0.5) / F.lit(total + 0.5 * (distinct + 1)))
    form = F.when(F.col("tokens") > 0, F.log10((F.greatest(n - spelling.DISCOUNT, F.lit(0.0)) + F.col("share")) / F.col("tokens"))).otherwise(0.0)
    of_row = (F.count(F.when(n > 0, 1)).alias("more_known"), F.sum(base).alias("more_base"), F.sum(form).alias("more_score"))
    looked_up = rare.join(counted, "key", "left").groupBy("row").agg(*of_row)
    with_tail = lambda name, more: (F.col(name) + F.coalesce(more, F.lit(0))).alias(name)
    return scored.drop("tail").join(looked_up, "row", "left").select(
        "doc_id", "held_out", "n_tokens", with_tail("n_known", "more_known"), F.lit(total).cast("long").alias("train_tokens"), with_tail("base_score", "more_base"), with_tail("score", "more_score"),
        "n_subwords",
    )
