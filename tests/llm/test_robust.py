"""Odd inputs: clashing column names, empty tables, very long texts, and what workers keep."""

import random
import time

import pytest
from pyspark.sql import functions as F
from tests.conftest import SMALL

from ownerdp.llm import bpe, common, decontaminate, exact_dedup, lm_scoring, pii, quality, simhash, substring_dedup
from ownerdp.llm.queries import byte_vocabulary, split_pattern

#: Names that the operators might like for columns of their own.
CLASHING = ["__sha", "__id", "__same", "__own", "__row", "__bad_id", "___sha", *(f"__{s}" for s in quality.STATISTICS)]


def clashing(spark, rows):
    return spark.createDataFrame(rows, "doc_id long, text string").withColumns({c: F.lit(i) for i, c in enumerate(CLASHING)})


def filters(spark):
    labels = spark.read.parquet(f"{SMALL}/labels.parquet")
    model = quality.fit_quality(spark.read.parquet(f"{SMALL}/documents.parquet"), labels)
    bench = spark.createDataFrame([(1, "one two three four five six seven eight nine ten")], "item_id long, text string")
    return {
        "quality": lambda d: quality.keep_good(d, model), "exact": exact_dedup.drop_exact_duplicates, "near": simhash.drop_near_duplicates,
        "benchmark": lambda d: decontaminate.drop_contaminated(d, bench),
    }


def test_columns_of_any_names_stay_as_they_are(spark):
    texts = ["a b c d e f g h", "a b c d e f g h", None, "", "one two three four five six seven eight nine ten", "x " * 300]
    docs = clashing(spark, [(i, t) for i, t in enumerate(texts)] + [(None, "z z"), (3, "")])
    for name, keep in filters(spark).items():
        out = keep(docs)
        assert out.columns == docs.columns, name
        assert all(r[c] == i for r in out.collect() for i, c in enumerate(CLASHING)), name


def test_empty_tables(spark):
    none = spark.createDataFrame([], "doc_id long, text string")
    for keep in filters(spark).values():
        assert keep(none).count() == 0
    for report in (
        exact_dedup.exact_duplicates(none), simhash.near_duplicates(none), simhash.similar_groups(none), pii.find_pii(none), substring_dedup.remove_repeated_passages(none),
        bpe.encode_documents(none, byte_vocabulary(), split_pattern()),
    ):
        assert report.count() == 0


def test_free_names():
    class Frame:
        columns = ["a", "__B", "____x"]

    assert common.free_names(Frame, "b", "c") == ["_____b", "_____c"]


def test_a_shared_folder_is_asked_for(spark, monkeypatch):
    class Context:
        master, applicationId = "spark://host:7077", "app"

        def getConf(self):
            return {}

    class Session:
        sparkContext = Context()
        conf = {}

    from ownerdp.sources import tables

    for module in (common, tables):
        with pytest.raises(ValueError, match="spark.checkpoint.dir"):
            module.shared_dir(Session())


def test_personal_data_in_long_texts_is_found_in_linear_time():
    began = time.time()
    digits = "7" * 1_000_000
    assert pii.base_spans(digits + "." + digits) == []
    assert [x[2] for x in pii.base_spans(f"{digits}x 10.0.0.1 {digits}.1.2")] == ["ip"]
    many = "call 555-123-4567 or 123-45-6789, a@b.cd; " * 20_000
    base, spans = pii.find(many)
    assert len(base) == 20_000 and len(spans) >= 40_000
    assert pii.base_spans("+1" + ")" * 500_000) == [] and pii.base_spans("a" * 500_000 + "@" + "b" * 500_000) == []
    assert time.time() - began < 60


def plain_find(text):
    """As the operator, but each proposal is compared with all spans."""
    base = pii.base_spans(text)
    spans, taken = [(s, e, k, pii.scored(text, s, e, k)) for s, e, k in base], [(s, e) for s, e, _ in base]
    for s, e, k in pii.proposals(text):
        if all(e <= a or b <= s for a, b in taken) and (x := pii.scored(text, s, e, k)) >= pii.ACCEPT:
            spans.append((s, e, k, x))
            taken.append((s, e))
    return sorted(spans, key=lambda x: (x[0], (pii.KINDS + pii.MORE_KINDS).index(x[2])))


def test_overlaps_as_by_comparing_all():
    rng = random.Random(3)
    parts = ["DE89 3704 0044 0532 0130 00", "GB82WEST12345698765432", "ssn 123-45-6789", "call (555) 123-4567", "+1 555 123 4567", "10.1.2.3", "4111 1111 1111 1111", "x@y.zz", "iban", "word"]
    for _ in range(300):
        text = rng.choice(["", " "]).join(rng.choice(parts) for _ in range(rng.randint(1, 12)))
        assert pii.find(text)[1] == plain_find(text)


def test_workers_keep_no_long_words():
    cache = common.BoundedCache(10)
    cache.young |= {"short": 1, "long" * 100: 2}
    cache.make_room(["short", "long" * 100])
    assert cache.young == {"short": 1}
    codec = bpe.Codec(byte_vocabulary(), split_pattern())
    codec.packed("word " + "x" * 5000)
    assert all(len(k) <= cache.LONGEST for k in codec.cache.young)
    words = lm_scoring.SubwordCodec(byte_vocabulary(), split_pattern())
    listed = [b"one", b"two", b"x" * 3000, b"one"]
    ids, length = words.subwords(words.find(listed, 4))
    assert length[0] == length[3] and ids[: length[0]].tolist() == ids[-length[0] :].tolist() and not words.full
    words.held = lm_scoring.BYTES_KEPT + 1
    assert words.full
    words.forget()
    assert not words.full and not words.places


def test_without_labels_nothing_is_rejected(spark):
    docs = clashing(spark, [(1, "a b c"), (2, None), (3, "")])
    labels = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    assert quality.keep_good(docs, quality.fit_quality(docs, labels)).count() == 3


def test_pipeline_of_an_empty_table(spark, tmp_path):
    import corpus_pipeline as p

    for name in ("documents", "labels", "benchmark"):
        spark.read.parquet(f"{SMALL}/{name}.parquet").limit(0).write.parquet(str(tmp_path / f"{name}.parquet"))
    assert p.run(spark, str(tmp_path)).count() == 0
