"""Encoding against a public library, packing, and that both lose nothing."""

import hashlib
import random

import numpy as np
import pytest
import tiktoken
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F
from tests.conftest import SMALL

from ownerdp.llm import bpe, packing
from ownerdp.llm.queries import QUERIES, byte_vocabulary, split_pattern

VOCABULARY, PATTERN = byte_vocabulary(), split_pattern()
CODEC = bpe.Codec(VOCABULARY, PATTERN)
PEER = tiktoken.Encoding("peer", pat_str=PATTERN, mergeable_ranks={k: i for i, k in enumerate(VOCABULARY)}, special_tokens={})
ODD = [None, "", " ", "\n\n  \t x", "a" * 5000, "don't <|endoftext|> stop", "naïve 漢字 ²½ ⅷ \u200b\u0301", "Wörter\u00a0und\u0085Zeilen\x1c", "é" * 300]


@settings(max_examples=300, deadline=None)
@given(st.text(max_size=60))
def test_codec_equals_the_library(text):
    ids = np.frombuffer(CODEC.packed(text), "<u4").tolist()
    assert ids == PEER.encode_ordinary(text) and CODEC.decode(CODEC.packed(text)).decode() == text


def test_perfect_hash_is_minimal():
    assert sorted(CODEC.hash.slot.tolist()) == list(range(len(VOCABULARY)))
    assert all(CODEC.hash.rank(k) == i for i, k in enumerate(VOCABULARY[:3000])) and CODEC.hash.rank(b"no such token") == -1
    assert bpe.PerfectHash([]).rank(b"x") == -1 and bpe.PerfectHash([b"x"]).rank(b"x") == 0


def test_documents(spark):
    rows = [(i, t) for i, t in enumerate(ODD)] + [(None, "null id"), (300, "repeated"), (300, "repeated")]
    docs = spark.createDataFrame(rows, "doc_id long, text string").withColumns({"n_tokens": F.lit("clash"), "ids": F.lit(0)})
    out = bpe.encode_documents(docs, VOCABULARY, PATTERN, keep_ids=True)
    assert out.count() == len(rows)
    for r in out.collect():
        text = dict(rows).get(r["doc_id"]) or ""
        assert r["ids"] == PEER.encode_ordinary(text) and r["n_tokens"] == len(r["ids"])
        assert r["decoded_sha256"] == hashlib.sha256(text.encode()).hexdigest()
        assert r["ids_sha256"] == hashlib.sha256(np.array(r["ids"], "<u4").tobytes()).hexdigest()
    texts = {r["doc_id"]: r["text"] for r in bpe.decode_documents(out, VOCABULARY).collect()}
    assert all(texts[i] == (t or "") for i, t in rows)
    assert bpe.encode_documents(docs.limit(0), VOCABULARY, PATTERN).count() == 0


@settings(max_examples=200, deadline=None)
@given(st.lists(st.integers(1, 20), max_size=80))
def test_best_fit_equals_a_plain_search(lengths):
    rows, free = [], []
    for i in sorted(range(len(lengths)), key=lambda i: -lengths[i]):
        fits = [f for f in free if f >= lengths[i]]
        if fits:
            free[free.index(min(fits))] -= lengths[i]
        else:
            free.append(20 - lengths[i])
        rows = free
    packed = packing.best_fit_decreasing(lengths, 20)
    assert sorted(20 - sum(lengths[i] for i in r) for r in packed) == sorted(rows) and sorted(i for r in packed for i in r) == list(range(len(lengths)))


def test_capacity_tree():
    tree, held = packing.CapacityTree(37), []
    rng = random.Random(1)
    for row in range(500):
        free = rng.randint(1, 37)
        tree.add(row, free)
        held.append(free)
        need = rng.randint(1, 37)
        best = min((f for f in held if f >= need), default=None)
        found = tree.take(need)
        assert (found[1] if found else None) == best
        if found:
            held.remove(best)


@pytest.mark.parametrize("length", [16, 2048])
def test_packing_loses_nothing(spark, length):
    rows = [(i, t) for i, t in enumerate(ODD)] + [(100 + i, "some words here " * i) for i in range(40)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    out = packing.stored(packing.pack_documents(docs, VOCABULARY, PATTERN, length)).collect()
    pieces: dict[int, dict[int, list[int]]] = {}
    for r in out:
        ids, cu = np.frombuffer(r["ids"], "<u2").tolist(), r["cu_seqlens"]
        assert len(ids) == length and cu[0] == 0 and len(cu) == len(r["doc_ids"]) + 1 == len(r["starts"]) + 1
        assert np.frombuffer(r["positions"], "<u2").tolist() == [i for a, b in zip(cu, cu[1:], strict=False) for i in range(b - a)]
        assert set(ids[cu[-1] :]) <= {len(VOCABULARY)}
        for d, s, a, b in zip(r["doc_ids"], r["starts"], cu, cu[1:], strict=False):
            pieces.setdefault(d, {})[s] = ids[a:b]
    assert len({(r["part"], r["row"]) for r in out}) == len(out)
    for d, t in rows:
        whole = [i for s in sorted(pieces[d]) for i in pieces[d][s]]
        assert whole == [*PEER.encode_ordinary(t or ""), len(VOCABULARY)]
    assert packing.pack_documents(docs.limit(0), VOCABULARY, PATTERN).count() == 0


def test_query_holds_all_tokens(spark):
    rows = QUERIES["op10_packing"](spark, SMALL)
    total = rows.agg(F.sum("n_tokens")).first()[0]
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    counted = QUERIES["op6_byte_bpe"](spark, SMALL).agg(F.sum("n_tokens")).first()[0]
    assert total == counted + docs.count()
