"""Exact, near and substring deduplication against brute force."""

import hashlib
import random
import re
from collections import Counter, defaultdict

import numpy as np
import pytest
import xxhash
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F
from tests.conftest import MEDIUM, SMALL

from ownerdp.llm import bloom, components, exact_dedup, simhash, substring_dedup
from ownerdp.llm.automaton import SuffixAutomaton
from ownerdp.llm.queries import QUERIES

EXTRA = {"row": 1, "h": "x", "fp": 2.0, "keep_id": 3, "key": "k", "kept": 0}


def frame(spark, rows):
    return spark.createDataFrame(rows, "doc_id long, text string").withColumns({k: F.lit(v) for k, v in EXTRA.items()})


def union_find(pairs):
    parent = {}

    def find(x):
        parent.setdefault(x, x)
        while parent[x] != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    for a, b in pairs:
        a, b = find(a), find(b)
        parent[max(a, b)] = min(a, b)
    return {x: find(x) for x in parent}


def test_exact_edges(spark):
    rows = [(1, "a"), (5, "a"), (5, "a"), (2, None), (3, ""), (4, "b"), (None, "b"), (None, "c"), (9, "x" * 200_000), (8, "x" * 200_000), (6, "A")]
    out = exact_dedup.exact_duplicates(frame(spark, rows)).collect()
    kept = Counter(r["text_sha256"] for r in out if r["kept"])
    assert len(out) == len(rows) and set(kept.values()) == {1} and len(kept) == 6
    by = {(r["doc_id"], r["text_sha256"]): r for r in out}
    sha = lambda t: hashlib.sha256(t.encode()).hexdigest()
    assert by[1, sha("a")]["keep_id"] == 5 and by[1, sha("a")]["group_size"] == 3 and by[2, sha("")]["keep_id"] == 3 and by[None, sha("b")]["keep_id"] == 4
    assert sorted((r["doc_id"], len(r["text"] or "")) for r in exact_dedup.drop_exact_duplicates(frame(spark, rows)).filter("doc_id is not null").collect()) == [(3, 0), (4, 1), (5, 1), (6, 1), (9, 200_000)]
    assert exact_dedup.drop_exact_duplicates(frame(spark, rows)).count() == 6
    assert exact_dedup.exact_duplicates(frame(spark, [])).count() == 0 and exact_dedup.drop_exact_duplicates(frame(spark, [])).count() == 0


def test_exact_without_the_broadcast(spark, monkeypatch):
    monkeypatch.setattr(exact_dedup, "broadcast_bits", lambda *_: None)
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    other = sorted(map(str, exact_dedup.exact_duplicates(docs).drop("suspected").collect()))
    monkeypatch.undo()
    assert other == sorted(map(str, exact_dedup.exact_duplicates(docs).drop("suspected").collect()))


def test_hot_copies(spark):
    docs = spark.range(9000).select(F.col("id").alias("doc_id"), F.when(F.col("id") % 3 == 0, "hot").otherwise(F.concat(F.lit("t"), F.floor(F.col("id") / 2).cast("string"))).alias("text"))
    out = exact_dedup.exact_duplicates(docs)
    assert out.filter("kept").count() == docs.select("text").distinct().count()
    assert out.filter("group_size = 3000 and keep_id = 8997").count() == 3000


def test_bloom_never_misses(spark):
    rng = np.random.default_rng(0)
    once, twice = rng.integers(-(2**62), 2**62, 5000), rng.integers(-(2**62), 2**62, 400)
    df = spark.createDataFrame([(int(x),) for x in [*once, *twice, *twice]], "h long").repartition(7)
    found = {r["h"] for r in bloom.possibly_repeated(df).collect()}
    assert set(twice.tolist()) <= found and len(found) < 600
    words, log2_bits = bloom.broadcast_bits(df.distinct(), 5400)
    assert bloom.contains(words, log2_bits, once).all()
    assert bloom.contains(words, log2_bits, rng.integers(-(2**62), 2**62, 5000)).mean() < 0.05
    assert bloom.broadcast_bits(df, 1 << 40) is None


def plain_fingerprint(text, size):
    words = re.findall(rb"[^\x20\x09-\x0D]+", re.sub(rb"[A-Z]", lambda m: m[0].lower(), (text or "").encode()))
    shingles = [b" ".join(words[i : i + size]) for i in range(len(words) - size + 1)] or ([b" ".join(words)] if words else [])
    h = [xxhash.xxh64_intdigest(s, 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def test_simhash_against_all_pairs(spark):
    rng = random.Random(3)
    words = [f"w{i}" for i in range(60)]
    texts = [None, "", "  \n", "One", "one TWO", "É é \u00a0x"] + [" ".join(rng.choice(words) for _ in range(rng.randint(1, 12))) for _ in range(150)]
    texts += [" ".join(rng.choice(words[:3]) for _ in range(rng.randint(3, 6))) for _ in range(200)]
    rows = [(i, t) for i, t in enumerate(texts)] + [(None, "one two"), (7, texts[7]), (7, texts[7])]
    fps = [plain_fingerprint(t, 3) for _, t in rows]
    links = [(a, b) for a in range(len(rows)) for b in range(a) if bin(fps[a] ^ fps[b]).count("1") <= 2]
    root = union_find([(i, i) for i in range(len(rows))] + links)
    low = defaultdict(list)
    for i, (d, _) in enumerate(rows):
        low[root[i]].append(d)
    want = sorted((str(d), fps[i], min(x for x in low[root[i]] if x is not None)) for i, (d, _) in enumerate(rows))
    got = simhash.near_duplicates(frame(spark, rows), 3, 2).collect()
    assert sorted((str(r["doc_id"]), r["fp"] % (1 << 64), r["component_id"]) for r in got) == want
    assert simhash.near_duplicates(frame(spark, []), 3, 2).count() == 0


@pytest.mark.parametrize(("distance", "segments"), [(2, 9), (2, 3), (1, 4), (3, 8)])
def test_links_are_complete(spark, distance, segments):
    rng = random.Random(distance)
    values = [rng.getrandbits(64) for _ in range(150)]
    for v in values[:120]:
        values.append(v ^ sum(1 << b for b in rng.sample(range(64), rng.randint(1, 4))))
    values = sorted({v - (1 << 64) if v >> 63 else v for v in values})
    want = {(a, b) for a in values for b in values if a < b and bin((a ^ b) % (1 << 64)).count("1") <= distance}
    df = spark.createDataFrame([(v,) for v in values], "fp long")
    assert {(r["a"], r["b"]) for r in simhash.fingerprint_links(df, distance, segments).collect()} == want
    with pytest.raises(ValueError):
        simhash.fingerprint_links(df, 4, 4)


@settings(max_examples=200, deadline=None)
@given(st.integers(0, 2**64 - 1), st.lists(st.integers(0, 63), max_size=6), st.integers(2, 16))
def test_some_chain_is_always_viable(value, flips, segments):
    other = value
    for b in flips:
        other ^= 1 << b
    distance = bin(value ^ other).count("1")
    parts = [bin((value ^ other) & m).count("1") for m in simhash._segment_masks(segments)]
    assert any(all(sum(parts[(i + j) % segments] for j in range(n)) * segments <= n * distance for n in range(1, segments + 1)) for i in range(segments))


def test_components(spark):
    rng = random.Random(0)
    pairs = [(i, i + 1) for i in range(100, 400)] + [(rng.randint(1000, 1400), rng.randint(1000, 1400)) for _ in range(350)] + [(5000, i) for i in range(5001, 5300)] + [(7, 7)]
    df = spark.createDataFrame(pairs, "a long, b long")
    want = union_find([p for p in pairs if p[0] != p[1]])
    assert {r["node"]: r["component"] for r in components.connected_components(df).collect()} == want
    assert components.connected_components(df.limit(0)).count() == 0


def test_similar_texts_against_all_pairs(spark):
    rng = random.Random(5)
    words = [f"w{i}" for i in range(400)]
    rows, n = [], 0
    for size in (8, 30, 120, 400):
        for _ in range(6):
            base = [rng.choice(words) for _ in range(size)]
            for _ in range(4):
                copy = list(base)
                for _ in range(rng.choice([0, 1, 1, max(1, size // 60)])):
                    copy[rng.randrange(size)] = "changed"
                rows.append((n, " ".join(copy)))
                n += 1
    rows += [(n, None), (n + 1, ""), (n + 2, "two words"), (n + 3, "Two words"), (n + 4, "else here")]
    sets = {i: {w for w in simhash.shingle_hashes(simhash.words_of(t or ""), 5).tolist()} for i, t in rows}
    links = [(a, b) for a in sets for b in sets if a < b and sets[a] and sets[b] and len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b])]
    root = union_find(links)
    left = {i for i, _ in rows} - {i for i in root if root[i] != i}
    for limit in (simhash.PAIRWISE, 2):
        simhash.PAIRWISE, before = limit, simhash.PAIRWISE
        try:
            out = simhash.drop_near_duplicates(frame(spark, rows))
            assert {r["doc_id"] for r in out.collect()} == left and out.columns[:2] == ["doc_id", "text"]
        finally:
            simhash.PAIRWISE = before


def brute_components(rows):
    """The smallest id of the group of each row, by comparing all pairs of sets."""
    sets = [(i, set(simhash.shingle_hashes(simhash.words_of(t), 5).tolist())) for i, t in rows]
    vocabulary = {h: n for n, h in enumerate(sorted(set().union(*(s for _, s in sets))))}
    held = np.zeros((len(sets), len(vocabulary)), np.float32)
    for n, (_, s) in enumerate(sets):
        held[n, [vocabulary[h] for h in s]] = 1
    shared, size = held @ held.T, held.sum(1)
    a, b = np.nonzero(np.triu(shared >= 0.8 * (size[:, None] + size[None, :] - shared), 1))
    return union_find([(sets[i][0], sets[j][0]) for i, j in zip(a.tolist(), b.tolist())])


def test_a_large_group_is_joined_like_all_pairs(spark):
    """Copies of one text that are similar to a sibling each but not to the centre: no head of the bucket links them."""
    rng = random.Random(11)
    base = [f"w{i}" for i in range(200)]
    rows = [(0, " ".join(base))]
    for pair in range(1000):
        mutated = list(base)
        for at in rng.sample(range(2, 198), 6):
            mutated[at] = f"m{pair}x{at}"
        sibling = list(mutated)
        for at in rng.sample([i for i in range(2, 198) if mutated[i] == base[i]], 3):
            sibling[at] = f"s{pair}x{at}"
        rows += [(2 * pair + 1, " ".join(mutated)), (2 * pair + 2, " ".join(sibling))]
    root = brute_components(rows)
    want = {i for i, _ in rows} - {i for i in root if root[i] != i}
    assert len(want) > 100
    assert {r["doc_id"] for r in simhash.drop_near_duplicates(frame(spark, rows)).collect()} == want


def test_repeated_lines_do_not_part_similar_texts(spark):
    rows = []
    for pair in range(12):
        words = [f"v{pair}x{i}" for i in range(204)]
        line = [f"line{pair}y{i}" for i in range(10)]
        rows += [(2 * pair, " ".join(words + line)), (2 * pair + 1, " ".join(words + line * 60))]
    root = brute_components(rows)
    assert len(root) == len(rows)
    assert {r["doc_id"] for r in simhash.drop_near_duplicates(frame(spark, rows)).collect()} == {2 * pair for pair in range(12)}


@settings(max_examples=200, deadline=None)
@given(st.lists(st.lists(st.sampled_from("abc"), max_size=14), max_size=4), st.lists(st.sampled_from("abc"), max_size=25))
def test_matching_statistics(passages, words):
    automaton = SuffixAutomaton()
    for p in passages:
        automaton.add(p)
    held = {tuple(p[i:j]) for p in passages for i in range(len(p)) for j in range(i, len(p) + 1)}
    want = [max(n for n in range(e + 1) if n == 0 or tuple(words[e - n : e]) in held) for e in range(1, len(words) + 1)]
    assert automaton.matches(words) == want


def plain_removal(texts, window):
    docs = [re.findall(rb"[^\x20\x09-\x0D]+", (t or "").encode()) for t in texts]
    counts = Counter(tuple(d[i : i + window]) for d in docs for i in range(len(d) - window + 1))
    out = []
    for d in docs:
        gone = {i + j for i in range(len(d) - window + 1) if counts[tuple(d[i : i + window])] > 1 for j in range(window)}
        out.append((len(d), len(gone), b" ".join(w for i, w in enumerate(d) if i not in gone)))
    return out


@pytest.mark.parametrize("chunk", [60, 1 << 19])
def test_substrings_against_brute_force(spark, chunk, monkeypatch):
    rng = random.Random(chunk)
    common = [[rng.choice("abcdefgh") for _ in range(rng.randint(3, 30))] for _ in range(5)]
    texts = [None, "", "one", " \u00a0x\u0085y  z\t\n"]
    for _ in range(150):
        words = []
        for _ in range(rng.randint(1, 5)):
            words += rng.choice(common)[rng.randint(0, 2) :] if rng.random() < 0.6 else [rng.choice("abcdefghijklmnopqrstuvwxyz") + rng.choice("xyz") for _ in range(rng.randint(1, 15))]
        texts.append(" ".join(words))
    texts += [texts[20], "same same same same same same same same"]
    rows = [(i, t) for i, t in enumerate(texts)] + [(None, texts[30]), (31, texts[31]), (31, texts[31])]
    monkeypatch.setattr(substring_dedup, "CHUNK_WORDS", chunk)
    want = plain_removal([t for _, t in rows], 6)
    for broadcast in (32 << 20, -1):
        monkeypatch.setattr(substring_dedup, "BROADCAST_BYTES", broadcast)
        got = substring_dedup.remove_repeated_passages(frame(spark, rows).repartition(3), 6, with_text=True).collect()
        ours = sorted((str(r["doc_id"]), r["n_words"], r["n_removed"], r["kept"]) for r in got)
        assert ours == sorted((str(d), n, g, k.decode()) for (d, _), (n, g, k) in zip(rows, want, strict=True))
    assert substring_dedup.remove_repeated_passages(frame(spark, [])).count() == 0


def test_reference_spans(spark):
    docs = frame(spark, [(1, "x a b c d e y"), (2, "a b c d"), (3, None)])
    out = {r["doc_id"]: (r["kept"], r["n_removed"]) for r in substring_dedup.remove_reference_spans(docs, ["q a b c d e r", "", None], 4).collect()}
    assert out == {1: ("x y", 5), 2: ("", 4), 3: ("", 0)}
    with pytest.raises(ValueError):
        substring_dedup.remove_reference_spans(docs, ["w " * 3_000_000], 4)


def test_queries_against_brute_force(spark):
    docs = spark.read.parquet(f"{MEDIUM}/documents.parquet").select("doc_id", "text").collect()
    want = {r["doc_id"]: f"{plain_fingerprint(r['text'], 3):016x}" for r in docs[:120]}
    got = {r["doc_id"]: r["fingerprint"] for r in QUERIES["op3_simhash"](spark, MEDIUM).collect()}
    assert len(got) == len(docs) and all(got[d] == f for d, f in want.items())
    out = QUERIES["op3_simhash"](spark, MEDIUM).collect()
    ids, fps = np.array([r["doc_id"] for r in out]), np.array([int(r["fingerprint"], 16) for r in out], np.uint64)
    a, b = np.nonzero(np.triu(np.bitwise_count(fps[:, None] ^ fps[None, :]) <= 2, 1))  # all pairs of the whole table
    root = union_find([(int(i), int(i)) for i in ids] + [(int(ids[i]), int(ids[j])) for i, j in zip(a, b, strict=True)])
    assert {r["doc_id"]: r["component_id"] for r in out} == root and len(a) > 20


@pytest.mark.parametrize("folder", [SMALL, MEDIUM])
def test_near_copies_of_the_given_tables_against_all_pairs(spark, folder):
    """Recall is whole on the given tables: every pair of similarity 0.8 or more is in one group, and groups hold nothing else."""
    docs = spark.read.parquet(f"{folder}/documents.parquet")
    rows = [(r["doc_id"], set(simhash.shingle_hashes(simhash.words_of(r["text"] or ""), 5).tolist())) for r in docs.collect()]
    holders, shared = defaultdict(list), Counter()
    for n, (_, s) in enumerate(rows):
        for h in s:
            holders[h].append(n)
    for its in holders.values():
        shared.update((a, b) for i, a in enumerate(its) for b in its[i + 1 :])
    links = [(rows[a][0], rows[b][0]) for (a, b), n in shared.items() if n >= 0.8 * (len(rows[a][1]) + len(rows[b][1]) - n)]
    root = union_find(links)
    groups = simhash.similar_groups(docs).collect()
    assert len(links) > 10 and {r["doc_id"] for r in groups} == set(root)
    assert {r["doc_id"] for r in groups if r["keep"]} == set(root.values())
