"""Language-model scores: the layer's gradients, its windows, the spelling of words, and the query's score, each against plain loops."""

import math
import random
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from ownerdp.llm import attention, lm_scoring, spelling
from ownerdp.llm.packing import _fast_encoder
from ownerdp.llm.queries import QUERIES, byte_vocabulary, split_pattern


def docs(spark, rows):
    return spark.createDataFrame(rows, "doc_id long, text string").withColumns({k: F.lit(1) for k in ("row", "key", "n", "ids", "tail", "held_out", "warm", "cell")})


def some_vocabulary(n, rng):
    starts = rng.random(n) < 0.5
    starts[-1] = True
    around = lambda k: rng.integers(0, 9, (k, 16))
    return attention.describe(rng.integers(0, 50, n).astype(float), around(n), starts, rng.integers(0, 50, 2 * n).astype(float), around(2 * n))


def test_gradients():
    rng = np.random.default_rng(0)
    v = some_vocabulary(300, rng)
    w = {k: x.astype(float) for k, x in attention.initial(v).items()}
    w["distance"] += rng.normal(size=attention.WINDOW)
    x = v.embedding[rng.integers(0, 300, (3, attention.WINDOW))].astype(float)
    goal = np.where(rng.random((3, attention.WINDOW)) < 0.4, rng.integers(0, attention.CLASSES, (3, attention.WINDOW)), -1)
    _, g = attention.loss_and_gradient(w, x, goal)
    for k in w:
        for _ in range(3):
            at = tuple(rng.integers(0, s) for s in w[k].shape)
            held, ends = w[k][at], []
            for step in (1e-5, -1e-5):
                w[k][at] = held + step
                ends.append(attention.loss_and_gradient(w, x, goal)[0])
            w[k][at] = held
            assert g[k][at] == pytest.approx((ends[0] - ends[1]) / 2e-5, rel=2e-3, abs=1e-7)


def plain_symbol_score(w, v, ids, end):
    """One token after the other, with its window's context alone."""
    total, seq, n = 0.0, [end, *ids, end], len(v.starts)
    for t in range(len(seq) - 1):
        if not v.starts[seq[t + 1]]:
            continue
        symbol = seq[t + 1] + (n if t + 2 < len(seq) and not v.starts[seq[t + 2]] else 0)
        first = max(0, t // attention.STRIDE * attention.STRIDE - (attention.WINDOW - attention.STRIDE))
        x = v.embedding[seq[first : t + 1]].astype(float)
        s = (x[-1] @ w["query"]) @ (x @ w["key"]).T / math.sqrt(attention.DIM) + w["distance"][np.arange(len(x))[::-1]]
        p = np.exp(s - s.max())
        z = np.maximum(x[-1] @ w["own"] + (p / p.sum()) @ (x @ w["value"]) @ w["mixed"] + w["hidden_bias"], 0) @ w["out"] + w["out_bias"]
        total += z[v.of_class[symbol]] - z.max() - math.log(np.exp(z - z.max()).sum()) + v.log_within[symbol]
    return total / math.log(10)


def test_windows_score_each_token_once():
    rng, n = np.random.default_rng(2), 300
    v = some_vocabulary(n, rng)
    w = attention.initial(v)
    w["distance"] = rng.normal(size=attention.WINDOW).astype(np.float32)
    texts = []
    for size in (0, 1, 5, 23, 24, 25, 31, 32, 33, 47, 48, 49, 130):
        ids = rng.integers(0, n - 1, size).astype(np.uint16)
        if size:
            ids[0] = np.flatnonzero(v.starts[:-1])[0]
        texts.append(ids)
    got = attention.Scorer(w, v).log10(texts, chunk=3)
    assert got.tolist() == pytest.approx([plain_symbol_score(w, v, i.tolist(), n - 1) for i in texts], rel=1e-4)
    assert len(attention.Scorer(w, v).log10([])) == 0


def test_training_windows_hold_each_token_once():
    rng, n = np.random.default_rng(5), 300
    v = some_vocabulary(n, rng)
    texts = [rng.integers(0, n - 1, size).astype(np.uint16) for size in (0, 1, 7, 31, 32, 33, 64, 700)]
    inputs, goals = attention.training_windows(texts, v)
    want: Counter = Counter()
    for ids in texts:
        its = attention.symbols(np.array([n - 1, *ids, n - 1]), v.starts)[1:]
        want.update(v.of_class[its[its >= 0]].tolist())
    assert Counter(goals[goals >= 0].tolist()) == want and inputs.shape == goals.shape and inputs.shape[1] == attention.WINDOW
    assert len(attention.training_windows([], v)[0]) == 0


def test_every_symbol_has_its_share():
    rng, n = np.random.default_rng(1), 400
    v = some_vocabulary(n, rng)
    possible = np.concatenate([v.starts, v.starts])
    possible[-1] = False
    each = np.bincount(v.of_class[possible], np.exp(v.log_within[possible]), attention.CLASSES)
    assert each == pytest.approx(np.ones(attention.CLASSES)) and (v.of_class[~possible] == -1).all()


def test_training_lowers_the_loss():
    rng, n = np.random.default_rng(3), 200
    v = some_vocabulary(n, rng)
    text = [np.tile(np.flatnonzero(v.starts)[:5], 400).astype(np.uint16)]
    trainer = attention.Trainer(attention.initial(v), v, 0.01, batch=8)
    for again in range(6):
        trainer.run(*attention.training_windows(text, v), seed=again)
    assert trainer.losses[-1] < 0.3 * trainer.losses[0]


def some_spelling(rng, n=60):
    goes_on = np.arange(n) % 2 == 1
    words = {tuple([2 * int(rng.integers(0, n // 2)), *(2 * rng.integers(0, n // 2, rng.integers(0, 4)) + 1).tolist()]): int(rng.integers(1, 9)) for _ in range(80)}
    ids, lengths = np.array([i for x in words for i in x]), np.array([len(x) for x in words])
    group = spelling.groups(np.bincount(ids, minlength=n) * goes_on)
    total = np.bincount(spelling.cells(ids, lengths, group), minlength=spelling.table_size(n))
    n_longer = np.bincount([x[0] for x in words if len(x) > 1], [c for x, c in words.items() if len(x) > 1], minlength=n)
    at = np.flatnonzero(total)
    return words, spelling.Spelling(at, total[at], n_longer, group, goes_on), goes_on


def test_spelling_is_a_distribution():
    words, s, goes_on = some_spelling(np.random.default_rng(0))
    ways = np.flatnonzero(goes_on)
    for last in range(60):
        total = np.exp(s.log_next[last, spelling.ENDS]) + np.exp(s.log_next[last, s.group[ways]].astype(float) + s.log_in_group[ways]).sum()
        empty = np.bincount(s.group[ways], minlength=spelling.GROUPS)[: spelling.ENDS] == 0  # groups that no subword is in keep a little
        assert total + np.exp(s.log_next[last, : spelling.ENDS][empty]).sum() == pytest.approx(1, rel=1e-3)
    for first in {x[0] for x in words}:
        seen = sum(max(c - spelling.DISCOUNT, 0) for x, c in words.items() if x[0] == first and len(x) > 1)
        assert seen + np.exp(s.log_mass[first]) == pytest.approx(s.n_longer[first])


def test_parts_of_words_in_a_row_are_those_of_each_alone():
    words, s, _ = some_spelling(np.random.default_rng(4))
    listed = list(words)
    share, tokens = s.parts(np.array([i for x in listed for i in x]), np.array([len(x) for x in listed]))
    for k, x in enumerate(listed):
        one = s.parts(np.array(x), np.array([len(x)]))
        assert (share[k], tokens[k]) == pytest.approx((one[0][0], one[1][0]))
        assert (tokens[k] == 0) == (len(x) == 1)
    assert spelling.log10_form(np.array([0, 3]), np.array([0.0, 0.5]), np.array([0.0, 10.0])).tolist() == pytest.approx([0.0, math.log10(2.75 / 10)])
    assert len(s.parts(np.zeros(0, int), np.zeros(0, int))[0]) == 0


def cut(text):
    return re.findall(rb"[^\x20\x09-\x0D]+", re.sub(rb"[A-Z]", lambda m: m[0].lower(), (text or "").encode()))


def is_held(d):
    return d is not None and zlib.crc32(str(d).encode()) % 5 == 1


def plain_base_scores(rows):
    counts: Counter = Counter()
    for d, t in rows:
        if not is_held(d):
            counts.update([*cut(t), b""])
    n, v = sum(counts.values()), len(counts)
    return {d: (len(cut(t)) + 1, sum(counts[x] > 0 for x in [*cut(t), b""]), n, sum(math.log10((counts[x] + 0.5) / (n + 0.5 * (v + 1))) for x in [*cut(t), b""])) for d, t in rows}


def plain_scores(rows, vocabulary, pattern):
    """The score of each text under the layer's first weights, from the documents alone, one token after the other."""
    encode = _fast_encoder(vocabulary, pattern).encode_ordinary
    starts = np.array([t.startswith(b" ") for t in vocabulary] + [True])
    n, end = len(starts), len(starts) - 1
    text_ids = lambda t: [i for x in cut(t) for i in encode(" " + x.decode())]
    flats = [np.array([end, *(i for d, t in part for i in (*text_ids(t), end))]) for part in ([r for r in rows if not is_held(r[0])],)]
    (flat,) = flats
    its = attention.symbols(flat, starts)

    def around(values, size):
        out = np.zeros((size, 16))
        hashed = [int(np.uint32(x) * np.uint32(2654435761) >> np.uint32(29)) for x in values.tolist()]
        for i in range(1, len(values)):
            out[values[i], hashed[i - 1]] += 1
            out[values[i - 1], 8 + hashed[i]] += 1
        return out

    with np.errstate(over="ignore"):
        of_ids, of_symbols = around(flat, n), around(its[its >= 0], 2 * n)
    v = attention.describe(of_ids[:, :8].sum(1), of_ids, starts, of_symbols[:, :8].sum(1), of_symbols)
    w = attention.initial(v)
    counts: Counter = Counter(x for d, t in rows if not is_held(d) for x in cut(t))
    group = spelling.groups(np.where(starts, 0, of_ids[:, :8].sum(1)))
    pairs, goes_on, kinds, tokens = defaultdict(float), defaultdict(float), defaultdict(float), defaultdict(float)
    for x, c in counts.items():
        e = encode(" " + x.decode())
        for a, b in zip(e, [*(int(group[i]) for i in e[1:]), spelling.ENDS], strict=True):
            pairs[a, b] += 1
        for i in e[1:]:
            goes_on[i] += 1
        if len(e) > 1:
            kinds[e[0]] += 1
            tokens[e[0]] += c
    total = defaultdict(float)
    share = np.full(spelling.GROUPS, 0.1)
    for (a, b), c in pairs.items():
        total[a] += c
        share[b] += c
    share /= share.sum()
    weight = np.array([goes_on[i] + 0.05 * (not starts[i]) for i in range(n)])
    in_group = np.bincount(group, weight, spelling.GROUPS)
    step = lambda a, b: (pairs[a, b] + spelling.STRENGTH * share[b]) / (total[a] + spelling.STRENGTH)

    def form(x):
        e = encode(" " + x.decode())
        if len(e) == 1:
            return 0.0
        p = 1 / (1 - step(e[0], spelling.ENDS))
        for a, b in zip(e, e[1:], strict=False):
            p *= step(a, int(group[b])) * weight[b] / in_group[group[b]]
        p *= step(e[-1], spelling.ENDS)
        unseen = (spelling.DISCOUNT * kinds[e[0]] + spelling.PRIOR) * p
        return math.log10((max(counts[x] - spelling.DISCOUNT, 0) + unseen) / (tokens[e[0]] + spelling.PRIOR))

    return {d: plain_symbol_score(w, v, text_ids(t), end) + sum(map(form, cut(t))) for d, t in rows}


def some_rows():
    rng = random.Random(1)
    words = ["The", "the", "of", "w\u00f6rd", "na\u00efve", "x1", "unknowable"]
    rows = [(i, " ".join(rng.choice([*words, f"rare{rng.randint(0, 60)}"]) for _ in range(rng.randint(0, 40)))) for i in range(120)]
    return [*rows, (500, None), (None, "the null"), (501, "\u00a0 \x1c \u00e9"), (502, "w " * 3000), (503, "qqxqzzkj " * 3)]


@pytest.mark.parametrize("head", [1 << 19, 20])
def test_scores_against_plain_loops(spark, head, monkeypatch):
    """All counts and the scores under the first weights, whether counts of words are broadcast or joined."""
    monkeypatch.setattr(lm_scoring, "MOST_HEAD_WORDS", head)
    monkeypatch.setattr(lm_scoring, "train", lambda encoded, vocabulary, windows: attention.initial(vocabulary))
    rows = some_rows()
    out = lm_scoring.score_documents(docs(spark, rows).repartition(3), byte_vocabulary(), split_pattern()).collect()
    want, scores = plain_base_scores(rows), plain_scores(rows, byte_vocabulary(), split_pattern())
    assert len(out) == len(rows)
    for r in out:
        assert (r["n_tokens"], r["n_known"], r["train_tokens"]) == want[r["doc_id"]][:3] and r["base_score"] == pytest.approx(want[r["doc_id"]][3])
        assert r["held_out"] == is_held(r["doc_id"]) and r["score"] == pytest.approx(scores[r["doc_id"]], rel=1e-4)


def test_trained_scores_and_odd_tables(spark):
    rows = some_rows()
    out = lm_scoring.score_documents(docs(spark, rows), byte_vocabulary(), split_pattern()).collect()
    assert len(out) == len(rows) and all(-1e7 < r["score"] < 0 for r in out)
    learnt = sum(r["score"] for r in out if not r["held_out"])
    assert learnt > sum(s for d, s in plain_scores(rows, byte_vocabulary(), split_pattern()).items() if not is_held(d))
    assert lm_scoring.score_documents(docs(spark, []), byte_vocabulary(), split_pattern()).count() == 0
    only_held = [(i, "a b") for i in range(40) if is_held(i)]
    assert lm_scoring.score_documents(docs(spark, only_held), byte_vocabulary(), split_pattern()).filter("train_tokens = 0 and n_known = 0 and score < 0").count() == len(only_held)


def test_model_beats_the_base_on_held_out_documents(spark):
    rows = QUERIES["op1_lm_score"](spark, "/root/testdata/sf0.1").filter("held_out").agg(F.sum("score"), F.sum("base_score")).first()
    assert rows[0] > rows[1]


def test_scorer_fills_its_slots(monkeypatch):
    """Texts of long words beside texts of short ones: few slots of a chunk stay empty, and each text scores as it does alone."""
    starts = np.arange(41) % 2 == 0  # even ids begin a token, the last one is the end
    counts = np.ones(41)
    around = np.ones((41, 16))
    vocabulary = attention.describe(counts, around, starts, np.ones(82), np.ones((82, 16)))
    scorer = attention.Scorer(attention.initial(vocabulary), vocabulary)
    documents = [np.array(([0, 2, 4, 6] if i % 2 else [8, 1, 3, 5, 7, 9, 11, 13]) * (240 // (4 if i % 2 else 8))) for i in range(40)]
    slots, plain = [], attention._asked

    def asked(which):
        found = plain(which)
        slots.append((found[0].size, len(found[1])))
        return found

    monkeypatch.setattr(attention, "_asked", asked)
    together = scorer.log10(documents, chunk=64)
    assert sum(size for size, _ in slots) < 1.4 * sum(real for _, real in slots)
    assert together == pytest.approx([scorer.log10([d])[0] for d in documents], rel=1e-5)


def test_words_that_come_together_are_encoded_together():
    """Few calls for many words, and each word's subwords are those it has alone, also where words hold blanks of other kinds."""
    codec, alone = lm_scoring.SubwordCodec(byte_vocabulary(), split_pattern()), _fast_encoder(byte_vocabulary(), split_pattern()).encode_ordinary
    plain, calls = codec.encode, []
    codec.encode = lambda text: calls.append(1) or plain(text)
    rng = random.Random(3)
    for words in ([f"w{rng.randint(0, 4000)}it's" for _ in range(20_000)], [" ", "a ", " b", "naïve", "\x1c\x1cx", "'s", "日本", "!?", "w1it's"], []):
        listed = [x.encode() for x in words]
        ids, lengths = codec.subwords(codec.find(listed, len(listed)))
        each = [alone(" " + x) for x in words]
        assert lengths.tolist() == [len(x) for x in each] and ids.tolist() == [i for x in each for i in x]
    assert len(calls) < 20


def test_training_fills_its_slots(monkeypatch):
    """Windows of long words beside windows of short ones in one step: few slots stay empty, and the gradient is that of the whole step."""
    rng, n = np.random.default_rng(7), 300
    v = some_vocabulary(n, rng)
    inputs = rng.integers(0, n, (128, attention.WINDOW))
    goals = np.where(rng.random((128, attention.WINDOW)) < np.where(np.arange(128) % 2, 0.1, 0.9)[:, None], rng.integers(0, attention.CLASSES, (128, attention.WINDOW)), -1)
    loss, g = attention.loss_and_gradient(attention.initial(v), v.embedding[inputs], goals)
    trainer, sizes, plain = attention.Trainer(attention.initial(v), v, 0.01), [], attention._sums
    monkeypatch.setattr(attention, "_sums", lambda *a: sizes.append(a[-1].size) or plain(*a))
    trainer.run(inputs, goals)
    assert sum(sizes) < 1.4 * (goals >= 0).sum() and trainer.losses == pytest.approx([loss], rel=1e-5)
    assert trainer.first / np.float32(0.1) == pytest.approx(np.concatenate([g[k].ravel() for k in trainer.w]), rel=1e-3, abs=1e-6)
