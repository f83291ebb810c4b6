"""The quality classifier against plain loops: its statistics, its splits, its weights, and the query's scores over a whole table."""

import math
import re
import zlib

import numpy as np
import pytest
from tests.conftest import MEDIUM

from ownerdp.llm import quality
from ownerdp.llm.queries import QUERIES


def plain_statistics(text):
    raw = text.encode()
    words = re.findall(rb"[^\x20\x09-\x0D]+", raw)
    if not words:
        return dict.fromkeys(quality.STATISTICS, 0.0)
    n, size = len(words), len(raw)
    among = lambda chars: sum(raw.count(bytes([c])) for c in chars)
    upper, lower, high = among(range(65, 91)), among(range(97, 123)), among(range(128, 256))
    letters = max(1, upper + lower + high)
    lines = [x for x in raw.split(b"\n") if x.strip()]
    return {
        "log_words": math.log(1 + n), "word_length": sum(map(len, words)) / n, "distinct_share": len(set(words)) / n,
        "repeated_next": sum(a == b for a, b in zip(words, words[1:], strict=False)) / n, "top_share": max(words.count(w) for w in set(words)) / n, "upper_share": upper / letters,
        "digit_share": among(b"0123456789") / size, "symbol_share": among(b"#$%&*+<=>@\\^_`{|}~") / size, "bar_share": raw.count(b"|") / n, "bang_share": raw.count(b"!") / n,
        "stop_share": (raw.count(b".") + raw.count(b"?")) / n, "comma_share": raw.count(b",") / n, "non_ascii_share": high / size, "line_words": n / len(lines),
        "repeated_lines": 1 - len(set(lines)) / len(lines), "long_words": sum(len(w) > 14 for w in words) / n, "short_words": sum(len(w) < 4 for w in words) / n,
        "capital_words": sum(w.isupper() for w in words) / n,
    }


def test_statistics_by_plain_loops():
    texts = ["", "  \n\t", "One", "AAA!! BBB!! aaa", "x x x\nx x x\n\nlast line? no.", "a | b | c, 1 2 3", "é è ### ***\n\n", "  wörd NAÏVE \x85", "verylongwordindeedyes " * 30]
    for t in texts:
        want = plain_statistics(t)
        assert quality.statistics(t) == pytest.approx([want[s] for s in quality.STATISTICS])


def test_the_best_split_by_trying_all():
    rng = np.random.default_rng(0)
    for _ in range(30):
        bins, y = rng.integers(0, 6, (60, 4)), rng.random(60)
        p = rng.random(60)
        gradient, hessian, rows = y - p, np.maximum(p * (1 - p), 1e-6), np.sort(rng.choice(60, 45, replace=False))

        def gain(s, k):
            low = [i for i in rows if bins[i, s] <= k]
            high = [i for i in rows if bins[i, s] > k]
            if len(low) < 5 or len(high) < 5:
                return 0.0
            part = lambda its: gradient[its].sum() ** 2 / (hessian[its].sum() + 1)
            return part(low) + part(high) - part(rows)

        best = max(gain(s, k) for s in range(4) for k in range(5))
        s, k = quality._best_split(bins, gradient, hessian, rows, 6, 5)
        assert gain(s, k) == pytest.approx(best)


def test_weights_are_a_minimum_of_the_penalised_loss():
    """At the minimum the slope of the loss equals the penalty where a weight is not zero, and is at most the penalty elsewhere."""
    rng = np.random.default_rng(2)
    r = (rng.random((1500, 12)) < rng.random(12)).astype(float)
    y = (rng.random(1500) < 1 / (1 + np.exp(-(2 * r[:, 0] - 1.5 * r[:, 3] + 0.3)))).astype(float)
    penalty = 0.01
    b, w = quality.fit_lasso(r, y, penalty, steps=4000)
    miss = 1 / (1 + np.exp(-(r @ w + b))) - y
    slope = r.T @ miss / len(y)
    assert abs(miss.mean()) < 1e-4
    assert slope[w != 0] == pytest.approx(-penalty * np.sign(w[w != 0]), abs=1e-4) and (np.abs(slope[w == 0]) <= penalty + 1e-4).all()


def test_the_querys_scores_by_plain_loops(spark):
    """The model that is fitted on the labelled rows of the contract, evaluated rule by rule on every document."""
    docs = spark.read.parquet(f"{MEDIUM}/documents.parquet").select("doc_id", "text").collect()
    labels = {r["doc_id"]: r["quality"] for r in spark.read.parquet(f"{MEDIUM}/labels.parquet").collect() if r["quality"] is not None}
    held = lambda d: zlib.crc32(str(d).encode()) % 4 == 2
    of = {r["doc_id"]: plain_statistics(r["text"] or "") for r in docs}
    learnt = sorted(d for d in labels if d in of and not held(d))
    model = quality.fit(np.array([[of[d][s] for s in quality.STATISTICS] for d in learnt]), np.array([float(labels[d]) for d in learnt]))
    got = {r["doc_id"]: r for r in QUERIES["op5_quality"](spark, MEDIUM).collect()}
    assert got.keys() == of.keys() and len(model.rules) > 3
    for d, x in of.items():
        odds = model.intercept + sum(w for conditions, w in model.rules if all((x[quality.STATISTICS[s]] > at) == above for s, above, at in conditions))
        assert got[d]["score"] == pytest.approx(1 / (1 + math.exp(-odds)), abs=1e-9)
        assert got[d]["held_out"] == held(d) and got[d]["predicted"] == int(got[d]["score"] >= 0.7)
