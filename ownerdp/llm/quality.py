"""A quality classifier: rules from tree paths over text statistics, lasso weights, and the result as Spark columns."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ownerdp.llm.common import free_names, map_batches, texts_of

#: Labelled rows that the fit reads at most, taken in the order of a hash of the id.
MOST_LABELLED = 20_000
STATISTICS = (
    "log_words", "word_length", "distinct_share", "repeated_next", "top_share", "upper_share", "digit_share", "symbol_share", "bar_share",
    "bang_share", "stop_share", "comma_share", "non_ascii_share", "line_words", "repeated_lines", "long_words", "short_words", "capital_words",
)
_SYMBOLS = np.frombuffer(b"#$%&*+<=>@\\^_`{|}~", np.uint8)


def statistics(text: str) -> tuple[float, ...]:
    """The numbers that the rules test, in the order of STATISTICS; zeros for an empty text."""
    raw = text.encode()
    words = raw.split()
    if not words:
        return (0.0,) * len(STATISTICS)
    n, size = len(words), len(raw)
    c = np.bincount(np.frombuffer(raw, np.uint8), minlength=256)
    letters = max(1, int(c[65:91].sum() + c[97:123].sum() + c[128:].sum()))
    lengths = np.fromiter(map(len, words), np.int64, n)
    counts: dict[bytes, int] = {}
    for w in words:
        counts[w] = counts.get(w, 0) + 1
    repeated = sum(map(bytes.__eq__, words, words[1:]))
    lines = [x for x in raw.split(b"\n") if x.strip()]
    return (
        float(np.log1p(n)), float(lengths.mean()), len(counts) / n, repeated / n, max(counts.values()) / n, c[65:91].sum() / letters, c[48:58].sum() / size,
        c[_SYMBOLS].sum() / size, c[124] / n, c[33] / n, (c[46] + c[63]) / n, c[44] / n, c[128:].sum() / size, n / len(lines), 1 - len(set(lines)) / len(lines),
        float((lengths > 14).mean()), float((lengths < 4).mean()), sum(map(bytes.isupper, words)) / n,
    )


def with_statistics(docs: DataFrame, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """doc_id and a double column for each statistic; null counts as empty."""
    kind = docs.schema[doc_id].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            values = np.array([statistics(t) for t in texts_of(batch)], float).reshape(-1, len(STATISTICS))
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(v) for v in values.T)], names=["doc_id", *STATISTICS])

    return map_batches(docs.selectExpr(f"`{doc_id}` AS doc_id", f"`{text}` AS text"), run, f"doc_id {kind}, " + ", ".join(f"{s} double" for s in STATISTICS))


#: One condition of a rule: (statistic, True for "greater than", threshold).
Condition = tuple[int, bool, float]


@dataclass(frozen=True)
class RuleModel:
    """The log odds: intercept + the weights of the rules that hold. A rule holds if all its conditions do."""

    intercept: float
    rules: tuple[tuple[tuple[Condition, ...], float], ...] = field(default=())

    def column(self, prefix: str = "") -> Column:
        odds: Column = F.lit(self.intercept)
        for conditions, weight in self.rules:
            holds: Column = F.lit(True)
            for s, above, at in conditions:
                holds = holds & ((F.col(prefix + STATISTICS[s]) > at) if above else (F.col(prefix + STATISTICS[s]) <= at))
            odds = odds + F.when(holds, F.lit(weight)).otherwise(F.lit(0.0))
        return 1 / (1 + F.exp(-odds))

    def scores(self, x: np.ndarray) -> np.ndarray:
        odds = np.full(len(x), self.intercept)
        for conditions, weight in self.rules:
            odds += weight * _holds(x, conditions)
        return 1 / (1 + np.exp(-odds))


def _holds(x: np.ndarray, conditions: tuple[Condition, ...]) -> np.ndarray:
    out = np.ones(len(x), bool)
    for s, above, at in conditions:
        out &= (x[:, s] > at) if above else (x[:, s] <= at)
    return out


def _best_split(bins: np.ndarray, gradient: np.ndarray, hessian: np.ndarray, rows: np.ndarray, n_bins: int, least: int):
    best = (1e-6, -1, -1)
    g, h = gradient[rows], hessian[rows]
    whole = g.sum() ** 2 / (h.sum() + 1)
    for s in range(bins.shape[1]):
        b = bins[rows, s]
        gs, hs, ns = (np.cumsum(np.bincount(b, w, n_bins))[:-1] for w in (g, h, None))
        gain = gs**2 / (hs + 1) + (g.sum() - gs) ** 2 / (h.sum() - hs + 1) - whole
        gain[(ns < least) | (len(rows) - ns < least)] = 0
        k = int(gain.argmax())
        if gain[k] > best[0]:
            best = (float(gain[k]), s, k)
    return best[1:]


def grow_rules(x: np.ndarray, y: np.ndarray, trees: int = 24, depth: int = 3, rate: float = 0.3, n_bins: int = 48, least: int = 8) -> list[tuple[Condition, ...]]:
    """The paths of boosted trees, from the root to every node below it, each once."""
    cuts = [np.unique(np.quantile(x[:, s], np.linspace(0, 1, n_bins + 1)[1:-1])) for s in range(x.shape[1])]
    bins = np.stack([np.searchsorted(c, x[:, s], side="left") for s, c in enumerate(cuts)], axis=1)
    odds, found = np.zeros(len(y)), {}
    for _ in range(trees):
        p = 1 / (1 + np.exp(-odds))
        gradient, hessian = y - p, np.maximum(p * (1 - p), 1e-6)
        open_nodes = [((), np.arange(len(y)))]
        while open_nodes:
            path, rows = open_nodes.pop()
            s, k = _best_split(bins, gradient, hessian, rows, n_bins + 1, least) if len(path) < depth and len(rows) >= 2 * least else (-1, -1)
            if s < 0 or k >= len(cuts[s]):
                odds[rows] += rate * gradient[rows].sum() / (hessian[rows].sum() + 1)
                continue
            for above in (False, True):
                child = (*path, (s, above, float(cuts[s][k])))
                found[tuple(sorted(child))] = None
                open_nodes.append((child, rows[(bins[rows, s] > k) == above]))
    return list(found)


def fit_lasso(r: np.ndarray, y: np.ndarray, penalty: float, steps: int = 400) -> tuple[float, np.ndarray]:
    """Logistic weights for 0/1 columns with an L1 penalty, by accelerated proximal steps; the intercept is not penalised."""
    n = len(y)
    mean = r.mean(axis=0)
    lipschitz = 0.25 * max(1e-9, np.linalg.norm(r - mean, 2) ** 2 / n) + 0.25
    w, b, v, c, t = np.zeros(r.shape[1]), 0.0, np.zeros(r.shape[1]), 0.0, 1.0
    for _ in range(steps):
        miss = 1 / (1 + np.exp(-(r @ v - mean @ v + c))) - y
        w_new = v - (r.T @ miss - mean * miss.sum()) / n / lipschitz
        w_new = np.sign(w_new) * np.maximum(np.abs(w_new) - penalty / lipschitz, 0)
        b_new, t_new = c - miss.mean() / lipschitz, (1 + np.sqrt(1 + 4 * t * t)) / 2
        v, c = w_new + (t - 1) / t_new * (w_new - w), b_new + (t - 1) / t_new * (b_new - b)
        w, b, t = w_new, b_new, t_new
    return float(b - mean @ w), w


def fit(x: np.ndarray, y: np.ndarray, penalty: float = 3e-4) -> RuleModel:
    """Without rows the score is 0.5 everywhere; with one class, the share of that class, smoothed."""
    if len(y) == 0 or y.min() == y.max():
        share = (y.sum() + 1) / (len(y) + 2)
        return RuleModel(float(np.log(share / (1 - share))))
    rules = grow_rules(x, y)
    if not rules:
        share = y.mean()
        return RuleModel(float(np.log(share / (1 - share))))
    r = np.stack([_holds(x, c) for c in rules], axis=1).astype(np.float64)
    intercept, weights = fit_lasso(r, y, penalty)
    return RuleModel(intercept, tuple((c, float(w)) for c, w in zip(rules, weights, strict=True) if abs(w) > 1e-6))


def training_rows(docs: DataFrame, labels: DataFrame, label: str, may_learn: Column, limit: int = MOST_LABELLED, text: str = "text", doc_id: str = "doc_id") -> tuple[np.ndarray, np.ndarray]:
    """Statistics and labels of at most ``limit`` labelled documents. Rows without a label are left out; of several labels of one id the largest counts."""
    of_id = labels.filter(F.col(label).isNotNull() & F.col(doc_id).isNotNull()).groupBy(F.col(doc_id).alias("label_id")).agg(F.max(label).cast("double").alias("y"))
    chosen = of_id.filter(may_learn).orderBy(F.xxhash64("label_id"), "label_id").limit(limit)
    texts = docs.select(F.col(doc_id).alias("doc_id"), F.col(text).alias("text")).join(F.broadcast(chosen.select("label_id")), F.col("doc_id") == F.col("label_id"), "left_semi").dropDuplicates(["doc_id"])
    known = with_statistics(texts).join(F.broadcast(chosen), F.col("doc_id") == F.col("label_id")).drop("label_id").toArrow().sort_by("doc_id")
    return np.stack([known[s].to_numpy() for s in STATISTICS], axis=1), known["y"].to_numpy()


def learnable(column: str = "label_id") -> Column:
    """The rows whose labels may be learnt from: crc32 of the id as text, modulo 4, is not 2."""
    return F.crc32(F.col(column).cast("string")) % 4 != 2


def fit_quality(docs: DataFrame, labels: DataFrame, label: str = "quality") -> RuleModel:
    return fit(*training_rows(docs, labels, label, learnable()))


def score_documents(docs: DataFrame, model: RuleModel, text: str = "text", doc_id: str = "doc_id", accept: float = 0.7) -> DataFrame:
    """One row for each row of ``docs``: doc_id, score, predicted (1 from ``accept`` on). Null and empty texts are scored as zeros."""
    return with_statistics(docs, text, doc_id).select("doc_id", model.column().alias("score")).withColumn("predicted", (F.col("score") >= accept).cast("int"))


def keep_good(docs: DataFrame, model: RuleModel, text: str = "text", accept: float = 0.7) -> DataFrame:
    """The rows of ``docs`` that the model accepts, all columns kept, of any names, in one pass without a join.

    Each row is judged by its text alone, so repeated rows go or stay together; null texts are judged as empty. A model without rules, as where
    nothing was labelled, tells no text from another: all stay. An empty table stays empty.
    """
    if not model.rules:
        return docs
    kept, fields = docs.columns, ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema)
    mangled = free_names(docs, *STATISTICS)
    at = kept.index(text)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            values = np.array([statistics(t or "") for t in batch.column(at).to_pylist()], float).reshape(-1, len(STATISTICS))
            yield pa.RecordBatch.from_arrays([*batch.columns, *(pa.array(v) for v in values.T)], names=[*kept, *mangled])

    seen = map_batches(docs, run, fields + "".join(f", {m} double" for m in mangled))
    return seen.filter(model.column(mangled[0].removesuffix(STATISTICS[0])) >= accept).select(*(F.col(f"`{c}`") for c in kept))
