"""The search for violations: its inputs, and that it tells shipped mechanisms from broken ones."""

import math

import pytest
from pyspark.sql import functions as F

from ownerdp.functions import aggregates as A
from ownerdp.functions.noise import TestNoise
from ownerdp.params import PrivacyParams
from ownerdp.plans.ownership import OwnedFrame
from ownerdp.plans.rewrite import private_aggregate
from ownerdp.stochastic import mechanisms as M
from ownerdp.stochastic.databases import adjacent_pairs, halton_databases, primes, sub_databases
from ownerdp.stochastic.search import Verdict, compare_histograms, failing_buckets, find_violation, find_violation_owner, sample_outputs

RUNS = 60_000
REGRESSION = ([-0.375, -0.055, 0.3], [-0.375, -0.055])


def pair(spark, larger=REGRESSION[0], smaller=REGRESSION[1]):
    return spark.createDataFrame([(0, larger, smaller)], "pair int, larger array<double>, smaller array<double>")


def test_points_fill_the_cube(spark):
    assert primes(4) == [2, 3, 5, 7]
    rows = [r["rows"] for r in halton_databases(spark, 8, 2, 1.0).orderBy("db_id").collect()]
    assert [(x + 1) / 2 for x, _ in rows] == pytest.approx([1 / 2, 1 / 4, 3 / 4, 1 / 8, 5 / 8, 3 / 8, 7 / 8, 1 / 16])
    assert [(y + 1) / 2 for _, y in rows[:4]] == pytest.approx([1 / 3, 2 / 3, 1 / 9, 4 / 9])


def test_graph_of_parts(spark):
    dbs = spark.createDataFrame([(1, [1.0, 2.0, 3.0])], "db_id long, rows array<double>")
    assert sub_databases(dbs).count() == 8 and adjacent_pairs(dbs).count() == 12
    parts = {r["mask"]: r["rows"] for r in sub_databases(dbs).collect()}
    assert parts[5] == [1.0, 3.0] and parts[0] == []


@pytest.mark.parametrize(("mechanism", "violates"), [(M.accurate_count_avg(1.0, -0.5, 0.5, "magnitude"), True), (M.accurate_count_avg(1.0, -0.5, 0.5, "range"), False), (M.Shipped(A.priv_avg("n", "x", -0.5, 0.5), 1.0), False)])
def test_noisy_average_regression(spark, mechanism, violates):
    samples = sample_outputs(pair(spark), mechanism, RUNS)
    found = failing_buckets(samples, RUNS, 1.0, low=-0.5, high=0.5, confidence=3.0)
    assert any(n for _, _, n in found) == violates


def test_small_budgets_break_the_exact_count_even_with_the_wide_scale(spark):
    """The exact count changes the scale of the noise, which add-or-remove neighbours see below eps of about 0.62."""
    samples = sample_outputs(pair(spark, [0.0, 0.0], [0.0]), M.accurate_count_avg(0.3, -0.5, 0.5, "range"), RUNS)
    assert any(n for _, _, n in failing_buckets(samples, RUNS, 0.3, low=-0.5, high=0.5, confidence=3.0))


def shipped(eps):
    ends = {"lo": -0.5, "hi": 0.5}
    return [M.Shipped(a, eps) for a in (A.priv_count_owners("n"), A.priv_sum("n", "x", **ends), A.priv_avg("n", "x", **ends), A.priv_var("n", "x", **ends), A.priv_stddev("n", "x", **ends))]


@pytest.mark.parametrize("eps", [1.0, math.log(3)])
def test_shipped_primitives_pass(spark, eps):
    dbs = halton_databases(spark, 3, 2, 0.5)
    for mechanism in shipped(eps):
        assert find_violation(spark, mechanism, dbs, eps, m=20_000, buckets=20) == Verdict(False, pairs_tried=12)


def test_a_fault_in_a_shipped_aggregate_is_found(spark, monkeypatch):
    """The tester runs the library's own code: halving the scale of its sums, or clamping without lower limits, must show."""
    dbs = spark.createDataFrame([(1, [0.5, 0.4]), (2, [-0.5, 0.1])], "db_id long, rows array<double>")
    mechanism = M.Shipped(A.priv_sum("n", "x", -0.5, 0.5), 1.0)
    assert not find_violation(spark, mechanism, dbs, 1.0, m=20_000, buckets=20, low=-3.0, high=3.0).violated
    monkeypatch.setattr(A.Sum, "scale", lambda self, eps, lo, hi: max(abs(lo), abs(hi)) / (2 * eps))
    assert find_violation(spark, mechanism, dbs, 1.0, m=20_000, buckets=20, low=-3.0, high=3.0).violated


def test_search_stops_at_the_first_violation(spark):
    dbs = spark.createDataFrame([(1, REGRESSION[0]), (2, [0.1, 0.2, 0.3])], "db_id long, rows array<double>")
    mechanism = M.accurate_count_avg(1.0, -0.5, 0.5, "magnitude")
    by_database = find_violation(spark, mechanism, dbs, 1.0, m=RUNS, low=-0.5, high=0.5, order="dfs", batch=1)
    by_level = find_violation(spark, mechanism, dbs, 1.0, m=RUNS, low=-0.5, high=0.5, order="bfs")
    assert by_database.violated and by_database.failing and by_database.pairs_tried == 12
    assert by_level.violated and by_level.pairs_tried in (6, 18, 24) and len(by_level.pair[0]) == len(by_level.pair[1]) + 1
    assert find_violation(spark, mechanism, dbs.limit(0), 1.0) == Verdict(False)


def test_whole_releases_with_and_without_an_owner(spark):
    rows = [(1, "a", 40.0), *((o, "a", 1.0) for o in range(2, 9))]
    df = spark.createDataFrame(rows, "o long, k string, v double")
    private = lambda data, noise: private_aggregate(OwnedFrame.of(data, "o"), [], [A.priv_sum("s", "v", 0, 1)], PrivacyParams(0.5), noise).df
    naive = lambda data, noise: data.agg((F.sum("v") + noise.laplace(2.0, "s", [])).alias("s"))
    assert not find_violation_owner(df, "o", private, "s", [1], 0.5, m=12, buckets=4).violated
    found = find_violation_owner(df, "o", naive, "s", [1], 0.5, m=12, buckets=4)
    assert found.violated and found.pair == (1,)


def test_unsafe_clamp_shows_its_owner(spark):
    with_nan = pair(spark, [0.1, float("nan")], [0.1])
    bad = failing_buckets(sample_outputs(with_nan, M.clamp_unsafe(1.0, -0.5, 0.5), 5000), 5000, 1.0)
    good = failing_buckets(sample_outputs(with_nan, M.Shipped(A.priv_sum("n", "x", -0.5, 0.5), 1.0), 5000), 5000, 1.0, confidence=3.0)
    assert any(n for _, _, n in bad) and not any(n for _, _, n in good)


def test_rounding_before_the_threshold_lets_too_much_pass(spark):
    assert M.passes_rounded(38.1, 39, 4) and not 38.1 >= 39
    rows = pair(spark, [0.0], [])
    eps, tau = 1.0, 5.5
    passed = {r: sample_outputs(rows, M.threshold_count(eps, tau, r), RUNS, TestNoise(2)).filter("side = 0").agg(F.avg((F.col("value") >= 0).cast("double"))).first()[0] for r in (True, False)}
    assert passed[False] == pytest.approx(M.expected_pass(1, tau, eps), rel=0.2) and passed[True] > 1.3 * passed[False]


def test_tolerance_and_confidence(spark):
    samples = spark.createDataFrame([(0, 0, float(i % 2)) for i in range(1000)] + [(0, 1, 0.0) for _ in range(1000)], "pair int, side int, value double")
    strict = {r["side"]: r["failing"] for r in compare_histograms(samples, 1000, 0.0, buckets=2, low=0.0, high=1.0).collect()}
    assert strict == {0: 1, 1: 1}
    loose = {r["side"]: r["failing"] for r in compare_histograms(samples, 1000, 0.0, delta=0.6, buckets=2, low=0.0, high=1.0).collect()}
    assert loose == {0: 0, 1: 0}
