"""The private aggregation on small tables with known answers, and its invariants."""

import math

import pytest
from pyspark.sql import functions as F
from tests.conftest import MEDIUM, SMALL

from ownerdp import measures
from ownerdp.functions import aggregates as A
from ownerdp.functions.clamp import clamp
from ownerdp.functions.noise import EntropyNoise, KeyedNoise, NoNoise, TestNoise, draw_tag, encode_keys
from ownerdp.ledger import BudgetExceeded, PrivacyLedger
from ownerdp.operators import baselines, bounds
from ownerdp.operators.sampling import REJECTED_SAMPLERS, limit_partitions
from ownerdp.params import PrivacyParams
from ownerdp.plans.ownership import OwnedFrame
from ownerdp.plans.rewrite import partials, private_aggregate
from ownerdp.sources.tables import read_table

EXACT = NoNoise(unsafe_for_tests=True)
ALL = PrivacyParams(1.0, 0.0, 900, suppress=False)


def owned(spark, rows, schema="o long, k string, v double"):
    return OwnedFrame.of(spark.createDataFrame(rows, schema), "o")


def got(result, *names):
    return {tuple(r[k] for k in result.keys): tuple(r[n] for n in names) for r in result.df.collect()}


def test_no_noise_must_be_asked_for():
    with pytest.raises(ValueError):
        NoNoise()


def test_two_steps_by_hand(spark):
    """One owner with many orders counts as its limit, a department of one owner vanishes."""
    people = owned(spark, [(1, "a", 0.0), (2, "a", 0.0), (3, "a", 0.0), (4, "b", 0.0)])
    orders = OwnedFrame.of(spark.createDataFrame([(1, f"i{j}") for j in range(20)] + [(2, "x"), (3, "y"), (4, "z")], "o long, item string"), "o")
    joined = people.join_owner(orders)
    result = private_aggregate(joined, ["k"], [A.priv_count("n", None, 0, 5)], PrivacyParams(1.0, 0.0, 1, tau=2.0), EXACT)
    assert got(result, "n") == {("a",): (7.0,)}


def test_an_owner_in_many_keys_is_limited(spark):
    rows = [(1, f"k{i}", 1.0) for i in range(1000)] + [(2, "k1", 1.0)]
    p = partials(owned(spark, rows), ["k"], [A.priv_sum("s", "v", 0, 1)])
    for strategy in ("window", "agg"):
        kept = limit_partitions(p, "__owner", 7, TestNoise(3), ["k"], strategy)
        assert kept.filter("__owner = 1").count() == 7 and kept.filter("__owner = 2").count() == 1
    same = [sorted(r["k"] for r in limit_partitions(p, "__owner", 7, TestNoise(3), ["k"], s).collect()) for s in ("window", "agg")]
    assert same[0] == same[1]


def test_the_limit_is_uniform(spark):
    rows = [(o, f"k{i}", 1.0) for o in range(3000) for i in range(6)]
    df = spark.createDataFrame(rows, "o long, k string, v double")
    counts = {r["k"]: r["count"] for r in limit_partitions(df, "o", 2, TestNoise(5), ["k"]).groupBy("k").count().collect()}
    chi = sum((n - 1000) ** 2 / 1000 for n in counts.values())
    assert sum(counts.values()) == 6000 and chi < 20
    first = limit_partitions(df, "o", 2, TestNoise(5), ["k"], "first").groupBy("k").count().count()
    assert first == 2  # the rejected sampler never shows the other four
    assert set(REJECTED_SAMPLERS) == {"first", "systematic", "bernoulli", "replacement"}
    free = limit_partitions(df, "o", 2, TestNoise(5), ["k"], "bernoulli").groupBy("o").count().agg(F.max("count")).first()[0]
    assert free > 2  # and this one does not bound what an owner contributes
    assert limit_partitions(df, "o", 2, TestNoise(5), ["k"], "systematic").groupBy("k").count().count() < 6
    assert limit_partitions(df, "o", 2, TestNoise(5), ["k"], "replacement").groupBy("o").count().agg(F.max("count")).first()[0] <= 2


def test_special_values(spark):
    rows = [(1, "a", float("nan")), (2, "a", float("inf")), (3, "a", -math.inf), (4, "a", None), (5, "a", -0.0), (None, "a", 7.0), (6, None, 3.0)]
    result = private_aggregate(owned(spark, rows), ["k"], [A.priv_sum("s", "v", -2, 10), A.priv_count("c", "v"), A.priv_count_owners(), A.priv_avg("m", "v", -2, 10)], ALL, EXACT)
    assert got(result, "s", "c", "owners") == {("a",): (8.0, 4.0, 5.0), (None,): (3.0, 1.0, 1.0)}
    one = spark.createDataFrame([(float("nan"),)], "x double")
    assert one.select(clamp(F.col("x"), 2, 5)).first()[0] == 2.0 and one.select(clamp(F.col("x"), -5, 5)).first()[0] == 0.0


def test_every_aggregate_by_hand(spark):
    rows = [(1, "a", 1.0), (1, "a", 3.0), (2, "a", 4.0), (3, "a", 9.0)]
    make = [A.priv_sum("s", "v", 0, 8), A.priv_avg("m", "v", 0, 10), A.priv_var("q", "v", 0, 10), A.priv_stddev("d", "v", 0, 10), A.priv_count("n", None, 0, 1)]
    (values,) = got(private_aggregate(owned(spark, rows), ["k"], make, ALL, EXACT), "s", "m", "q", "d", "n").values()
    assert values == pytest.approx((4 + 4 + 8, 5.0, (4 + 16 + 81) / 3 - 25, math.sqrt(26 / 3), 3.0))
    quantiles = [A.priv_median("h", "v", 0, 16), A.priv_min("lo", "v", 0, 16), A.priv_max("hi", "v", 0, 16), A.priv_ntile("t", "v", 3, 0, 16), A.priv_quantile("q9", "v", 0.9, 0, 16, per_owner="one")]
    (values,) = got(private_aggregate(owned(spark, rows), ["k"], quantiles, ALL, EXACT), "h", "lo", "hi", "t").values()
    assert values[:3] == pytest.approx((4, 2, 9), abs=1e-4) and values[3] == pytest.approx([2, 4], abs=1e-4)


def test_empty_inputs(spark):
    none = owned(spark, [])
    assert private_aggregate(none, ["k"], [A.priv_sum("s", "v", 0, 1)], PrivacyParams(1.0, 1e-5), TestNoise(1)).df.count() == 0
    assert private_aggregate(none, [], [A.priv_sum("s", "v", 0, 1), A.priv_avg("m", "v", 0, 1)], PrivacyParams(1.0), TestNoise(1)).df.count() == 1


def test_public_domain_keeps_absent_keys(spark):
    domain = spark.createDataFrame([("a",), ("z",), (None,)], "k string")
    result = private_aggregate(owned(spark, [(1, "a", 1.0), (1, "b", 1.0), (1, "c", 1.0)]), ["k"], [A.priv_sum("s", "v", 0, 1)], PrivacyParams(1.0), EXACT, key_domain=domain)
    assert got(result, "s") == {("a",): (1.0,), ("z",): (0.0,), (None,): (0.0,)}


def test_leftovers_merge_each_owner_once(spark):
    rows = [(o, "big", 1.0) for o in range(50)] + [(o, f"rare{o}", 1.0) for o in range(40)] + [(1, "rare_x", 1.0)]
    result = private_aggregate(owned(spark, rows), ["k"], [A.priv_count_owners()], PrivacyParams(1.0, 0.0, 3, tau=10.0), EXACT, leftovers=True)
    rows = {(r["k"], r["is_leftover"]): r["owners"] for r in result.df.collect()}
    assert rows == {("big", False): 50.0, (None, True): 40.0}


def test_removing_an_owner_moves_results_within_bounds(spark):
    df = read_table(spark, SMALL, "events")
    c_u, top = 2, 50.0
    release = lambda d: private_aggregate(OwnedFrame.of(d, "user_id"), ["event_type"], [A.priv_sum("s", "value", 0, top)], PrivacyParams(1.0, 0.0, c_u, suppress=False), EXACT).df
    owners = [r[0] for r in df.select("user_id").distinct().orderBy("user_id").limit(5).collect()]
    assert measures.observed_sensitivity(df, "user_id", release, ["event_type"], ["s"], owners) <= c_u * top + 1e-9
    limited = lambda d: limit_partitions(d.groupBy("user_id", "event_type").count(), "user_id", c_u, TestNoise(0), ["event_type"])
    assert measures.observed_stability(df, "user_id", limited, owners) <= c_u
    naive = lambda d: baselines.exact_histogram(d, "event_type")
    assert measures.observed_sensitivity(df, "user_id", naive, ["event_type"], ["n"], owners) > 1  # a row-unit count moves by more than its sensitivity


def test_noise_is_laplace_and_keyed(spark):
    df = spark.range(40_000)
    noise = TestNoise(9)
    x = df.select(noise.laplace(3.0, "t", [F.col("id")]).alias("x"))
    mean, middle, tail = x.agg(F.avg("x"), F.percentile(F.abs("x"), F.lit(0.5)), F.avg((F.abs("x") > 9).cast("double"))).first()
    assert abs(mean) < 0.1 and middle == pytest.approx(3 * math.log(2), rel=0.04) and tail == pytest.approx(math.exp(-3), rel=0.1)
    secret = KeyedNoise("s")
    a, b = (df.limit(50).select(secret.laplace(1.0, "t", [F.col("id")])).collect() for _ in range(2))
    assert a == b and KeyedNoise().secret != KeyedNoise().secret
    assert noise.draw(2.0, "m|V1:5") == pytest.approx(spark.range(5, 6).select(noise.laplace(2.0, "m", [F.col("id").cast("string")])).first()[0])


def test_no_two_draws_are_shared(spark):
    """Names that look like parts of others, the hidden count and a second query with the same noise object: each has noise of its own."""
    rows = [(o, "a", 1.0) for o in range(200)]
    names = ["v", "v_sum", "v_count", "owners", "4:v", "v/sum"]
    aggs = [A.priv_avg("v", "v", 0, 4), *(A.priv_sum(n, "v", 0, 4) for n in names[1:])]
    for noise in (TestNoise(3), KeyedNoise(), EntropyNoise()):
        (row,) = private_aggregate(owned(spark, rows), ["k"], aggs, PrivacyParams(7.0, 0.0, 1, suppress=False), noise).df.collect()
        draws = [round(row[n] - 200, 6) for n in names[1:]]
        assert len(set(draws)) == len(draws)
    tags = {draw_tag(n, p) for n in ("", "a", "a/sum", "1:a") for p in ("value", "sum", "sum/value", "owners")}
    assert len(tags) == 16
    with pytest.raises(ValueError):
        A.priv_sum("", "v", 0, 1)
    noise = KeyedNoise("fixed")
    free = PrivacyParams(1.0, 0.0, 1, suppress=False)
    once, twice = (private_aggregate(owned(spark, rows), ["k"], [A.priv_count_owners()], free, noise).df.first()["owners"] for _ in range(2))
    assert once != twice  # nothing cancels between two queries
    again = [private_aggregate(owned(spark, rows), ["k"], [A.priv_count_owners()], free, noise, label="batch 7").df.first()["owners"] for _ in range(2)]
    assert again[0] == again[1] != once
    result = private_aggregate(owned(spark, rows), ["k"], [A.priv_count_owners()], free, noise)
    assert result.df.collect() == result.df.collect()
    # the hidden count is another draw than the released one: the key passes by the hidden one alone
    released, hidden = set(), set()
    for seed in range(14):
        shown = private_aggregate(owned(spark, rows), ["k"], [A.priv_count_owners()], PrivacyParams(0.2, 0.0, 1, tau=200.0), TestNoise(seed)).df.collect()
        free_run = private_aggregate(owned(spark, rows), ["k"], [A.priv_count_owners()], PrivacyParams(0.2, 0.0, 1, tau=-1e9), TestNoise(seed)).df.first()["owners"]
        (released if free_run >= 200 else hidden).add(bool(shown))
    assert released == hidden == {True, False}


def test_key_encoding_tells_lists_apart(spark):
    rows = spark.createDataFrame([("a", "bc"), ("ab", "c"), (None, "NULL"), ("NULL", None), ("N", "N"), ("", "")], "x string, y string")
    assert rows.select(encode_keys([F.col("x"), F.col("y")]).alias("e")).distinct().count() == 6


def test_entropy_noise_is_written_once(spark):
    result = private_aggregate(OwnedFrame.of(read_table(spark, SMALL, "orders"), "o_custkey"), ["o_orderpriority"], [A.priv_count("n", None, 0, 5)], PrivacyParams(6.0, 1e-5, 5), EntropyNoise())
    assert sorted(result.df.collect()) == sorted(result.df.collect()) and "__nonce" not in result.df.columns


def test_intervals_and_rounding(spark):
    rows = [(o, "a", 1.0) for o in range(100)]
    result = private_aggregate(owned(spark, rows), ["k"], [A.priv_count_owners("n"), A.priv_avg("m", "v", 0, 2)], PrivacyParams(2.0, 0.0, 1, suppress=False), TestNoise(4), intervals=0.99, rounded=True)
    (row,) = result.df.collect()
    assert row["n_lo"] <= 100 <= row["n_hi"] and row["n"] % 1 == 0 and row["m_lo"] <= 1 <= row["m_hi"]
    widths = []
    for is_rounded in (False, True):  # the scale is 2 / 3, so the rounded one is a step of 1 wider
        r = private_aggregate(owned(spark, rows), ["k"], [A.priv_count_owners("n")], PrivacyParams(1.5, 0.0, 1, suppress=False), TestNoise(4), intervals=0.5, rounded=is_rounded).df.first()
        widths.append(r["n_hi"] - r["n_lo"])
    assert widths == pytest.approx([2 * math.log(2) / 1.5, 2 * math.log(2) / 1.5 + 1.0])


def test_automatic_limits(spark):
    assert [bounds.codes("signed", 3), bounds.codes("unsigned", 2)] == [[-3, -2, -1, 0, 1, 2, 3], [0, 1, 2]]
    x = spark.createDataFrame([(v,) for v in (0.0, 1.0, 2.0, 3.0, 4.0, 1024.0, 1025.0, 2.0**40, -3.0, float("nan"), float("inf"), 0.3)], "x double")
    assert [r[0] for r in x.select(bounds.bin_of(F.col("x"), "signed")).collect()] == [0, 1, 2, 3, 3, 11, 12, 41, -3, 0, 64, 1]
    for name, want in (("events", (2048.0, 4096.0)), ("orders", (2.0**19, 2.0**23)), ("balances", (-1024.0, 16384.0))):
        from ownerdp.workloads.queries import _owner_sums

        row = bounds.approx_bounds(_owner_sums(spark, MEDIUM, name), [], "p", 1.0, EXACT, kind="signed" if name == "balances" else "unsigned").first()
        assert (row["lower"], row["upper"]) == want
    failed = private_aggregate(OwnedFrame.of(read_table(spark, MEDIUM, "events"), "user_id"), [], [A.priv_sum("s", "value")], PrivacyParams(0.1), EXACT).df.first()
    assert failed["s"] is None
    found = private_aggregate(OwnedFrame.of(read_table(spark, MEDIUM, "events"), "user_id"), [], [A.priv_sum("s", "value")], PrivacyParams(2.0), EXACT).df.first()
    truth = read_table(spark, MEDIUM, "events").agg(F.sum("value")).first()[0]
    assert found["s"] == pytest.approx(truth, rel=0.05) and 0 <= found["s_outside"] < 0.2


def test_results_do_not_depend_on_layout(spark):
    df = read_table(spark, SMALL, "orders")
    run = lambda d, s="combine": sorted(private_aggregate(OwnedFrame.of(d, "o_custkey"), ["o_orderpriority"], [A.priv_count("n", None, 0, 5)], PrivacyParams(6.0, 1e-5, 3), TestNoise(1), strategy=s).df.collect())
    assert run(df) == run(df.repartition(7).orderBy(F.desc("o_totalprice"))) == run(df, "copartition")


def test_plan_limits_before_the_shuffle(spark):
    df = private_aggregate(OwnedFrame.of(read_table(spark, SMALL, "orders"), "o_custkey"), ["o_orderpriority"], [A.priv_count("n", None, 0, 5)], PrivacyParams(6.0, 1e-5, 3), TestNoise(1)).df
    plan = df._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning") == 3 and plan.count("WindowGroupLimit") == 2
    assert "ReadSchema: struct<o_custkey:bigint,o_orderpriority:string>" in plan


def test_single_owner_keys_are_hidden_as_often_as_promised(spark):
    from ownerdp.workloads.queries import QUERIES

    for r in QUERIES["suppression_runs"](spark, SMALL).collect():
        assert r["suppression_rate"] == pytest.approx(r["predicted"], abs=4 * math.sqrt(r["predicted"] * (1 - r["predicted"]) / 1_000_000) + 1e-6)
    for r in QUERIES["coverage_runs"](spark, SMALL).collect():
        assert r["coverage"] == pytest.approx(r["level"], abs=0.002)


def test_median_error_follows_the_formula(spark):
    from ownerdp.workloads.queries import QUERIES

    for r in QUERIES["median_error_runs"](spark, MEDIUM).collect():
        assert r["median_relative_error"] == pytest.approx(r["predicted"], rel=0.01)


def test_ledger(spark, tmp_path):
    ledger = PrivacyLedger(spark, str(tmp_path / "ledger"), eps_limit=1.0, delta_limit=1e-5)
    ledger.charge("orders", "o_custkey", 0.6, 1e-6, "q", "p1")
    with pytest.raises(BudgetExceeded):
        ledger.charge("orders", "o_custkey", 0.5, 0.0)
    ledger.charge("events", "user_id", 0.5, 0.0)
    assert ledger.spent("orders", "o_custkey") == (0.6, 1e-6) and ledger.known("p1") and not ledger.known("p2")
    a, b = (PrivacyLedger.plan_hash(read_table(spark, SMALL, "orders").filter("o_totalprice > 5")) for _ in range(2))
    assert a == b
