"""Which method is how far off over many runs, and which mechanisms the search for violations accepts."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ownerdp import measures
from ownerdp.functions import aggregates as A
from ownerdp.functions.noise import RunNoise
from ownerdp.operators import baselines, quantile
from ownerdp.operators.threshold import owner_threshold
from ownerdp.params import PrivacyParams
from ownerdp.plans.rewrite import OWNERS, cross_owner, partials
from ownerdp.sources.tables import materialise
from ownerdp.stochastic import mechanisms as M
from ownerdp.stochastic.databases import halton_databases
from ownerdp.stochastic.search import find_violation
from ownerdp.workloads import tables as T
from ownerdp.workloads.queries import query
from ownerdp.workloads.spec import SEED, Workload, rounded, sql_threshold

EPS = 0.1
RUNS = 1_000_000
#: Runs of medians, which search or draw anew each time, and of the row-level engine that the published comparison ran so often.
FEW_RUNS = 10_000
#: Noisy rows that a measure over runs makes at most; queries of many keys have fewer runs, as their result says.
MOST_ROWS = 100_000_000
_TOP = 105_000.0  # above every price, as the published limits are

# One record of the first query, by three engines ------------------------------------------------------------------------------


def _record(spark: SparkSession, d: str):
    return T.LINES_BY_SUPPLIER[0](spark, d).filter("l_returnflag = 'A' AND l_linestatus = 'F'")


def _error(runs: DataFrame, value, exact: float) -> DataFrame:
    return measures.median_relative_error(runs.select(value.alias("noisy"), F.lit(float(exact)).alias("exact")))


def _ours(owned, agg: A.Agg, exact: float, runs: int) -> DataFrame:
    """The shipped partials, sums and release of one aggregate over one record: no threshold, one partition, all of the budget."""
    noise = RunNoise(SEED)
    bounded = partials(owned, [], [agg])
    if isinstance(agg, A.Quantile):
        cells = quantile.leaf_counts(bounded, [], agg.p, agg.lo, agg.hi, agg.depth).toPandas()
        at, counts, depth, lo, width = cells["cell"].to_numpy(), cells["n"].to_numpy(), agg.depth, agg.lo, agg.hi - agg.lo

        def search(rows: pd.Series) -> pd.Series:
            one = lambda run: quantile.search(at, counts, agg.q[0], depth, EPS, lambda scale, what: noise.draw(scale, f"{run}|{what}"))
            return rows.map(lambda run: lo + width * one(run) / (1 << depth))

        spark = bounded.sparkSession
        slots = spark.range(0, runs, 1, 4 * spark.sparkContext.defaultParallelism).withColumnRenamed("id", "run")
        return _error(slots, F.pandas_udf(search, "double")("run"), exact)
    totals = cross_owner(bounded, [], [agg]).drop(OWNERS)
    return _error(measures.repeated(totals, runs), agg.release(A.Context(noise, [F.col("run")], EPS), agg.lo, agg.hi), exact)


def _by_rows(df: DataFrame, kind: str, col: str | None, sensitivity: float, exact: float, runs: int) -> DataFrame:
    noise = RunNoise(SEED + 1)
    if kind == "median":
        cells = df.filter(F.col(col).isNotNull()).groupBy(baselines.median_cells(F.col(col), sensitivity).alias("cell")).agg(F.count(F.lit(1)).alias("n")).toPandas()
        u = np.random.default_rng(SEED).random(runs)
        values = baselines.drawn_median(cells["cell"].to_numpy(), cells["n"].to_numpy(), u, sensitivity, EPS)
        return _error(df.sparkSession.createDataFrame(pd.DataFrame({"value": values})), F.col("value"), exact)
    totals = baselines.row_unit_totals(df, [], kind, col, sensitivity)
    return _error(measures.repeated(totals, runs), baselines.row_unit_value(kind, [F.col("run")], sensitivity, EPS, noise), exact)


def _by_joins(df: DataFrame, sensitivity: float, exact: float, delta: float) -> DataFrame:
    totals = df.agg(F.count(F.lit(1)).cast("double").alias("s"))
    noise = RunNoise(SEED + 2).laplace(baselines.join_scale(0.0, EPS, [sensitivity], delta), "row_join", [F.col("run")])
    return _error(measures.repeated(totals, RUNS), F.col("s") + noise, exact)


JOIN_DELTA = 1e-6

_Q1_COUNTS = "SELECT count(*) AS n, max(c) AS most, count(DISTINCT o) AS owners FROM (SELECT l_suppkey AS o, count(*) OVER (PARTITION BY l_suppkey) AS c FROM lineitem WHERE l_returnflag = 'A' AND l_linestatus = 'F' AND l_suppkey IS NOT NULL)"
_SMOOTH = f"(SELECT max(exp(-{float(EPS / (2 * np.log(2 / JOIN_DELTA)))!r} * k) * (%s + k)) FROM range(0, {int(np.ceil(2 * np.log(2 / JOIN_DELTA) / EPS)) + 1}) AS t(k))"


@query("q1_predicted", f"""WITH c AS ({_Q1_COUNTS}) SELECT engine, "limit", round(predicted, 6) AS predicted FROM (
SELECT 'owner level' AS engine, most::DOUBLE AS "limit", ln(2) * most / {EPS} / n AS predicted FROM c
UNION ALL SELECT 'row level', most::DOUBLE, ln(2) * most / {EPS} / n FROM c
UNION ALL SELECT 'row level, joins', most::DOUBLE, ln(2) * 2 * {_SMOOTH % 'most'} / {EPS} / n FROM c
UNION ALL SELECT 'owner level', 1.0, (n - owners) / n FROM c
UNION ALL SELECT 'row level', 1.0, ln(2) / {EPS} / n FROM c
UNION ALL SELECT 'row level, joins', 1.0, ln(2) * 2 * {_SMOOTH % '1'} / {EPS} / n FROM c)""")
def _(spark, d):
    """What the formulas say of the count's median relative error: that of the noise, or for owners cut to one row each the rows that are lost."""
    n, most, owners = _record(spark, d).unowned().groupBy("o").agg(F.count(F.lit(1)).alias("n")).agg(F.sum("n"), F.max("n"), F.count(F.lit(1))).first()
    rows = []
    for limit in (float(most), 1.0):
        rows.append(("owner level", limit, float(np.log(2)) * most / EPS / n if limit > 1 else (n - owners) / n))
        rows.append(("row level", limit, float(np.log(2)) * limit / EPS / n))
        rows.append(("row level, joins", limit, float(np.log(2)) * baselines.join_scale(0.0, EPS, [limit], JOIN_DELTA) / n))
    return rounded(spark.createDataFrame(rows, "engine string, `limit` double, predicted double"), 6)


@query("q1_comparison")
def _(spark, d):
    """The median relative error of count, average and median of one record over runs of each engine's own code, all with the limit that holds for
    the data, and of the count with the limit 1: there the owner-level result loses most rows, while row-level ones look precise and protect nobody.

    For averages and medians the row-level engine gets one row of each owner, its mean or median, so that its limit is one of owners as well. The engine that smooths join frequencies adds noise for twice the smooth sensitivity, so at least twice the scale; averages and medians it
    does not know.
    """
    owned = _record(spark, d)
    rows = owned.unowned()
    each = rows.groupBy("o").agg(F.count(F.lit(1)).alias("n"), F.avg("price").alias("mean"), F.percentile("price", F.lit(0.5)).alias("middle"))
    n, most, mean, middle = each.agg(F.sum("n"), F.max("n"), F.avg("mean"), F.percentile("middle", F.lit(0.5))).first()
    count = lambda limit: A.priv_count("n", None, 0.0, limit)
    cases = [
        ("count", "owner level", float(most), RUNS, _ours(owned, count(float(most)), n, RUNS)),
        ("count", "row level", float(most), FEW_RUNS, _by_rows(rows, "count", None, float(most), n, FEW_RUNS)),
        ("count", "row level, joins", float(most), RUNS, _by_joins(rows, float(most), n, JOIN_DELTA)),
        ("average", "owner level", _TOP, RUNS, _ours(owned, A.priv_avg("m", "price", 0.0, _TOP), mean, RUNS)),
        ("average", "row level", _TOP, FEW_RUNS, _by_rows(each, "average", "mean", _TOP, mean, FEW_RUNS)),
        ("median", "owner level", _TOP, FEW_RUNS, _ours(owned, A.priv_median("m", "price", 0.0, _TOP), middle, FEW_RUNS)),
        ("median", "row level", _TOP, FEW_RUNS, _by_rows(each, "median", "middle", _TOP, middle, FEW_RUNS)),
        ("count", "owner level", 1.0, RUNS, _ours(owned, count(1.0), n, RUNS)),
        ("count", "row level", 1.0, FEW_RUNS, _by_rows(rows, "count", None, 1.0, n, FEW_RUNS)),
        ("count", "row level, joins", 1.0, RUNS, _by_joins(rows, 1.0, n, JOIN_DELTA)),
    ]
    out = None
    for aggregate, engine, limit, runs, error in cases:
        row = error.select(F.lit(aggregate).alias("aggregate"), F.lit(engine).alias("engine"), F.lit(limit).alias("limit"), F.lit(runs).alias("runs"), "median_relative_error")
        out = row if out is None else out.unionByName(row)
    return rounded(out, 6)


# The join queries over runs ------------------------------------------------------------------------------------------------------

#: query: the relation, its keys, the rows of an owner that count in a group, the groups of an owner, the table of owners
JOIN_QUERIES = {
    "q4": (T.late_orders(None), ["priority"], 5, 5, "customer"), "q13": (T.ORDER_COUNTS, ["n_orders"], 1, 1, "customer"),
    "q16": (T.SUPPLIED_PARTS, ["p_brand", "p_type", "p_size"], 1, 5, "supplier"), "q21": (T.WAITING, ["supplier"], 1, 1, "supplier"),
}


def _exact_groups(spark: SparkSession, d: str, name: str) -> tuple[DataFrame, dict]:
    """(owners, exact) of each group before any sampling, and the parameters: the budget is halved between the count and the hidden owner count."""
    source, keys, most, c_u, table = JOIN_QUERIES[name]
    params = Workload(*source, keys, [], PrivacyParams(EPS, 0.0, c_u), owners_of=table).params_for(spark, d)
    per_owner = source[0](spark, d).unowned().groupBy("o", *keys).agg(F.count(F.lit(1)).alias("n"))
    groups = per_owner.groupBy(*keys).agg(F.count(F.lit(1)).cast("double").alias("owners"), F.sum(F.least("n", F.lit(most))).cast("double").alias("exact"))
    each = EPS / 2 / c_u
    return groups, {"delta": params.delta, "tau": owner_threshold(EPS / 2, params.delta, c_u), "noise_scale": most / each, "owner_scale": 1 / each}


def _expected_sql(name: str) -> str:
    (_, sql), keys, _, c_u, table = JOIN_QUERIES[name]
    tau, scale = sql_threshold(EPS / 2, EPS, c_u, table), 2 * c_u / EPS
    x = f"((SELECT * FROM tau) - owners) / {scale!r}"
    return f"""WITH tau AS (SELECT {tau}), g AS (SELECT {', '.join(keys)}, count(DISTINCT o) AS owners FROM ({sql}) GROUP BY {', '.join(keys)})
SELECT round((SELECT exp(-{EPS} * pow(ln(count(*)::DOUBLE), 2)) FROM {table}), 6) AS delta, round((SELECT * FROM tau), 6) AS tau, count(*) AS keys,
round(avg(CASE WHEN {x} >= 0 THEN 1 - 0.5 * exp(-({x})) ELSE 0.5 * exp({x}) END), 6) AS expected_suppression FROM g"""


def _expected(name: str):
    def run(spark: SparkSession, d: str) -> DataFrame:
        groups, p = _exact_groups(spark, d, name)
        hidden = measures.expected_suppression(F.col("owners"), F.lit(p["tau"]), F.lit(p["owner_scale"]))
        return rounded(groups.agg(F.count(F.lit(1)).alias("keys"), F.avg(hidden).alias("expected_suppression")).select(F.lit(p["delta"]).alias("delta"), F.lit(p["tau"]).alias("tau"), "keys", "expected_suppression"), 6)

    return run


for _name in JOIN_QUERIES:
    query(f"tjoin_{_name}", _expected_sql(_name))(_expected(_name))


@query("tjoin_runs")
def _(spark, d):
    """Median relative error over the rows that are returned, and the share of rows that are not, over runs of each join query."""
    out = None
    for name in JOIN_QUERIES:
        groups, p = _exact_groups(spark, d, name)
        rows = materialise(groups, "tjoin-groups")
        runs = max(1, min(RUNS, MOST_ROWS // max(1, rows.count())))
        noise, at = RunNoise(SEED), [F.col("run"), *(x for key in JOIN_QUERIES[name][1] for x in (F.isnull(key), F.col(key)))]
        drawn = measures.repeated(rows, runs).select(
            "exact", (F.col("owners") + noise.laplace(p["owner_scale"], f"{name}|owners", at) >= p["tau"]).alias("shown"), (F.col("exact") + noise.laplace(p["noise_scale"], name, at)).alias("noisy")
        )
        error = F.abs(F.col("noisy") - F.col("exact")) / F.col("exact")
        row = drawn.agg(F.percentile_approx(F.when(F.col("shown"), error), 0.5, 20_000).alias("median_relative_error"), F.avg(1 - F.col("shown").cast("double")).alias("suppression_rate"))
        row = row.select(F.lit(name).alias("query"), F.lit(runs).alias("runs"), F.lit(p["delta"]).alias("delta"), F.lit(p["tau"]).alias("tau"), "median_relative_error", "suppression_rate")
        out = row if out is None else out.unionByName(row)
    return rounded(out, 6)


# The search for violations -------------------------------------------------------------------------------------------------------

_EPS, _DELTA = 1.0, 0.05
_VALUE = {"lo": -0.5, "hi": 0.5}
#: mechanism: whether it is to be found, the mechanism, Halton databases, runs of each part, the grid
TRIED = {
    "owners": (False, M.Shipped(A.priv_count_owners("n"), _EPS), 256, 6000, (-5.0, 8.0)),
    "count": (False, M.Shipped(A.priv_count("n", "x", 0.0, 1.0), _EPS), 256, 6000, (-5.0, 8.0)),
    "sum": (False, M.Shipped(A.priv_sum("n", "x", **_VALUE), _EPS), 256, 6000, (-3.0, 3.0)),
    "average": (False, M.Shipped(A.priv_avg("n", "x", **_VALUE), _EPS), 256, 6000, (-0.5, 0.5)),
    "variance": (False, M.Shipped(A.priv_var("n", "x", **_VALUE), _EPS), 256, 6000, (0.0, 0.25)),
    "deviation": (False, M.Shipped(A.priv_stddev("n", "x", **_VALUE), _EPS), 256, 6000, (0.0, 0.5)),
    "median": (False, M.ShippedQuantile(A.priv_median("n", "x", **_VALUE, depth=6), _EPS), 16, 1500, (-0.5, 0.5)),
    "limits": (False, M.ShippedLimits(_EPS), 256, 500, (-264.0, 264.0)),
    "threshold": (False, M.ShippedThreshold(_EPS, _DELTA), 256, 6000, (-5.0, 12.0)),
    "average, exact count, wide noise": (False, M.accurate_count_avg(_EPS, -0.5, 0.5, "range"), 256, 6000, (-0.5, 0.5)),
    "average, exact count, narrow noise": (True, M.accurate_count_avg(_EPS, -0.5, 0.5, "magnitude"), 256, 6000, (-0.5, 0.5)),
    "sum, narrow noise": (True, M.narrow_sum(_EPS, -0.5, 0.5), 256, 6000, (-3.0, 3.0)),
}


@query("tester_verdicts")
def _(spark, d):
    """(mechanism, databases, pairs, violated): every primitive as it is shipped, and versions with defects, on the parts of Halton databases of two numbers."""
    rows = []
    for name, (_, mechanism, n, runs, (low, high)) in TRIED.items():
        delta = _DELTA if name == "threshold" else 0.0
        found = find_violation(spark, mechanism, halton_databases(spark, n, 2, 0.5), _EPS, delta, m=runs, buckets=20, batch=256, low=low, high=high, noise=RunNoise(SEED))
        rows.append((name, n, found.pairs_tried, found.violated))
    return spark.createDataFrame(rows, "mechanism string, databases int, pairs int, violated boolean")
