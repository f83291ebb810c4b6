"""All queries of the library on the given tables, with SQL for those that another engine can answer as well."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ownerdp import measures
from ownerdp.functions import aggregates as A
from ownerdp.functions.clamp import safe_divide
from ownerdp.functions.noise import NoNoise, RunNoise, TestNoise
from ownerdp.operators import baselines, bounds
from ownerdp.operators.sampling import limit_partitions
from ownerdp.operators.threshold import owner_threshold, single_owner_suppression, suppress_rare_keys
from ownerdp.params import PrivacyParams, error_vs_aggs, laplace_median_error
from ownerdp.plans.rewrite import private_aggregate
from ownerdp.sources.catalog import OwnerCatalog, lineitem_by_customer
from ownerdp.sources.tables import materialise, read_table, shared_dir
from ownerdp.stochastic.databases import adjacent_pairs, halton_databases
from ownerdp.workloads import tables as T
from ownerdp.workloads.spec import PLACES, SEED, Release, Workload, rounded, sql_laplace, sql_message

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def _exact() -> NoNoise:
    return NoNoise(unsafe_for_tests=True, seed=SEED)


def _noise() -> TestNoise:
    return TestNoise(SEED)


def _add(name: str, workload: Workload) -> None:
    QUERIES[name] = workload.run
    ORACLES[name] = workload.oracle()


def query(name: str, sql: str | None = None):
    def keep(function: Query) -> Query:
        QUERIES[name] = function
        if sql is not None:
            ORACLES[name] = sql
        return function

    return keep


def _r(x: str, name: str | None = None) -> str:
    return f"round({x}, {PLACES})" + (f" AS {name}" if name else "")


# Private aggregates, one by one -----------------------------------------------------------------------------------------

_P = PrivacyParams(eps=4.0, delta=1e-5, c_u=5)
_BY_PRIORITY = dict(source=T.ORDERS[0], sql=T.ORDERS[1], keys=["priority"])
for _kind, _release in {
    "count_owners": Release("owners", "owners"), "count": Release("count", "n", "price"), "count_rows": Release("count", "n", None, 0.0, 5.0), "sum": Release("sum", "total", "price", 0.0, 1e6),
    "avg": Release("avg", "mean", "price", 0.0, 5e5), "var": Release("var", "variance", "price", 0.0, 5e5), "stddev": Release("stddev", "deviation", "price", 0.0, 5e5),
}.items():
    _add(f"p_{_kind}", Workload(releases=[_release], params=_P, **_BY_PRIORITY))
_add("p_multi", Workload(releases=[Release("owners", "owners"), Release("count", "n", None, 0.0, 5.0), Release("sum", "total", "price", 0.0, 1e6)], params=_P.with_(eps=9.0), **_BY_PRIORITY))
_add("p_global", Workload(T.ORDERS[0], T.ORDERS[1], [], [Release("count", "n", None, 0.0, 25.0), Release("sum", "total", "price", 0.0, 5e6)], PrivacyParams(1.0)))
_add("p_two_keys", Workload(T.ORDERS[0], T.ORDERS[1], ["priority", "status"], [Release("count", "n", None, 0.0, 3.0)], _P.with_(c_u=8)))
_add("intervals", Workload(releases=[Release("count", "n", None, 0.0, 5.0), Release("sum", "total", "price", 0.0, 1e6)], params=_P.with_(eps=6.0), intervals=0.95, **_BY_PRIORITY))
_add("leftovers", Workload(T.ORDERS[0], T.ORDERS[1], ["month"], [Release("count", "n", None, 0.0, 2.0)], PrivacyParams(8.0, 1e-5, 5), leftovers=True))
_add("public_domain", Workload(
    T.ORDERS[0], T.ORDERS[1], ["priority"], [Release("count", "n", None, 0.0, 5.0)], PrivacyParams(1.0, 0.0, 3),
    domain="SELECT '1-URGENT' AS priority UNION ALL SELECT '5-LOW' UNION ALL SELECT '9-NONE'",
))
_add("rare_month", Workload(T.ORDERS[0], T.ORDERS[1], ["month"], [Release("owners", "owners")], PrivacyParams(4.0, 1e-5, 10)))
_add("rare_month_one_partition", Workload(T.ORDERS[0], T.ORDERS[1], ["month"], [Release("owners", "owners")], PrivacyParams(4.0, 1e-5, 1)))
_add("flagship", Workload(T.ORDERS[0], T.ORDERS[1], ["priority"], [Release("count", "n", None, 0.0, 5.0), Release("sum", "total", "price", 0.0, 1e6)], PrivacyParams(6.0, 1e-5, 5)))

# the experiments: count, average, with a wrong limit; with and without noise
_Q1 = dict(source=T.ONE_RECORD[0], sql=T.ONE_RECORD[1], keys=["l_returnflag", "l_linestatus"])
_ONE = PrivacyParams(0.1, 0.0, 1, suppress=False)
_SIX = PrivacyParams(0.1, 0.0, 6, suppress=False)
for _suffix, _noisy in (("", True), ("_exact", False)):
    _add(f"q1_count{_suffix}", Workload(releases=[Release("count", "n", None, 0.0, 132.0)], params=_ONE, noisy=_noisy, **_Q1))
    _add(f"q1_avg{_suffix}", Workload(releases=[Release("avg", "price_mean", "price", 0.0, 105_000.0)], params=_ONE, noisy=_noisy, **_Q1))
    _add(f"q1_wrong{_suffix}", Workload(releases=[Release("count", "n", None, 0.0, 1.0)], params=_ONE, noisy=_noisy, **_Q1))
    for _name, _window in (("q4", None), ("q4_window", ("1996-07-01", "1996-10-01"))):
        _s = T.late_orders(_window)
        _add(f"{_name}{_suffix}", Workload(_s[0], _s[1], ["priority"], [Release("count", "n", None, 0.0, 5.0)], PrivacyParams(0.1, 0.0, 5, suppress=_noisy), noisy=_noisy, owners_of="customer"))
    _add(f"q13{_suffix}", Workload(T.ORDER_COUNTS[0], T.ORDER_COUNTS[1], ["n_orders"], [Release("owners", "owners")], PrivacyParams(0.1, 0.0, 1, suppress=_noisy), noisy=_noisy, owners_of="customer"))
    _add(f"q16{_suffix}", Workload(T.SUPPLIED_PARTS[0], T.SUPPLIED_PARTS[1], ["p_brand", "p_type", "p_size"], [Release("owners", "owners")], PrivacyParams(0.1, 0.0, 5, suppress=_noisy), noisy=_noisy, owners_of="supplier"))
    _add(f"q21{_suffix}", Workload(T.WAITING[0], T.WAITING[1], ["supplier"], [Release("owners", "owners")], PrivacyParams(0.1, 0.0, 1, suppress=_noisy), noisy=_noisy, owners_of="supplier"))
_add("two_step_example", Workload(T.CUSTOMER_ORDERS[0], T.CUSTOMER_ORDERS[1], ["segment"], [Release("count", "n", None, 0.0, 5.0)], PrivacyParams(1.0, 0.0, 1, tau=2.0)))
_add("cohort_sum", Workload(T.CUSTOMER_ORDERS[0], T.CUSTOMER_ORDERS[1], ["nation"], [Release("sum", "total", "price", 0.0, 1e5)], PrivacyParams(2.0, 1e-5, 1)))


# The stages -------------------------------------------------------------------------------------------------------------


@query("stage_one", f"SELECT user_id AS o, event_type, count(*) AS n, {_r('sum(value)', 'total')} FROM events GROUP BY ALL")
def _(spark, d):
    owned = T.EVENTS[0](spark, d)
    return rounded(owned.group("event_type", n=F.count(F.lit(1)), total=F.sum("value")).unowned())


_LIMIT = f"SELECT o, k, n FROM (SELECT user_id AS o, json_extract_string(props, '$.k') AS k, count(*) AS n FROM events GROUP BY ALL) QUALIFY row_number() OVER (PARTITION BY o ORDER BY md5({sql_message('limit', ['o', 'k'])})) <= 7"


def _pairs(spark, d) -> DataFrame:
    return T.EVENT_KEYS[0](spark, d).group("k", n=F.count(F.lit(1))).unowned()


@query("stage_limit", _LIMIT)
def _(spark, d):
    return limit_partitions(_pairs(spark, d), "o", 7, _noise(), ["k"])


@query("stage_limit_agg", _LIMIT)
def _(spark, d):
    return limit_partitions(_pairs(spark, d), "o", 7, _noise(), ["k"], strategy="agg")


_add("stage_two", Workload(T.EVENTS[0], T.EVENTS[1], ["event_type"], [Release("owners", "owners"), Release("sum", "total", "value", 0.0, 2000.0)], PrivacyParams(1.0, 0.0, 3, suppress=False), noisy=False))


@query("threshold_only", f"SELECT k, owners FROM (SELECT json_extract_string(props, '$.k') AS k, count(DISTINCT user_id) AS owners FROM events GROUP BY ALL) WHERE owners + {sql_laplace(2.0, 'owners', ['k'])} >= 72.5")
def _(spark, d):
    counts = baselines.exact_owner_count(T.frame(T.EVENT_KEYS, spark, d), "o", ["k"])
    return suppress_rare_keys(counts, F.col("owners") + _noise().laplace(2.0, "owners", [F.col("k")]), 72.5)


# The ladder of histograms -----------------------------------------------------------------------------------------------

_K = "(SELECT user_id AS o, json_extract_string(props, '$.k') AS k FROM events)"


def _hist(function):
    return lambda spark, d: rounded(function(T.frame(T.EVENT_KEYS, spark, d)))


query("hist_exact", f"SELECT k, count(*) AS n FROM {_K} GROUP BY k")(_hist(lambda df: baselines.exact_histogram(df, "k")))
query("hist_naive", f"SELECT k, {_r('n + ' + sql_laplace(1 / 0.5, 'naive', ['k']), 'n')} FROM (SELECT k, count(*) AS n FROM {_K} GROUP BY k)")(_hist(lambda df: baselines.naive_row_histogram(df, "k", 0.5, _noise())))
_OWNERS_OF = f"(SELECT k, count(DISTINCT o) AS n FROM {_K} GROUP BY k)"
query("hist_owner", f"SELECT k, {_r('n + ' + sql_laplace(2.0, 'owner', ['k']), 'n')} FROM {_OWNERS_OF}")(_hist(lambda df: baselines.owner_histogram(df, "o", "k", 0.5, _noise())))
query("hist_owner_rows", f"SELECT k, {_r('n + ' + sql_laplace(4.0, 'owner', ['k']), 'n')} FROM (SELECT k, sum(least(c, 2)) AS n FROM (SELECT o, k, count(*) AS c FROM {_K} GROUP BY ALL) GROUP BY k)")(
    _hist(lambda df: baselines.owner_histogram(df, "o", "k", 0.5, _noise(), 2))
)
query("hist_threshold", f"SELECT * FROM (SELECT k, {_r('n + ' + sql_laplace(2.0, 'owner', ['k']), 'n')} FROM {_OWNERS_OF}) WHERE n >= 70")(_hist(lambda df: baselines.thresholded_histogram(df, "o", "k", 0.5, 70.0, _noise())))
query("hist_private", f"""WITH kept AS (SELECT o, k FROM (SELECT DISTINCT o, k FROM {_K}) QUALIFY row_number() OVER (PARTITION BY o ORDER BY md5({sql_message('histogram', ['o', 'k'])})) <= 4),
c AS (SELECT k, count(*) AS n FROM kept GROUP BY k) SELECT k, {_r('n + ' + sql_laplace(1.0, 'private', ['k']), 'n')} FROM c WHERE n + {sql_laplace(1.0, 'private', ['k'])} >= {owner_threshold(4.0, 0.05, 4)!r}""")(
    _hist(lambda df: baselines.private_histogram(df, "o", "k", 4.0, 0.05, 4, _noise()))
)

# Baselines --------------------------------------------------------------------------------------------------------------


def _domain(spark: SparkSession) -> DataFrame:
    return spark.sql("SELECT * FROM VALUES ('A', 'F'), ('A', 'O'), ('N', 'F'), ('N', 'O'), ('R', 'F'), ('R', 'O'), ('X', 'X') AS t(l_returnflag, l_linestatus)")


_DOMAIN = "(VALUES ('A', 'F'), ('A', 'O'), ('N', 'F'), ('N', 'O'), ('R', 'F'), ('R', 'O'), ('X', 'X')) AS t(l_returnflag, l_linestatus)"
_FLAGS = ["l_returnflag", "l_linestatus"]


def _lines(spark, d) -> DataFrame:
    return T.frame(T.LINES_BY_SUPPLIER, spark, d)


@query("row_unit_count", f"SELECT l_returnflag, l_linestatus, {_r('coalesce(n, 0) + ' + sql_laplace(10.0, 'row_count', _FLAGS), 'value')} FROM {_DOMAIN} LEFT JOIN (SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY ALL) USING (l_returnflag, l_linestatus)")
def _(spark, d):
    return rounded(baselines.row_unit_release(_lines(spark, d), _domain(spark), _FLAGS, "count", None, 1.0, 0.1, _noise()))


@query("row_unit_avg", f"""SELECT l_returnflag, l_linestatus, {_r('52500.0 + (coalesce(s, 0) + ' + sql_laplace(105000.0 / 0.1, 'row_avg_sum', _FLAGS) + ') / greatest(coalesce(n, 0) + ' + sql_laplace(20.0, 'row_avg_count', _FLAGS) + ', 1.0)', 'value')}
FROM {_DOMAIN} LEFT JOIN (SELECT l_returnflag, l_linestatus, count(*) AS n, sum(greatest(0, least(105000, l_extendedprice)) - 52500) AS s FROM lineitem GROUP BY ALL) USING (l_returnflag, l_linestatus)""")
def _(spark, d):
    return rounded(baselines.row_unit_release(_lines(spark, d), _domain(spark), _FLAGS, "average", "price", 105_000.0, 0.1, _noise()))


@query("row_unit_median")
def _(spark, d):
    return rounded(baselines.row_unit_release(_lines(spark, d), _domain(spark), _FLAGS, "median", "price", 105_000.0, 0.1, _noise()))


@query("row_unit_join_count", f"""SELECT status, {_r('coalesce(n, 0) + ' + sql_laplace(50.0, 'row_join', ['status']), 'value')} FROM (VALUES ('F'), ('O'), ('P')) AS t(status)
LEFT JOIN (SELECT o_orderstatus AS status, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY ALL) USING (status)""")
def _(spark, d):
    joined = lineitem_by_customer(spark, d).unowned().withColumnRenamed("o_orderstatus", "status")
    return rounded(baselines.row_unit_join_count(joined, spark.sql("SELECT * FROM VALUES ('F'), ('O'), ('P') AS t(status)"), ["status"], 5.0, 0.1, _noise()))


@query("row_unit_join_count_smooth")
def _(spark, d):
    lines, orders = read_table(spark, d, "lineitem"), read_table(spark, d, "orders")
    by = [baselines.max_frequency(lines, "l_orderkey"), baselines.max_frequency(orders, "o_orderkey")]
    joined = lineitem_by_customer(spark, d).unowned().withColumnRenamed("o_orderstatus", "status")
    return rounded(baselines.row_unit_join_count(joined, spark.sql("SELECT * FROM VALUES ('F'), ('O'), ('P') AS t(status)"), ["status"], 0.0, 1.0, _noise(), by, 1e-6))


@query("exact_owner_count", "SELECT event_type, count(DISTINCT user_id) AS owners FROM events GROUP BY ALL")
def _(spark, d):
    return baselines.exact_owner_count(T.frame(T.EVENTS, spark, d), "o", ["event_type"])


# Limits found privately, quantiles ----------------------------------------------------------------------------------------

_BIN_SQL = {
    "events": ("SELECT user_id AS o, sum(value) AS p FROM events GROUP BY ALL", "unsigned"),
    "orders": ("SELECT o_custkey AS o, sum(o_totalprice) AS p FROM orders GROUP BY ALL", "unsigned"),
    "balances": ("SELECT c_custkey AS o, sum(c_acctbal) AS p FROM customer GROUP BY ALL", "signed"),
}


def _bins_sql(name: str) -> str:
    source, kind = _BIN_SQL[name]
    top = "CASE WHEN p = 0 THEN 0 ELSE sign(p)::INT * (greatest(0, least(63, (CASE WHEN pow(2, floor(log2(abs(p)))) = abs(p) THEN floor(log2(abs(p))) ELSE floor(log2(abs(p))) + 1 END)))::INT + 1) END"
    return f"SELECT '{name}' AS source, greatest({top}, {0 if kind == 'unsigned' else -64}) AS bin, count(*) AS n FROM ({source}) GROUP BY ALL"


def _owner_sums(spark, d, name) -> DataFrame:
    table, owner, column = {"events": ("events", "user_id", "value"), "orders": ("orders", "o_custkey", "o_totalprice"), "balances": ("customer", "c_custkey", "c_acctbal")}[name]
    return read_table(spark, d, table).groupBy(F.col(owner).alias("o")).agg(F.sum(column).alias("p"))


@query("bounds_bins", " UNION ALL ".join(map(_bins_sql, _BIN_SQL)))
def _(spark, d):
    parts = [bounds.bin_counts(_owner_sums(spark, d, n), [], "p", k).select(F.lit(n).alias("source"), "bin", "n") for n, (_, k) in _BIN_SQL.items()]
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


def _chosen_sql(name: str) -> str:
    grid = "range(0, 65)" if _BIN_SQL[name][1] == "unsigned" else "range(-64, 65)"
    noisy = sql_laplace(1.0, "bounds|", []).replace(f"'{SEED}|bounds||'", f"'{SEED}|bounds||||' || bin || '|'")
    up = lambda c: f"CASE WHEN {c} = 0 THEN 0 WHEN {c} > 0 THEN pow(2, {c} - 1) WHEN {c} = -1 THEN 0 ELSE -pow(2, -{c} - 2) END"
    return f"""SELECT '{name}' AS source, CASE WHEN lo = 0 THEN 0 ELSE -({up('(-lo)')}) END::DOUBLE AS lower, ({up('hi')})::DOUBLE AS upper FROM (SELECT min(bin) AS lo, max(bin) AS hi FROM (
SELECT bin, coalesce(n, 0) + {noisy} AS m FROM (SELECT unnest({grid}) AS bin) LEFT JOIN (SELECT bin, n FROM ({_bins_sql(name)})) USING (bin)) WHERE m > {bounds.bounds_threshold(1.0, 1 - 1e-9)!r})"""


@query("bounds_chosen", " UNION ALL ".join(map(_chosen_sql, _BIN_SQL)))
def _(spark, d):
    parts = [bounds.approx_bounds(_owner_sums(spark, d, n), [], "p", 1.0, _noise(), kind=k).select(F.lit(n).alias("source"), "lower", "upper") for n, (_, k) in _BIN_SQL.items()]
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


@query("bounds_sum")
def _(spark, d):
    return rounded(private_aggregate(T.EVENTS[0](spark, d), [], [A.priv_sum("total", "value")], PrivacyParams(4.0), _noise()).df)


@query("bounds_fail")
def _(spark, d):
    """With too small a budget no bin stands out: the aggregate is NULL."""
    return rounded(private_aggregate(T.EVENTS[0](spark, d), [], [A.priv_sum("total", "value")], PrivacyParams(0.1), _noise()).df)


@query("bounds_sweep")
def _(spark, d):
    """How P and the budget move the threshold and with it the chosen limits, over one set of owner sums."""
    sums, out = _owner_sums(spark, d, "events"), None
    for p in (0.9, 0.999, 1 - 1e-9):
        for eps in (0.1, 1.0, 5.0):
            row = bounds.approx_bounds(sums, [], "p", eps, _noise(), p, "unsigned").select(F.lit(p).alias("p"), F.lit(eps).alias("eps"), F.lit(bounds.bounds_threshold(1 / eps, p)).alias("threshold"), "lower", "upper")
            out = row if out is None else out.unionByName(row)
    return rounded(out)


_DEPTH = 20


def _bisect_sql(q: float) -> str:
    cell = f"least(floor(greatest(0, least(105000, v)) / 105000 * {2**_DEPTH}), {2**_DEPTH - 1})"
    return f"""SELECT l_returnflag, l_linestatus, {_r(f'105000.0 * (cell + 0.5) / {2**_DEPTH}', 'value')} FROM (SELECT *, {cell} AS cell, row_number() OVER (PARTITION BY l_returnflag, l_linestatus ORDER BY v) AS r, count(*) OVER (PARTITION BY l_returnflag, l_linestatus) AS n
FROM (SELECT l_suppkey, l_returnflag, l_linestatus, quantile_cont(l_extendedprice, 0.5) AS v FROM lineitem GROUP BY ALL)) WHERE r = greatest(1, ceil({q} * n))"""


def _bisected(make, params=_SIX, noise=None, source=T.LINES_BY_SUPPLIER):
    return lambda spark, d: rounded(private_aggregate(source[0](spark, d), _FLAGS, [make("value")], params, noise or _exact()).df)


query("median_bisect", _bisect_sql(0.5))(_bisected(lambda n: A.priv_median(n, "price", 0.0, 105_000.0)))
query("p_quantile", _bisect_sql(0.9))(_bisected(lambda n: A.priv_quantile(n, "price", 0.9, 0.0, 105_000.0)))
query("p_min", _bisect_sql(0.0))(_bisected(lambda n: A.priv_min(n, "price", 0.0, 105_000.0)))
query("p_max", _bisect_sql(1.0))(_bisected(lambda n: A.priv_max(n, "price", 0.0, 105_000.0)))
query("p_median")(_bisected(lambda n: A.priv_median(n, "price", 0.0, 105_000.0), PrivacyParams(60.0, 0.0, 6, suppress=False), TestNoise(SEED)))
query("p_ntile")(_bisected(lambda n: A.priv_ntile(n, "price", 4, 0.0, 105_000.0)))
query("q1_median")(_bisected(lambda n: A.priv_median(n, "price", 0.0, 105_000.0), _ONE, TestNoise(SEED), T.ONE_RECORD))

# Sweeps and measures ------------------------------------------------------------------------------------------------------

_SWEEP = [1, 5, 10, 15, 20, 25]


@query("limit_error_orders", " UNION ALL ".join(f"SELECT {c} AS c_u, {_r(f'sum(greatest(n - {c}, 0)) / sum(n)', 'lost_share')} FROM (SELECT o_custkey, count(*) AS n FROM orders GROUP BY ALL)" for c in _SWEEP))
def _(spark, d):
    return rounded(measures.partition_limit_error(read_table(spark, d, "orders").groupBy("o_custkey").agg(F.count(F.lit(1)).alias("n")), "n", _SWEEP))


#: Relations whose owners have different numbers of partitions: the table, the owner, the partition as both engines read it
_SHAPES = {
    "months of suppliers": ("lineitem", "l_suppkey", "date_trunc('month', l_shipdate)"), "weeks of suppliers": ("lineitem", "l_suppkey", "date_trunc('week', l_shipdate)"),
    "suppliers of parts": ("lineitem", "l_partkey", "l_suppkey"), "orders of customers": ("orders", "o_custkey", "o_orderkey"),
    "hours of users": ("events", "user_id", "date_trunc('hour', ts)"), "events of users": ("events", "user_id", "event_id"),
}
_SYNTHETIC_LIMITS = (1, 25, 50, 75, 100, 125, 150, 200)
_SHAPES_SQL = " UNION ALL ".join(f"SELECT '{name}' AS distribution, n, count(*) AS owners FROM (SELECT {o}, count(DISTINCT {p}) AS n FROM {t} WHERE {o} IS NOT NULL GROUP BY {o}) GROUP BY n" for name, (t, o, p) in _SHAPES.items())


@query("limit_error_synthetic", f"SELECT distribution, c_u, {_r('sum(owners * greatest(n - c_u, 0)) / nullif(sum(owners * n), 0)', 'lost_share')} FROM ({_SHAPES_SQL}), unnest({list(_SYNTHETIC_LIMITS)!r}::INT[]) AS t(c_u) GROUP BY ALL")
def _(spark, d):
    """What limits on partitions lose for owners of the given tables whose numbers of partitions are distributed differently."""
    counts = None
    for name, (table, owner, partition) in _SHAPES.items():
        pairs = read_table(spark, d, table).filter(F.col(owner).isNotNull()).select(F.col(owner).alias("o"), F.expr(partition).alias("p")).distinct()
        shape = pairs.groupBy("o").agg(F.count("p").alias("n")).groupBy("n").agg(F.count(F.lit(1)).alias("owners")).select(F.lit(name).alias("distribution"), "n", "owners")
        counts = shape if counts is None else counts.unionByName(shape)
    limits = counts.select("distribution", "n", "owners", F.explode(F.array(*map(F.lit, _SYNTHETIC_LIMITS))).alias("c_u"))
    lost, everything = F.sum(F.col("owners") * F.greatest(F.col("n") - F.col("c_u"), F.lit(0))), F.sum(F.col("owners") * F.col("n"))
    return rounded(limits.groupBy("distribution", "c_u").agg((lost.cast("double") / F.nullif(everything, F.lit(0))).alias("lost_share")))


_COUNTS_SQL = "SELECT n_orders, count(*) AS owners FROM (SELECT c_custkey, count(o_orderkey) AS n_orders FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY ALL) GROUP BY ALL"


def _hidden(tau: float, scale: float) -> str:
    d = f"({tau!r} - owners) / {scale!r}"
    return f"CASE WHEN {d} >= 0 THEN 1 - 0.5 * exp(-({d})) ELSE 0.5 * exp({d}) END"


@query("delta_sweep", " UNION ALL ".join(f"SELECT {k} AS k, {_r('avg(' + _hidden(owner_threshold(0.05, 10.0**-k, 1), 20.0) + ')', 'suppression_rate')} FROM ({_COUNTS_SQL})" for k in range(2, 11)))
def _(spark, d):
    """The expected share of hidden keys for delta = 10^-k, from the noise's distribution function."""
    owned = T.ORDER_COUNTS[0](spark, d).unowned()
    counts = owned.groupBy("n_orders").agg(F.count(F.lit(1)).alias("owners"))
    hidden = lambda tau: measures.expected_suppression(F.col("owners"), F.lit(tau), F.lit(20.0))
    rates = [F.struct(F.lit(k).alias("k"), F.avg(hidden(owner_threshold(0.05, 10.0**-k, 1))).alias("suppression_rate")) for k in range(2, 11)]
    return rounded(counts.agg(F.array(*rates).alias("all")).select(F.inline("all")))


#: The quantities of all lines, moved onto [50, 150] by their least and greatest: value and how often, so a few rows whatever the table holds.
_CLAMPED_SQL = "SELECT 50 + 100 * (q - min(q) OVER ()) / nullif(max(q) OVER () - min(q) OVER (), 0) AS x, n FROM (SELECT l_quantity AS q, count(*)::DOUBLE AS n FROM lineitem WHERE l_quantity IS NOT NULL GROUP BY ALL)"
_SCALE = "(u + 200) / (eps * 100)"


def _quantities(spark, d) -> DataFrame:
    """(x, n)"""
    counts = read_table(spark, d, "lineitem").filter("l_quantity IS NOT NULL").groupBy(F.col("l_quantity").alias("q")).agg(F.count(F.lit(1)).cast("double").alias("n"))
    limits = counts.agg(F.min("q").alias("lo"), F.max("q").alias("hi"))
    return counts.crossJoin(F.broadcast(limits)).select((50 + 100 * (F.col("q") - F.col("lo")) / F.nullif(F.col("hi") - F.col("lo"), F.lit(0))).alias("x"), "n")


@query("clamp_sweep", f"""WITH v AS ({_CLAMPED_SQL}), b AS (SELECT range::DOUBLE AS u, sum(n * greatest(x - range, 0)) / sum(n) AS bias FROM v, range(60, 151, 5) GROUP BY ALL),
c AS (SELECT x, sum(n) OVER (ORDER BY x) AS upto, sum(n) OVER () AS n FROM v), e AS (SELECT unnest([0.05, 0.1, 0.5, 1.0]::DOUBLE[]) AS eps),
best AS (SELECT eps, min(x) AS x FROM c, e WHERE upto >= (1 - 1 / (eps * 100)) * n GROUP BY ALL)
SELECT eps, u AS "upper", {_r(f'bias + {_SCALE}', 'sum_error')}, {_r(f'bias + {_SCALE} * exp(-bias / ({_SCALE}))', 'expected_error')}, {_r('x', 'best_upper')} FROM b, best JOIN e USING (eps)""")
def _(spark, d):
    """The error of a clamped noisy mean of 100 values, distributed as the lines' quantities on [50, 150], lower limit -200, by the upper limit, in both forms.

    The first form is least where as many values lie above as the noise's scale grows: at the quantile 1 - 1 / (eps * 100).
    """
    values = materialise(_quantities(spark, d), "clamp-values")
    uppers = values.select("x", "n", F.explode(F.array(*(F.lit(float(u)) for u in range(60, 151, 5)))).alias("upper"))
    biases = uppers.groupBy("upper").agg((F.sum(F.col("n") * F.greatest(F.col("x") - F.col("upper"), F.lit(0.0))) / F.sum("n")).alias("bias"))
    placed = values.select("x", F.sum("n").over(Window.orderBy("x")).alias("upto"), F.sum("n").over(Window.partitionBy()).alias("n"), F.explode(F.array(*map(F.lit, (0.05, 0.1, 0.5, 1.0)))).alias("eps"))
    upper, eps, bias = F.col("upper"), F.col("eps"), F.col("bias")
    best = placed.filter(F.col("upto") >= (1 - 1 / (eps * 100)) * F.col("n")).groupBy("eps").agg(F.min("x").alias("best_upper"))
    scale = (upper + 200) / (eps * 100)
    return rounded(biases.crossJoin(F.broadcast(best)).select("eps", "upper", (bias + scale).alias("sum_error"), (bias + scale * F.exp(-bias / scale)).alias("expected_error"), "best_upper"))


_CLAMP_RUNS, _CLAMP_VALUES, _CLAMP_EPS = 1000, 100, 0.1
_CLAMP_UPPERS = (60.0, 80.0, 100.0, 109.0, 120.0, 140.0, 160.0)


#: Columns of the given tables whose values are distributed so, moved to about 100; each has few distinct values
_CLAMPED = {
    "uniform": ("lineitem", "l_quantity", "50 + 100 * (v - lo) / nullif(hi - lo, 0)"),
    "bimodal": ("lineitem", "CASE WHEN l_linestatus = 'F' THEN 70 ELSE 120 END + l_quantity / 5", "v"),
    "exponential": ("events", "floor(value)", "50 + 50 * v / nullif(mean, 0)"),
    "bell": ("orders", None, "100 * v / mean"),
}


def _clamped_values(spark: SparkSession, d: str, name: str) -> DataFrame:
    """(distribution, x, n): each distinct value and how often the table has it."""
    table, column, moved = _CLAMPED[name]
    rows = read_table(spark, d, table)
    values = rows.select(F.expr(column).cast("double").alias("v")) if column else rows.filter("o_custkey IS NOT NULL").groupBy("o_custkey").agg(F.count(F.lit(1)).cast("double").alias("v"))
    counts = values.filter("v IS NOT NULL").groupBy("v").agg(F.count(F.lit(1)).cast("double").alias("n"))
    about = counts.agg(F.min("v").alias("lo"), F.max("v").alias("hi"), (F.sum(F.col("v") * F.col("n")) / F.sum("n")).alias("mean"))
    return counts.crossJoin(F.broadcast(about)).select(F.lit(name).alias("distribution"), F.expr(moved).cast("double").alias("x"), "n")


@query("clamp_sweep_distributions")
def _(spark, d):
    """Mean and median of the absolute error over runs, each of 100 values drawn from those of whole columns of the given tables and clamped by the engine:
    quantities, quantities beside the line's status, the events' values in whole units, the orders of each customer.

    For uniform values the median has its least where the expected absolute error has it, near 109, and not where bias and noise scale add up to the least.
    """
    noise, at = RunNoise(SEED), [F.col("run"), F.col("i"), F.col("distribution")]
    listed, whole = None, Window.partitionBy("distribution")
    for name in _CLAMPED:
        listed = _clamped_values(spark, d, name) if listed is None else listed.unionByName(_clamped_values(spark, d, name))
    upto = F.sum("n").over(whole.orderBy("x").rowsBetween(Window.unboundedPreceding, 0))
    placed = materialise(listed, "clamp-values").select("distribution", "x", "n", upto.alias("upto"), F.sum("n").over(whole).alias("of"), (F.sum(F.col("x") * F.col("n")).over(whole) / F.sum("n").over(whole)).alias("truth"))
    draws = spark.range(0, _CLAMP_RUNS, 1, max(8, spark.sparkContext.defaultParallelism)).select(F.col("id").alias("run"), F.explode(F.sequence(F.lit(1), F.lit(_CLAMP_VALUES))).alias("i"))
    draws = draws.select("run", "i", F.explode(F.array(*map(F.lit, _CLAMPED))).alias("distribution")).withColumn("u", noise.uniform("value", at))
    rank = F.col("u") * F.col("of")
    values = draws.join(F.broadcast(placed), "distribution").filter((rank >= F.col("upto") - F.col("n")) & (rank < F.col("upto")))
    uppers = [F.struct(F.lit(up).alias("upper"), F.avg(F.greatest(F.lit(-200.0), F.least(F.lit(up), F.col("x")))).alias("mean")) for up in _CLAMP_UPPERS]
    means = values.groupBy("distribution", "truth", "run").agg(F.array(*uppers).alias("all")).select("distribution", "truth", "run", F.inline("all"))
    noisy = F.col("mean") + noise.laplace((F.col("upper") + 200) / (_CLAMP_EPS * _CLAMP_VALUES), "noise", [F.col("run"), F.col("distribution"), F.col("upper")])
    error = means.select("distribution", "upper", F.abs(noisy - F.col("truth")).alias("error"))
    return rounded(error.groupBy("distribution", "upper").agg(F.avg("error").alias("mean_error"), F.percentile("error", F.lit(0.5)).alias("median_error")))


@query("median_error_runs")
def _(spark, d):
    """The median relative error of the count over runs, beside its formula, for several budgets and numbers of aggregates."""
    exact = _lines(spark, d).filter("l_returnflag = 'A' AND l_linestatus = 'F'").groupBy(*_FLAGS).agg(F.count(F.lit(1)).alias("n"))
    exact = spark.createDataFrame(exact.collect(), exact.schema)  # one row
    out = None
    for eps in (0.01, 0.05, 0.1, 0.5, 1.0):
        for n in (1, 2, 4, 8):
            runs = measures.noise_runs(spark, exact, _FLAGS, "n", 132 * n / eps, 1_000_000, RunNoise(SEED), f"e{eps}n{n}")
            row = measures.median_relative_error(runs).select(F.lit(eps).alias("eps"), F.lit(n).alias("aggregates"), "median_relative_error")
            row = row.join(exact.select((F.lit(error_vs_aggs(132, eps, n)) / F.col("n")).alias("predicted")))
            out = row if out is None else out.unionByName(row)
    return rounded(out)


@query("suppression_runs")
def _(spark, d):
    """Keys of one owner, every supplier's own among the lines: how often they stay hidden over runs, 1,000,000 draws at least, beside (1 - delta)^(1 / c_u)."""
    owners = T.frame(T.LINES_BY_SUPPLIER, spark, d).groupBy(F.col("o").alias("k")).agg(F.countDistinct("o").alias("owners"))
    one = materialise(owners.filter("owners = 1"), "single-owner-keys")
    n_runs, out = -(-1_000_000 // max(1, one.count())), None
    for delta in (0.12, 0.01):
        for c_u in (1, 5):
            tau = owner_threshold(0.1, delta, c_u)
            runs = measures.noise_runs(spark, one, ["k"], "owners", c_u / 0.1, n_runs, RunNoise(SEED), f"d{delta}c{c_u}")
            row = measures.suppression_rate(runs, F.col("noisy") < tau).select(F.lit(delta).alias("delta"), F.lit(c_u).alias("c_u"), "suppression_rate", F.lit(single_owner_suppression(delta, c_u)).alias("predicted"))
            out = row if out is None else out.unionByName(row)
    return rounded(out)


@query("coverage_runs")
def _(spark, d):
    """How often the interval of a count of customers with orders, one row of each, holds the exact count over runs."""
    orders = T.ORDERS[0](spark, d).unowned().groupBy("o").agg(F.count(F.lit(1)).alias("n"))
    exact = orders.agg(F.coalesce(F.sum(F.least("n", F.lit(1))), F.lit(0)).alias("n")).select(F.lit("only").alias("k"), "n")
    one, out = spark.createDataFrame(exact.collect(), exact.schema), None
    for level in (0.5, 0.9, 0.95):
        width = A.priv_count("n", None, 0, 1).half_width(level, 0.1, 0, 1)
        runs = measures.noise_runs(spark, one, ["k"], "n", 10.0, 1_000_000, RunNoise(SEED), f"l{level}")
        row = measures.interval_coverage(runs.withColumns({"lo": F.col("noisy") - width, "hi": F.col("noisy") + width}), "lo", "hi").select(F.lit(level).alias("level"), "coverage")
        out = row if out is None else out.unionByName(row)
    return rounded(out)


@query("noise_formula", f"SELECT eps, {_r('ln(2) * most / eps', 'median_noise')} FROM (SELECT max(c) AS most FROM (SELECT count(*) AS c FROM ({T.ONE_RECORD[1]}) GROUP BY o)), (VALUES (0.1::DOUBLE), (1.0::DOUBLE)) AS t(eps)")
def _(spark, d):
    """The median noise of the first query's count with the limit that holds for the table: the most lines that a supplier has in the record."""
    most = T.ONE_RECORD[0](spark, d).unowned().groupBy("o").agg(F.count(F.lit(1)).alias("n")).agg(F.max("n").alias("most"))
    each = [F.struct(F.lit(e).alias("eps"), (F.col("most") * laplace_median_error(1, e)).alias("median_noise")) for e in (0.1, 1.0)]
    return rounded(most.select(F.inline(F.array(*each))))


# Attacks, and the tester's inputs -------------------------------------------------------------------------------------------


@query("nan_attack", f"SELECT {_r('sum(greatest(0, least(100, v)))', 'total')} FROM (SELECT user_id, CASE WHEN user_id = 3 THEN 0 ELSE count(*) END AS v FROM events GROUP BY user_id)")
def _(spark, d):
    """One owner's values become NaN, others pass through infinities and a division by zero; the sum stays finite."""
    owned = T.EVENTS[0](spark, d).with_column("v", F.when(F.col("o") == 3, F.lit(float("nan"))).otherwise(safe_divide(F.lit(1.0), F.lit(1.0) + F.coalesce(safe_divide(F.lit(0.0), F.lit(0.0)), F.lit(0.0)))))
    return rounded(private_aggregate(owned, [], [A.priv_sum("total", "v", 0.0, 100.0)], PrivacyParams(1.0), _exact()).df)


def _digits_sql(base: int) -> str:
    return f"(WITH RECURSIVE r(i, n, f, x) AS (SELECT i, i, 1.0::DOUBLE / {base}, 0.0::DOUBLE FROM range(1, 257) AS t(i) UNION ALL SELECT i, n // {base}, f / {base}, x + f * (n % {base}) FROM r WHERE n > 0) SELECT i, x FROM r WHERE n = 0)"


@query("halton_points", f"""SELECT a.i AS db_id, {_r('lo + ((a.x * 2 - 1) * 0.5 + 0.5) * (hi - lo)', 'x')}, {_r('lo + ((b.x * 2 - 1) * 0.5 + 0.5) * (hi - lo)', 'y')} FROM {_digits_sql(2)} AS a JOIN {_digits_sql(3)} AS b USING (i),
(SELECT min(l_extendedprice) AS lo, max(l_extendedprice) AS hi FROM lineitem)""")
def _(spark, d):
    """256 databases of two prices that evenly fill the range which the lines' prices have."""
    limits = read_table(spark, d, "lineitem").agg(F.min("l_extendedprice").alias("lo"), F.max("l_extendedprice").alias("hi"))
    dbs = halton_databases(spark, 256, 2, 0.5).crossJoin(F.broadcast(limits))
    price = lambda i: F.col("lo") + (F.get("rows", F.lit(i)) + 0.5) * (F.col("hi") - F.col("lo"))
    return rounded(dbs.select("db_id", price(0).alias("x"), price(1).alias("y")))


@query("search_graph", "SELECT l_orderkey AS db_id, mask::INT AS mask, removed::INT AS removed FROM (SELECT l_orderkey FROM lineitem WHERE l_orderkey IS NOT NULL GROUP BY l_orderkey HAVING count(l_extendedprice) = 3), range(0, 8) AS b(mask), range(0, 3) AS c(removed) WHERE (mask >> removed) & 1 = 1")
def _(spark, d):
    """The graph of the parts of every order of three lines, as a database of three prices."""
    prices = read_table(spark, d, "lineitem").filter("l_orderkey IS NOT NULL").groupBy(F.col("l_orderkey").alias("db_id")).agg(F.array_sort(F.collect_list("l_extendedprice")).alias("rows"))
    return adjacent_pairs(prices.filter(F.size("rows") == 3))


# After a release --------------------------------------------------------------------------------------------------------------


def _released(spark, d) -> DataFrame:
    return Workload(T.ORDERS[0], T.ORDERS[1], ["priority"], [Release("count", "n", None, 0.0, 5.0)], _P).run(spark, d)


_RELEASED = Workload(T.ORDERS[0], T.ORDERS[1], ["priority"], [Release("count", "n", None, 0.0, 5.0)], _P).oracle()


@query("p_rank", f"SELECT priority, n, row_number() OVER (ORDER BY n DESC) AS place FROM ({_RELEASED})")
def _(spark, d):
    return _released(spark, d).withColumn("place", F.row_number().over(Window.orderBy(F.desc("n"))))


@query("p_share", f"SELECT priority, {_r('n / sum(n) OVER ()', 'share')} FROM ({_RELEASED})")
def _(spark, d):
    return rounded(_released(spark, d).select("priority", (F.col("n") / F.sum("n").over(Window.partitionBy())).alias("share")))


@query("p_topk", f"SELECT * FROM ({_RELEASED}) ORDER BY n DESC LIMIT 2")
def _(spark, d):
    return _released(spark, d).orderBy(F.desc("n")).limit(2)


@query("p_having", f"SELECT * FROM ({_RELEASED}) WHERE n > 2900")
def _(spark, d):
    return _released(spark, d).filter("n > 2900")


@query("sink_roundtrip", _RELEASED)
def _(spark, d):
    path = f"{shared_dir(spark)}/sink-{uuid.uuid4().hex}"
    _released(spark, d).write.parquet(path)
    return spark.read.parquet(path)


@query("scan_parquet", "SELECT count(*) AS n FROM orders WHERE o_orderstatus = 'F'")
def _(spark, d):
    owned = OwnerCatalog.of_folder(spark, d, ["orders"]).owned("orders").filter("o_orderstatus = 'F'")
    return private_aggregate(owned, [], [A.priv_count("n", None, 0.0, 1e6)], PrivacyParams(1.0), _exact()).df.select(F.col("n").cast("long").alias("n"))


@query("p_expr_key", "SELECT decade, count(*)::DOUBLE AS owners FROM (SELECT DISTINCT o_custkey, year(o_orderdate) // 2 * 2 AS decade FROM orders) GROUP BY decade")
def _(spark, d):
    owned = OwnerCatalog.of_folder(spark, d, ["orders"]).owned("orders")
    decade = (F.floor(F.year("o_orderdate") / 2) * 2).cast("int").alias("decade")
    return private_aggregate(owned, [decade], [A.priv_count_owners()], PrivacyParams(1.0, 0.0, 100, suppress=False), _exact()).df


def _expanded(spark, d, sets: list[list[str]]) -> DataFrame:
    """Grouping sets outside: the level joins the key, so the limit on an owner's partitions spans all sets."""
    owned = T.ORDERS[0](spark, d)
    levels = F.array(*(F.struct(F.lit(i).alias("level"), *((F.col(k) if k in s else F.lit(None).cast("string")).alias(f"g_{k}") for k in ("priority", "status"))) for i, s in enumerate(sets)))
    wide = owned.explode("s", levels).select(F.col("s.level").alias("level"), F.col("s.g_priority").alias("g_priority"), F.col("s.g_status").alias("g_status"))
    return private_aggregate(wide, ["level", "g_priority", "g_status"], [A.priv_count_owners()], PrivacyParams(1.0, 0.0, 100, suppress=False), _exact()).df


def _expanded_sql(sets: list[list[str]]) -> str:
    one = lambda i, s: f"SELECT {i} AS level, {'o_orderpriority' if 'priority' in s else 'NULL'} AS g_priority, {'o_orderstatus' if 'status' in s else 'NULL'} AS g_status, count(DISTINCT o_custkey)::DOUBLE AS owners FROM orders GROUP BY 1, 2, 3"
    return " UNION ALL ".join(one(i, s) for i, s in enumerate(sets))


_ROLLUP = [["priority", "status"], ["priority"], []]
_CUBE = [*_ROLLUP, ["status"]]
query("p_rollup", _expanded_sql(_ROLLUP))(lambda spark, d: _expanded(spark, d, _ROLLUP))
query("p_cube", _expanded_sql(_CUBE))(lambda spark, d: _expanded(spark, d, _CUBE))


@query("p_pivot", "SELECT status, count(DISTINCT o_custkey) FILTER (o_orderpriority = '1-URGENT')::DOUBLE AS urgent, count(DISTINCT o_custkey) FILTER (o_orderpriority = '5-LOW')::DOUBLE AS low FROM (SELECT *, o_orderstatus AS status FROM orders) GROUP BY status")
def _(spark, d):
    """The values of the pivoted column are public, so all are released; the table is turned afterwards."""
    domain = spark.sql("SELECT s.col AS status, p.col AS priority FROM (SELECT explode(array('F', 'O', 'P')) AS col) s, (SELECT explode(array('1-URGENT', '5-LOW')) AS col) p")
    long = private_aggregate(T.ORDERS[0](spark, d), ["status", "priority"], [A.priv_count_owners()], PrivacyParams(1.0, 0.0, 100), _exact(), key_domain=domain).df
    return long.groupBy("status").pivot("priority", ["1-URGENT", "5-LOW"]).agg(F.first("owners")).select("status", F.col("1-URGENT").alias("urgent"), F.col("5-LOW").alias("low"))


