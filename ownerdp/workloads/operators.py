"""Queries for every operation that is legal before a private aggregation, and for streams."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ownerdp.functions import aggregates as A
from ownerdp.functions.noise import NoNoise, TestNoise
from ownerdp.params import PrivacyParams
from ownerdp.plans.ownership import OwnedFrame
from ownerdp.plans.rewrite import private_aggregate
from ownerdp.plans.sql import private_sql
from ownerdp.sources.catalog import OwnerCatalog
from ownerdp.sources.tables import read_table, shared_dir
from ownerdp.streaming import windowed
from ownerdp.workloads.queries import ORACLES, QUERIES, query
from ownerdp.workloads.spec import SEED, Release, Workload, rounded, sql_message

_ALL = PrivacyParams(1.0, 0.0, 900, suppress=False)
_BIG = 1e12


def _orders(spark: SparkSession, d: str, *columns: str) -> OwnedFrame:
    return OwnedFrame.of(read_table(spark, d, "orders").select(F.col("o_custkey").alias("o"), *columns), "o")


def _customers(spark: SparkSession, d: str, *columns: str) -> OwnedFrame:
    return OwnedFrame.of(read_table(spark, d, "customer").select(F.col("c_custkey").alias("o"), *columns), "o")


def _events(spark: SparkSession, d: str, *columns: str) -> OwnedFrame:
    return OwnedFrame.of(read_table(spark, d, "events").select(F.col("user_id").alias("o"), *columns), "o")


def legal(name: str, sql: str, keys: list[str], value: str | None = None):
    """A query over the operation's result: the bounded answer without noise, with limits that nothing reaches."""

    def keep(source):
        releases = [Release("owners", "owners"), Release("count", "n", None, 0.0, _BIG)] + ([Release("sum", "total", value, -_BIG, _BIG)] if value else [])
        w = Workload(source, sql, keys, releases, _ALL, noisy=False)
        QUERIES[f"t_{name}"], ORACLES[f"t_{name}"] = w.run, w.oracle()
        return source

    return keep


O = "SELECT o_custkey AS o"  # noqa: E741


@legal("project", f"{O}, o_orderstatus AS s, o_totalprice * 2 AS v FROM orders", ["s"], "v")
def _(spark, d):
    return _orders(spark, d, "o_orderstatus", "o_totalprice").select(F.col("o_orderstatus").alias("s"), (F.col("o_totalprice") * 2).alias("v"))


@legal("filter", f"{O}, o_orderstatus AS s FROM orders WHERE o_totalprice BETWEEN 1000 AND 200000 AND o_orderpriority LIKE '1%' AND o_orderstatus IN ('F', 'O') AND o_orderdate IS NOT NULL", ["s"])
def _(spark, d):
    rows = _orders(spark, d, F.col("o_orderstatus").alias("s"), "o_totalprice", "o_orderpriority", "o_orderdate")
    return rows.filter(F.col("o_totalprice").between(1000, 200000) & F.col("o_orderpriority").like("1%") & F.col("s").isin("F", "O") & F.col("o_orderdate").isNotNull())


@legal("inner_agg", f"{O}, o_orderstatus AS s, sum(o_totalprice) + min(o_totalprice) + max(o_totalprice) + avg(o_totalprice) + count(o_orderkey) AS v FROM orders GROUP BY ALL", ["s"], "v")
def _(spark, d):
    p = F.col("o_totalprice")
    return _orders(spark, d, F.col("o_orderstatus").alias("s"), "o_totalprice", "o_orderkey").group("s", v=F.sum(p) + F.min(p) + F.max(p) + F.avg(p) + F.count("o_orderkey"))


@legal("inner_distinct", f"{O}, count(DISTINCT o_orderpriority) AS k FROM orders GROUP BY ALL", ["k"])
def _(spark, d):
    return _orders(spark, d, "o_orderpriority").group(k=F.countDistinct("o_orderpriority"))


_ROLL = "SELECT o_custkey AS o, o_orderstatus AS s, o_orderpriority AS p, GROUPING_ID(o_custkey, o_orderstatus, o_orderpriority) AS level FROM orders GROUP BY GROUPING SETS ((o_custkey, o_orderstatus, o_orderpriority), (o_custkey, o_orderstatus), (o_custkey)%s)"


@legal("inner_rollup", _ROLL % "", ["level", "s"])
def _(spark, d):
    return _orders(spark, d, F.col("o_orderstatus").alias("s"), F.col("o_orderpriority").alias("p")).rollup("s", "p", n=F.count(F.lit(1)))


@legal("inner_cube", _ROLL % ", (o_custkey, o_orderpriority)", ["level", "s"])
def _(spark, d):
    return _orders(spark, d, F.col("o_orderstatus").alias("s"), F.col("o_orderpriority").alias("p")).cube("s", "p", n=F.count(F.lit(1)))


@legal("join_owner", f"{O}, c_mktsegment AS s, o_totalprice AS v FROM orders JOIN customer ON o_custkey = c_custkey", ["s"], "v")
def _(spark, d):
    return _orders(spark, d, F.col("o_totalprice").alias("v")).join_owner(_customers(spark, d, F.col("c_mktsegment").alias("s")))


_E2 = "(SELECT user_id AS u, ts AS t2, event_type AS e2 FROM events)"


@legal("join_range", f"SELECT user_id AS o, event_type AS s FROM events JOIN {_E2} ON user_id = u AND t2 > ts AND t2 <= ts + INTERVAL 1 HOUR", ["s"])
def _(spark, d):
    left, right = _events(spark, d, F.col("event_type").alias("s"), "ts"), _events(spark, d, F.col("ts").alias("t2"))
    return left.join_owner(right, condition=lambda a, b: (b["t2"] > a["ts"]) & (b["t2"] <= a["ts"] + F.expr("INTERVAL 1 HOUR")))


@legal("join_asof", "SELECT e.user_id AS o, e.event_type AS s, p.value AS v FROM (SELECT * FROM events WHERE event_type = 'purchase') e ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'click') p ON e.user_id = p.user_id AND e.ts >= p.ts", ["s"], "v")
def _(spark, d):
    both = _events(spark, d, F.col("event_type").alias("s"), "ts", "value")
    bought, clicked = both.filter("s = 'purchase'").select("s", "ts"), both.filter("s = 'click'").select(F.col("ts").alias("t2"), F.col("value").alias("v"))
    return bought.asof_owner(clicked, "ts", "t2", ["v"])


_BIG_ORDERS = "(SELECT o_custkey AS u, o_orderstatus AS s FROM orders WHERE o_totalprice > 450000)"


@legal("join_left", f"SELECT c_custkey AS o, s FROM customer LEFT JOIN {_BIG_ORDERS} ON c_custkey = u", ["s"])
def _(spark, d):
    return _customers(spark, d).join_owner(_orders(spark, d, F.col("o_orderstatus").alias("s"), "o_totalprice").filter("o_totalprice > 450000").select("s"), "left")


@legal("join_full", f"SELECT coalesce(c_custkey, u) AS o, s, c FROM (SELECT c_custkey, 1 AS c FROM customer WHERE c_acctbal > 0) FULL JOIN {_BIG_ORDERS} ON c_custkey = u", ["s", "c"])
def _(spark, d):
    rich = _customers(spark, d, "c_acctbal").filter("c_acctbal > 0").select(F.lit(1).alias("c"))
    return rich.join_owner(_orders(spark, d, F.col("o_orderstatus").alias("s"), "o_totalprice").filter("o_totalprice > 450000").select("s"), "full")


@legal("join_semi", f"SELECT c_custkey AS o, c_mktsegment AS s FROM customer WHERE EXISTS (SELECT 1 FROM {_BIG_ORDERS} WHERE u = c_custkey)", ["s"])
def _(spark, d):
    return _customers(spark, d, F.col("c_mktsegment").alias("s")).semi_owner(_orders(spark, d, "o_totalprice").filter("o_totalprice > 450000"))


@legal("join_anti", f"SELECT c_custkey AS o, c_mktsegment AS s FROM customer WHERE NOT EXISTS (SELECT 1 FROM {_BIG_ORDERS} WHERE u = c_custkey)", ["s"])
def _(spark, d):
    return _customers(spark, d, F.col("c_mktsegment").alias("s")).anti_owner(_orders(spark, d, "o_totalprice").filter("o_totalprice > 450000"))


@legal("join_self", f"{O}, a.o_orderstatus AS s FROM orders a JOIN orders b ON a.o_custkey = b.o_custkey AND a.o_orderkey < b.o_orderkey".replace("o_custkey AS o", "a.o_custkey AS o"), ["s"])
def _(spark, d):
    other = _orders(spark, d, F.col("o_orderkey").alias("k2"))
    return _orders(spark, d, F.col("o_orderstatus").alias("s"), F.col("o_orderkey").alias("k1")).join_owner(other, condition=lambda a, b: a["k1"] < b["k2"])


@legal("join_public", "SELECT c_custkey AS o, n_name AS s FROM customer JOIN nation ON c_nationkey = n_nationkey", ["s"])
def _(spark, d):
    nation = read_table(spark, d, "nation").select("n_nationkey", F.col("n_name").alias("s"))
    return _customers(spark, d, "c_nationkey").join_public(nation, F.col("c_nationkey") == F.col("n_nationkey"))


@legal("window_rank", f"SELECT o, r FROM ({O}, rank() OVER (PARTITION BY o_custkey ORDER BY o_orderdate) AS r FROM orders) WHERE r <= 3", ["r"])
def _(spark, d):
    return _orders(spark, d, "o_orderdate").window("r", F.rank(), ["o_orderdate"]).filter("r <= 3")


@legal("window_lag", "SELECT user_id AS o, event_type AS s, coalesce(value - lag(value) OVER (PARTITION BY user_id ORDER BY ts, event_id), 0) AS v FROM events", ["s"], "v")
def _(spark, d):
    return _events(spark, d, F.col("event_type").alias("s"), "ts", "event_id", "value").window("before", F.lag("value"), ["ts", "event_id"]).with_column("v", F.coalesce(F.col("value") - F.col("before"), F.lit(0.0)))


@legal("window_frame", "SELECT user_id AS o, event_type AS s, sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS v FROM events", ["s"], "v")
def _(spark, d):
    return _events(spark, d, F.col("event_type").alias("s"), "ts", "event_id", "value").window("v", F.sum("value"), ["ts", "event_id"], ("rows", -2, 0))


@legal("topk_owner", f"SELECT o, s, v FROM ({O}, o_orderstatus AS s, o_totalprice AS v, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) WHERE r <= 2", ["s"], "v")
def _(spark, d):
    return _orders(spark, d, F.col("o_orderstatus").alias("s"), F.col("o_totalprice").alias("v"), "o_orderkey").top_per_owner(2, F.desc("v"), F.col("o_orderkey"))


_A, _B = f"{O}, o_orderstatus AS s FROM orders WHERE o_totalprice > 300000", f"{O}, o_orderstatus AS s FROM orders WHERE o_orderpriority = '1-URGENT'"


def _two(spark, d) -> tuple[OwnedFrame, OwnedFrame]:
    rows = _orders(spark, d, F.col("o_orderstatus").alias("s"), "o_totalprice", "o_orderpriority")
    return rows.filter("o_totalprice > 300000").select("s"), rows.filter("o_orderpriority = '1-URGENT'").select("s")


@legal("union", f"{_A} UNION ALL {_B}", ["s"])
def _(spark, d):
    a, b = _two(spark, d)
    return a.union(b)


@legal("distinct", f"SELECT DISTINCT * FROM ({_A})", ["s"])
def _(spark, d):
    return _two(spark, d)[0].distinct()


@legal("intersect", f"{_A} INTERSECT {_B}", ["s"])
def _(spark, d):
    a, b = _two(spark, d)
    return a.intersect(b)


@legal("except", f"{_A} EXCEPT ALL {_B}", ["s"])
def _(spark, d):
    a, b = _two(spark, d)
    return a.except_(b)


@legal("explode", "SELECT user_id AS o, unnest([event_type, substr(event_type, 1, 1)]) AS s FROM events", ["s"])
def _(spark, d):
    return _events(spark, d, "event_type").explode("s", F.array("event_type", F.substring("event_type", 1, 1)))


class _Pieces:
    """A table function: the parts of a text between dashes."""

    def eval(self, text: str):
        for piece in (text or "").split("-"):
            yield (piece,)


@legal("udtf", f"{O}, unnest(string_split(o_orderpriority, '-')) AS s FROM orders", ["s"])
def _(spark, d):
    spark.udtf.register("ownerdp_pieces", F.udtf(_Pieces, returnType="s string"))
    _orders(spark, d, "o_orderpriority").unowned().createOrReplaceTempView("ownerdp_udtf_rows")
    return OwnedFrame.of(spark.sql("SELECT o, s FROM ownerdp_udtf_rows, LATERAL ownerdp_pieces(o_orderpriority)"), "o")


@legal("scalar_string", "SELECT doc_id AS o, lower(substr(lang, 1, 1)) || length(trim(source)) || regexp_extract(source, '([0-9])', 1) AS s, len(string_split(coalesce(text, ''), ' ')) AS v FROM documents", ["s"], "v")
def _(spark, d):
    rows = OwnedFrame.of(read_table(spark, d, "documents").select(F.col("doc_id").alias("o"), "lang", "source", "text"), "o")
    return rows.select(F.concat(F.lower(F.substring("lang", 1, 1)), F.length(F.trim("source")).cast("string"), F.regexp_extract("source", "([0-9])", 1)).alias("s"), F.size(F.split(F.coalesce("text", F.lit("")), " ")).alias("v"))


@legal("scalar_date", f"{O}, year(o_orderdate) AS s, date_diff('day', DATE '1995-01-01', o_orderdate::DATE) + month(date_trunc('month', o_orderdate)) + month(o_orderdate + INTERVAL 2 MONTH) AS v FROM orders", ["s"], "v")
def _(spark, d):
    t = F.col("o_orderdate")
    return _orders(spark, d, "o_orderdate").select(F.year(t).alias("s"), (F.datediff(t, F.lit("1995-01-01")) + F.month(F.date_trunc("month", t)) + F.month(F.add_months(t, 2))).alias("v"))


@legal("scalar_math", f"{O}, floor(log2(o_totalprice))::INT AS s, abs(-sqrt(o_totalprice)) + round(o_totalprice / 7) + greatest(1, least(5, pow(o_totalprice, 0.1))) AS v FROM orders", ["s"], "v")
def _(spark, d):
    p = F.col("o_totalprice")
    return _orders(spark, d, "o_totalprice").select(F.floor(F.log2(p)).cast("int").alias("s"), (F.abs(-F.sqrt(p)) + F.round(F.try_divide(p, F.lit(7))) + F.greatest(F.lit(1.0), F.least(F.lit(5.0), F.pow(p, F.lit(0.1))))).alias("v"))


@legal("scalar_array", "SELECT vec_id AS o, label AS s, list_sum([x * 2 FOR x IN embedding IF x > 0])::DOUBLE + len(embedding) AS v FROM embeddings", ["s"], "v")
def _(spark, d):
    rows = OwnedFrame.of(read_table(spark, d, "embeddings").select(F.col("vec_id").alias("o"), F.col("label").alias("s"), "embedding"), "o")
    doubled = F.transform(F.filter("embedding", lambda x: x > 0), lambda x: x.cast("double") * 2)
    return rows.select("s", (F.aggregate(doubled, F.lit(0.0), lambda a, x: a + x) + F.size("embedding")).alias("v"))


@legal("scalar_json", "SELECT user_id AS o, event_type AS s, json_extract_string(props, '$.k')::DOUBLE AS v FROM events", ["s"], "v")
def _(spark, d):
    return _events(spark, d, F.col("event_type").alias("s"), F.from_json("props", "k int")["k"].cast("double").alias("v"))


@legal("scalar_case", f"{O}, CASE WHEN o_totalprice > 250000 THEN 'high' WHEN nullif(o_orderstatus, 'P') IS NULL THEN 'open' ELSE coalesce(o_orderpriority, 'none') END AS s FROM orders", ["s"])
def _(spark, d):
    rows = _orders(spark, d, "o_totalprice", "o_orderstatus", "o_orderpriority")
    return rows.select(F.when(F.col("o_totalprice") > 250000, "high").when(F.nullif(F.col("o_orderstatus"), F.lit("P")).isNull(), "open").otherwise(F.coalesce("o_orderpriority", F.lit("none"))).alias("s"))


@legal("udf", f"{O}, o_orderstatus AS s, o_totalprice / 2 AS v FROM orders", ["s"], "v")
def _(spark, d):
    def half(x: pd.Series) -> pd.Series:
        return x / 2  # NULL stays NULL; an error would stop the job and so tell about a row

    return _orders(spark, d, F.col("o_orderstatus").alias("s"), "o_totalprice").with_column("v", F.pandas_udf(half, "double")("o_totalprice"))


@legal("udaf", f"{O}, quantile_cont(o_totalprice, 0.5) AS v, count(*) AS s FROM orders GROUP BY ALL", ["s"], "v")
def _(spark, d):
    kind = read_table(spark, d, "orders").schema["o_custkey"].dataType.simpleString()

    def middle(rows: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"o": [rows["o"].iloc[0]], "s": [len(rows)], "v": [rows["o_totalprice"].median()]})

    return _orders(spark, d, "o_totalprice").apply_per_owner(middle, f"o {kind}, s long, v double")


@query("sql_surface", "SELECT o_orderpriority, count(DISTINCT o_custkey)::DOUBLE AS owners, sum(least(3, n))::DOUBLE AS n FROM (SELECT o_custkey, o_orderpriority, count(*) AS n FROM orders WHERE o_totalprice > 100000 GROUP BY ALL) GROUP BY ALL")
def _(spark, d):
    OwnerCatalog.of_folder(spark, d, ["orders", "customer"]).create_views("dp_")
    text = "SELECT o_orderpriority, priv_count_owners() AS owners, priv_count(*, 0, 3) AS n FROM dp_orders WHERE o_totalprice > 100000 GROUP BY o_orderpriority WITH PRIVACY (eps 1, partitions 900, threshold -1e9)"
    return private_sql(spark, text, noise=NoNoise(unsafe_for_tests=True, seed=SEED)).df


@query("sql_keys", "SELECT year(o_orderdate) AS y, o_orderpriority, count(DISTINCT o_custkey)::DOUBLE AS owners FROM orders WHERE o_custkey IN (SELECT c_custkey FROM customer WHERE c_acctbal > 0) GROUP BY ALL")
def _(spark, d):
    """Keys that are expressions, and a subquery that asks about rows of the same owner."""
    OwnerCatalog.of_folder(spark, d, ["orders", "customer"]).create_views("dp_")
    text = "SELECT year(o_orderdate) AS y, o_orderpriority, priv_count_owners() AS owners FROM dp_orders WHERE o_custkey IN (SELECT c_custkey FROM dp_customer WHERE c_acctbal > 0) GROUP BY 1, o_orderpriority WITH PRIVACY (eps 1, partitions 900, threshold -1e9)"
    return private_sql(spark, text, noise=NoNoise(unsafe_for_tests=True, seed=SEED)).df


# Streams -----------------------------------------------------------------------------------------------------------------------


def _folder(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/stream-{name}-{uuid.uuid4().hex}"


def _partials(spark: SparkSession, d: str, window, delay: str = "1 minute", keys: tuple[str, ...] = ()) -> DataFrame:
    return windowed.windowed_partials(windowed.replay(spark, d), "user_id", window, keys, delay, "ts", n=F.count(F.lit(1)), total=F.sum("value"))


def _stream(spark: SparkSession, d: str, window, delay: str = "1 minute") -> DataFrame:
    """The partials of all windows that the end of the replayed table has closed; the last open ones do not appear."""
    return windowed.run_to_end(_partials(spark, d, window, delay).drop("w"), _folder(spark, "rows"), _folder(spark, "state"))


def _periods(spark: SparkSession, d: str, window, period: str) -> DataFrame:
    return windowed.run_to_end(windowed.by_period(_partials(spark, d, window), period), _folder(spark, "rows"), _folder(spark, "state"))


def _closed(sql_windows: str, end: str) -> str:
    return f"SELECT w_start, count(*)::DOUBLE AS owners, sum(least(5, n))::DOUBLE AS n FROM (SELECT user_id AS o, w_start, count(*) AS n FROM ({sql_windows}) GROUP BY ALL) WHERE {end} <= (SELECT max(ts) - INTERVAL 1 MINUTE FROM events) GROUP BY ALL"


def _windows_released(partials: DataFrame) -> DataFrame:
    aggs = [A.priv_count_owners(), A.priv_sum("n", "n", 0.0, 5.0)]
    return private_aggregate(OwnedFrame.of(partials, "o"), ["w_start"], aggs, PrivacyParams(1.0, 0.0, 900, suppress=False), NoNoise(unsafe_for_tests=True, seed=SEED)).df


@query("s_replay", "SELECT event_type, count(*) AS n FROM events GROUP BY ALL")
def _(spark, d):
    rows = windowed.run_to_end(windowed.replay(spark, d).select("event_type"), _folder(spark, "rows"), _folder(spark, "state"))
    return rows.groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))


@query("s_tumbling", _closed("SELECT *, time_bucket(INTERVAL 6 HOUR, ts) AS w_start FROM events", "w_start + INTERVAL 6 HOUR"))
def _(spark, d):
    return windowed.clock_times(_windows_released(_stream(spark, d, windowed.tumbling("ts", "6 hours"))), "w_start")


@query("s_sliding", _closed("SELECT *, unnest([time_bucket(INTERVAL 6 HOUR, ts), time_bucket(INTERVAL 6 HOUR, ts) - INTERVAL 6 HOUR]) AS w_start FROM events", "w_start + INTERVAL 12 HOUR"))
def _(spark, d):
    return windowed.clock_times(_windows_released(_stream(spark, d, windowed.sliding("ts", "12 hours", "6 hours"))), "w_start")


@query("s_session", """WITH e AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events),
s AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts RANGE UNBOUNDED PRECEDING) AS s FROM e),
g AS (SELECT count(*) AS n, max(ts) + INTERVAL 30 MINUTE AS e FROM s GROUP BY user_id, s)
SELECT count(*) AS sessions, sum(n)::BIGINT AS n FROM g WHERE e <= (SELECT max(ts) - INTERVAL 1 MINUTE FROM events)""")
def _(spark, d):
    """Sessions of an owner end after half an hour without a row; those that the watermark has closed."""
    return _stream(spark, d, windowed.sessions("ts", "30 minutes")).groupBy().agg(F.count(F.lit(1)).alias("sessions"), F.sum("n").alias("n"))


_DAY_PARAMS = PrivacyParams(8.0, 1e-3, 5)
_DAYS_SQL = "SELECT user_id AS o, time_bucket(INTERVAL 1 DAY, ts) AS w_start, count(*) AS n FROM events GROUP BY ALL HAVING time_bucket(INTERVAL 1 DAY, ts) + INTERVAL 1 DAY <= (SELECT max(ts) - INTERVAL 10 MINUTE FROM events)"
_LATE = Workload(lambda spark, d: None, _DAYS_SQL, ["w_start"], [Release("sum", "n", "n", 0.0, 5.0)], _DAY_PARAMS)


@query("s_late", _LATE.oracle())
def _(spark, d):
    """Windows of one day, private: each is released once, after the watermark, where enough owners share it."""
    rows = windowed.clock_times(_stream(spark, d, windowed.tumbling("ts", "1 day"), "10 minutes"), "w_start", "w_end")
    return rounded(private_aggregate(OwnedFrame.of(rows, "o"), ["w_start"], [A.priv_sum("n", "n", 0.0, 5.0)], _DAY_PARAMS, TestNoise(SEED)).df)


_WINDOWS_SQL = "SELECT DISTINCT user_id AS o, time_bucket(INTERVAL 6 HOUR, ts) AS w_start, date_trunc('day', ts) AS p, user_id || '|' || epoch(date_trunc('day', ts))::BIGINT AS account FROM events WHERE date_trunc('day', ts) + INTERVAL 1 DAY <= (SELECT max(ts) - INTERVAL 1 MINUTE FROM events)"


@query("s_quota", f"SELECT o, w_start, p AS period FROM ({_WINDOWS_SQL}) QUALIFY row_number() OVER (PARTITION BY account ORDER BY md5({sql_message('limit', ['account', 'w_start'])})) <= 2")
def _(spark, d):
    """The library's quota: at most two windows of an owner in each day, chosen uniformly once the day is closed."""
    rows = _periods(spark, d, windowed.tumbling("ts", "6 hours"), "1 day")
    return windowed.clock_times(windowed.quota(rows, 2, TestNoise(SEED)).select("o", "w_start", "period"), "w_start", "period")


@query("s_release", f"""WITH k AS (SELECT * FROM ({_WINDOWS_SQL}) QUALIFY row_number() OVER (PARTITION BY account ORDER BY md5({sql_message('limit', ['account', 'w_start'])})) <= 2)
SELECT w_start, count(*)::DOUBLE AS owners FROM k GROUP BY w_start""")
def _(spark, d):
    """The whole path, without noise: windows by period, the limit on each owner within the period, the release of each batch."""
    path = _folder(spark, "released")
    rows = windowed.by_period(_partials(spark, d, windowed.tumbling("ts", "6 hours")), "1 day")
    free = PrivacyParams(1.0, 0.0, 2, suppress=False)
    windowed.release_stream(rows, [], [A.priv_count_owners()], free, NoNoise(unsafe_for_tests=True, seed=SEED), path, _folder(spark, "state")).awaitTermination()
    return windowed.clock_times(spark.read.schema("w_start timestamp, owners double").parquet(f"{path}/batch=*"), "w_start")
