"""Which operations are accepted, by the frame and by the check of analysed plans."""

import pytest
from pyspark.sql import Window
from pyspark.sql import functions as F
from tests.conftest import SMALL

from ownerdp.functions import aggregates as A
from ownerdp.functions.noise import NoNoise, TestNoise
from ownerdp.ledger import BudgetExceeded, PrivacyLedger
from ownerdp.params import PrivacyParams
from ownerdp.plans.ownership import OwnedFrame, OwnershipError, owner_column, propagate_owner, validate_ownership
from ownerdp.plans.rewrite import private_aggregate
from ownerdp.plans.sql import parse_private, private_sql
from ownerdp.sources.catalog import OwnerCatalog, bucket_by_owner
from ownerdp.sources.tables import read_table


@pytest.fixture(scope="module")
def catalog(spark):
    c = OwnerCatalog.of_folder(spark, SMALL)
    c.create_views("own_")
    return c


GOOD = [
    "SELECT o_custkey, o_totalprice * 2 AS v FROM own_orders WHERE o_orderstatus = 'F'",
    "SELECT o_custkey AS who, o_orderstatus FROM own_orders",
    "SELECT o_custkey, o_orderpriority, sum(o_totalprice) AS s FROM own_orders GROUP BY o_custkey, o_orderpriority",
    "SELECT c_custkey, o_totalprice FROM own_customer JOIN own_orders ON c_custkey = o_custkey AND o_totalprice > 5",
    "SELECT c_custkey, n_name FROM own_customer JOIN own_nation ON c_nationkey = n_nationkey",
    "SELECT o_custkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderdate) AS r FROM own_orders",
    "SELECT o_custkey FROM own_orders UNION ALL SELECT c_custkey FROM own_customer",
    "SELECT DISTINCT user_id, event_type FROM own_events",
    "SELECT c_custkey, c_name FROM own_customer LEFT SEMI JOIN own_orders ON c_custkey = o_custkey",
    "SELECT user_id, explode(array(1, 2)) AS x FROM own_events",
    "SELECT o_custkey FROM (SELECT o_custkey, count(*) AS n FROM own_orders GROUP BY o_custkey HAVING count(*) > 1)",
    "SELECT c_custkey, c_name FROM own_customer WHERE EXISTS (SELECT 1 FROM own_orders WHERE o_custkey = c_custkey AND o_totalprice > 5)",
    "SELECT c_custkey FROM own_customer WHERE NOT EXISTS (SELECT w FROM (SELECT o_custkey AS w FROM own_orders) WHERE w = c_custkey)",
    "SELECT c_custkey, c_name FROM own_customer WHERE c_custkey IN (SELECT o_custkey FROM own_orders WHERE o_totalprice > 5)",
    "SELECT c_custkey, c_name FROM own_customer WHERE c_nationkey IN (SELECT n_nationkey FROM own_nation WHERE n_name > 'F')",
    "SELECT c_custkey, c_acctbal / (SELECT max(n_nationkey) FROM own_nation) AS v FROM own_customer",
    "WITH big AS (SELECT o_custkey, o_totalprice FROM own_orders WHERE o_totalprice > 5) SELECT a.o_custkey, b.o_totalprice FROM big a JOIN big b ON a.o_custkey = b.o_custkey",
    "SELECT o_custkey, o_orderstatus, count(*) AS n FROM own_orders GROUP BY GROUPING SETS ((o_custkey, o_orderstatus), (o_custkey))",
    "SELECT o_custkey, o_orderkey FROM own_orders EXCEPT SELECT o_custkey, o_orderkey FROM own_orders WHERE o_totalprice > 5",
]
BAD = {
    "SELECT o_totalprice FROM own_orders": "drops the owner",
    "SELECT o_orderpriority, count(*) AS n FROM own_orders GROUP BY o_orderpriority": "without the owner",
    "SELECT c_custkey, o_totalprice FROM own_customer JOIN own_orders ON c_nationkey < o_orderkey": "equate their owners",
    "SELECT c_custkey, o_totalprice FROM own_customer CROSS JOIN own_orders": "equate their owners",
    "SELECT o_custkey, row_number() OVER (PARTITION BY o_orderstatus ORDER BY o_orderdate) AS r FROM own_orders": "not partitioned by the owner",
    "SELECT o_custkey FROM own_orders LIMIT 5": "limit",
    "SELECT o_custkey, o_totalprice / (SELECT max(o_totalprice) FROM own_orders) AS v FROM own_orders": "scalar subquery",
    "SELECT n_name FROM own_nation": "no owner",
    "SELECT c_custkey, n_name FROM own_nation LEFT JOIN own_customer ON c_nationkey = n_nationkey": "no owner",
    "SELECT o_custkey, o_orderkey FROM own_orders WHERE o_orderkey IN (SELECT l_orderkey FROM own_lineitem WHERE l_suppkey = 3)": "subquery without the owner",
    "SELECT o_custkey, o_orderkey FROM own_orders WHERE EXISTS (SELECT 1 FROM own_lineitem WHERE l_suppkey = 3)": "subquery without the owner",
    "SELECT o_custkey FROM own_orders WHERE EXISTS (SELECT 1 FROM own_customer WHERE c_custkey = o_custkey OR c_custkey = 7)": "subquery without the owner",
    "SELECT o_custkey FROM own_orders WHERE EXISTS (SELECT 1 FROM own_customer WHERE c_nationkey = o_orderkey)": "subquery without the owner",
    "SELECT o_custkey, (SELECT count(*) FROM own_customer WHERE c_custkey = o_custkey) AS n FROM own_orders": "scalar subquery",
    "SELECT o_custkey, n_name FROM own_orders CROSS JOIN (SELECT n_name FROM own_nation WHERE (SELECT count(*) FROM own_customer) > 5)": "scalar subquery",
    "SELECT o_custkey, o_orderkey FROM own_orders UNION ALL SELECT o_orderkey, o_custkey FROM own_orders": "different columns",
    "SELECT o_custkey, o_orderkey FROM own_orders INTERSECT SELECT o_orderkey, o_custkey FROM own_orders": "different columns",
    "SELECT o_custkey, o_orderkey FROM own_orders EXCEPT SELECT o_orderkey, o_custkey FROM own_orders": "different columns",
    "SELECT o_custkey % 2 AS who, count(*) AS n FROM own_orders GROUP BY o_custkey": "drops the owner",
    "SELECT o_custkey, row_number() OVER (PARTITION BY o_custkey % 2 ORDER BY o_orderdate) AS r FROM own_orders": "not partitioned by the owner",
    "SELECT o_custkey, o_orderstatus, count(*) AS n FROM own_orders GROUP BY ROLLUP (o_custkey, o_orderstatus)": "grouping without the owner",
    "WITH n AS (SELECT count(*) AS n FROM own_orders) SELECT c_custkey, n FROM own_customer CROSS JOIN n": "without the owner",
    "SELECT c_custkey FROM own_customer WHERE c_custkey NOT IN (SELECT o_orderkey FROM own_orders)": "subquery without the owner",
    "SELECT n_nationkey FROM own_nation LEFT SEMI JOIN own_customer ON n_nationkey = c_nationkey": "chosen by private ones",
    "SELECT o_custkey, monotonically_increasing_id() AS place FROM own_orders": "depends on the place",
}


@pytest.mark.parametrize("sql", GOOD)
def test_accepts(spark, catalog, sql):
    df = spark.sql(sql)
    validate_ownership(df)
    assert owner_column(df) == df.columns[0]


@pytest.mark.parametrize("sql", BAD)
def test_rejects(spark, catalog, sql):
    with pytest.raises(OwnershipError, match=BAD[sql]):
        validate_ownership(spark.sql(sql))


def test_deduplication_needs_the_owner(spark, catalog):
    orders = spark.table("own_orders")
    validate_ownership(orders.dropDuplicates(["o_custkey", "o_orderstatus"]))
    with pytest.raises(OwnershipError, match="deduplication"):
        validate_ownership(orders.dropDuplicates(["o_orderstatus"]))


def test_what_a_release_reads_is_checked(spark, catalog):
    """Whatever way rows, keys and arguments came about, private_aggregate refuses those that mix owners."""
    orders, one = catalog.owned("orders"), PrivacyParams(1.0, 0.0, 1, suppress=False)
    most = F.max("o_totalprice").over(Window.partitionBy("o_orderstatus"))
    release = lambda owned, keys=(), aggs=None: private_aggregate(owned, list(keys), aggs or [A.priv_count_owners()], one, TestNoise(1))
    release(orders.with_column("m", F.max("o_totalprice").over(Window.partitionBy("o_custkey"))), ["m"])
    attempts = [
        (orders.with_column("m", most), ["m"], None),
        (orders, [most.alias("m")], None),
        (orders, [], [A.priv_sum("s", most, 0, 1)]),
        (orders.select("o_orderstatus", most.alias("m")), [], None),
        (orders.filter("(SELECT count(*) FROM own_customer) > 7"), [], None),
        (orders.filter("o_orderkey IN (SELECT l_orderkey FROM own_lineitem WHERE l_suppkey = 3)"), [], None),
        (orders, [], [A.priv_sum("s", F.expr("CASE WHEN (SELECT count(*) FROM own_orders WHERE o_custkey = 7) > 0 THEN 1 ELSE 0 END"), 0, 1)]),
        (orders.join_public(orders.unowned().groupBy("o_orderstatus").agg(F.max("o_totalprice").alias("m")), "o_orderstatus"), ["m"], None),
        (OwnedFrame(spark.table("own_orders").dropDuplicates(["o_orderstatus"]), "o_custkey"), [], None),
        (OwnedFrame(spark.table("own_orders"), "o_orderkey"), [], None),
        (OwnedFrame(read_table(spark, SMALL, "orders"), "o_custkey"), [], None),
    ]
    for owned, keys, aggs in attempts:
        with pytest.raises(OwnershipError):
            release(owned, keys, aggs)
    for text in (
        "SELECT priv_sum(CASE WHEN (SELECT count(*) FROM own_orders WHERE o_custkey = 7) > 0 THEN 1 ELSE 0 END, 0, 1) AS s FROM own_customer",
        "SELECT priv_count(max(c_acctbal) OVER (PARTITION BY c_nationkey), 0, 1) AS s FROM own_customer",
    ):
        with pytest.raises(OwnershipError):
            private_sql(spark, text + " WITH PRIVACY (eps 1)")
    with pytest.raises(OwnershipError, match="list of keys"):
        private_aggregate(orders, ["o_orderstatus"], [A.priv_count_owners()], one, TestNoise(1), key_domain=orders.unowned().select("o_orderstatus").distinct())
    released = release(orders, ["o_orderstatus"]).fixed().df
    assert private_aggregate(orders, ["o_orderstatus"], [A.priv_count_owners()], one, TestNoise(1), key_domain=released.select("o_orderstatus")).df.count() == released.count()


def test_releases_are_charged(spark, tmp_path):
    ledger = PrivacyLedger(spark, str(tmp_path / "ledger"), eps_limit=1.0)
    catalog = OwnerCatalog.of_folder(spark, SMALL, ["orders", "customer", "events"])
    catalog.create_views("led_")
    both = catalog.owned("customer").join_owner(catalog.owned("orders").select("o_totalprice"))
    private_aggregate(both, [], [A.priv_count_owners()], PrivacyParams(0.6), TestNoise(1), ledger=ledger)
    assert ledger.spent("orders", "c_custkey") == ledger.spent("customer", "c_custkey") == (0.6, 0.0)
    with pytest.raises(BudgetExceeded):
        private_aggregate(both, [], [A.priv_count_owners()], PrivacyParams(0.6), TestNoise(1), ledger=ledger)
    private_sql(spark, "SELECT event_type, priv_count_owners() AS n FROM led_events GROUP BY event_type WITH PRIVACY (eps 0.5, delta 1e-5, partitions 5)", ledger=ledger)
    assert ledger.spent("events", "user_id") == (0.5, 1e-5)


def test_frame_keeps_rows_and_owner(spark, catalog):
    orders = catalog.owned("orders")
    assert orders.select("o_totalprice").columns == ["o_custkey", "o_totalprice"]
    assert propagate_owner(orders, ["o_totalprice"]).columns == ["o_custkey", "o_totalprice"]
    assert propagate_owner(orders, group_by=["o_orderstatus"], n=F.count(F.lit(1))).columns == ["o_custkey", "o_orderstatus", "n"]
    for attempt in (lambda: orders.collect(), lambda: orders.write, lambda: orders.toPandas(), lambda: orders.show()):
        with pytest.raises(OwnershipError):
            attempt()
    with pytest.raises(OwnershipError):
        orders.with_column("o_custkey", F.lit(1))
    with pytest.raises(OwnershipError):
        orders.join_public(catalog.public("nation"), F.lit(True), "full")
    with pytest.raises(OwnershipError):
        catalog.owned("nation")
    with pytest.raises(OwnershipError):
        catalog.public("orders")
    with pytest.raises(OwnershipError):
        orders.join_owner(orders)


def test_pandas_functions_cannot_change_owners(spark, catalog):
    changed = catalog.owned("events").select("value").apply_per_owner(lambda rows: rows.assign(user_id=0)[["user_id", "value"]], "user_id long, value double")
    with pytest.raises(Exception, match="changed the owner"):
        changed.unowned().collect()


def test_other_formats(spark, tmp_path):
    df = read_table(spark, SMALL, "customer").select("c_custkey", "c_mktsegment")
    catalog = OwnerCatalog(spark)
    for source in ("csv", "json", "orc", "parquet"):
        path = str(tmp_path / source)
        df.write.format(source).option("header", True).save(path)
        catalog.register_format(source, source, path, "c_custkey", "c_custkey long, c_mktsegment string", **({"header": "true"} if source == "csv" else {}))
        assert catalog.owned(source).unowned().count() == df.count()
    bucket_by_owner(df, "ownerdp_bucketed", "c_custkey", 4)
    catalog.register_table("bucketed", "ownerdp_bucketed", "c_custkey")
    plan = catalog.owned("bucketed").group("c_mktsegment", n=F.count(F.lit(1))).unowned()._jdf.queryExecution().executedPlan().toString()
    assert "Bucketed: true" in plan and "Exchange" not in plan
    spark.sql("DROP TABLE ownerdp_bucketed")


def test_sql_text(spark, catalog):
    keys, aggs, relation, settings = parse_private("SELECT k, priv_sum(a + f(b, 1), 0, 5) AS s, priv_count_owners() AS n FROM (SELECT 1, ',') t WHERE x IN (1, 2) GROUP BY k WITH PRIVACY (eps 1.5, partitions 3, delta 1e-6)")
    assert keys == ["k"] and [a.name for a in aggs] == ["s", "n"] and relation == "SELECT * FROM (SELECT 1, ',') t WHERE x IN (1, 2)"
    assert settings == {"eps": 1.5, "c_u": 3, "delta": 1e-6}
    text = "SELECT segment, priv_sum(v, 0, 10) AS s FROM (SELECT c_custkey, c_mktsegment AS segment, 1 AS v FROM own_customer JOIN own_orders ON c_custkey = o_custkey) GROUP BY segment WITH PRIVACY (eps 1, threshold -1)"
    result = private_sql(spark, text, noise=NoNoise(unsafe_for_tests=True))
    assert result.df.count() == 5
    by_expression = "SELECT year(o_orderdate) AS y, priv_count_owners() AS n FROM own_orders GROUP BY {} WITH PRIVACY (eps 1, partitions 9, threshold -1e9, intervals 0.9)"
    for by in ("y", "1", "year(o_orderdate)"):
        assert private_sql(spark, by_expression.format(by), noise=NoNoise(unsafe_for_tests=True)).df.columns == ["y", "n", "n_lo", "n_hi"]
    assert "is_leftover" in private_sql(spark, "SELECT o_orderstatus, priv_count_owners() AS n FROM own_orders GROUP BY o_orderstatus WITH PRIVACY (eps 1, delta 1e-5, leftovers)", noise=TestNoise(1)).df.columns
    for wrong in ("GROUP BY o_custkey WITH PRIVACY (eps 1)", "GROUP BY 2 WITH PRIVACY (eps 1)", "GROUP BY y WITH PRIVACY (eps 1, budget 3)", "GROUP BY y, o_orderstatus WITH PRIVACY (eps 1)"):
        with pytest.raises(OwnershipError):
            private_sql(spark, f"SELECT year(o_orderdate) AS y, priv_count_owners() AS n FROM own_orders {wrong}")
    for bad in ("SELECT a, priv_count_owners() AS n FROM own_orders", "SELECT priv_count_owners() AS n FROM own_orders LIMIT 3", "SELECT priv_nothing(x) AS n FROM own_orders"):
        with pytest.raises(OwnershipError):
            private_sql(spark, bad + (" WITH PRIVACY (eps 1)" if "LIMIT" not in bad else ""))


def test_missing_owner_is_left_out(spark):
    df = spark.createDataFrame([(1, "a"), (None, "b")], "o long, k string")
    assert OwnedFrame.of(df, "o").unowned().count() == 1
    with pytest.raises(OwnershipError):
        OwnedFrame.of(df, "x")
