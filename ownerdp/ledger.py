"""What has been spent on each table, and by which releases."""

from __future__ import annotations

import datetime
import hashlib
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Ends the id of the row that takes a charge back.
REFUSED = ":refused"
SCHEMA = "id string, at timestamp, table string, owner string, eps double, delta double, query string, plan string"


class BudgetExceeded(ValueError):
    """The query would spend more than the table allows."""


class PrivacyLedger:
    """An append-only Parquet table. Charges add up: losses of several releases on one table compose."""

    def __init__(self, spark: SparkSession, path: str, eps_limit: float = float("inf"), delta_limit: float = float("inf")):
        self.spark, self.path, self.eps_limit, self.delta_limit = spark, path, eps_limit, delta_limit

    def entries(self) -> DataFrame:
        try:
            return self.spark.read.schema(SCHEMA).parquet(self.path)
        except Exception as error:
            if "PATH_NOT_FOUND" in str(error):
                return self.spark.createDataFrame([], SCHEMA)
            raise

    def spent(self, table: str, owner: str) -> tuple[float, float]:
        its = self.entries().filter((F.col("table") == table) & (F.col("owner") == owner))
        refused = its.filter(F.col("id").endswith(REFUSED)).select(F.regexp_replace("id", f"{REFUSED}$", "").alias("id"))
        row = its.join(refused, "id", "left_anti").agg(F.sum("eps"), F.sum("delta")).first()
        return row[0] or 0.0, row[1] or 0.0

    @staticmethod
    def plan_hash(df: DataFrame) -> str:
        """Equal for the same query over the same data, so that a stored release can be used again without spending."""
        return hashlib.sha256(df._jdf.queryExecution().analyzed().canonicalized().toString().encode()).hexdigest()

    def known(self, plan: str) -> bool:
        return not self.entries().filter(F.col("plan") == plan).isEmpty()

    def charge(self, table: str, owner: str, eps: float, delta: float, query: str = "", plan: str = "") -> str:
        """Writes the charge before the query runs; takes it back and raises if the table allows no more.

        The charge is written before the sum is read, so of two charges at once that exceed the limit together at least one is refused.
        """
        if eps < 0 or delta < 0:
            raise ValueError("a charge cannot be negative")
        number = self._append(table, owner, eps, delta, query, plan)
        e, d = self.spent(table, owner)
        if e > self.eps_limit * (1 + 1e-12) or d > self.delta_limit * (1 + 1e-12):
            self._append(table, owner, 0.0, 0.0, query, "", number + REFUSED)
            raise BudgetExceeded(f"{table}: {e:g} of eps {self.eps_limit:g}, {d:g} of delta {self.delta_limit:g}")
        return number

    def _append(self, table: str, owner: str, eps: float, delta: float, query: str, plan: str, number: str | None = None) -> str:
        row = (number or uuid.uuid4().hex, datetime.datetime.now(), table, owner, float(eps), float(delta), query, plan)
        self.spark.createDataFrame([row], SCHEMA).coalesce(1).write.mode("append").parquet(self.path)
        return row[0]
