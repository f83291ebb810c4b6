"""Which tables belong to owners, and by which column."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession

from ownerdp.plans.ownership import OwnedFrame, OwnershipError, declare_owner
from ownerdp.sources.tables import read_table

#: Owners of the given tables; None: public. The customer view of lineitem is declared separately.
GIVEN = {
    "customer": "c_custkey", "orders": "o_custkey", "lineitem": "l_suppkey", "events": "user_id", "supplier": "s_suppkey", "conversations": "conv_id",
    "documents": "source", "labels": "doc_id", "embeddings": "vec_id", "part": None, "nation": None, "region": None, "benchmark": None,
}


@dataclass
class OwnerCatalog:
    spark: SparkSession
    tables: dict[str, tuple[DataFrame, str | None]] = field(default_factory=dict)

    @classmethod
    def of_folder(cls, spark: SparkSession, folder: str, names=GIVEN) -> OwnerCatalog:
        catalog = cls(spark)
        for name in names:
            catalog.register(name, read_table(spark, folder, name), GIVEN.get(name))
        return catalog

    def register(self, name: str, df: DataFrame, owner: str | None = None) -> None:
        """With an owner the table is private, without one public."""
        if owner is not None and owner not in df.columns:
            raise OwnershipError(f"{name} has no column {owner}")
        self.tables[name] = (df, owner)

    def register_format(self, name: str, source: str, path: str, owner: str | None = None, schema: str | None = None, **options) -> None:
        """Any format that Spark reads: parquet, orc, csv, json."""
        reader = self.spark.read.format(source).options(**options)
        self.register(name, (reader.schema(schema) if schema else reader).load(path), owner)

    def register_table(self, name: str, table: str, owner: str | None = None) -> None:
        self.register(name, self.spark.table(table), owner)

    def lookup(self, name: str) -> tuple[DataFrame, str | None]:
        if name not in self.tables:
            raise OwnershipError(f"{name} is not registered")
        return self.tables[name]

    def owned(self, name: str) -> OwnedFrame:
        df, owner = self.lookup(name)
        if owner is None:
            raise OwnershipError(f"{name} is public")
        return OwnedFrame.of(df, owner, name)

    def public(self, name: str) -> DataFrame:
        df, owner = self.lookup(name)
        if owner is not None:
            raise OwnershipError(f"{name} is private")
        return df

    def create_views(self, prefix: str = "") -> None:
        """Temporary views whose owner columns carry the flag by which plans are checked; rows without an owner are left out."""
        for name, (df, owner) in self.tables.items():
            (df if owner is None else declare_owner(df, owner, name)).createOrReplaceTempView(prefix + name)


def bucket_by_owner(df: DataFrame, table: str, owner: str, buckets: int) -> None:
    """Stores a table so that queries by owner need no shuffle of it."""
    df.write.bucketBy(buckets, owner).sortBy(owner).mode("overwrite").saveAsTable(table)


def lineitem_by_customer(spark: SparkSession, folder: str) -> OwnedFrame:
    """The trusted view of lineitem whose owner is the customer of the order."""
    orders = read_table(spark, folder, "orders")
    lines = read_table(spark, folder, "lineitem")
    return OwnedFrame.of(lines.join(orders, lines["l_orderkey"] == orders["o_orderkey"]), "o_custkey", "lineitem")
