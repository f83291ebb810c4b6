"""What a private query gives back."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ownerdp.functions.aggregates import Agg
from ownerdp.functions.noise import Noise
from ownerdp.params import PrivacyParams
from ownerdp.sources.tables import materialise


@dataclass
class PrivateResult:
    """Released rows. Anything done to them afterwards is free. Keyed noise gives the same rows at every action; ``fixed`` writes them once."""

    df: DataFrame
    keys: list[str]
    aggs: list[Agg]
    params: PrivacyParams
    noise: Noise

    def fixed(self) -> PrivateResult:
        return PrivateResult(materialise(self.df, "release"), self.keys, self.aggs, self.params, self.noise)

    def sorted(self) -> DataFrame:
        """In the order of the keys, so that the order of rows tells nothing about the data."""
        return self.df.orderBy(*self.keys)

    def whole(self, *names: str) -> DataFrame:
        """The named counts rounded to whole numbers."""
        return self.df.withColumns({n: F.round(n).cast("long") for n in names})

    def save(self, path: str, source: str = "parquet", partition_by: list[str] | None = None) -> None:
        writer = self.sorted().write.format(source)
        (writer.partitionBy(*partition_by) if partition_by else writer).save(path)
