"""Private releases of streams: windows are released once, when the watermark has closed the accounting period in which they end, and of each
owner at most c_u windows of a period enter, chosen uniformly.

The watermark depends on the timestamps of all owners and is treated as public clock time.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ownerdp.functions.aggregates import Agg
from ownerdp.functions.noise import Noise
from ownerdp.ledger import PrivacyLedger
from ownerdp.operators.sampling import limit_partitions
from ownerdp.params import PrivacyParams
from ownerdp.plans.ownership import OwnedFrame
from ownerdp.plans.rewrite import private_aggregate


def replay(spark: SparkSession, folder: str, table: str = "events", files_per_trigger: int = 1) -> DataFrame:
    """A stored table, a file or a folder of files, as a stream of its files."""
    path = f"{folder}/{table}.parquet"
    schema = spark.read.parquet(path).schema
    reader = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger)
    place = spark._jvm.org.apache.hadoop.fs.Path(path)
    if place.getFileSystem(spark._jsc.hadoopConfiguration()).getFileStatus(place).isFile():
        return reader.option("pathGlobFilter", f"{table}.parquet").parquet(folder)
    return reader.parquet(path)


def in_utc(df: DataFrame, time: str) -> DataFrame:
    """Clock times without a zone as instants, read as UTC, which watermarks need."""
    if df.schema[time].dataType.simpleString() != "timestamp_ntz":
        return df
    return df.withColumn(time, F.from_utc_timestamp(F.col(time).cast("timestamp"), F.current_timezone()))


def clock_times(df: DataFrame, *times: str) -> DataFrame:
    """The other way round."""
    return df.withColumns({t: F.to_utc_timestamp(F.col(t), F.current_timezone()).cast("timestamp_ntz") for t in times})


def tumbling(time: str, length: str) -> Column:
    return F.window(time, length)


def sliding(time: str, length: str, slide: str) -> Column:
    """A row is in length / slide windows, all of which count against its owner's limit."""
    return F.window(time, length, slide)


def sessions(time: str, gap: str) -> Column:
    return F.session_window(time, gap)


def windowed_partials(df: DataFrame, owner: str, window: Column, keys: Sequence[str], delay: str | None, time: str, **aggregates: Column) -> DataFrame:
    """One row for each owner, window and keys. On a stream, late rows beyond ``delay`` are dropped and windows appear once closed.

    ``w`` is the window itself, by which ``by_period`` goes on.
    """
    source = in_utc(df, time)
    source = source.withWatermark(time, delay) if delay is not None and df.isStreaming else source
    grouped = source.groupBy(F.col(owner).alias("o"), window.alias("w"), *keys).agg(*(a.alias(n) for n, a in aggregates.items()))
    return grouped.select("o", "w", F.col("w.start").alias("w_start"), F.col("w.end").alias("w_end"), *keys, *aggregates)


PERIOD = "period"


def by_period(partials: DataFrame, period: str) -> DataFrame:
    """The same rows with the start of the accounting period in which their window ends.

    On a stream they are held back until the watermark has passed the end of the period, so all rows of a period appear in one batch, and Spark
    drops the state of the period then.
    """
    values = [c for c in partials.columns if c not in ("o", "w", "w_start", "w_end")]
    if not partials.isStreaming:
        return partials.withColumn(PERIOD, F.window(F.col("w.end") - F.expr("INTERVAL 1 MICROSECOND"), period)["start"]).drop("w")
    closed = partials.withColumn("at", F.window_time("w"))
    rows = closed.groupBy(F.window("at", period).alias("p"), "o", "w_start").agg(F.collect_list(F.struct("w_end", *values)).alias("rows"))
    return rows.select("o", "w_start", F.col("p.start").alias(PERIOD), F.inline("rows")).select("o", "w_start", "w_end", *values, PERIOD)


def quota(rows: DataFrame, c_u: int, noise: Noise, keys: Sequence[str] = ()) -> DataFrame:
    """At most c_u (window, keys) of each owner in each period, chosen uniformly among all of them: what ``release_periods`` lets through."""
    return limit_partitions(with_account(rows), ACCOUNT, c_u, noise, ["w_start", *keys]).drop(ACCOUNT)


#: An owner in one period: what a release of periods protects, and what its limits bound.
ACCOUNT = "account"


def with_account(rows: DataFrame) -> DataFrame:
    return rows.withColumn(ACCOUNT, F.concat_ws("|", F.col("o").cast("string"), F.unix_timestamp(PERIOD).cast("string")))


def release_periods(rows: DataFrame, keys: Sequence[str], aggs: Sequence[Agg], params: PrivacyParams, noise: Noise, label: str | None = None) -> DataFrame:
    """A noisy row for each window and keys that enough owners share, of whole periods (``by_period``). Each owner spends eps and delta once in each period.

    ``aggs`` read the columns of the partials; params.c_u bounds the (window, keys) of an owner in a period.
    """
    return private_aggregate(OwnedFrame.of(with_account(rows), ACCOUNT), ["w_start", *keys], aggs, params, noise, label=label).df


def _write(batch: DataFrame, path: str, number: int) -> None:
    batch.write.mode("overwrite").parquet(f"{path}/batch={number}")


def run_to_end(stream: DataFrame, path: str, checkpoint: str) -> DataFrame:
    """Runs a stream over what is there; its rows lie in ``path``, one folder for each batch, which a batch that runs again overwrites."""
    _write(stream.sparkSession.createDataFrame([], stream.schema), path, -1)
    stream.writeStream.foreachBatch(lambda batch, number: _write(batch, path, number)).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
    return stream.sparkSession.read.schema(stream.schema).parquet(f"{path}/batch=*")


def release_stream(
    rows: DataFrame, keys: Sequence[str], aggs: Sequence[Agg], params: PrivacyParams, noise: Noise, path: str, checkpoint: str, ledger: PrivacyLedger | None = None, table: str = "",
    available_now: bool = True,
):
    """Starts a query that writes the release of the periods (``by_period``) that each batch closes.

    Each of these periods is charged to the ledger before it is released, under the name of the period, so a batch that runs again is neither
    charged nor drawn anew: its noise is named by the stream's path and the batch.
    """

    def write(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        if ledger is not None:
            for r in batch.select(PERIOD).distinct().collect():  # the few periods that one batch closes
                name = f"{path}|{r[PERIOD]}"
                if not ledger.known(name):
                    ledger.charge(table, "o", params.eps, params.delta, f"period {r[PERIOD]}", name)
        held = spark.read.schema(batch.schema).parquet(_kept(batch, f"{path}-rows", number))
        _write(release_periods(held, keys, aggs, params, noise, f"{path}|{number}"), path, number)

    writer = rows.writeStream.foreachBatch(write).option("checkpointLocation", checkpoint)
    return (writer.trigger(availableNow=True) if available_now else writer).start()


def _kept(batch: DataFrame, path: str, number: int) -> str:
    """The batch, written once: a release reads its rows several times, and a batch of a stream would be computed each time."""
    _write(batch, path, number)
    return f"{path}/batch={number}"
