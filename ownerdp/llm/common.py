"""What the operators share: tables in the shared folder, code on the executors, per-worker caches."""

from __future__ import annotations

import ctypes
import os
import re
import tempfile
import uuid
import zipfile
from collections.abc import Callable, Iterable, Iterator
from pathlib import Path

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_SHIPPED: set[str] = set()
_OWN_DIR: dict[str, str] = {}
_WORKER: dict[str, tuple[str, object]] = {}

#: A word of the contracts is a run of characters other than the space and TAB, LF, VT, FF, CR;
#: ``bytes.split()`` without arguments splits at exactly these six.
WORD_PATTERN = r"[^\x20\x09-\x0D]+"


def shared_dir(spark: SparkSession) -> str:
    """The folder that the driver and all executors see: ``spark.checkpoint.dir``. Where it is unset, a new local one, if all runs in one process."""
    set_by_cluster = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if set_by_cluster:
        return set_by_cluster.rstrip("/")
    if not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    app = spark.sparkContext.applicationId
    if app not in _OWN_DIR:
        _OWN_DIR[app] = "file://" + tempfile.mkdtemp(prefix="ownerdp-")
    return _OWN_DIR[app]


def materialise(df: DataFrame, label: str, partition_by: list[str] | None = None) -> DataFrame:
    """Cuts the lineage: writes ``df`` as Parquet in the shared folder and reads it with its own schema.

    Spark's commit protocol makes the write safe against lost executors, and a later stage that fails reads it again
    instead of computing it again.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"
    writer = df.write.option("compression", "zstd")
    if partition_by:
        writer = writer.partitionBy(*partition_by)
    writer.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


#: Rows of ids and hashes, below 100 bytes each, that are broadcast at most.
MOST_BROADCAST_ROWS = 400_000


def small_side(df: DataFrame, label: str) -> DataFrame:
    """The rows, written out and counted: marked for a broadcast if they are few enough, else left to a shuffled join."""
    out = materialise(df, label)
    return F.broadcast(out) if out.count() <= MOST_BROADCAST_ROWS else out


def free_names(df: DataFrame, *names: str) -> list[str]:
    """These names, each behind as many underscores as no column of ``df`` needs to begin with."""
    lead = "__"
    while any(c.lower().startswith(lead) for c in df.columns):
        lead += "_"
    return [lead + n for n in names]


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def ship_package(spark: SparkSession) -> None:
    """Sends this package to the executors once per application, for clusters whose workers lack it."""
    app = spark.sparkContext.applicationId
    if app in _SHIPPED:
        return
    root = Path(__file__).resolve().parents[2]
    if not (root / "ownerdp").is_dir():  # already imported from a shipped archive
        return
    target = os.path.join(tempfile.mkdtemp(prefix="ownerdp-code-"), "ownerdp_code.zip")
    with zipfile.ZipFile(target, "w") as archive:
        for source in sorted((root / "ownerdp").rglob("*.py")):
            archive.write(source, source.relative_to(root))
    spark.sparkContext.addPyFile(target)
    _SHIPPED.add(app)


def per_worker(kind: str, key: str, make: Callable[[], object]):
    """A value that one Python worker keeps from task to task, such as a cache of bounded size; one of each kind."""
    if kind not in _WORKER or _WORKER[kind][0] != key:
        _WORKER.pop(kind, None)
        _WORKER[kind] = (key, make())
    return _WORKER[kind][1]


def keep_freed_memory(most: int = 64 << 20) -> None:
    """Tells the C library of this worker to keep up to so many bytes that were freed, instead of giving them back and asking for them again.

    Steps that make and drop arrays of some 100 kB spend half their time on that otherwise. Does nothing where the library has no such setting.
    """
    try:
        library = ctypes.CDLL(None)
        library.mallopt(-1, most)  # M_TRIM_THRESHOLD
        library.mallopt(-3, most // 4)  # M_MMAP_THRESHOLD
    except (OSError, AttributeError, TypeError):
        pass


class BoundedCache:
    """A mapping of at most ``2 * limit`` entries with keys of at most LONGEST: two generations, of which the older one is dropped when the newer is full."""

    LONGEST = 256

    def __init__(self, limit: int):
        self.limit, self.young, self.old = limit, {}, {}

    def make_room(self, added: Iterable = ()) -> None:
        """To be called once what was added has been used; long keys among it go at once."""
        for key in added:
            if len(key) > self.LONGEST:
                del self.young[key]
        if len(self.young) >= self.limit:
            self.old, self.young = self.young, {}

    def find(self, key):
        if (value := self.young.get(key)) is None and (value := self.old.get(key)) is not None:
            self.young[key] = value
        return value


def map_batches(df: DataFrame, function: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]], schema: str) -> DataFrame:
    ship_package(df.sparkSession)
    return df.mapInArrow(function, schema)


def column_values(batch: pa.RecordBatch, name: str) -> list:
    return batch.column(batch.schema.get_field_index(name)).to_pylist()


def texts_of(batch: pa.RecordBatch, name: str = "text") -> list[str]:
    """The texts of a batch; null counts as empty."""
    return [x or "" for x in column_values(batch, name)]


def digest_text(*values) -> "F.Column":
    return F.sha2(F.concat_ws(",", *values), 256)
