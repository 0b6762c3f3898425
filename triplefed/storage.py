"""Tables that cut lineage, under the session's checkpoint folder: plain folders, and tables dealt into slots.

A slot is a worker's bucket. Tables dealt alike are read slot by slot, one task each, so joins on the slot and whatever
else need no exchange. Sessions by themselves ask that a join's keys all be keys of the dealing; ``local_session`` is a
session of the same application that doesn't.
"""

from __future__ import annotations

import tempfile
import threading
import uuid
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Settings under which joins of tables dealt alike stay local, and a bound slot is the only one read.
LOCAL = {
    "spark.sql.requireAllClusterKeysForCoPartition": "false",
    "spark.sql.sources.bucketing.autoBucketedScan.enabled": "false",
    "spark.sql.autoBroadcastJoinThreshold": "-1",
    "spark.sql.adaptive.autoBroadcastJoinThreshold": "-1",
}


def root(spark: SparkSession) -> str:
    """The folder that ``spark.checkpoint.dir`` names. Only a local master, where all share one disk, may do without."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not found:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        found = "file://" + tempfile.mkdtemp(prefix="triplefed-")
        spark.sparkContext.setCheckpointDir(found)
    return found.rstrip("/")


def new_folder(spark: SparkSession) -> str:
    """A new folder; its files go when the driver's JVM ends."""
    path = f"{root(spark)}/tables/{uuid.uuid4().hex}"
    jvm = spark.sparkContext._jvm
    at = jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).deleteOnExit(at)
    return path


#: The setting under which what an action shuffled goes when the action ends, not when the driver collects its garbage.
CLEAN = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
_cleaning: dict[int, tuple[int, str | None]] = {}
_lock = threading.Lock()


@contextmanager
def tidy(spark: SparkSession):
    """Actions made within leave no shuffle files. Threads may be within at once; the last one out puts the setting back."""
    key = id(spark)
    with _lock:
        n, before = _cleaning.get(key, (0, None))
        if not n:
            before = spark.conf.get(CLEAN, None)
            spark.conf.set(CLEAN, "true")
        _cleaning[key] = n + 1, before
    try:
        yield
    finally:
        with _lock:
            n, before = _cleaning.pop(key)
            if n > 1:
                _cleaning[key] = n - 1, before
            elif before is None:
                spark.conf.unset(CLEAN)
            else:
                spark.conf.set(CLEAN, before)


def save(df: DataFrame, partition_by: list[str] | None = None) -> DataFrame:
    """Written once, read by all that follows. What the writing shuffled goes with its end."""
    spark = df.sparkSession
    path = new_folder(spark)
    with tidy(spark):
        df.write.partitionBy(*partition_by).parquet(path) if partition_by else df.write.parquet(path)
    return spark.read.schema(T.StructType([T.StructField(f.name, f.dataType, True) for f in df.schema])).parquet(path)


def discard(df: DataFrame) -> None:
    """Takes away the files of what ``save`` gave, once nothing reads it any more."""
    files = df.inputFiles()
    if files:
        spark = df.sparkSession
        at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(files[0]).getParent()
        at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


def _murmur3(x: int) -> int:
    """The hash by which Spark deals out an int, as a signed 32-bit number."""
    mask = 0xFFFFFFFF

    def turn(v: int, r: int) -> int:
        return (v << r | v >> (32 - r)) & mask

    k = turn(x * 0xCC9E2D51 & mask, 15) * 0x1B873593 & mask
    h = (turn(42 ^ k, 13) * 5 + 0xE6546B64) & mask ^ 4
    h = (h ^ h >> 16) * 0x85EBCA6B & mask
    h = (h ^ h >> 13) * 0xC2B2AE35 & mask
    h ^= h >> 16
    return h - (1 << 32) if h >> 31 else h


_slots: dict[int, list[int]] = {}


def slots(workers: int) -> list[int]:
    """For each worker the smallest number that is dealt to its bucket, so that every worker has one of its own."""
    if workers not in _slots:
        found: dict[int, int] = {}
        i = 0
        while len(found) < workers:
            found.setdefault(_murmur3(i) % workers, i)
            i += 1
        _slots[workers] = [found[k] for k in range(workers)]
    return _slots[workers]


def slot_of(worker, workers: int):
    """The slot of a column of workers."""
    return F.element_at(F.array(*(F.lit(s) for s in slots(workers))), worker + 1)


def save_by_worker(df: DataFrame, workers: int) -> str:
    """A table of ``df``, which has ``worker``, with ``slot`` added, a bucket for each worker, sorted by ``src``. Returns its
    name, which every session of the application knows."""
    spark = df.sparkSession
    name = f"triplefed_{uuid.uuid4().hex}"
    dealt = df.withColumn("slot", slot_of(F.col("worker"), workers)).repartition(workers, "slot")
    with tidy(spark):
        dealt.write.format("parquet").bucketBy(workers, "slot").sortBy("src").option("path", new_folder(spark)).saveAsTable(name)
    return name


def add_by_worker(df: DataFrame, name: str, workers: int) -> None:
    """Appends to such a table, a file for each bucket that gets rows."""
    spark = df.sparkSession
    columns = spark.table(name).columns
    df.withColumn("slot", slot_of(F.col("worker"), workers)).select(*columns).repartition(workers, "slot").write.insertInto(name)
    spark.catalog.refreshTable(name)
    local_session(spark).catalog.refreshTable(name)


def drop(spark: SparkSession, name: str) -> None:
    spark.sql(f"DROP TABLE IF EXISTS {name}")


_sessions: dict[str, SparkSession] = {}


def local_session(spark: SparkSession) -> SparkSession:
    """A session with ``LOCAL`` set, one for each application; the given session's settings stay as they are."""
    app = spark.sparkContext.applicationId
    if app not in _sessions:
        made = spark.newSession()
        for k, v in {**LOCAL, "spark.sql.session.timeZone": spark.conf.get("spark.sql.session.timeZone")}.items():
            made.conf.set(k, v)
        _sessions[app] = made
    return _sessions[app]
