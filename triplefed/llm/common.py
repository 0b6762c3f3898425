"""Shared plumbing of the training-data operators.

Nothing here depends on the rest of the library, and nothing in the rest depends on this.
"""

from __future__ import annotations

import os
import tempfile
import uuid
import zipfile
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
LOWER = UPPER.lower()

#: Java and DuckDB spelling of a run of characters other than blank and the five ASCII line and tab controls.
WORD = r"[^\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables; the path may be any that Spark's readers open."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def ascii_lower(c: Column | str) -> Column:
    """Only A-Z change; no locale or Unicode rule applies."""
    return F.translate(F.col(c) if isinstance(c, str) else c, UPPER, LOWER)


def shared_dir(spark: SparkSession) -> str:
    """The folder that the session's ``spark.checkpoint.dir`` names. Only a local master, where all share one disk, may do
    without."""
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not root:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        root = "file://" + tempfile.mkdtemp(prefix="triplefed-checkpoint-")
        spark.sparkContext.setCheckpointDir(root)
    return root.rstrip("/")


#: The setting under which what an action shuffled goes when the action ends, not when the driver collects its garbage.
CLEAN = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


@contextmanager
def tidy(spark: SparkSession) -> Iterator[None]:
    """Actions made within leave no shuffle files."""
    before = spark.conf.get(CLEAN, None)
    spark.conf.set(CLEAN, "true")
    try:
        yield
    finally:
        spark.conf.unset(CLEAN) if before is None else spark.conf.set(CLEAN, before)


def materialize(df: DataFrame) -> DataFrame:
    """Writes ``df`` to the shared folder and reads it back: lineage ends there, and losing an executor costs nothing. What
    the writing shuffled goes with its end.

    The files go when the driver's JVM ends.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/triplefed/{uuid.uuid4().hex}"
    with tidy(spark):
        df.write.parquet(path)
    jvm = spark.sparkContext._jvm
    place = jvm.org.apache.hadoop.fs.Path(path)
    place.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).deleteOnExit(place)
    return spark.read.schema(T.StructType([T.StructField(f.name, f.dataType, True) for f in df.schema])).parquet(path)


#: Bytes of rows that go to a Python worker at a time; a longer row goes alone. Spark's 64 MB are held several times over,
#: by the JVM and by the worker, while such a batch grows, is sent and comes back.
BATCH = ("spark.sql.execution.arrow.maxBytesPerBatch", "4m")
_shipped: dict[str, str] = {}


def ship(spark: SparkSession) -> None:
    """Gives the executors this package, once per application, so that Python workers need no shared PYTHONPATH. Batches of
    rows get a bound in bytes, if the session has set none: it changes what is held at once, no result."""
    if spark.conf.get(BATCH[0], None) is None:
        spark.conf.set(*BATCH)
    app = spark.sparkContext.applicationId
    if app in _shipped:
        return
    package = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    out = os.path.join(tempfile.mkdtemp(prefix="triplefed-code-"), "triplefed_code.zip")
    with zipfile.ZipFile(out, "w") as z:
        for at, _, names in os.walk(package):
            for name in names:
                if name.endswith(".py"):
                    full = os.path.join(at, name)
                    z.write(full, os.path.relpath(full, os.path.dirname(package)))
    spark.sparkContext.addPyFile(out)
    _shipped[app] = out


def power_of_two(n: float, low: int = 16, high: int = 1 << 20) -> int:
    out = low
    while out < n and out < high:
        out *= 2
    return out


def ranked(df: DataFrame, group: list[str], order: Column, ties: list[str], value: str | None, rows: int) -> DataFrame:
    """Adds ``rank`` (from 0) and, given ``value``, its ``running`` total up to and with the row, within each group.

    Rows go by ``order``, a uniform non-negative 32-bit number, then by ``ties``. A group may hold any share of all
    rows: it is cut into buckets of the order, each bucket is summed first, and the windows run over single buckets.
    """
    buckets = power_of_two(rows / 256)
    shift = 32 - (buckets.bit_length() - 1)
    given = df.withColumn("__order", order).withColumn("__bucket", F.shiftright("__order", shift))
    # null groups are a group: keys of the join are compared null-safely through a pair of plain columns
    keys = []
    for i, g in enumerate(group):
        given = given.withColumn(f"__null{i}", F.col(g).isNull()).withColumn(f"__key{i}", F.coalesce(F.col(g).cast("string"), F.lit("")))
        keys += [f"__null{i}", f"__key{i}"]
    amount = F.col(value) if value else F.lit(0)
    sums = given.groupBy(*keys, "__bucket").agg(F.count(F.lit(1)).alias("__n"), F.sum(amount).alias("__sum"))
    before = Window.partitionBy(*keys).orderBy("__bucket").rowsBetween(Window.unboundedPreceding, -1)
    sums = sums.select(
        *keys, "__bucket",
        F.coalesce(F.sum("__n").over(before), F.lit(0)).alias("__rank0"),
        F.coalesce(F.sum("__sum").over(before), F.lit(0)).alias("__sum0"),
    )
    within = Window.partitionBy(*keys, "__bucket").orderBy("__order", *ties)
    out = given.join(sums, [*keys, "__bucket"]).withColumn("rank", F.col("__rank0") + F.row_number().over(within) - 1)
    if value:
        out = out.withColumn("running", F.col("__sum0") + F.sum(value).over(within.rowsBetween(Window.unboundedPreceding, 0)))
    return out.drop(*keys, "__bucket", "__order", "__rank0", "__sum0")
