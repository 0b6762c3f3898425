"""Query logs and updates as streams."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from triplefed.storage import root


def read_log(spark: SparkSession, sf_dir: str, files: int = 1) -> DataFrame:
    """The events as a stream of queries: seq, ts, template_id, user."""
    from triplefed.sources.graphs import read_table

    schema = read_table(spark, sf_dir, "events").schema
    raw = spark.readStream.schema(schema).option("maxFilesPerTrigger", files).option("pathGlobFilter", "*.parquet")
    # the reader wants a folder: the file is named as the only one of its folder's that fits
    stream = raw.option("pathGlobFilter", "events.parquet").parquet(sf_dir) if _is_file(spark, f"{sf_dir}/events.parquet") else raw.parquet(f"{sf_dir}/events.parquet")
    return stream.select(F.col("event_id").alias("seq"), F.col("ts").cast("timestamp").alias("ts"), F.col("event_type").alias("template_id"), F.col("user_id").alias("user"))


def _is_file(spark: SparkSession, path: str) -> bool:
    jvm = spark.sparkContext._jvm
    at = jvm.org.apache.hadoop.fs.Path(path)
    return at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(at).isFile()


def drain(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Runs a stream over all that is there now and gives what it wrote."""
    spark = stream.sparkSession
    at = f"{root(spark)}/streams/{uuid.uuid4().hex}"
    if mode == "append":
        q = stream.writeStream.format("parquet").option("path", f"{at}/out").option("checkpointLocation", f"{at}/state").outputMode("append").trigger(availableNow=True).start()
        q.awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{at}/out")
    q = stream.writeStream.foreachBatch(lambda df, i: df.write.mode("overwrite").parquet(f"{at}/out")).option("checkpointLocation", f"{at}/state").outputMode("complete").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{at}/out")


def frequency(log: DataFrame, length: str = "1 day", slide: str | None = None) -> DataFrame:
    """Queries of each template in each window; tumbling, or sliding by ``slide``."""
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    return log.groupBy(w.alias("w"), "template_id").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "template_id", "n")


def sessions(log: DataFrame, gap: str = "30 minutes") -> DataFrame:
    return log.groupBy(F.session_window("ts", gap).alias("w"), "template_id").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "template_id", "n")


def triggers(log: DataFrame, freq: int = 3) -> DataFrame:
    """template_id, seen: a row once, when a template's count first goes above ``freq``. State is a count for each."""

    def count(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        seen = state.get[0] if state.exists else 0
        more = sum(len(b) for b in batches)
        state.update((seen + more,))
        if seen <= freq < seen + more:
            yield pd.DataFrame({"template_id": [key[0]], "freq": [freq]})

    return log.groupBy("template_id").applyInPandasWithState(count, "template_id string, freq int", "n long", "append", GroupStateTimeout.NoTimeout)


def deduplicated(log: DataFrame, late: str = "1 hour") -> DataFrame:
    return log.withWatermark("ts", late).dropDuplicatesWithinWatermark(["seq"])


def with_graph(log: DataFrame, t: DataFrame, predicate: str) -> DataFrame:
    """Each query's user with what the graph says of it: stream and static join."""
    facts = t.where(F.col("p") == predicate).select(F.col("s").alias("who"), F.col("o").alias("value"))
    return log.withColumn("who", F.concat(F.lit("customer/"), F.col("user").cast("string"))).join(facts, "who").select("seq", "who", "value")


def within(log: DataFrame, other: DataFrame, minutes: int = 5) -> DataFrame:
    """Pairs of queries of one user, the second within some minutes after the first: stream and stream join."""
    a = log.withWatermark("ts", "1 hour").select(F.col("seq").alias("seq_a"), F.col("ts").alias("ts_a"), F.col("user").alias("user_a"))
    b = other.withWatermark("ts", "1 hour").select(F.col("seq").alias("seq_b"), F.col("ts").alias("ts_b"), F.col("user").alias("user_b"))
    return a.join(b, F.expr(f"user_a = user_b AND ts_b > ts_a AND ts_b <= ts_a + INTERVAL {minutes} MINUTES")).select("seq_a", "seq_b")


LATE_SQL = """SELECT strftime(date_trunc('day', ts), '%Y-%m-%d') AS window_start, count(*) AS n FROM events
    WHERE ts >= TIMESTAMP '2024-01-11' AND date_trunc('day', ts) + INTERVAL 1 DAY <= (SELECT max(ts) - INTERVAL 1 DAY FROM events) GROUP BY 1"""


def late_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Queries in each day, of a log whose first file begins on the 11th and whose second holds the days before: its rows
    are all later than the watermark allows and are dropped. Days that the watermark hasn't passed aren't out yet."""
    from triplefed.sources.graphs import read_table

    at = f"{root(spark)}/streams/{uuid.uuid4().hex}"
    events = read_table(spark, sf_dir, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"))
    for part in ("ts >= TIMESTAMP '2024-01-11'", "ts < TIMESTAMP '2024-01-11'"):
        # the stream runs over what is there, ends, and goes on where it was when the second file has come
        events.where(part).coalesce(1).write.mode("append").parquet(f"{at}/log")
        log = spark.readStream.schema(events.schema).parquet(f"{at}/log").withWatermark("ts", "1 day")
        days = log.groupBy(F.window("ts", "1 day").alias("w")).agg(F.count(F.lit(1)).alias("n"))
        days = days.select(F.date_format("w.start", "yyyy-MM-dd").alias("window_start"), "n")
        days.writeStream.format("parquet").option("path", f"{at}/out").option("checkpointLocation", f"{at}/state").outputMode("append").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(days.schema).parquet(f"{at}/out")


def apply_updates(stream: DataFrame, apply: Callable[[DataFrame, int], None], checkpoint: str) -> None:
    """Each micro-batch of (op, s, p, o) once. A batch is marked under the checkpoint when it has been applied, so that a
    restart between the two applies it again; deletes of what is gone and inserts of what is there do nothing, which makes
    that harmless. A marked batch is passed over."""
    spark = stream.sparkSession
    jvm = spark.sparkContext._jvm

    def once(df: DataFrame, number: int) -> None:
        mark = jvm.org.apache.hadoop.fs.Path(f"{checkpoint}/applied/{number}")
        system = mark.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
        if not system.exists(mark):
            apply(df, number)
            system.mkdirs(mark)

    stream.writeStream.foreachBatch(once).option("checkpointLocation", f"{checkpoint}/state").trigger(availableNow=True).start().awaitTermination()


def updated_graph(spark: SparkSession, sf_dir: str) -> DataFrame:
    """p, n after a stream of updates: a fifth of two predicates' triples deleted, then that of one inserted again."""
    from triplefed.operators.patterns import MainIndex
    from triplefed.operators.updates import split_batches
    from triplefed.sources.graphs import shop_graph

    at = f"{root(spark)}/streams/{uuid.uuid4().hex}"
    t = shop_graph(spark, sf_dir).where(F.col("p").isin("brand", "partKind"))
    main = MainIndex(t, both=False)
    fifth = split_batches(main.triples(), 5, 1).drop("batch")
    fifth.select(F.lit("D").alias("op"), "s", "p", "o").coalesce(1).write.mode("append").parquet(f"{at}/log")
    fifth.where("p = 'brand'").select(F.lit("I").alias("op"), "s", "p", "o").coalesce(1).write.mode("append").parquet(f"{at}/log")

    def apply(df: DataFrame, number: int) -> None:
        main.delete(df.where("op = 'D'"), 2 * number + 1)
        main.insert(df.where("op = 'I'"), 2 * number + 2)

    for _ in range(2):  # the second run finds every batch marked
        log = spark.readStream.schema("op string, s string, p string, o string").option("maxFilesPerTrigger", 1).parquet(f"{at}/log")
        apply_updates(log, apply, f"{at}/checkpoint")
    return main.triples().groupBy("p").agg(F.count(F.lit(1)).alias("n"))
