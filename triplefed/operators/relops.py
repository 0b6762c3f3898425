"""Relational operators around the methods that Spark has no single call for."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def asof_join(left: DataFrame, right: DataFrame, on: str, left_time: str, right_time: str, value: str) -> DataFrame:
    """``left`` with the ``value`` of the last ``right`` row of the same key not later than it, or null.

    Both sides are merged and sorted once; the last value seen is carried on. No row meets more than one other, and a
    key's rows are streamed through a window. Of rows of the same time, ``right`` comes first.
    """
    a = left.select("*", F.col(left_time).alias("__t"), F.lit(1).alias("__side"), F.lit(None).cast(right.schema[value].dataType).alias("__v"))
    b = right.groupBy(on, F.col(right_time).alias("__t")).agg(F.max(value).alias("__v"))
    b = b.select(*(F.col(on) if c == on else F.lit(None).cast(left.schema[c].dataType).alias(c) for c in left.columns), "__t", F.lit(0).alias("__side"), "__v")
    carried = F.last("__v", ignorenulls=True).over(Window.partitionBy(on).orderBy("__t", "__side").rowsBetween(Window.unboundedPreceding, 0))
    return a.unionByName(b).withColumn(f"last_{value}", carried).where("__side = 1").drop("__t", "__side", "__v")


def range_join(left: DataFrame, right: DataFrame, on: list[str], point: str, low: str, high: str, width: float) -> DataFrame:
    """Rows of ``left`` whose ``point`` is in [low, high) of ``right``: an equi-join on buckets of ``width``, each
    interval in all buckets that it touches, and the exact test."""
    bucket = lambda c: F.floor(F.col(c) / F.lit(width)).cast("long")
    a = left.withColumn("__bucket", bucket(point))
    b = right.where(F.col(low) < F.col(high)).withColumn("__bucket", F.explode(F.sequence(bucket(low), bucket(high))))
    return a.join(b, [*on, "__bucket"]).where((F.col(point) >= F.col(low)) & (F.col(point) < F.col(high))).drop("__bucket")


def skew_join(left: DataFrame, right: DataFrame, on: str, hot: DataFrame, salts: int = 16) -> DataFrame:
    """An inner join in which the keys in ``hot`` are spread: their left rows are salted, their right rows repeated for
    each salt; other keys are neither. ``hot``: one column, the keys."""
    marked = hot.select(F.col(on), F.lit(True).alias("__hot")).distinct()
    a = left.join(marked, on, "left").withColumn("__salt", F.when(F.col("__hot"), F.pmod(F.xxhash64(*left.columns), F.lit(salts))).otherwise(F.lit(0)).cast("int")).drop("__hot")
    b = right.join(marked, on, "left").withColumn("__salt", F.explode(F.when(F.col("__hot"), F.sequence(F.lit(0), F.lit(salts - 1))).otherwise(F.array(F.lit(0))))).drop("__hot")
    return a.join(b, [on, "__salt"]).drop("__salt")


def hot_keys(t: DataFrame, on: str, share: float = 0.01) -> DataFrame:
    """Keys with more than a share of all rows: fewer than 1 / share."""
    counts = t.groupBy(on).agg(F.count(F.lit(1)).alias("n"))
    return counts.crossJoin(F.broadcast(counts.agg((F.sum("n") * share).alias("least")))).where("n > least").select(on)  # one row


def top_k_per(t: DataFrame, key: str, order: list, k: int) -> DataFrame:
    return t.withColumn("rank", F.row_number().over(Window.partitionBy(key).orderBy(*order))).where(F.col("rank") <= k)


def reachable(edges: DataFrame, start: DataFrame, hops: int) -> DataFrame:
    """v, hop: vertices within ``hops`` of ``start`` (v), at their least distance; each step is written."""
    from triplefed.storage import save

    seen = frontier = save(start.select("v").distinct().withColumn("hop", F.lit(0)))
    for hop in range(1, hops + 1):
        new = frontier.select(F.col("v").alias("s")).join(edges.select("s", "o"), "s").select(F.col("o").alias("v")).distinct()
        frontier = save(new.join(seen, "v", "left_anti").withColumn("hop", F.lit(hop)))
        if frontier.isEmpty():
            break
        seen = save(seen.unionByName(frontier))
    return seen


def deterministic_sample(t: DataFrame, percent: int, *key: str) -> DataFrame:
    h = F.conv(F.substring(F.md5(F.concat_ws("|", *key)), 1, 8), 16, 10).cast("long")
    return t.where(h % 100 < percent)
