"""A balanced vertex partitioning with few cut edges: label propagation under a size limit."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from triplefed.federation import WORKERS, worker_of
from triplefed.storage import save


def mincut_partition(t: DataFrame, n: int = WORKERS, rounds: int = 6, slack: float = 1.3, kind: str = "xxhash64") -> DataFrame:
    """v, part. Vertices start by hash. In a round each vertex would join the part that most of its neighbours are in;
    of those that gain, a part admits as many as it has room for, drawn evenly by hash, so that no list is sorted.

    Every round is a join, an aggregate by vertex and part, and a write; no vertex's neighbours meet in one row.
    """
    edges = t.select(F.col("s").alias("a"), F.col("o").alias("b")).where("a <> b")
    both = save(edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))))
    now = save(both.select(F.col("a").alias("v")).distinct().select("v", worker_of("v", n, kind).alias("part")))
    total = now.count()
    limit = max(1, int(slack * total / n))
    for r in range(rounds):
        votes = both.join(now.select(F.col("v").alias("b"), "part"), "b").groupBy(F.col("a").alias("v"), "part").agg(F.count(F.lit(1)).alias("votes"))
        best = votes.groupBy("v").agg(F.max(F.struct("votes", F.xxhash64("v", "part", F.lit(r)).alias("h"), "part")).alias("best"))
        own = votes.join(now, ["v", "part"]).select("v", F.col("votes").alias("own"))
        wish = now.join(best, "v").join(own, "v", "left").select("v", "part", F.col("best.part").alias("to"), (F.col("best.votes") - F.coalesce("own", F.lit(0))).alias("gain"))
        # half of those who gain move in a round, else neighbours swap sides for ever
        wish = save(wish.withColumn("move", (F.col("to") != F.col("part")) & (F.col("gain") > 0) & (F.pmod(F.xxhash64("v", F.lit(r)), F.lit(2)) == 0)))
        room = now.groupBy("part").agg(F.count(F.lit(1)).alias("size"))
        asked = wish.where("move").groupBy(F.col("to").alias("part")).agg(F.count(F.lit(1)).alias("asked"))
        share = room.join(asked, "part").select(F.col("part").alias("to"), (F.greatest(F.lit(0), limit - F.col("size")) / F.col("asked")).alias("share"))
        luck = F.pmod(F.xxhash64("v", F.lit(-r - 1)), F.lit(1 << 20)) / F.lit(1 << 20)
        # as many rows as parts
        now = save(wish.join(F.broadcast(share), "to", "left").select("v", F.when(F.col("move") & (luck < F.coalesce("share", F.lit(1.0))), F.col("to")).otherwise(F.col("part")).alias("part")))
    return now


def largest_part(assign: DataFrame) -> DataFrame:
    size = assign.groupBy("part").agg(F.count(F.lit(1)).alias("n"))
    return size.select("part", "n", F.max("n").over(Window.partitionBy(F.lit(1))).alias("largest"))
