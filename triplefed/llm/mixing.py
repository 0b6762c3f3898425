"""Mixing sources to target weights by weighted fair queueing. DataFrame functions only.

Every source is a queue of its documents in a fixed pseudo-random order, run through up to ``most`` times. A pass of a
document gets a virtual finish time: the words its source has sent by then, divided by the source's target. All passes
are ordered by finish time over all sources, and the mix ends where the total budget is used up.

Defined cases: a null source is a source of its own and comes last; a null or blank text has size 0 and is never
taken (taken 0); repeated rows are documents of their own; an empty table gives no rows; only the named columns are
read. A document's place in its queue depends on its id alone, so reruns agree.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from triplefed.llm.common import WORD, materialize, ranked, table

MOST = 3
#: Two rounds of this many bins close in on the last pass taken.
BINS = 4096
#: Past this finish time no pass can be taken: targets sum to the budget.
END = MOST + 1.0


def size_column(text: str = "text") -> Column:
    return F.coalesce(F.regexp_count(F.col(text), F.lit(WORD)), F.lit(0)).cast("long")


def shuffle_column(doc_id: str = "doc_id", seed: str = "mix") -> Column:
    """A uniform 32-bit number from the id; md5, so that any SQL engine can check it."""
    text = F.concat(F.lit(f"{seed}:"), F.coalesce(F.col(doc_id).cast("string"), F.lit("null")))
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("long")


def targets(sizes: DataFrame, weights: int = 3, most: int = MOST) -> DataFrame:
    """Per source: source_rank, source_size, target. What a source can't take is shared out by weight again.

    The level at which that ends is found in one sorted sweep over the sources; a source is capped if the level that
    the sources from it on would share is not below its own.
    """
    by_name = Window.orderBy(F.col("source").asc_nulls_last())
    s = sizes.groupBy("source").agg(F.sum("size").alias("source_size"))
    s = s.withColumn("source_rank", F.row_number().over(by_name)).withColumn("weight", (F.col("source_rank") - 1) % weights + 1)
    s = s.withColumn("cap", F.lit(most) * F.col("source_size")).withColumn("level", F.col("cap") / F.col("weight"))
    sweep = Window.orderBy("level", "source_rank")
    every = Window.partitionBy(F.lit(1))
    s = s.withColumn("total", F.sum("source_size").over(every))
    s = s.withColumn("cap_before", F.coalesce(F.sum("cap").over(sweep.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    s = s.withColumn("weight_from", F.sum("weight").over(sweep.rowsBetween(0, Window.unboundedFollowing)))
    s = s.withColumn("capped", (F.col("total") - F.col("cap_before")) / F.col("weight_from") >= F.col("level"))
    s = s.withColumn("rest", F.col("total") - F.coalesce(F.sum(F.when(F.col("capped"), F.col("cap"))).over(every), F.lit(0)))
    s = s.withColumn("rest_weight", F.sum(F.when(~F.col("capped"), F.col("weight"))).over(every))
    share = F.col("rest") / F.col("rest_weight") * F.col("weight")
    return s.select("source", "source_rank", "source_size", "total", F.when(F.col("capped"), F.col("cap").cast("double")).otherwise(share).alias("target"))


def mix(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", source: str = "source", weights: int = 3, most: int = MOST) -> DataFrame:
    """Per document: doc_id, source, size, source_size, target, passes (0 to ``most``) and taken (size times passes)."""
    out = _queues(docs, doc_id, text, source, weights, most)
    return out.select("doc_id", "source", "size", "source_size", "target", "passes", (F.col("size") * F.col("passes")).alias("taken"))


def _queues(docs: DataFrame, doc_id: str, text: str, source: str, weights: int, most: int) -> DataFrame:
    """All documents with their place in their queue and their passes.

    The text is read once, to count; what is sorted are rows of four numbers. Queues are cut into buckets (see
    ``ranked``), so a source with a third of all rows is spread like any other.
    """
    sizes = materialize(docs.select(F.col(doc_id).alias("doc_id"), F.col(source).alias("source"), size_column(text).alias("size")))
    of_source = materialize(targets(sizes, weights, most))
    # one row for each source: a size bound by the number of sources, left to Spark's own check of it
    joined = sizes.join(of_source, sizes["source"].eqNullSafe(of_source["source"])).drop(of_source["source"])
    queued = ranked(joined, ["source"], shuffle_column(), ["doc_id", "size"], "size", sizes.count())
    queued = materialize(queued.withColumn("order", shuffle_column()).drop("rank"))
    last = _last_pass(queued, most)
    if last is None:
        passes = F.lit(0)
    else:
        passes = sum((F.when(_upto(_finish(e), last), 1).otherwise(0) for e in range(1, most + 1)), F.lit(0))
        passes = F.when(F.col("size") > 0, passes).otherwise(0)
    return queued.withColumn("passes", passes.cast("int"))


def _finish(epoch: int) -> Column:
    return (F.lit(epoch - 1) * F.col("source_size") + F.col("running")) / F.col("target")


def _upto(finish: Column, last: tuple) -> Column:
    at, rank, order, doc = last
    return (finish < at) | ((finish == at) & ((F.col("source_rank") < rank) | ((F.col("source_rank") == rank) & ((F.col("order") < order) | ((F.col("order") == order) & (F.coalesce("doc_id", F.lit(-1)) <= doc))))))


def _last_pass(queued: DataFrame, most: int) -> tuple | None:
    """The last pass that the budget holds, as its sort key: range-partitioned sums, twice, then one small bin in full."""
    every = queued.where("size > 0").select("*", F.explode(F.array(*(F.struct(_finish(e).alias("finish")) for e in range(1, most + 1)))).alias("pass")).select(
        "size", "total", "source_rank", "order", F.coalesce("doc_id", F.lit(-1)).alias("doc_id"), F.col("pass.finish").alias("finish")
    ).where(F.col("finish") < END)
    low, width, spent, budget = 0.0, END, 0, None
    for _ in range(2):
        step = width / BINS
        bins = every.where((F.col("finish") >= low) & (F.col("finish") < low + width)).groupBy(F.floor((F.col("finish") - low) / step).alias("bin")).agg(F.sum("size").alias("size"), F.max("total").alias("total"))
        running = bins.withColumn("after", F.sum("size").over(Window.orderBy("bin")) + spent)
        over = running.where("after > total").orderBy("bin").select("bin", (F.col("after") - F.col("size")).alias("before"), "total").limit(1).collect()
        if not over:  # the budget holds all passes of the range, which happens only without rows
            break
        spent, budget = over[0]["before"], over[0]["total"]
        low, width = low + over[0]["bin"] * step, step
    if budget is None:
        every_pass = queued.where("size > 0").limit(1).collect()
        return (END, 0, 0, 0) if every_pass else None
    keys = ["finish", "source_rank", "order", "doc_id"]
    # the width of the inner bins rounds; a margin on both sides and exact sums keep it right
    margin = width * 2
    before = every.where(F.col("finish") < low - margin).agg(F.coalesce(F.sum("size"), F.lit(0)).alias("s")).collect()[0]["s"]
    inner = every.where((F.col("finish") >= low - margin) & (F.col("finish") < low + width + margin))
    inner = inner.withColumn("after", F.sum("size").over(Window.orderBy(*keys).rowsBetween(Window.unboundedPreceding, 0)) + before)
    found = inner.where(F.col("after") <= budget).orderBy(*(F.col(k).desc() for k in keys)).select(*keys).limit(1).collect()
    return tuple(found[0]) if found else (low - margin, 0, 0, 0)


def mixed_documents(docs: DataFrame, weights: int = 3, most: int = MOST) -> DataFrame:
    """The documents of the mix with their own columns; one taken in several passes comes as often.

    What a pass takes of a source is the front of its queue, so the last place taken says it all: no text moves, and
    what is joined is one row for each source. Rows alike in id and size share a place and go together.
    """
    place = lambda size: F.struct(shuffle_column().alias("order"), F.coalesce("doc_id", F.lit(-1)).alias("id"), size.alias("size"))
    queues = _queues(docs, "doc_id", "text", "source", weights, most).withColumn("place", place(F.col("size")))
    fronts = queues.groupBy(F.col("source").alias("__source")).agg(*(F.max(F.when(F.col("passes") >= e, F.col("place"))).alias(f"__last{e}") for e in range(1, most + 1)))
    fronts = materialize(fronts)
    found = docs.withColumn("__size", size_column()).join(fronts, docs["source"].eqNullSafe(fronts["__source"]))
    passes = sum((F.when(place(F.col("__size")) <= F.col(f"__last{e}"), 1).otherwise(0) for e in range(1, most + 1)), F.lit(0))
    found = found.withColumn("__passes", F.when(F.col("__size") > 0, passes).otherwise(0)).where("__passes > 0")
    return found.withColumn("__pass", F.explode(F.sequence(F.lit(1), "__passes"))).select(*(docs[c] for c in docs.columns))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix(table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken")


ORACLE = f"""
WITH d AS (SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '{WORD}')) AS size,
                  ('0x' || substr(md5('mix:' || coalesce(CAST(doc_id AS VARCHAR), 'null')), 1, 8))::BIGINT AS o FROM documents),
s AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size, row_number() OVER (ORDER BY source NULLS LAST) AS r FROM d GROUP BY source),
w AS (SELECT *, (r - 1) % 3 + 1 AS weight, {MOST} * source_size AS cap, {MOST} * source_size / ((r - 1) % 3 + 1) AS lvl, CAST(sum(source_size) OVER () AS BIGINT) AS total FROM s),
c AS (SELECT *, (total - coalesce(sum(cap) OVER (ORDER BY lvl, r ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))
               / sum(weight) OVER (ORDER BY lvl, r ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) >= lvl AS capped FROM w),
t AS (SELECT *, CASE WHEN capped THEN CAST(cap AS DOUBLE)
                     ELSE CAST(total - coalesce(sum(CASE WHEN capped THEN cap END) OVER (), 0) AS DOUBLE) / sum(CASE WHEN NOT capped THEN weight END) OVER () * weight END AS target FROM c),
q AS (SELECT doc_id, size, o, r, source_size, target, total, CAST(sum(size) OVER (PARTITION BY r ORDER BY o, doc_id, size ROWS UNBOUNDED PRECEDING) AS BIGINT) AS upto
      FROM d JOIN t ON d.source IS NOT DISTINCT FROM t.source),
p AS (SELECT *, ((e - 1) * source_size + upto) / target AS finish FROM q, (SELECT unnest(range(1, {MOST} + 1)) AS e) WHERE size > 0),
k AS (SELECT *, sum(size) OVER (ORDER BY finish, r, o, doc_id ROWS UNBOUNDED PRECEDING) AS spent FROM p),
n AS (SELECT doc_id, sum(size) AS taken FROM k WHERE spent <= total GROUP BY doc_id)
SELECT q.doc_id, CAST(q.size AS BIGINT) AS size, q.source_size, q.target, CAST(coalesce(n.taken, 0) AS BIGINT) AS taken FROM q LEFT JOIN n ON q.doc_id = n.doc_id"""
