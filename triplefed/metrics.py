"""Cost measures: replication, balance, communication, convergence, coverage, scale."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from triplefed.operators.patterns import scan_pattern
from triplefed.query import QueryGraph, is_var


def loads(placed: DataFrame, workers: int, column: str = "worker") -> DataFrame:
    """worker, load of all workers, those with nothing too."""
    spark = placed.sparkSession
    got = placed.groupBy(F.col(column).cast("int").alias("worker")).agg(F.count(F.lit(1)).alias("load"))
    every = spark.range(workers).select(F.col("id").cast("int").alias("worker"))
    return every.join(got, "worker", "left").select("worker", F.coalesce("load", F.lit(0)).alias("load"))


def gini(of: DataFrame) -> DataFrame:
    """gini of worker loads: 0 when all are equal, (N-1)/N when one has all. As many rows as workers."""
    ranked = of.withColumn("i", F.row_number().over(Window.orderBy("load", "worker"))).withColumn("n", F.count(F.lit(1)).over(Window.partitionBy(F.lit(1))))
    return ranked.agg((F.sum((2 * F.col("i") - F.col("n") - 1) * F.col("load")) / F.greatest(F.lit(1), F.max("n") * F.sum("load"))).alias("gini"))


def gini_sql(loads_sql: str) -> str:
    return f"SELECT CAST(sum((2 * i - n - 1) * load) AS DOUBLE) / greatest(1, max(n) * sum(load)) AS gini FROM (SELECT load, row_number() OVER (ORDER BY load, worker) AS i, count(*) OVER () AS n FROM ({loads_sql}))"


def replication_ratio(replicas: DataFrame, triples: DataFrame, count: str = "modules") -> DataFrame:
    """replica_rows, triples, ratio. ``distinct``: a pair that several modules hold at one worker counts once."""
    rows = replicas if count == "modules" else replicas.select("worker", "src", "prop").distinct()
    one = rows.agg(F.count(F.lit(1)).alias("replica_rows")).crossJoin(triples.agg(F.count(F.lit(1)).alias("triples")))  # one row each
    return one.withColumn("ratio", F.col("replica_rows") / F.col("triples"))


def cumulative(log: DataFrame) -> DataFrame:
    """seq, cum_s: time of queries and copies so far."""
    return log.select("seq", F.sum(F.col("exec_s") + F.col("redist_s")).over(Window.orderBy("seq").rowsBetween(Window.unboundedPreceding, 0)).alias("cum_s"))


def mode_share(log: DataFrame) -> DataFrame:
    n = F.count(F.lit(1))
    return log.groupBy("mode").agg(n.alias("queries")).withColumn("share", F.col("queries") / F.sum("queries").over(Window.partitionBy(F.lit(1))))


def converged_at(log: DataFrame) -> DataFrame:
    """seq of the last copy."""
    return log.where("n_modules > 0").agg(F.max("seq").alias("converged_at"))


def relevant(t: DataFrame, queries: list[QueryGraph], level: str = "pattern") -> DataFrame:
    """The distinct triples that a workload touches: those that match a pattern, or those of answers (``match``)."""
    out = None
    for q in queries:
        answer = None
        if level == "match":
            from triplefed.operators.patterns import run_centralised

            answer = run_centralised(t, q)
        for e in q.patterns:
            part = t
            for column, term in zip("spo", e, strict=True):
                if not is_var(term):
                    part = part.where(F.col(column) == term)
            if answer is not None:
                named = [(c, v) for c, v in zip("spo", e, strict=True) if is_var(v)]
                keys = answer.select(*(F.col(v[1:]).alias(c) for c, v in named)).distinct()
                part = part.join(keys, [c for c, _ in named], "left_semi")
            part = part.select("s", "p", "o")
            out = part if out is None else out.unionByName(part)
    return out.distinct()


def coverage(t: DataFrame, queries: list[QueryGraph], level: str = "pattern") -> DataFrame:
    one = relevant(t, queries, level).agg(F.count(F.lit(1)).alias("covered")).crossJoin(t.agg(F.count(F.lit(1)).alias("triples")))  # one row each
    return one.withColumn("share", F.col("covered") / F.col("triples"))


def edge_cut(t: DataFrame, assign: DataFrame) -> DataFrame:
    """edges, cut, and the largest part over the mean one. ``assign``: v, part."""
    a = assign.select(F.col("v").alias("s"), F.col("part").alias("part_s"))
    b = assign.select(F.col("v").alias("o"), F.col("part").alias("part_o"))
    cut = t.join(a, "s").join(b, "o").agg(F.count(F.lit(1)).alias("edges"), F.count_if(F.col("part_s") != F.col("part_o")).alias("cut"))
    size = assign.groupBy("part").agg(F.count(F.lit(1)).alias("n")).agg((F.max("n") / F.avg("n")).alias("balance"))
    return cut.crossJoin(size)  # one row each


def linearity(points: DataFrame) -> DataFrame:
    """r2 of seconds over triples."""
    return points.agg(F.regr_r2("seconds", "triples").alias("r2"))


def pattern_rows(t: DataFrame, q: QueryGraph) -> list[int]:
    return [scan_pattern(t, e).count() for e in q.patterns]
