"""Virtual workers: which repository holds a triple at first, and to which worker a core binding hashes."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from triplefed.sources.graphs import _TABLE_OF

WORKERS = 8


def worker_of(c: Column | str, n: int = WORKERS, kind: str = "md5") -> Column:
    """``md5``: equal in any SQL engine; ``xxhash64``: faster."""
    c = F.col(c) if isinstance(c, str) else c
    if kind == "md5":
        return (F.conv(F.substring(F.md5(c), 1, 8), 16, 10).cast("long") % n).cast("int")
    if kind == "xxhash64":
        return F.pmod(F.xxhash64(c), F.lit(n)).cast("int")
    raise ValueError(kind)


def worker_sql(c: str, n: int = WORKERS) -> str:
    return f"CAST(('0x' || substr(md5({c}), 1, 8))::BIGINT % {n} AS INT)"


def place(triples: DataFrame, policy: str = "random", n: int = WORKERS, seed: int = 0, kind: str = "md5", assign: DataFrame | None = None) -> DataFrame:
    """s, p, o, home. Policies: random, hash_s, hash_o, by_source (a repository for each table), by_region (entities
    whose keys fall together stay together), mincut (``assign``: v, part)."""
    if policy == "random":
        home = worker_of(F.concat_ws("|", F.lit(str(seed)), "s", "p", "o"), n, kind)
    elif policy == "hash_s":
        home = worker_of("s", n, kind)
    elif policy == "hash_o":
        home = worker_of("o", n, kind)
    elif policy == "by_source":
        names = sorted({*_TABLE_OF.values(), "derived"})
        home = F.lit(names.index("derived") % n)
        for i, t in enumerate(names):
            of = [p for p, x in _TABLE_OF.items() if x == t]
            if of:
                home = F.when(F.col("p").isin(of), F.lit(i % n)).otherwise(home)
    elif policy == "by_region":
        number = F.regexp_extract("s", r"(\d+)", 1)
        home = F.when(number == "", F.lit(0)).otherwise(F.try_mod(number.cast("long"), F.lit(n))).cast("int")
    elif policy == "mincut":
        return triples.join(assign.select(F.col("v").alias("s"), F.col("part").alias("home")), "s").select("s", "p", "o", "home")
    else:
        raise ValueError(policy)
    return triples.withColumn("home", home.cast("int"))


def place_sql(policy: str, n: int = WORKERS, seed: int = 0) -> str:
    """The column ``home`` for the policies that SQL can state."""
    return {"random": worker_sql(f"concat('{seed}|', s, '|', p, '|', o)", n), "hash_s": worker_sql("s", n), "hash_o": worker_sql("o", n), "by_region": f"CAST(CASE WHEN regexp_extract(s, '(\\d+)', 1) = '' THEN 0 ELSE regexp_extract(s, '(\\d+)', 1)::BIGINT % {n} END AS INT)"}[policy]
