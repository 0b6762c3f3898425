"""k-hop replication: a worker holds every triple within k hops of the vertices that it owns."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from triplefed.federation import WORKERS, worker_of
from triplefed.operators.patterns import scan_pattern
from triplefed.operators.semijoin import run_distributed
from triplefed.query import QueryGraph, is_var
from triplefed.stats import TYPE, degrees
from triplefed.storage import save


def hash_assignment(t: DataFrame, n: int = WORKERS) -> DataFrame:
    """v, part of every vertex by hash, where no cut is wanted."""
    return t.select(F.col("s").alias("v")).unionAll(t.select(F.col("o").alias("v"))).distinct().select("v", worker_of("v", n).alias("part"))


def hubs(t: DataFrame, sigma: float = 3.0) -> DataFrame:
    """Vertices that are not expanded: classes, and those whose degree is far above the mean."""
    d = degrees(t)
    cut = d.agg((F.avg("degree") + sigma * F.stddev_pop("degree")).alias("cut"))
    return d.crossJoin(F.broadcast(cut)).where("degree > cut").select("v").unionAll(t.where(F.col("p") == TYPE).select(F.col("o").alias("v"))).distinct()  # the cut is one row


def hub_predicates(t: DataFrame, stop: DataFrame) -> frozenset[str]:
    """Predicates with a hub among their objects, and with ``^`` those with one among their subjects: beyond these a planner
    can't count on an expansion."""
    ends = [t.join(stop.withColumnRenamed("v", end), end, "left_semi").select("p").distinct().collect() for end in "os"]  # predicates
    return frozenset(mark + r["p"] for mark, rows in zip(("", "^"), ends, strict=True) for r in rows)


def khop_partition(t: DataFrame, k: int = 2, assign: DataFrame | None = None, n: int = WORKERS, directed: bool = True, hub_cutoff: bool = True, write=save, hub_vertices: DataFrame | None = None) -> DataFrame:
    """worker, s, p, o. Each hop joins the frontier's ends with the triples, and is written before the next."""
    spo = t.select("s", "p", "o")
    owner = assign if assign is not None else hash_assignment(t, n)
    out = spo.join(owner.select(F.col("v").alias("s"), F.col("part").alias("worker")), "s").select("worker", "s", "p", "o")
    if not directed:
        out = out.unionByName(spo.join(owner.select(F.col("v").alias("o"), F.col("part").alias("worker")), "o").select("worker", "s", "p", "o")).distinct()
    stop = None
    if hub_cutoff and k > 1:
        stop = hub_vertices if hub_vertices is not None else write(hubs(t))
    out = frontier = write(out)
    for hop in range(2, k + 1):
        ends = frontier.select("worker", F.col("o").alias("v"))
        if not directed:
            ends = ends.unionByName(frontier.select("worker", F.col("s").alias("v")))
        ends = ends.distinct()
        if stop is not None:
            ends = ends.join(stop, "v", "left_anti")
        new = spo.join(ends.withColumnRenamed("v", "s"), "s").select("worker", "s", "p", "o")
        if not directed:
            new = new.unionByName(spo.join(ends.withColumnRenamed("v", "o"), "o").select("worker", "s", "p", "o"))
        if hop == k:
            return write(out.unionByName(new).distinct())
        frontier = write(new.distinct().join(out, ["worker", "s", "p", "o"], "left_anti"))
        out = write(out.unionByName(frontier))
    return out


def centre(q: QueryGraph, k: int, directed: bool = True, require_type: bool = False, hub_predicates: frozenset[str] = frozenset()) -> str | None:
    """A variable from which every pattern lies within k hops under the same directions, or None. With
    ``require_type`` it must have a type edge, without which no planner can know that it is owned like the others."""
    best = None
    for v in q.vertices:
        if not is_var(v) or (require_type and not any(e.s == v and e.p == TYPE for e in q.patterns)):
            continue
        reach, distance = {v: 0}, {}
        for hop in range(1, k + 1):
            for i, e in enumerate(q.patterns):
                if i not in distance and ((e.s in reach and reach[e.s] < hop) or (not directed and e.o in reach and reach[e.o] < hop)):
                    distance[i] = hop
            for i, d in distance.items():
                if d == hop:
                    e = q.patterns[i]
                    if e.p not in hub_predicates:
                        reach.setdefault(e.o, hop)
                    if not directed and f"^{e.p}" not in hub_predicates:
                        reach.setdefault(e.s, hop)
        if len(distance) == len(q.patterns) and (best is None or max(distance.values()) < best[0]):
            best = (max(distance.values()), v)
    return best[1] if best else None


def khop_query(tk: DataFrame, t: DataFrame, q: QueryGraph, k: int = 2, assign: DataFrame | None = None, n: int = WORKERS, directed: bool = True, require_type: bool = False, hub_predicates: frozenset[str] = frozenset()) -> tuple[str, DataFrame]:
    """Mode and answer: local joins on the replicas, keeping answers whose centre the worker owns, or semi-joins."""
    c = centre(q, k, directed, require_type, hub_predicates)
    if c is None:
        return "distributed", run_distributed(t, q)
    out = None
    for e in q.patterns:
        part = scan_pattern(tk.withColumnRenamed("worker", "home"), e, True)
        part = part.drop("found") if "found" in part.columns else part
        out = part if out is None else out.join(part, [x for x in part.columns if x in out.columns])
    if assign is None:
        out = out.where(worker_of(c[1:], n) == F.col("home"))
    else:
        out = out.join(assign.select(F.col("v").alias(c[1:]), F.col("part").alias("home")), [c[1:], "home"], "left_semi")
    return "parallel", out.select(*(v[1:] for v in q.variables))


HUBS_SQL = """hubs AS (SELECT v FROM (SELECT v, count(*) AS degree FROM (SELECT s AS v FROM g UNION ALL SELECT o FROM g) GROUP BY v),
    (SELECT avg(degree) + 3 * stddev_pop(degree) AS cut FROM (SELECT count(*) AS degree FROM (SELECT s AS v FROM g UNION ALL SELECT o FROM g) GROUP BY v))
    WHERE degree > cut UNION SELECT o FROM g WHERE p = 'type')"""


def khop_sql(k: int, n: int = WORKERS, graph: str = "g", directed: bool = True, stop: bool = False) -> tuple[str, str]:
    """The replicas over hash owners: a WITH list of a relation for each hop, and the last one's name. ``stop``: hubs, as in
    ``HUBS_SQL``, are not expanded."""
    from triplefed.federation import worker_sql

    own = f"SELECT {worker_sql('s', n)} AS worker, s, p, o FROM {graph}"
    parts = [f"k1 AS ({own if directed else f'{own} UNION SELECT {worker_sql(chr(111), n)}, s, p, o FROM {graph}'})"]
    for hop in range(2, k + 1):
        ends = f"SELECT worker, o AS v FROM k{hop - 1}" + ("" if directed else f" UNION SELECT worker, s FROM k{hop - 1}")
        parts.append(f"f{hop} AS (SELECT DISTINCT worker, v FROM ({ends})" + (" WHERE v NOT IN (SELECT v FROM hubs))" if stop else ")"))
        more = [f"SELECT worker, s, p, o FROM {graph} JOIN (SELECT worker, v AS {end} FROM f{hop}) USING ({end})" for end in ("s" if directed else "so")]
        parts.append(f"k{hop} AS (SELECT worker, s, p, o FROM k{hop - 1} UNION {' UNION '.join(more)})")
    return ", ".join(parts), f"k{k}"


__all__ = ["centre", "hash_assignment", "hub_predicates", "hubs", "khop_partition", "khop_query", "khop_sql"]
