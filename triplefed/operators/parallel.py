"""Parallel mode: every worker joins its own modules; the union of the answers is the answer, without duplicates."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from triplefed.federation import worker_of
from triplefed.operators.cap import Module
from triplefed.operators.patterns import project
from triplefed.plans.order import Relation, order_relations
from triplefed.plans.tree import RedistTree
from triplefed.query import QueryGraph, is_var
from triplefed.storage import local_session, slot_of

#: A module's rows at a worker up to which it is hashed in memory; larger ones are sorted, which can spill.
HASHED_ROWS = 2_000_000


def run_parallel(q: QueryGraph, tree: RedistTree, match: dict[int, Module] | Callable[[int], DataFrame], hint: str | None = None, semantics: str = "homomorphism") -> DataFrame:
    """Joins on worker and shared vertices in the order of fewest probes. All rows of an answer lie on the one worker that
    its core binding hashes to, and core rows lie nowhere else, so nothing is found twice.

    Modules that are tables dealt by worker are joined slot by slot, without an exchange, and where the core is a constant
    only its worker's slot is read. ``match`` may also give plain rows (worker, src, prop) for each tree edge.
    """
    tables = not callable(match) and all(m.table for m in match.values())
    key = "slot" if tables else "worker"
    names = {v: f"v{k}" for k, v in enumerate(q.vertices)}
    parts: list[DataFrame] = []
    relations: list[Relation] = []
    for i, n in enumerate(tree.nodes):
        if tables:
            m = match[i].read(local_session(match[i].df.sparkSession))
            if not is_var(tree.root):
                m = m.where(F.col("slot") == slot_of(worker_of(F.lit(tree.root), match[i].workers, match[i].kind), match[i].workers))
        else:
            m = match(i) if callable(match) else match[i].df
        for vertex, column in ((n.source, "src"), (n.prop, "prop")):
            if not is_var(vertex):
                m = m.where(F.col(column) == vertex)
        if n.source == n.prop:
            m = m.where("src = prop").select(key, F.col("src").alias(names[n.source]))
        else:
            m = m.select(key, F.col("src").alias(names[n.source]), F.col("prop").alias(names[n.prop]))
        parts.append(m)
        relations.append(_relation(n, None if callable(match) else match[i]))
    out = None
    for i in order_relations(relations):
        part, wish = parts[i], hint
        if wish is None and tables:
            wish = "shuffle_hash" if match[i].rows <= HASHED_ROWS * match[i].workers else "merge"
        if out is None:
            out = part
        else:
            out = out.join(part.hint(wish) if wish else part, [key, *(c for c in part.columns if c in out.columns and c != key)])
    rows = out.select(*(F.col(names[v]).alias(v[1:]) for v in q.vertices if is_var(v)))
    return project(rows, q, semantics)


def _relation(n, module: Module | None) -> Relation:
    """A module as the order sees it: its rows, less what a constant of the query leaves out."""
    if module is None:
        return Relation(1.0, {v: 1.0 for v in (n.source, n.prop) if is_var(v)})
    rows, distinct = float(module.rows), {n.source: max(1.0, module.n_src), n.prop: max(1.0, module.n_prop)}
    for v in (n.source, n.prop):
        if not is_var(v):
            rows /= distinct[v]
    return Relation(rows, {v: min(d, max(1.0, rows)) for v, d in distinct.items() if is_var(v)})


def exchanges(df: DataFrame) -> int:
    """Exchanges in the physical plan."""
    text = df._jdf.queryExecution().executedPlan().toString().split("== Initial Plan ==")[0]
    return sum("Exchange " in line for line in text.splitlines())


def merged_index(modules: dict[tuple, Module]) -> DataFrame:
    """worker, s, p, o of all modules in one table, each triple once at a worker: the layout that modules are compared with."""
    out = None
    for path, m in modules.items():
        direction, predicate, _ = path[-1]
        s, o = ("src", "prop") if direction == "out" else ("prop", "src")
        part = m.df.select("worker", F.col(s).alias("s"), F.lit(predicate).alias("p"), F.col(o).alias("o"))
        out = part if out is None else out.unionByName(part)
    return out.distinct()


def run_merged(q: QueryGraph, tree: RedistTree, merged: DataFrame, workers: int, kind: str = "md5", semantics: str = "homomorphism") -> DataFrame:
    """Every worker joins all that it holds for a pattern, whichever copy brought it there; so an answer may be found at
    several workers, and only the one that the core hashes to may give it."""
    from triplefed.operators.patterns import scan_pattern
    from triplefed.plans.order import order_patterns

    out = None
    for i in order_patterns(q, None):
        part = scan_pattern(merged.withColumnRenamed("worker", "home"), q.patterns[i], True)
        part = part.drop("found") if "found" in part.columns else part
        out = part if out is None else out.join(part, [c for c in part.columns if c in out.columns])
    core = F.col(tree.root[1:]) if is_var(tree.root) else F.lit(tree.root)
    return project(out.where(F.col("home") == worker_of(core, workers, kind)), q, semantics)
