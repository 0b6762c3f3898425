"""Core-anchored propagation: copies of what a query touches, placed around the bindings of its core.

A module is one tree edge's copy: worker, src, prop. Rows of core edges go to the worker that their core binding hashes
to. Rows of a deeper edge go wherever their source value is a propagated value of the parent module. Each module is
written before its children read it.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from triplefed.federation import WORKERS, worker_of
from triplefed.plans.tree import RedistTree
from triplefed.storage import add_by_worker, save_by_worker


def in_space(path: tuple, space: str | None) -> tuple:
    """The path by which a module that serves only one template's queries is known."""
    return path if space is None else ((space, path[0]), *path[1:])


def root_of(path: tuple):
    return path[0][1] if isinstance(path[0], tuple) else path[0]


def module_id(path: tuple) -> str:
    return hashlib.md5(repr(path).encode()).hexdigest()[:12]


def edge_rows(t: DataFrame, path: tuple) -> DataFrame:
    """src, prop (and home) of the triples that the last step of a path selects."""
    direction, predicate, far = path[-1]
    src, prop = ("s", "o") if direction == "out" else ("o", "s")
    rows = t.where(F.col("p") == predicate)
    if len(path) == 2 and root_of(path) is not None:
        rows = rows.where(F.col(src) == root_of(path))
    if far is not None:
        rows = rows.where(F.col(prop) == far)
    home = ["home"] if "home" in t.columns else []
    return rows.select(F.col(src).alias("src"), F.col(prop).alias("prop"), *home)


def place_core_edges(rows: DataFrame, workers: int = WORKERS, kind: str = "md5") -> DataFrame:
    return rows.select(worker_of("src", workers, kind).alias("worker"), "src", "prop")


def support(module: DataFrame) -> DataFrame:
    """The values that a module propagates, and where."""
    return module.select("worker", F.col("prop").alias("src")).distinct()


def propagate(rows: DataFrame, parent: DataFrame, few: bool = False) -> DataFrame:
    """Rows of an edge at each worker that has their source value; as the graph and the support are sets, so is this.
    ``few``: the support goes to every worker, so that the rows, which may be all of a predicate, stay where they are."""
    values = support(parent)
    return rows.join(F.broadcast(values) if few else values, "src").select("worker", "src", "prop")


@dataclass
class Module:
    """A copy: worker, src, prop. ``table`` is its table dealt by worker, where it has one; ``n_src`` and ``n_prop`` are
    about how many sources and propagated values there are, counted at each worker.

    Updates append: rows carry the number of the batch they were ``born`` in, deleted ones go to the table ``dead`` with
    the batch they ``died`` in. Both are dealt alike, so leaving the dead out costs no exchange.
    """

    path: tuple
    df: DataFrame
    rows: int
    table: str | None = None
    n_src: float = 0.0
    n_prop: float = 0.0
    workers: int = WORKERS
    kind: str = "md5"
    dead: str | None = None
    buried: int = 0

    @property
    def id(self) -> str:
        return module_id(self.path)

    @property
    def closed(self) -> bool:
        return isinstance(self.path[0], tuple)

    def read(self, spark: SparkSession) -> DataFrame:
        """slot, worker, src, prop of what is live, in a session that may be the local one."""
        rows = spark.table(self.table)
        if self.dead is not None:
            gone = spark.table(self.dead)
            rows = rows.join(gone, [*(rows[c] == gone[c] for c in ("slot", "src", "prop")), gone["died"] > rows["born"]], "left_anti")
        return rows.select("slot", "worker", "src", "prop")

    def append(self, new: DataFrame, number: int) -> Module:
        n = new.count()
        if not n:
            return self
        add_by_worker(new.select("worker", "src", "prop").withColumn("born", F.lit(number)), self.table, self.workers)
        grow = (self.rows + n) / max(1, self.rows)
        return replace(self, df=self.read(new.sparkSession).select("worker", "src", "prop"), rows=self.rows + n, n_src=self.n_src * grow, n_prop=self.n_prop * grow)

    def bury(self, gone: DataFrame, number: int) -> Module:
        n = gone.count()
        if not n:
            return self
        out = gone.select("worker", "src", "prop").withColumn("died", F.lit(number))
        spark = gone.sparkSession
        dead = self.dead
        if dead is None:
            dead = save_by_worker(out, self.workers)
        else:
            add_by_worker(out, dead, self.workers)
        made = replace(self, rows=self.rows - n, dead=dead, buried=self.buried + n)
        if made.buried > COMPACT * max(1, made.rows):
            return stored(self.path, made.read(spark), self.workers, self.kind)
        return replace(made, df=made.read(spark).select("worker", "src", "prop"))


#: Rows of a copy up to which its propagated values are broadcast.
BROADCAST_ROWS = 1_000_000
#: Dead rows, as a share of live ones, beyond which a module is written anew.
COMPACT = 0.25


def stored(path: tuple, placed: DataFrame, workers: int = WORKERS, kind: str = "md5") -> Module:
    """Written by worker, and measured in one pass over what was written."""
    spark = placed.sparkSession
    name = save_by_worker(placed.select("worker", "src", "prop", F.lit(0).alias("born")), workers)
    df = spark.table(name).select("worker", "src", "prop")
    n = df.agg(F.count(F.lit(1)).alias("rows"), F.approx_count_distinct(F.struct("worker", "src")).alias("s"), F.approx_count_distinct(F.struct("worker", "prop")).alias("p")).collect()[0]
    return Module(path, df, n["rows"], name, n["s"], n["p"], workers, kind)


@dataclass
class CapReport:
    added: list[str]
    rows_added: int
    levels: int


def redistribute(t: DataFrame, tree: RedistTree, has: Callable[[tuple], Module | None], put: Callable[[Module], None], workers: int = WORKERS, kind: str = "md5", parallel_levels: bool = True, close_cycles: str | None = None) -> CapReport:
    """Level by level; modules that are there already are passed over. Edges of one level run as concurrent jobs.

    ``close_cycles``, a template's text: rows of an edge whose far end stands elsewhere in the tree as well are kept only
    where that end is placed too. Such copies are smaller and lack what other queries need, so they are known under that
    template alone.
    """
    report = CapReport([], 0, tree.levels)

    def known(at: int) -> tuple:
        return in_space(tree.path(at), close_cycles)

    def make(at: int) -> Module | None:
        path = known(at)
        if has(path) is not None:
            return None
        rows = edge_rows(t, path).select("src", "prop")
        node = tree.nodes[at]
        if node.parent is None:
            placed = place_core_edges(rows, workers, kind)
        else:
            parent = has(known(node.parent))
            placed = propagate(rows, parent.df, parent.rows <= BROADCAST_ROWS)
        if close_cycles is not None:
            for j, other in enumerate(tree.nodes):
                if j != at and other.prop == node.prop and other.level < node.level and has(known(j)) is not None:
                    ends = has(known(j)).df.select("worker", "prop").distinct()
                    placed = placed.join(ends, ["worker", "prop"], "left_semi")
        return stored(path, placed, workers, kind)

    for level in range(1, tree.levels + 1):
        todo, paths = [], set()
        for i, n in enumerate(tree.nodes):
            if n.level == level and known(i) not in paths:
                paths.add(known(i))
                todo.append(i)
        if parallel_levels and len(todo) > 1:
            with ThreadPoolExecutor(len(todo)) as pool:
                made = list(pool.map(make, todo))
        else:
            made = [make(i) for i in todo]
        for m in made:
            if m is not None:
                put(m)
                report.added.append(m.id)
                report.rows_added += m.rows
    return report


def module_plan(t: DataFrame, tree: RedistTree, workers: int = WORKERS, kind: str = "md5") -> dict[tuple, DataFrame]:
    """All modules of a tree as one lazy plan, nothing written: for estimates before a copy, and for checks."""
    out: dict[tuple, DataFrame] = {}
    for i, n in sorted(enumerate(tree.nodes), key=lambda x: x[1].level):
        path = tree.path(i)
        if path not in out:
            rows = edge_rows(t, path).select("src", "prop")
            out[path] = place_core_edges(rows, workers, kind) if n.parent is None else propagate(rows, out[tree.path(n.parent)])
    return out


def paths_sql(paths: list[tuple], workers: int = WORKERS, graph: str = "shop", view: str | None = None) -> tuple[str, dict[tuple, str]]:
    """The same as SQL: a WITH list of a relation for each path and each path above it, and their names. Each reads only
    the tables of its predicate, or ``view``, a SELECT of s, p and o."""
    from triplefed.federation import worker_sql
    from triplefed.sources.graphs import edge_sql, quoted

    names: dict[tuple, str] = {}
    parts: list[str] = []
    for path in sorted({p[:n] for p in paths for n in range(2, len(p) + 1)}, key=lambda p: (len(p), repr(p))):
        direction, predicate, far = path[-1]
        src, prop = ("s", "o") if direction == "out" else ("o", "s")
        ends = {src: root_of(path) if len(path) == 2 else None, prop: far}
        if view is None:
            rows = f"SELECT {src} AS src, {prop} AS prop FROM ({edge_sql(graph, predicate, ends['s'], ends['o'])})"
        else:
            where = [f"p = '{predicate}'", *(f"{c} = {quoted(x)}" for c, x in ends.items() if x is not None)]
            rows = f"SELECT {src} AS src, {prop} AS prop FROM {view} WHERE {' AND '.join(where)}"
        names[path] = f"m{len(names)}"
        if len(path) == 2:
            made = f"SELECT {worker_sql('src', workers)} AS worker, src, prop FROM ({rows})"
        else:
            made = f"SELECT q.worker, r.src, r.prop FROM ({rows}) r JOIN (SELECT DISTINCT worker, prop AS src FROM {names[path[:-1]]}) q USING (src)"
        parts.append(f"{names[path]} AS ({made})")
    return ", ".join(parts), names


def tree_paths(tree: RedistTree) -> list[tuple]:
    return list(dict.fromkeys(tree.path(i) for i in range(len(tree.nodes))))
