"""Batches of deletes and inserts: the main set and every module stay as a recomputation would make them.

What changes is found module by module from the roots on, and only in modules whose predicate the batch has or whose
parent's propagated values changed. ``deletions`` and ``insertions`` give these changes; nothing else need be written.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from triplefed.operators.cap import Module, edge_rows, place_core_edges, propagate, support
from triplefed.storage import save


def _top_down(modules: dict[tuple, Module]) -> list[tuple]:
    return sorted(modules, key=lambda p: (len(p), repr(p)))


def _predicates(batch: DataFrame) -> set[str]:
    return {r["p"] for r in batch.select("p").distinct().collect()}  # at most all predicates


def delete_from_graph(t: DataFrame, batch: DataFrame) -> DataFrame:
    """Deleting what is not there does nothing."""
    return t.join(batch.select("s", "p", "o").distinct(), ["s", "p", "o"], "left_anti").select(*t.columns)


def insert_into_graph(t: DataFrame, batch: DataFrame) -> DataFrame:
    """Inserting what is there already does nothing."""
    new = batch.select(*t.columns).dropDuplicates(["s", "p", "o"]).join(t, ["s", "p", "o"], "left_anti").select(*t.columns)
    return t.unionByName(new)


def deletions(modules: dict[tuple, Module], batch: DataFrame, write=save) -> dict[tuple, DataFrame]:
    """Rows that go, by path, of the modules that lose any: deleted triples, and rows at a worker whose source value has lost
    its last support in the parent module there. What a module no longer propagates goes on to its children. All joins but
    that with the batch are on the worker, so nothing moves between workers."""
    out: dict[tuple, DataFrame] = {}
    lost: dict[tuple, DataFrame] = {}
    batch = batch.select("s", "p", "o").distinct()
    touched = _predicates(batch)
    for path in _top_down(modules):
        old, gone = modules[path].df, None
        if path[-1][1] in touched:
            gone = old.join(edge_rows(batch, path).select("src", "prop"), ["src", "prop"], "left_semi")
        if path[:-1] in lost:
            orphans = old.join(lost[path[:-1]], ["worker", "src"], "left_semi")
            gone = orphans if gone is None else gone.unionByName(orphans).distinct()
        if gone is None:
            continue
        gone = write(gone.select("worker", "src", "prop"))
        if gone.isEmpty():
            continue
        out[path] = gone
        if any(p[:-1] == path for p in modules):
            ends = support(gone)
            still = old.join(gone, ["worker", "src", "prop"], "left_anti").select("worker", F.col("prop").alias("src"))
            lost[path] = write(ends.join(still, ["worker", "src"], "left_anti"))
    return out


def insertions(modules: dict[tuple, Module], after: DataFrame, batch: DataFrame, workers: int, kind: str = "md5", write=save) -> dict[tuple, DataFrame]:
    """Rows that come, by path; ``after`` is the graph with the batch. New rows of an edge go where their source value is
    supported; values that are supported for the first time call in their rows from the whole graph."""
    out: dict[tuple, DataFrame] = {}
    fresh: dict[tuple, DataFrame] = {}
    batch = batch.select("s", "p", "o").distinct()
    touched = _predicates(batch)
    for path in _top_down(modules):
        old, parent, add = modules[path].df, path[:-1], None
        if path[-1][1] in touched:
            new = edge_rows(batch, path).select("src", "prop").distinct()
            if parent not in modules:
                add = place_core_edges(new, workers, kind)
            else:
                above = modules[parent].df
                above = above.unionByName(out[parent]) if parent in out else above
                add = propagate(new, above)
        if parent in fresh:
            called = edge_rows(after, path).select("src", "prop").join(fresh[parent], "src").select("worker", "src", "prop")
            add = called if add is None else add.unionByName(called)
        if add is None:
            continue
        add = write(add.distinct().join(old, ["worker", "src", "prop"], "left_anti").select("worker", "src", "prop"))
        if add.isEmpty():
            continue
        out[path] = add
        if any(p[:-1] == path for p in modules):
            fresh[path] = write(support(add).join(old.select("worker", F.col("prop").alias("src")), ["worker", "src"], "left_anti"))
    return out


def apply_deletes(modules: dict[tuple, Module], batch: DataFrame, write=save) -> dict[tuple, DataFrame]:
    """Contents by path after the batch."""
    gone = deletions(modules, batch, write)
    return {p: m.df.join(gone[p], ["worker", "src", "prop"], "left_anti") if p in gone else m.df for p, m in modules.items()}


def apply_inserts(modules: dict[tuple, Module], after: DataFrame, batch: DataFrame, workers: int, kind: str = "md5", write=save) -> dict[tuple, DataFrame]:
    """Contents by path after the batch."""
    add = insertions(modules, after, batch, workers, kind, write)
    return {p: m.df.unionByName(add[p]) if p in add else m.df for p, m in modules.items()}


def split_batches(t: DataFrame, share: int = 5, batches: int = 50) -> DataFrame:
    """batch, s, p, o: one in ``share`` triples by hash, dealt into batches."""
    h = F.conv(F.substring(F.md5(F.concat_ws("|", "s", "p", "o")), 1, 8), 16, 10).cast("long")
    return t.withColumn("h", h).where(F.col("h") % share == 0).select((F.floor(F.col("h") / share) % batches).cast("long").alias("batch"), "s", "p", "o")
