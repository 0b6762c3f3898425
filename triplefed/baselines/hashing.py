"""Static hash partitioning on subjects or objects: star queries on that end are local, all others semi-join."""

from __future__ import annotations

from pyspark.sql import DataFrame

from triplefed.operators.patterns import scan_pattern
from triplefed.operators.semijoin import run_distributed
from triplefed.query import QueryGraph


def is_local(q: QueryGraph, end: str) -> bool:
    return len({getattr(e, end) for e in q.patterns}) == 1


def hash_query(placed: DataFrame, q: QueryGraph, end: str = "s") -> tuple[str, DataFrame]:
    """``placed``: by hash of ``end``. Local joins are on home and shared variables."""
    if not is_local(q, end):
        return "distributed", run_distributed(placed, q)
    out = None
    for e in q.patterns:
        part = scan_pattern(placed, e, True)
        part = part.drop("found") if "found" in part.columns else part
        out = part if out is None else out.join(part, [c for c in part.columns if c in out.columns])
    return "parallel", out.select(*(v[1:] for v in q.variables))
