"""Pattern queries as portable SQL: a relation for each pattern, joined in a connected order.

Nothing is left to an optimizer: a relation reads only the tables of its predicate, constants are applied inside it, joins
are explicit, and they begin at the most selective pattern.
"""

from __future__ import annotations

from triplefed.query import Pattern, QueryGraph, is_var
from triplefed.sources.graphs import edge_sql, graph_sql, quoted

#: Rough sizes of what carries a predicate, smallest first; only their order matters.
_SIZES = {"inRegion": 1, "suppNation": 2, "quotes": 2, "sameText": 2, "custNation": 3, "segment": 3, "brand": 4, "partKind": 4, "partSize": 4, "byUser": 5, "eventKind": 5, "placedBy": 6, "status": 6, "priority": 6, "orderYear": 6, "type": 8}


def relation(graph: str, e: Pattern, view: str | None = None) -> str:
    """The pattern's bindings, a column for each variable. ``view``: a name to read triples from instead of the tables."""
    where: list[str] = []
    if view is None and not is_var(e.p):
        constant = [None if is_var(t) else t for t in (e.s, e.o)]
        rows, terms = edge_sql(graph, e.p, *constant), (("s", e.s), ("o", e.o))
    else:
        rows, terms = view or graph_sql(graph), tuple(zip("spo", e, strict=True))
        where += [f"{c} = {quoted(t)}" for c, t in terms if not is_var(t)]
    first: dict[str, str] = {}
    for column, term in terms:
        if is_var(term):
            if term in first:
                where.append(f"{column} = {first[term]}")
            first.setdefault(term, column)
    columns = ", ".join(f"{c} AS {v[1:]}" for v, c in first.items()) or "true AS found"
    found = f"SELECT {columns} FROM {f'({rows})' if ' ' in rows else rows}" + (f" WHERE {' AND '.join(where)}" if where else "")
    return found if first else f"{found} LIMIT 1"


def connected_order(q: QueryGraph) -> list[int]:
    """Patterns with constants first, then those that join with most of what is bound, then the smaller."""
    left, out, bound = set(range(len(q.patterns))), [], set()
    while left:
        def rank(i: int) -> tuple:
            e = q.patterns[i]
            held = sum(v in bound for v in e.variables)
            free = len(e.variables) - held
            constants = sum(not is_var(t) for t in (e.s, e.o)) - (e.p == "type")
            return (bool(bound) and not held, free if bound else 0, -constants, _SIZES.get(e.p, 7), i)

        best = min(left, key=rank)
        out.append(best)
        left.remove(best)
        bound |= {*q.patterns[best].variables}
    return out


def to_sql(q: QueryGraph, graph: str = "shop", semantics: str = "homomorphism", view: str | None = None) -> str:
    """SELECT with a column for each variable, in order of first mention."""
    source, bound = "", set()
    for i in connected_order(q):
        e = q.patterns[i]
        part = f"({relation(graph, e, view)}) r{i}"
        on = [v[1:] for v in e.variables if v in bound]
        source = f"{source} {'JOIN' if on else 'CROSS JOIN'} {part}{f' USING ({chr(44).join(on)})' if on else ''}" if source else part
        bound |= {*e.variables}
    where = []
    if semantics == "injective":
        ends = [v[1:] for v in q.vertices if is_var(v)]
        where = [f"{a} <> {b}" for i, a in enumerate(ends) for b in ends[i + 1:]]
    columns = ", ".join(v[1:] for v in q.variables) or "found"
    return f"SELECT {columns} FROM {source}" + (f" WHERE {' AND '.join(where)}" if where else "")


def with_graph(graph: str, body: str) -> str:
    """For what reads all triples, and more than once."""
    return f"WITH g AS MATERIALIZED ({graph}) {body}"
