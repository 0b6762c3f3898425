"""Pattern queries: graphs of labelled edges over variables and constants, canonical forms and templates."""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import lru_cache


def is_var(term: str) -> bool:
    return term.startswith("?")


@dataclass(frozen=True)
class Pattern:
    s: str
    p: str
    o: str

    def __iter__(self):
        return iter((self.s, self.p, self.o))

    @property
    def variables(self) -> tuple[str, ...]:
        return tuple(dict.fromkeys(t for t in self if is_var(t)))


@dataclass(frozen=True)
class QueryGraph:
    """A conjunction of patterns. A term that comes twice is one vertex, a constant as well."""

    patterns: tuple[Pattern, ...]
    name: str = field(default="", compare=False)

    @property
    def vertices(self) -> tuple[str, ...]:
        return tuple(dict.fromkeys(t for e in self.patterns for t in (e.s, e.o)))

    @property
    def variables(self) -> tuple[str, ...]:
        return tuple(dict.fromkeys(v for e in self.patterns for v in e.variables))

    def edges_at(self, vertex: str) -> list[int]:
        return [i for i, e in enumerate(self.patterns) if vertex in (e.s, e.o)]

    def connected(self) -> bool:
        if not self.patterns:
            return True
        seen, todo = set(), [self.patterns[0].s]
        while todo:
            v = todo.pop()
            if v in seen:
                continue
            seen.add(v)
            todo += [x for i in self.edges_at(v) for x in (self.patterns[i].s, self.patterns[i].o)]
        return seen >= set(self.vertices)

    def bind(self, values: dict[str, str]) -> QueryGraph:
        return QueryGraph(tuple(Pattern(*(values.get(t, t) for t in e)) for e in self.patterns), self.name)


def bgp(text: str, name: str = "") -> QueryGraph:
    """``?a p ?b . ?b q c/1``: terms by blanks, patterns by a dot between blanks."""
    return QueryGraph(tuple(Pattern(*part.split()) for part in text.split(" . ")), name)


def _coloured(q: QueryGraph, colour: dict[str, str]) -> dict[str, str]:
    """Colours told apart by what surrounds their vertices, again and again until nothing more comes apart."""
    variables = q.variables
    kinds = len(set(colour.values()))
    while True:
        name = lambda t: colour.get(t, t)  # noqa: E731, B023
        around = {v: sorted((("s" if e.s == v else "") + ("p" if e.p == v else "") + ("o" if e.o == v else ""), name(e.s), name(e.p), name(e.o)) for e in q.patterns if v in e) for v in variables}
        ranks = {k: f"?{i:06d}" for i, k in enumerate(sorted({repr((colour[v], around[v])) for v in variables}))}
        colour = {v: ranks[repr((colour[v], around[v]))] for v in variables}
        if len(ranks) == kinds:
            return colour
        kinds = len(ranks)


def _alike(q: QueryGraph, u: str, v: str) -> bool:
    """Whether swapping two variables gives the same patterns."""
    swap = {u: v, v: u}
    return {tuple(swap.get(t, t) for t in e) for e in q.patterns} == {tuple(e) for e in q.patterns}


@lru_cache(maxsize=10_000)
def canonical(q: QueryGraph) -> tuple[str, dict[str, str]]:
    """Text that renaming variables and reordering patterns don't change, and what each variable is called in it.

    Vertices are coloured by what surrounds them. While some are still equal, each of the first such group is told apart
    in turn and colours are refined anew; of all texts so reached the smallest is taken. Of vertices whose swap changes
    nothing one will do, so stars with equal rays, of any number of patterns, take no longer than others.
    """
    best: list[tuple[str, dict[str, str]]] = []

    def settle(colour: dict[str, str]) -> None:
        groups: dict[str, list[str]] = {}
        for v in q.variables:
            groups.setdefault(colour[v], []).append(v)
        open_ = min((c for c, g in groups.items() if len(g) > 1), default=None)
        if open_ is None:
            names = {v: f"?v{i}" for i, v in enumerate(sorted(q.variables, key=colour.__getitem__))}
            text = " . ".join(sorted(" ".join(names.get(t, t) for t in e) for e in q.patterns))
            if not best or text < best[0][0]:
                best[:] = [(text, names)]
            return
        tried: list[str] = []
        for v in groups[open_]:
            if not any(_alike(q, u, v) for u in tried):
                tried.append(v)
                settle(_coloured(q, {**colour, v: f"{open_}!"}))

    settle(_coloured(q, dict.fromkeys(q.variables, "?")))
    return best[0]


@dataclass(frozen=True)
class Template:
    """A query with variables for its constants; ``text`` is canonical, ``graph`` is what ``text`` says."""

    text: str

    @property
    def graph(self) -> QueryGraph:
        return bgp(self.text)


def _lifted(q: QueryGraph) -> tuple[QueryGraph, dict[str, str], dict[str, str]]:
    """The canonical query with variables for its constants, what constant each of these stands for, and what the query's
    own variables are called in it."""
    text, names = canonical(q)
    given = bgp(text)
    open_: dict[str, str] = {}
    for t in given.vertices:
        if not is_var(t):
            open_[t] = f"?const{len(open_)}"
    lifted = QueryGraph(tuple(Pattern(open_.get(e.s, e.s), e.p, open_.get(e.o, e.o)) for e in given.patterns))
    return lifted, {v: t for t, v in open_.items()}, names


@lru_cache(maxsize=10_000)
def template_of(q: QueryGraph) -> tuple[Template, tuple[tuple[str, str], ...]]:
    """The template, and for each of its vertices the term of the query that stands there (variables as ``?``).

    Every occurrence of one constant is one vertex. It is made from the canonical query, so equal queries fill a template's
    vertices alike.
    """
    lifted, constant, _ = _lifted(q)
    text, names = canonical(lifted)
    return Template(text), tuple(sorted((names[v], constant.get(v, "?")) for v in lifted.vertices))


@lru_cache(maxsize=10_000)
def vertices_in_template(q: QueryGraph) -> tuple[tuple[str, str], ...]:
    """(variable of the query, vertex of its template)."""
    lifted, _, own = _lifted(q)
    names = canonical(lifted)[1]
    return tuple((v, names[own[v]]) for v in q.variables)
